"""Adversaries who know more, and decoy values that hold them off."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from capbuckets.functions.exact import order_key


def corrupted_share(size: Column, known: Column, sigma: Column | int) -> Column:
    """Share of the real rows left in a bucket after ``known`` of them have been ruled out, among ``sigma`` decoys."""
    return (size - known) / (size - known + sigma)


def worst_certainty(sigma: Column | int) -> Column:
    """Certainty about the last row of a bucket when all others are known: 1 / (1 + sigma)."""
    return F.lit(1.0) / (F.lit(1) + sigma)


def corruption_attack(sa_side: DataFrame, known: int, sigma: int, salt: str, v: str = "v") -> DataFrame:
    """(bucket, v, prob): shares after ``known`` rows of each bucket, chosen by a salted hash, have been ruled out."""
    ranked = sa_side.select("bucket", F.col(v).alias("v")).withColumn("_i", F.row_number().over(Window.partitionBy("bucket", "v").orderBy(F.lit(1))))
    order = Window.partitionBy("bucket").orderBy(order_key(salt, F.col("bucket"), F.col("v"), F.col("_i")))
    left = ranked.withColumn("_r", F.row_number().over(order)).where(F.col("_r") > known)
    counts = left.groupBy("bucket", "v").agg(F.count(F.lit(1)).alias("c"))
    size = F.sum("c").over(Window.partitionBy("bucket"))
    return counts.select("bucket", "v", (F.col("c") / (size + sigma)).alias("prob"))


def domain_order(sa: DataFrame, salt: str) -> DataFrame:
    """(v, i): the sensitive values numbered from 0 in a salted order."""
    order = Window.partitionBy(F.lit(1)).orderBy(order_key(salt, F.col("v")), "v")
    return sa.select("v").distinct().select("v", (F.row_number().over(order) - 1).cast("bigint").alias("i"))


def decoys(sa: DataFrame, sigma: int, salt: str, forbidden: DataFrame | None = None) -> DataFrame:
    """(bucket, v): ``sigma`` different values for each bucket that it doesn't hold, from the compact sensitive side.

    Values stand in a salted ring; a bucket begins at a place of its own and takes the first ``sigma`` values from there on that
    it neither holds nor finds in ``forbidden`` (bucket, values), which some row of the bucket can rule out. It looks at no more
    places than it may have to pass over, so the work follows the buckets' sizes and not the domain. Raises if a
    bucket leaves fewer than ``sigma`` candidates.
    """
    ring = domain_order(sa, salt)
    size = ring.agg(F.count(F.lit(1)).alias("_d"))  # one row
    taken = sa.select("bucket", "v").distinct()
    if forbidden is not None:
        out = forbidden.join(sa.select("bucket").distinct(), "bucket", "left_semi").select("bucket", F.explode("values").alias("v"))
        taken = taken.unionByName(out.join(ring.select("v"), "v", "left_semi").select("bucket", "v")).distinct()
    passed = taken.groupBy("bucket").agg(F.count(F.lit(1)).alias("_k")).crossJoin(size)
    passed = passed.withColumn("_k", F.when(F.col("_d") - F.col("_k") < sigma, F.raise_error(F.lit("too few values are left for decoys"))).otherwise(F.col("_k")).cast("bigint"))
    tried = passed.select("bucket", "_d", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("_k") + (sigma - 1))).alias("_j"))
    begin = F.pmod(F.conv(F.substring(order_key(salt, F.col("bucket")), 1, 13), 16, 10).cast("bigint"), F.col("_d"))
    places = tried.select("bucket", "_j", F.pmod(begin + F.col("_j"), F.col("_d")).alias("i")).join(ring, "i")
    free = places.join(taken, ["bucket", "v"], "left_anti").withColumn("_r", F.row_number().over(Window.partitionBy("bucket").orderBy("_j")))
    return free.where(F.col("_r") <= sigma).select("bucket", "v")


def inject_decoys(sa: DataFrame, sigma: int, salt: str, forbidden: DataFrame | None = None) -> DataFrame:
    """(bucket, v, cnt): the sensitive side with decoys; nothing tells them from real rows."""
    return sa.select("bucket", "v", "cnt").unionByName(decoys(sa, sigma, salt, forbidden).withColumn("cnt", F.lit(1).cast("bigint"))) if sigma else sa


def decoy_distortion(sa: DataFrame, with_decoys: DataFrame) -> DataFrame:
    """(v, cnt, published, excess): rows of each value before and after."""
    a, b = sa.groupBy("v").agg(F.sum("cnt").cast("bigint").alias("cnt")), with_decoys.groupBy("v").agg(F.sum("cnt").cast("bigint").alias("published"))
    return a.join(b, "v", "full").select("v", F.coalesce("cnt", F.lit(0)).cast("bigint").alias("cnt"), "published").withColumn("excess", F.col("published") - F.col("cnt"))


def pair_counts(qi_side: DataFrame, sa: DataFrame, z: Column, min_support: int = 1) -> DataFrame:
    """(z, v, pairs, base): rows of each pair of a quasi-identifier and a value as the release lets one expect them,
    and as many as there would be without any association. Both sides are summed by bucket before they meet.

    Pairs that never meet belong to the answer, so it has a row for each z with ``min_support`` rows and each value: the
    product is the result, and how its sides are sent is left to Spark, which knows their sizes."""
    zs = qi_side.select("bucket", z.alias("z")).groupBy("bucket", "z").agg(F.count(F.lit(1)).alias("nz"))
    sizes = sa.groupBy("bucket").agg(F.sum("cnt").alias("size"))
    met = zs.join(sa, "bucket").join(sizes, "bucket").groupBy("z", "v").agg(F.sum(F.col("nz") * F.col("cnt") / F.col("size")).alias("pairs"))
    of_z, of_v = zs.groupBy("z").agg(F.sum("nz").alias("n_z")).where(F.col("n_z") >= min_support), sa.groupBy("v").agg(F.sum("cnt").alias("n_v"))
    every = of_z.crossJoin(of_v.crossJoin(of_v.agg(F.sum("n_v").alias("n"))))
    out = every.join(met, ["z", "v"], "left")
    return out.select("z", "v", F.col("n_z").cast("bigint").alias("n_z"), F.coalesce("pairs", F.lit(0.0)).alias("pairs"), (F.col("n_z") * F.col("n_v") / F.col("n")).alias("base"))


def negative_associations(qi_side: DataFrame, sa: DataFrame, z: Column, tau: float = 0.5, min_support: int = 1) -> DataFrame:
    """(z, v, lift): pairs that occur at most ``tau`` times as often as without association."""
    lift = F.col("pairs") / F.col("base")
    return pair_counts(qi_side, sa, z, min_support).where(lift <= tau).select("z", "v", lift.alias("lift"))


def exclusion_attack(qi_side: DataFrame, sa: DataFrame, z: Column, assoc: DataFrame) -> DataFrame:
    """(bucket, z, v, prob, prob_after): shares in the buckets of rows with z, before and after values that z rules out are dropped."""
    zs = qi_side.select("bucket", z.alias("z")).distinct()
    sizes = sa.groupBy("bucket").agg(F.sum("cnt").alias("size"))
    met = zs.join(sa, "bucket").join(sizes, "bucket")
    out = met.join(assoc.select("z", "v", F.lit(True).alias("_out")), ["z", "v"], "left").withColumn("kept", F.when(F.col("_out").isNull(), F.col("cnt")).otherwise(0))
    left = F.sum("kept").over(Window.partitionBy("bucket", "z"))
    return out.select("bucket", "z", "v", (F.col("cnt") / F.col("size")).alias("prob"), F.when(left > 0, F.col("kept") / F.when(left > 0, left)).otherwise(0.0).alias("prob_after"))


def forbidden_values(qi_side: DataFrame, z: Column, assoc: DataFrame) -> DataFrame:
    """(bucket, values): values that at least one row of the bucket can rule out."""
    return qi_side.select("bucket", z.alias("z")).distinct().join(assoc, "z").groupBy("bucket").agg(F.collect_set("v").alias("values"))


def safe_decoys(qi_side: DataFrame, sa: DataFrame, z: Column, assoc: DataFrame, sigma: int, salt: str) -> DataFrame:
    """:func:`inject_decoys` without values that an association rules out."""
    return inject_decoys(sa, sigma, salt, forbidden_values(qi_side, z, assoc))
