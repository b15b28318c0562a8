"""Releases: the quasi-identifying side and the sensitive side, joined by nothing but the bucket; and their measures."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def publish(assigned: DataFrame, qi: Sequence[str], v: str = "v", salt: str | None = None) -> tuple[DataFrame, DataFrame]:
    """(QI side, sensitive side): each is dealt out by bucket and sorted by its own columns, so rows can't be matched by place.

    The row key, the class and every other column stay behind. Duplicates are kept. With a salt, buckets get names that say
    nothing about their size class.
    """
    bucket = F.col("bucket") if salt is None else F.xxhash64(F.lit(salt), F.col("bucket"))
    named = assigned.withColumn("bucket", bucket)
    qi_side = named.select(*qi, "bucket").repartition("bucket").sortWithinPartitions("bucket", *qi)
    sa_side = named.select("bucket", v).repartition("bucket").sortWithinPartitions("bucket", v)
    return qi_side, sa_side


def compact(sa_side: DataFrame, v: str = "v") -> DataFrame:
    """(bucket, v, cnt): the sensitive side with repeats counted."""
    return sa_side.groupBy("bucket", F.col(v).alias("v")).agg(F.count(F.lit(1)).alias("cnt"))


def bucket_risk(sa: DataFrame) -> DataFrame:
    """(bucket, v, cnt, size, prob): the share of each value in its bucket, from the compact side."""
    sizes = sa.groupBy("bucket").agg(F.sum("cnt").alias("size"))
    return sa.join(sizes, "bucket").select("bucket", "v", "cnt", "size", (F.col("cnt") / F.col("size")).alias("prob"))


def person_risk(qi_side: DataFrame, sa: DataFrame, qi: Sequence[str]) -> DataFrame:
    """(qi..., v, prob): for each combination of quasi-identifiers the largest share of a value in a bucket that holds it."""
    where = qi_side.select(*qi, "bucket").distinct()
    return where.join(bucket_risk(sa), "bucket").groupBy(*qi, "v").agg(F.max("prob").alias("prob"))


def audit(assigned: DataFrame, caps: DataFrame, v: str = "v") -> DataFrame:
    """One row (n_rows, buckets, violations, max_ratio_ok): no value of a bucket exceeds its cap."""
    sa = compact(assigned.select("bucket", v), v)
    risk = bucket_risk(sa).join(caps.select(F.col("v").alias("_v"), "cap_num", "cap_den"), F.col("v").eqNullSafe(F.col("_v")))
    over = F.col("cnt") * F.col("cap_den") > F.col("size") * F.col("cap_num")
    return risk.agg(F.coalesce(F.sum("cnt"), F.lit(0)).cast("bigint").alias("n_rows"), F.count_distinct("bucket").alias("buckets"), F.count_if(over).alias("violations"), F.coalesce(F.bool_and(~over), F.lit(True)).alias("ok"))


def bag_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row (difference): rows that one of two tables has more often than the other."""
    return a.exceptAll(b).unionAll(b.exceptAll(a)).agg(F.count(F.lit(1)).alias("difference"))


def bucket_sizes(sa: DataFrame) -> DataFrame:
    return sa.groupBy("bucket").agg(F.sum("cnt").cast("bigint").alias("size"))


def release_loss(sa: DataFrame) -> DataFrame:
    """One row (n_rows, loss, mse): squared sizes less one, summed over buckets; divided by rows less one."""
    s = bucket_sizes(sa).agg(F.sum("size").alias("n_rows"), F.sum((F.col("size") - 1) * (F.col("size") - 1)).alias("loss"))
    return s.select("n_rows", "loss", (F.col("loss") / (F.col("n_rows") - 1)).alias("mse"))


def extreme_losses(n: int) -> dict[str, tuple[int, float]]:
    """(loss, mse) of the two extremes: each row a bucket, and all rows in one bucket."""
    return {"raw": (0, 0.0), "one_bucket": ((n - 1) ** 2, float(n - 1))}


def layout_mse(loss: int, n: int) -> float:
    return loss / (n - 1)


def map_histogram(sa: DataFrame) -> DataFrame:
    """(bucket, values): the sensitive side as one map a bucket."""
    return sa.groupBy("bucket").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("v", "cnt")))).alias("values"))
