"""Dealing rows into the buckets of a layout: one distributed ranking, then arithmetic.

Rows of a value are ranked by a salted hash of the row. The rank is made in shards named by leading digits of that hash, as
many as the commonest value's rows ask for, so a value that many rows share is not sorted in one task. A small table of cut points says which ranks of a value go
to which class; within a class rows are dealt to its buckets in turn, so counts of a value differ by one at most.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from capbuckets.functions.exact import order_key

#: Rows of a shard, about, at most; most cut points that are broadcast, and most values that are collected.
SHARD_ROWS, MAX_BROADCAST, MAX_VALUES = 1 << 18, 200_000, 2_000_000


def split_counts(counts: Sequence[int], q1: Sequence[int], q2: Sequence[int], layout: Sequence[tuple[int, int]], order: str = "rare_first") -> list[tuple[int, int]]:
    """(rows in class 1, rows in class 2) of each value of a valid two-size layout.

    Class 1 starts at its bounds; the surplus moves to class 2 until that is full, value by value in ``order``: ``key``,
    ``rare_first``, ``common_first``, or ``spread`` (a row at a time in turn).
    """
    (s1, b1), (s2, b2) = layout
    o = np.asarray(counts, np.int64)
    bound1, bound2 = np.minimum(np.asarray(q1) * b1, o), np.minimum(np.asarray(q2) * b2, o)
    take1 = bound1.copy()
    slack = bound1 + bound2 - o  # rows that may be in either class
    surplus = int(take1.sum()) - s1 * b1
    if (slack < 0).any() or surplus < 0 or int(bound2.sum()) < s2 * b2:
        raise ValueError("the layout is not valid")
    if order == "spread":
        level, gone = 0, np.zeros_like(slack)
        low, high = 0, int(slack.max(initial=0))
        while low < high:  # the most rows that every value can give in turn
            level = (low + high + 1) // 2
            low, high = (level, high) if int(np.minimum(slack, level).sum()) <= surplus else (low, level - 1)
        gone = np.minimum(slack, low)
        more = np.flatnonzero(slack > low)[: surplus - int(gone.sum())]
        gone[more] += 1
    else:
        rank = {"key": np.arange(len(o)), "rare_first": np.lexsort((np.arange(len(o)), o)), "common_first": np.lexsort((np.arange(len(o)), -o))}[order]
        gone = np.zeros_like(slack)
        before = np.cumsum(slack[rank]) - slack[rank]
        gone[rank] = np.clip(surplus - before, 0, slack[rank])
    take1 = take1 - gone
    return list(zip(take1.tolist(), (o - take1).tolist(), strict=True))


def split_plan(caps: DataFrame, layout: Sequence[tuple[int, int]]) -> DataFrame:
    """:func:`split_counts` with ``rare_first`` as columns: (v, cnt, take1, take2), by a running sum over the histogram."""
    from capbuckets.functions.exact import quota

    (s1, b1), (s2, b2) = layout
    bound = lambda s, b: F.least(quota(F.lit(s), F.col("cap_num"), F.col("cap_den")) * b, F.col("cnt"))
    c = caps.select("v", "cnt", bound(s1, b1).alias("u1"), bound(s2, b2).alias("u2")).withColumn("slack", F.col("u1") + F.col("u2") - F.col("cnt"))
    one = Window.partitionBy(F.lit(1))
    before = F.coalesce(F.sum("slack").over(one.orderBy("cnt", "v").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    surplus = F.sum("u1").over(one) - s1 * b1
    gone = F.greatest(F.lit(0).cast("bigint"), F.least(F.col("slack"), surplus - before))
    return c.select("v", "cnt", (F.col("u1") - gone).alias("take1")).withColumn("take2", F.col("cnt") - F.col("take1"))


@dataclass(frozen=True)
class Cut:
    """Ranks lo + 1 .. hi of value ``v`` go to class ``class_id``: dealt from ``prefix`` on over ``b`` buckets from ``first`` on."""

    v: object
    class_id: int
    lo: int
    hi: int
    prefix: int
    b: int
    first: int
    s: int


def cut_points(values: Sequence, takes: Sequence[Sequence[int]], layout: Sequence[tuple[int, int]]) -> list[Cut]:
    """Cut points of all values; ``takes[i][j]`` is the number of rows of value i in class j."""
    out, done, prefix, first = [], [0] * len(values), 0, 0
    for j, (s, b) in enumerate(layout):
        prefix = 0
        for i, v in enumerate(values):
            t = int(takes[i][j])
            if t:
                out.append(Cut(v, j + 1, done[i], done[i] + t, prefix, b, first, s))
            done[i] += t
            prefix += t
        first += b
    return out


def shard_digits(rows: int) -> int:
    """Leading hexadecimal digits that cut ``rows`` rows of one value into shards of about ``SHARD_ROWS`` at most."""
    digits = 0
    while rows > SHARD_ROWS * 16**digits:
        digits += 1
    return digits


def rank_rows(df: DataFrame, v: str, key: Sequence[str], salt: str, most: int | None = None) -> DataFrame:
    """Adds ``_t`` (1, 2, ...): the rank of the row among the rows of its value, in the order of the salted hash and the key.

    ``most`` is the number of rows of the commonest value; it is counted where it is not known. It decides on the number of
    shards alone, never on ranks.
    """
    if most is None:
        most = df.groupBy(v).agg(F.count(F.lit(1)).alias("_n")).agg(F.coalesce(F.max("_n"), F.lit(0))).first()[0]
    digits = shard_digits(most)
    h = order_key(salt, *[F.col(k) for k in key])
    keyed = df.withColumn("_h", h).withColumn("_shard", F.substring("_h", 1, digits))
    sums = keyed.groupBy(F.col(v).alias("_v"), "_shard").agg(F.count(F.lit(1)).alias("_n"))
    before = F.coalesce(F.sum("_n").over(Window.partitionBy("_v").orderBy("_shard").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = sums.select("_v", F.col("_shard").alias("_s"), before.alias("_before"))
    inside = F.row_number().over(Window.partitionBy(v, "_shard").orderBy("_h", *key))
    ranked = keyed.withColumn("_r", inside)
    return ranked.join(offsets, ranked[v].eqNullSafe(offsets["_v"]) & (ranked["_shard"] == offsets["_s"])).withColumn("_t", F.col("_before") + F.col("_r")).drop("_h", "_shard", "_v", "_s", "_before", "_r")


def assign(df: DataFrame, v: str, key: Sequence[str], cuts: Sequence[Cut], salt: str) -> DataFrame:
    """Adds ``class_id`` and ``bucket`` (0, 1, ... over all classes) to every row."""
    return place(rank_rows(df, v, key, salt, max((c.hi for c in cuts), default=0)), v, cuts)


def place(ranked: DataFrame, v: str, cuts: Sequence[Cut]) -> DataFrame:
    """:func:`assign` for rows that :func:`rank_rows` has ranked: ranks don't follow from the cut points, so one ranking does for many."""
    spark = ranked.sparkSession
    kind = ranked.schema[v].dataType.simpleString()
    by_value: dict = {}
    for c in cuts:
        by_value.setdefault(c.v, []).append((c.class_id, c.lo, c.hi, c.prefix, c.b, c.first))
    table = spark.createDataFrame(list(by_value.items()), f"_v {kind}, _cuts array<struct<class_id:int,lo:bigint,hi:bigint,prefix:bigint,b:bigint,first:bigint>>")
    table = F.broadcast(table) if len(cuts) <= MAX_BROADCAST else table
    met = ranked.join(table, ranked[v].eqNullSafe(table["_v"]))
    cut = F.get(F.filter("_cuts", lambda c: (F.col("_t") > c["lo"]) & (F.col("_t") <= c["hi"])), 0)
    met = met.withColumn("_cut", cut)
    bucket = F.col("_cut.first") + F.pmod(F.col("_cut.prefix") + F.col("_t") - F.col("_cut.lo"), F.col("_cut.b"))
    return met.select(*[c for c in ranked.columns if c != "_t"], F.col("_cut.class_id").alias("class_id"), bucket.alias("bucket"))


def collect_caps(caps: DataFrame, most: int = MAX_VALUES) -> list:
    """The caps table, or a histogram, on the driver, in the order of the values; its size is that of the sensitive domain and is checked."""
    rows = caps.orderBy(F.asc_nulls_first("v")).limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError("the sensitive domain is too large for the driver")
    return rows


def two_size_cuts(caps_rows: Sequence, layout: Sequence[tuple[int, int]], order: str = "rare_first") -> list[Cut]:
    """Cut points of a two-size layout, from collected caps."""
    q = [[min(s, s * r.cap_num // r.cap_den) for r in caps_rows] for s, _ in layout]
    takes = split_counts([r.cnt for r in caps_rows], q[0], q[1], layout, order)
    return cut_points([r.v for r in caps_rows], takes, layout)


def deal(df: DataFrame, v: str, key: Sequence[str], buckets: int, salt: str) -> DataFrame:
    """Deals all rows over ``buckets`` buckets: the one-size case."""
    from capbuckets.operators.policy import histogram

    rows = collect_caps(histogram(df, v))
    n = sum(r.cnt for r in rows)
    return assign(df, v, key, cut_points([r.v for r in rows], [[r.cnt] for r in rows], [(-(-n // buckets), buckets)]), salt)
