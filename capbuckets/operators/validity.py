"""Whether rows can be dealt into a layout so that no bucket exceeds a cap. One aggregate over the caps decides."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from capbuckets.functions.exact import ceil_div, quota


def quota_table(caps: DataFrame, low: int, high: int) -> DataFrame:
    """(s, v, quota): most copies of each value in one bucket, for all sizes from ``low`` to ``high``."""
    sizes = caps.select("*", F.explode(F.sequence(F.lit(low), F.lit(high))).alias("s"))
    return sizes.select("s", "v", quota(F.col("s"), F.col("cap_num"), F.col("cap_den")).alias("quota"))


def class_bounds(caps: DataFrame, layout: Sequence[tuple[int, int]]) -> DataFrame:
    """(v, cnt, free_1, held_1, ...): for each class of (size, buckets), quota times buckets and the same held to the supply."""
    out = caps.select("v", "cnt", "cap_num", "cap_den")
    for i, (s, b) in enumerate(layout, 1):
        free = quota(F.lit(s), F.col("cap_num"), F.col("cap_den")) * b
        out = out.withColumn(f"free_{i}", free).withColumn(f"held_{i}", F.least(free, F.col("cnt")))
    return out.drop("cap_num", "cap_den")


def fits_one_size(s: Column, b: Column, form: str = "quota") -> Column:
    """Whether a value fits into b buckets of size s: by its spread over the buckets (``ceil``) or by its quota."""
    if form == "ceil":
        return ceil_div(F.col("cnt"), b) * F.col("cap_den") <= s * F.col("cap_num")
    return F.col("cnt") <= quota(s, F.col("cap_num"), F.col("cap_den")) * b


def valid_one_size(caps: DataFrame, s: int, b: int, form: str = "quota") -> DataFrame:
    """One row (valid)."""
    fits = fits_one_size(F.lit(s).cast("bigint"), F.lit(b).cast("bigint"), form)
    return caps.agg((F.bool_and(fits) & (F.sum("cnt") == s * b)).alias("valid"))


def two_size_tests(q1: Column, b1: Column, q2: Column, b2: Column, s1: Column, s2: Column, mult: Column, n: Column) -> dict[str, Column]:
    """The conditions as aggregates over values (or classes of ``mult`` values)."""
    o = F.col("cnt")
    return {
        "privacy_ok": F.bool_and(q1 * b1 + q2 * b2 >= o),
        "fill1_ok": F.sum(mult * F.least(q1 * b1, o)) >= F.first(s1 * b1),
        "fill2_ok": F.sum(mult * F.least(q2 * b2, o)) >= F.first(s2 * b2),
        "room_ok": F.first(s1 * b1 + s2 * b2) == F.first(n),
    }


def valid_two_size(caps: DataFrame, layouts: DataFrame) -> DataFrame:
    """(s1, b1, s2, b2, privacy_ok, fill1_ok, fill2_ok, room_ok, valid) for each layout of a small table of layouts.

    Privacy: both classes together can take every row of each value. Fill: either class can be filled up. Room: the
    layout holds just as many rows as there are.
    """
    total = F.broadcast(caps.agg(F.sum("cnt").alias("n")))
    grid = caps.crossJoin(F.broadcast(layouts)).crossJoin(total)
    c = {k: F.col(k).cast("bigint") for k in ("s1", "b1", "s2", "b2")}
    q1, q2 = (quota(c[s], F.col("cap_num"), F.col("cap_den")) for s in ("s1", "s2"))
    tests = two_size_tests(q1, c["b1"], q2, c["b2"], c["s1"], c["s2"], F.lit(1), F.col("n"))
    out = grid.groupBy("s1", "b1", "s2", "b2").agg(*[e.alias(k) for k, e in tests.items()])
    return out.withColumn("valid", F.col("privacy_ok") & F.col("fill1_ok") & F.col("fill2_ok") & F.col("room_ok"))


def subset_tests(bounds: DataFrame, rooms: Sequence[int]) -> DataFrame:
    """(mask, supply, room, ok) for every non-empty set of classes, from (cnt, ub) with an array of bounds by class.

    A layout is valid if and only if each set of classes can be filled from what the values may put into it together
    (by the smallest cut of the flow from values to classes), and all rows fit.
    """
    q = len(rooms)
    if q > 12:
        raise ValueError("the subset test is for few classes; use operators.exact.flow_split beyond")
    has = lambda i: F.getbit(F.col("mask"), F.lit(i)) == 1
    room = sum((F.when(has(i), F.lit(int(r)).cast("bigint")).otherwise(F.lit(0).cast("bigint")) for i, r in enumerate(rooms)), F.lit(0).cast("bigint"))
    put = sum((F.when(has(i), F.col("ub")[i]).otherwise(F.lit(0).cast("bigint")) for i in range(q)), F.lit(0).cast("bigint"))
    grid = bounds.select("cnt", "ub", F.explode(F.sequence(F.lit(1).cast("bigint"), F.lit((1 << q) - 1).cast("bigint"))).alias("mask"))
    out = grid.groupBy("mask").agg(F.sum(F.least(put, F.col("cnt"))).alias("supply")).withColumn("room", room)
    return out.withColumn("ok", F.col("supply") >= F.col("room"))


def _bounds(caps: DataFrame, layout: Sequence[tuple[int, int]]) -> DataFrame:
    return caps.select("cnt", F.array(*[quota(F.lit(s), F.col("cap_num"), F.col("cap_den")) * b for s, b in layout]).alias("ub"))


def valid_multi(caps: DataFrame, layout: Sequence[tuple[int, int]]) -> DataFrame:
    """One row (valid), by every set of classes."""
    rooms = [s * b for s, b in layout]
    tests = subset_tests(_bounds(caps, layout), rooms).agg(F.bool_and("ok").alias("ok"))
    return tests.crossJoin(caps.agg((F.sum("cnt") == sum(rooms)).alias("full"))).select((F.col("ok") & F.col("full")).alias("valid"))


def valid_naive_multi(bounds: DataFrame, rooms: Sequence[int]) -> DataFrame:
    """One row (valid): the two-size conditions class by class. They do not suffice for three classes; kept as a counterexample."""
    each = [F.sum(F.least(F.col("ub")[i], F.col("cnt"))) >= r for i, r in enumerate(rooms)]
    privacy = F.bool_and(F.aggregate("ub", F.lit(0).cast("bigint"), lambda a, x: a + x) >= F.col("cnt"))
    ok = privacy & (F.sum("cnt") == sum(rooms))
    for e in each:
        ok = ok & e
    return bounds.agg(ok.alias("valid"))


#: The three-class counterexample. Room of each class; (values, rows of each, bounds by class).
THREE_CLASS_ROOMS = (20, 20, 30)
THREE_CLASS = ((10, 5, (0, 0, 5)), (1, 20, (20, 20, 20)))


def three_class_bounds(spark) -> DataFrame:
    rows = [(i, c, list(ub)) for times, c, ub in THREE_CLASS for i in range(times)]
    return spark.createDataFrame(rows, "v int, cnt bigint, ub array<bigint>")
