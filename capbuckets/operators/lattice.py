"""All layouts of two bucket sizes that hold just n rows, addressed by position and never listed unless asked for.

With sizes s1 < s2 these are (b1 - i d1, b2 + i d2) for i = 0 .. last, where (b1, b2) has the fewest large buckets and
d1, d2 come from the least common multiple. Loss grows with the position.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import gcd

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from capbuckets.functions.exact import ceil_div, div


@dataclass(frozen=True)
class Lattice:
    s1: int
    s2: int
    b1: int
    b2: int
    d1: int
    d2: int
    last: int

    def at(self, i: int) -> tuple[int, int]:
        return self.b1 - i * self.d1, self.b2 + i * self.d2

    def loss(self, i: int) -> int:
        b1, b2 = self.at(i)
        return b1 * (self.s1 - 1) ** 2 + b2 * (self.s2 - 1) ** 2

    def cutoff(self, best: int | None) -> int:
        """Last position with a loss strictly under ``best``; -1 if there is none."""
        if best is None:
            return self.last
        step = self.d2 * (self.s2 - 1) ** 2 - self.d1 * (self.s1 - 1) ** 2
        return min(self.last, (best - 1 - self.loss(0)) // step) if self.loss(0) < best else -1


def lattice(n: int, s1: int, s2: int) -> Lattice | None:
    """The lattice of two sizes; None if no layout holds just n rows."""
    g = gcd(s1, s2)
    if n % g:
        return None
    b2 = n // g * pow(s2 // g, -1, s1 // g) % (s1 // g) if s1 > g else 0
    b1 = (n - s2 * b2) // s1
    return None if n < s2 * b2 else Lattice(s1, s2, b1, b2, s2 // g, s1 // g, b1 // (s2 // g))


def interval_and(*intervals: tuple[int, int]) -> tuple[int, int]:
    """Intersection of sublists given as (first, last); empty if first > last."""
    return max(a for a, _ in intervals), min(b for _, b in intervals)


def size_pairs(spark: SparkSession, low: int, high: int) -> DataFrame:
    """(s1, s2) with low <= s1 < s2 <= high, as bigint."""
    sizes = spark.range(low, high)
    return sizes.select(F.col("id").alias("s1"), F.explode(F.sequence(F.col("id") + 1, F.lit(high).cast("bigint"))).alias("s2"))


def lattice_columns(n: Column, s1: Column, s2: Column) -> dict[str, Column]:
    """Expressions for g, and for the first pair once g is a column."""
    g = F.array_max(F.filter(F.sequence(F.lit(1).cast("bigint"), s1), lambda x: (F.pmod(s1, x) == 0) & (F.pmod(s2, x) == 0)))
    first = F.get(F.filter(F.sequence(F.lit(0).cast("bigint"), div(s1, F.col("g")) - 1), lambda b: F.pmod(n - s2 * b, s1) == 0), 0)
    return {"g": g, "b2_0": first}


def lattice_grid(pairs: DataFrame, n: Column | int) -> DataFrame:
    """(s1, s2, b1_0, b2_0, d1, d2, k) for each pair of sizes that has a layout; k is the last position."""
    n = F.lit(n).cast("bigint") if isinstance(n, int) else n
    e = lattice_columns(n, F.col("s1"), F.col("s2"))
    with_first = pairs.withColumn("g", e["g"]).withColumn("b2_0", e["b2_0"]).where(F.col("b2_0").isNotNull()).where(F.col("s2") * F.col("b2_0") <= n)
    out = with_first.withColumn("b1_0", div(n - F.col("s2") * F.col("b2_0"), F.col("s1"))).withColumn("d1", div(F.col("s2"), F.col("g"))).withColumn("d2", div(F.col("s1"), F.col("g")))
    return out.withColumn("k", div(F.col("b1_0"), F.col("d1"))).select("s1", "s2", "b1_0", "b2_0", "d1", "d2", "k")


def loss_of(s1: Column, b1: Column, s2: Column, b2: Column) -> Column:
    return b1 * (s1 - 1) * (s1 - 1) + b2 * (s2 - 1) * (s2 - 1)


def lattice_at(grid: DataFrame, i: Column) -> DataFrame:
    """The layouts at position ``i`` of each lattice: (s1, s2, pos, b1, b2, loss)."""
    at = grid.withColumn("pos", i).where("pos BETWEEN 0 AND k")
    return at.select("s1", "s2", "pos", (F.col("b1_0") - F.col("pos") * F.col("d1")).alias("b1"), (F.col("b2_0") + F.col("pos") * F.col("d2")).alias("b2")).withColumn("loss", loss_of(F.col("s1"), F.col("b1"), F.col("s2"), F.col("b2")))


def enumerate_layouts(grid: DataFrame) -> DataFrame:
    """Every layout of every lattice; for small n only, see :func:`count_layouts`."""
    return lattice_at(grid.withColumn("i", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("k")))), F.col("i"))


def count_layouts(grid: DataFrame) -> DataFrame:
    """One row (layouts): how many layouts there are, without listing them."""
    return grid.agg(F.coalesce(F.sum(F.col("k") + 1), F.lit(0)).cast("bigint").alias("layouts"))


def loss_cutoff(grid: DataFrame, best: Column) -> DataFrame:
    """(s1, s2, cut): the last position with a loss strictly under ``best``, -1 if none."""
    zero = loss_of(F.col("s1"), F.col("b1_0"), F.col("s2"), F.col("b2_0"))
    step = F.col("d2") * (F.col("s2") - 1) * (F.col("s2") - 1) - F.col("d1") * (F.col("s1") - 1) * (F.col("s1") - 1)
    cut = F.when(zero >= best, F.lit(-1).cast("bigint")).otherwise(F.least(F.col("k"), ceil_div(F.greatest(best - zero, F.lit(0).cast("bigint")), step) - 1))
    return grid.select("s1", "s2", cut.alias("cut"))
