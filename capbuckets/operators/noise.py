"""The Laplace mechanism on counts, and what the ratio of two noisy counts still tells."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from capbuckets.functions.exact import uniform
from capbuckets.operators.risk import rule_confidence


def laplace(epsilon: float, salt: str, *keys: Column) -> Column:
    """A Laplace draw of scale 1 / epsilon that follows from the keys, by the inverse of the distribution function."""
    u = uniform(salt, *keys) - 0.5
    return -F.signum(u) * F.log(1 - 2 * F.abs(u)) / epsilon


def laplace_count(count: Column, epsilon: float, salt: str, *keys: Column) -> Column:
    return count + laplace(epsilon, salt, *keys)


def noisy_rule_confidence(df: DataFrame, qi: Sequence[str], epsilon: float, v: str = "v", salt: str = "n0", min_support: int = 1) -> DataFrame:
    """(qi..., v, x, y, conf, noisy_x, noisy_y, noisy_conf): the ratio of two answers of the mechanism beside the true one."""
    rules = rule_confidence(df, qi, v, min_support)
    keys = [F.col(q) for q in qi]
    noisy = rules.withColumn("noisy_x", laplace_count(F.col("x"), epsilon, f"{salt}x", *keys)).withColumn("noisy_y", laplace_count(F.col("y"), epsilon, f"{salt}y", *keys, F.col("v")))
    return noisy.withColumn("noisy_conf", F.when(F.abs("noisy_x") >= 1, F.col("noisy_y") / F.col("noisy_x")))


def ratio_moments(x: Column, y: Column, epsilon: float) -> dict[str, Column]:
    """Approximate bias factor, mean and variance of the noisy ratio; they lose meaning when x is not far over 1 / epsilon."""
    spread = 2.0 / (epsilon * epsilon) / (x * x)
    share = y / x
    return {"factor": 1 + spread, "mean": share * (1 + spread), "var": spread * (1 + share * share)}


def ratio_convergence(spark: SparkSession, sizes: Sequence[int], ratio: float, epsilon: float, reps: int, salt: str = "r0") -> DataFrame:
    """(x, mean, var): of the noisy ratio over ``reps`` draws for each size; draws with a noisy count under 1 are left out."""
    grid = spark.range(reps).withColumnRenamed("id", "rep").withColumn("x", F.explode(F.array(*[F.lit(s).cast("bigint") for s in sizes])))
    keys = (F.col("x"), F.col("rep"))
    drawn = grid.select("x", laplace_count(F.col("x"), epsilon, f"{salt}x", *keys).alias("a"), laplace_count(F.col("x") * ratio, epsilon, f"{salt}y", *keys).alias("b")).where(F.abs("a") >= 1)
    return drawn.groupBy("x").agg(F.avg(F.col("b") / F.col("a")).alias("mean"), F.var_pop(F.col("b") / F.col("a")).alias("var"))


def density_ratio(answer: Column, x: Column, other: Column, epsilon: float) -> Column:
    """Ratio of the mechanism's densities at ``answer`` for two true counts; at most e^epsilon if these differ by one."""
    return F.exp(epsilon * (F.abs(answer - other) - F.abs(answer - x)))
