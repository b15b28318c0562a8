"""Inference from raw data: how sure a rule (quasi-identifiers -> value) is."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def rule_counts(df: DataFrame, qi: Sequence[str], v: str = "v") -> DataFrame:
    """(qi..., v, x, y): rows that match the quasi-identifiers, and those of them with the value; both counts in one aggregate."""
    pairs = df.groupBy(*qi, F.col(v).alias("v")).agg(F.count(F.lit(1)).alias("y"))
    totals = pairs.groupBy(*qi).agg(F.sum("y").cast("bigint").alias("x"))
    return pairs.join(totals, list(qi)).select(*qi, "v", "x", "y")


def rule_confidence(df: DataFrame, qi: Sequence[str], v: str = "v", min_support: int = 1, min_conf: float = 0.0) -> DataFrame:
    """(qi..., v, x, y, conf) of the rules with enough support and confidence."""
    conf = F.col("y") / F.col("x")
    return rule_counts(df, qi, v).where((F.col("x") >= min_support) & (conf >= min_conf)).select("*", conf.alias("conf"))


def rule_cube(df: DataFrame, qi: Sequence[str], v: str = "v", min_support: int = 1) -> DataFrame:
    """Rules over every subset of the quasi-identifiers; those left out are null, and ``level`` names the subset by bits."""
    n = len(qi)
    cube = df.cube(*qi, F.col(v).alias("v")).agg(F.count(F.lit(1)).alias("c"), F.grouping_id().alias("g"))
    level = F.call_function("div", F.col("g"), F.lit(2))
    pairs = cube.where(F.pmod("g", F.lit(2)) == 0).select(*qi, "v", F.col("c").alias("y"), level.alias("level"))
    totals = cube.where(F.pmod("g", F.lit(2)) == 1).select(*[F.col(q).alias(f"_{q}") for q in qi], F.col("c").alias("x"), level.alias("_level"))
    on = F.col("level") == F.col("_level")
    for q in qi:
        on = on & F.col(q).eqNullSafe(F.col(f"_{q}"))
    out = pairs.join(totals, on).where(F.col("x") >= min_support)
    return out.select(*qi, "v", "level", "x", "y", (F.col("y") / F.col("x")).alias("conf")) if n else out


def useful_outcome(rules: DataFrame, harmless: Sequence) -> DataFrame:
    """Rules with the values that are no breach merged into one outcome (a null value)."""
    merged = F.when(F.col("v").isin(*harmless), F.lit(None)).otherwise(F.col("v"))
    keys = [c for c in rules.columns if c not in ("v", "y", "conf")]
    return rules.groupBy(*keys, merged.alias("v")).agg(F.sum("y").cast("bigint").alias("y")).withColumn("conf", F.col("y") / F.col("x"))


def leave_one_out(rules: DataFrame) -> DataFrame:
    """Confidence with and without the target row: what others reveal stays when the row is taken out."""
    return rules.where("x > 1").select("*", ((F.col("y") - 1) / (F.col("x") - 1)).alias("conf_without"))
