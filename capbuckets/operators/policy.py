"""Histograms of the sensitive column, cap policies over them, and what follows from a policy alone.

A histogram has (v, cnt); caps have (v, cnt, cap_num, cap_den): the tolerated inference probability as a ratio of whole
numbers, at most 1. All decisions of the engine are made on these small tables.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from capbuckets.functions.exact import ceil_div


def histogram(df: DataFrame, sensitive: str = "v", nulls: str = "category") -> DataFrame:
    """(v, cnt): one scan of one column, counted on each task first. Nulls are a value, or an error with ``nulls='reject'``."""
    value = F.col(sensitive)
    if nulls == "reject":
        value = F.when(value.isNull(), F.raise_error(F.lit(f"null in the sensitive column {sensitive}"))).otherwise(value)
    elif nulls != "category":
        raise ValueError("nulls must be 'category' or 'reject'")
    return df.select(value.alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("cnt"))


def with_total(hist: DataFrame) -> DataFrame:
    """Adds ``n``, the number of rows, to a histogram (a one-row broadcast)."""
    return hist.crossJoin(F.broadcast(hist.agg(F.coalesce(F.sum("cnt"), F.lit(0)).cast("bigint").alias("n"))))


def linear_caps(hist: DataFrame, a: int, b_num: int, b_den: int, a_den: int = 1) -> DataFrame:
    """cap = min(1, a / a_den * cnt / n + b_num / b_den)."""
    den = F.col("n") * (b_den * a_den)
    return with_total(hist).select("v", "cnt", F.least(F.col("cnt") * (a * b_den) + F.col("n") * (b_num * a_den), den).alias("cap_num"), den.alias("cap_den"))


def uniform_caps(hist: DataFrame, ell: int) -> DataFrame:
    """cap = 1 / ell for every value: the uniform diversity policy."""
    return hist.select("v", "cnt", F.lit(1).cast("bigint").alias("cap_num"), F.lit(ell).cast("bigint").alias("cap_den"))


def mixed_caps(hist: DataFrame, overrides: Mapping, open_values: Sequence, a: int, b_num: int, b_den: int) -> DataFrame:
    """Cap 1 for ``open_values``, (num, den) of ``overrides`` where given, the linear rule for the rest."""
    rest = linear_caps(hist, a, b_num, b_den)
    num, den = F.col("cap_num"), F.col("cap_den")
    for value, (x, y) in overrides.items():
        num, den = F.when(F.col("v") == value, F.lit(x).cast("bigint")).otherwise(num), F.when(F.col("v") == value, F.lit(y).cast("bigint")).otherwise(den)
    opened = F.coalesce(F.col("v").isin(*open_values), F.lit(False)) if open_values else F.lit(False)
    one = F.lit(1).cast("bigint")
    return rest.select("v", "cnt", F.when(opened, one).otherwise(num).alias("cap_num"), F.when(opened, one).otherwise(den).alias("cap_den"))


def caps_feasible(caps: DataFrame) -> DataFrame:
    """One row (feasible, offenders): a release under the caps exists if and only if no value is more frequent than its cap."""
    ok = F.col("cap_num") * F.col("n") >= F.col("cnt") * F.col("cap_den")
    return with_total(caps).agg(F.coalesce(F.bool_and(ok), F.lit(True)).alias("feasible"), F.count_if(~ok).alias("offenders"))


def size_bounds(caps: DataFrame) -> DataFrame:
    """One row (m_min, ell): the smallest bucket size that can hold any value, and the size that the strictest cap asks for."""
    need = ceil_div(F.col("cap_den"), F.col("cap_num"))
    return caps.agg(F.min(need).alias("m_min"), F.max(need).alias("ell"))


def ell_for(caps: DataFrame) -> DataFrame:
    """One row (ell): the uniform diversity that models the policy, 1 / (smallest cap) rounded up."""
    return size_bounds(caps).select("ell")


def max_ell(hist: DataFrame) -> DataFrame:
    """One row (max_ell): the largest diversity for which no value is too frequent."""
    return with_total(hist).agg(F.min(F.call_function("div", F.col("n"), F.col("cnt"))).alias("max_ell"))


def ell_eligible(caps: DataFrame) -> DataFrame:
    """One row (ell, max_ell, eligible): whether the uniform diversity that models the policy can be had at all."""
    return ell_for(caps).crossJoin(max_ell(caps)).select("ell", "max_ell", (F.col("ell") <= F.col("max_ell")).alias("eligible"))


def classes(caps: DataFrame) -> DataFrame:
    """(cnt, cap_num, cap_den, mult): values alike in count and cap are one class; there are at most about sqrt(2 n) counts."""
    return caps.groupBy("cnt", "cap_num", "cap_den").agg(F.count(F.lit(1)).alias("mult"))
