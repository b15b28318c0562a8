"""The uniform baseline: buckets of ell or ell + 1 rows with ell different values each."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from capbuckets.functions.exact import div
from capbuckets.operators.assign import deal
from capbuckets.operators.policy import histogram


def fixed_ell_layout(n: int, ell: int) -> list[tuple[int, int]]:
    """Sizes and buckets: n div ell buckets, the remainder spread evenly (one row each, unless n is very small)."""
    b = n // ell
    if not b:
        return []
    size, more = divmod(n, b)
    return [(s, c) for s, c in ((size, b - more), (size + 1, more)) if c]


def fixed_ell_loss(n: Column, ell: Column) -> Column:
    """The loss of :func:`fixed_ell_layout` as a column."""
    b = div(n, ell)
    size, more = div(n, b), F.pmod(n, b)
    return (b - more) * (size - 1) * (size - 1) + more * size * size


def fixed_ell_assign(df: DataFrame, v: str, key: Sequence[str], ell: int, salt: str, ignore_privacy: bool = False) -> DataFrame:
    """Deals the rows over n div ell buckets: no value stands twice in a bucket if none is too frequent.

    If one is, there is no such release, and this raises unless ``ignore_privacy``.
    """
    facts = histogram(df, v).agg(F.sum("cnt").alias("n"), F.max("cnt").alias("most")).first()
    buckets = (facts.n or 0) // ell
    if not buckets or facts.most > buckets and not ignore_privacy:
        raise ValueError(f"a value with {facts.most} of {facts.n} rows rules out {ell} different values a bucket")
    return deal(df, v, key, buckets, salt)
