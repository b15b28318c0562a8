"""SQL functions and a table function for sessions that work in SQL."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


class LatticeRows:
    """lattice_rows(n, s1, s2): (pos, b1, b2) of every layout with the two sizes that holds just n rows."""

    def eval(self, n: int, s1: int, s2: int) -> Iterator[tuple[int, int, int]]:
        from capbuckets.operators.lattice import lattice

        lat = lattice(n, s1, s2)
        if lat is not None:
            for i in range(lat.last + 1):
                yield (i, *lat.at(i))


def register(spark: SparkSession) -> None:
    """Temporary functions ``cap_quota(size, num, den)``, ``cap_ceil_div(a, b)`` and ``lattice_rows(n, s1, s2)``."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cap_quota(size BIGINT, num BIGINT, den BIGINT) RETURNS BIGINT RETURN least(size, size * num DIV den)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cap_ceil_div(a BIGINT, b BIGINT) RETURNS BIGINT RETURN (a + b - 1) DIV b")
    spark.udtf.register("lattice_rows", udtf(LatticeRows, returnType="pos bigint, b1 bigint, b2 bigint"))
