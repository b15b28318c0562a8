"""Writing a release: two tables, each in an order of its own."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write_release(qi_side: DataFrame, sa_side: DataFrame, path: str, mode: str = "errorifexists", files: int | None = None) -> None:
    """Parquet below ``path``/qi and ``path``/sensitive; ``files`` bounds the number of files of each side.

    Buckets are never directories: there may be as many as a fifth of the rows. Files are clustered by bucket, so a read
    for some buckets skips row groups by their statistics.
    """
    for side, name in ((qi_side, "qi"), (sa_side, "sensitive")):
        out = side if files is None else side.repartitionByRange(files, "bucket")
        out.sortWithinPartitions(*out.columns if name == "sensitive" else ["bucket", *[c for c in out.columns if c != "bucket"]]).write.mode(mode).parquet(f"{path}/{name}")


def write_bucketed(side: DataFrame, table: str, buckets: int) -> None:
    """A catalog table hashed by bucket: joins of two such sides on the bucket need no exchange."""
    side.write.mode("overwrite").bucketBy(buckets, "bucket").sortBy("bucket").saveAsTable(table)
