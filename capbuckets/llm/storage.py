"""Shared intermediate storage, size estimates and column selection for the operators of this subpackage."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from capbuckets.session import ship

_OWN_ROOTS: dict[str, str] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The table ``name`` below ``sf_dir``, through Spark's own reader, so any store that Spark reads will do."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_root(spark: SparkSession) -> str:
    """The folder that all executors share: ``spark.checkpoint.dir``; one of our own only where that is unset and all run in one process."""
    ship(spark)
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    app = spark.sparkContext.applicationId
    if spark.sparkContext.master.partition("[")[0] != "local":
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if app not in _OWN_ROOTS:
        _OWN_ROOTS[app] = f"file://{tempfile.mkdtemp(prefix='capbuckets-')}"
        spark.sparkContext.setCheckpointDir(_OWN_ROOTS[app])
    return _OWN_ROOTS[app]


def shared_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder; the JVM removes it when it exits."""
    path = f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"
    jvm = spark.sparkContext._jvm
    hadoop = jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(hadoop)
    return path


def materialize(df: DataFrame, name: str) -> DataFrame:
    """``df`` written as Parquet into the shared folder and read again: lineage ends there, and Spark knows the true size."""
    spark = df.sparkSession
    path = shared_path(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def fresh(df: DataFrame, *names: str) -> list[str]:
    """Names like ``names`` that no column of ``df`` has, whatever the case of its letters."""
    taken = {c.lower() for c in df.columns}
    out = []
    for name in names:
        while name.lower() in taken:
            name = f"_{name}"
        taken.add(name.lower())
        out.append(name)
    return out


def plan_bytes(df: DataFrame, text: str) -> int:
    """Bytes of ``df``: the optimizer's figure, for a scan that of its files; where it has none, the sum of the texts."""
    known = int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    if known < 1 << 60:
        return known
    return df.agg(F.coalesce(F.sum(F.octet_length(text)), F.lit(0)).alias("n")).first().n


def shuffle_partitions(spark: SparkSession, total_bytes: int, target: int = 16 << 20, least: int | None = None) -> int:
    """Partitions for ``total_bytes``, so that one holds about ``target`` bytes; never fewer than the session's own number."""
    own = int(spark.conf.get("spark.sql.shuffle.partitions")) if least is None else least
    return min(1 << 20, max(1, own, -(-total_bytes // target)))
