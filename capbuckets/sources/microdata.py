"""Microdata: tables with one row a participant, quasi-identifying columns and one sensitive column ``v``.

The builders make such tables from the given ones; each keeps a row key, which a release drops. ``SQL`` has the same
tables as DuckDB text, for the oracles.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from capbuckets.functions.exact import div, pick, uniform


@dataclass(frozen=True)
class Microdata:
    """A microdata table: ``df`` with its row key, quasi-identifiers and sensitive column."""

    df: DataFrame
    key: tuple[str, ...]
    qi: tuple[str, ...]
    v: str = "v"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


EVENT_QI = ("event_type", "hour", "dom", "dow", "ugroup", "kdec", "quarter")
LINE_QI = ("l_returnflag", "l_linestatus", "l_linenumber", "ship_year", "ship_month", "l_discount", "l_tax")
LINE_KEY = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")


def events_microdata(spark: SparkSession, sf_dir: str, v) -> Microdata:
    e = table(spark, sf_dir, "events")
    k = F.get_json_object("props", "$.k").cast("int")
    df = e.select("event_id", "event_type", F.hour("ts").alias("hour"), F.dayofmonth("ts").alias("dom"), (F.dayofweek("ts") - 1).alias("dow"), F.pmod("user_id", F.lit(10)).cast("int").alias("ugroup"), div(k, 10).cast("int").alias("kdec"), div(F.minute("ts"), 15).cast("int").alias("quarter"), v.alias("v"))
    return Microdata(df, ("event_id",), EVENT_QI)


def band(column: str, width: float, top: int):
    """least(top, floor(column / width)) as an int."""
    return F.least(F.lit(top), F.floor(F.col(column) / width)).cast("int")


def occ50(spark, sf_dir) -> Microdata:
    """Long-tailed values of 50 bands; stands in for occupations."""
    return events_microdata(spark, sf_dir, band("value", 4.0, 49))


def edu14(spark, sf_dir) -> Microdata:
    """Long-tailed values of 14 bands; stands in for education."""
    return events_microdata(spark, sf_dir, band("value", 15.0, 13))


def k100(spark, sf_dir) -> Microdata:
    m = events_microdata(spark, sf_dir, F.get_json_object("props", "$.k").cast("int"))
    return Microdata(m.df, m.key, ("event_type", "hour", "dow"))


def corr(spark, sf_dir) -> Microdata:
    """``occ50`` with an eighth quasi-identifier that depends on the value in seven rows of ten."""
    raw = F.when(uniform("corr", F.col("event_id")) < 0.3, pick("band", 5, F.col("event_id")).cast("int")).otherwise(F.least(F.lit(4), div(F.col("v"), 10).cast("int")))
    m = occ50(spark, sf_dir)
    return Microdata(m.df.withColumn("corr_band", raw), m.key, (*m.qi, "corr_band"))


def lineitem_microdata(spark, sf_dir, v) -> Microdata:
    li = table(spark, sf_dir, "lineitem")
    df = li.select("*", F.year("l_shipdate").alias("ship_year"), F.month("l_shipdate").alias("ship_month"), v.alias("v"))
    return Microdata(df, LINE_KEY, LINE_QI)


def price50(spark, sf_dir) -> Microdata:
    return lineitem_microdata(spark, sf_dir, band("l_extendedprice", 2000.0, 49))


def qty50(spark, sf_dir) -> Microdata:
    """Nearly flat values: the control case."""
    return lineitem_microdata(spark, sf_dir, F.col("l_quantity").cast("int"))


def bigdom(spark, sf_dir) -> Microdata:
    return lineitem_microdata(spark, sf_dir, F.col("l_partkey"))


def psize50(spark, sf_dir) -> Microdata:
    return Microdata(table(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_type", F.col("p_size").alias("v")), ("p_partkey",), ("p_brand", "p_type"))


def acct(spark, sf_dir) -> Microdata:
    """Customers with their nation's region; the value is a band of the balance."""
    c, n = table(spark, sf_dir, "customer"), table(spark, sf_dir, "nation")
    df = c.join(n, c.c_nationkey == n.n_nationkey).select("c_custkey", "n_regionkey", "c_nationkey", "c_mktsegment", F.floor((F.col("c_acctbal") + 1000) / 1000).cast("int").alias("v"))
    return Microdata(df, ("c_custkey",), ("n_regionkey", "c_nationkey", "c_mktsegment"))


def lang4(spark, sf_dir) -> Microdata:
    d = table(spark, sf_dir, "documents")
    df = d.select("doc_id", "source", F.least(F.lit(9), div(F.col("n_chars"), 500)).cast("int").alias("length_band"), F.col("text").rlike("[àâäáãéèêëíîïóôöúùûüçñß]").alias("has_accent"), F.col("lang").alias("v"))
    return Microdata(df, ("doc_id",), ("source", "length_band", "has_accent"))


def toxic2(spark, sf_dir) -> Microdata:
    d, x = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return Microdata(d.select("doc_id", "lang", "source").join(x.select("doc_id", F.col("toxic").alias("v")), "doc_id"), ("doc_id",), ("lang", "source"))


def role3(spark, sf_dir) -> Microdata:
    """Roles depend on the turn, so some turns rule a role out."""
    return Microdata(table(spark, sf_dir, "conversations").select("conv_id", F.col("turn").cast("int").alias("turn"), F.col("role").alias("v")), ("conv_id", "turn", "v"), ("turn",))


def embed10(spark, sf_dir) -> Microdata:
    e = table(spark, sf_dir, "embeddings")
    signs = [(F.element_at("embedding", i + 1) > 0).cast("int").alias(f"sign{i}") for i in range(4)]
    return Microdata(e.select("vec_id", *signs, F.col("label").alias("v")), ("vec_id",), tuple(f"sign{i}" for i in range(4)))


def four_rows(spark) -> Microdata:
    """Four people in two buckets: the smallest worked release."""
    rows = [(1, "M", "54321", "Brain Tumor", 1), (2, "M", "54322", "Indigestion", 1), (3, "F", "61234", "Cancer", 2), (4, "F", "61434", "HIV", 2)]
    return Microdata(spark.createDataFrame(rows, "id int, gender string, zip string, v string, bucket bigint"), ("id",), ("gender", "zip"))


#: Rows of each of the 14 values in the 50-row worked layout.
FIFTY = [1] * 8 + [6] * 4 + [9] * 2


def fifty_rows(spark, sf_dir: str | None = None) -> Microdata:
    """The worked layout's rows; with ``sf_dir`` they are the 50 quantities that line items have, ``v`` a band of the quantity."""
    if sf_dir is not None:
        i = (F.col("l_quantity") - 1).cast("int")
        v = F.when(i < 8, i + 1).when(i < 32, F.lit(9) + F.floor((i - 8) / 6)).otherwise(F.lit(13) + F.floor((i - 32) / 9)).cast("int")
        return Microdata(table(spark, sf_dir, "lineitem").select("l_quantity").distinct().select(i.alias("id"), F.concat(F.lit("q"), i % 5).alias("q"), v.alias("v")), ("id",), ("q",))
    rows = [(i, f"q{i % 5}", v + 1) for i, v in enumerate(v for v, c in enumerate(FIFTY) for _ in range(c))]
    return Microdata(spark.createDataFrame(rows, "id int, q string, v int"), ("id",), ("q",))


def scaled_domain(m: Microdata, gamma: int, salt: str = "g0") -> Microdata:
    """Each value split at random into ``gamma`` values: v -> gamma * v + (0 .. gamma - 1)."""
    return Microdata(m.df.withColumn("v", (F.col("v") * gamma + pick(salt, gamma, *[F.col(c) for c in m.key])).cast("int")), m.key, m.qi)


MICRODATA = {f.__name__: f for f in (occ50, edu14, k100, corr, price50, qty50, bigdom, psize50, acct, lang4, toxic2, role3, embed10)}

_EVENTS = "event_id, event_type, hour(ts)::INT AS hour, day(ts)::INT AS dom, dayofweek(ts)::INT AS dow, (user_id % 10)::INT AS ugroup, ((props->>'$.k')::INT // 10)::INT AS kdec, (minute(ts) // 15)::INT AS quarter"
_LINES = "*, year(l_shipdate)::INT AS ship_year, month(l_shipdate)::INT AS ship_month"
SQL = {
    "occ50": f"SELECT {_EVENTS}, least(49, floor(value / 4.0))::INT AS v FROM events",
    "edu14": f"SELECT {_EVENTS}, least(13, floor(value / 15.0))::INT AS v FROM events",
    "k100": f"SELECT {_EVENTS}, (props->>'$.k')::INT AS v FROM events",
    "price50": f"SELECT {_LINES}, least(49, floor(l_extendedprice / 2000.0))::INT AS v FROM lineitem",
    "qty50": f"SELECT {_LINES}, l_quantity::INT AS v FROM lineitem",
    "bigdom": f"SELECT {_LINES}, l_partkey AS v FROM lineitem",
    "psize50": "SELECT p_partkey, p_brand, p_type, p_size AS v FROM part",
    "acct": "SELECT c_custkey, n_regionkey, c_nationkey, c_mktsegment, floor((c_acctbal + 1000) / 1000)::INT AS v FROM customer JOIN nation ON c_nationkey = n_nationkey",
    "lang4": "SELECT doc_id, source, least(9, n_chars // 500)::INT AS length_band, regexp_matches(text, '[àâäáãéèêëíîïóôöúùûüçñß]') AS has_accent, lang AS v FROM documents",
    "toxic2": "SELECT doc_id, lang, source, toxic AS v FROM documents JOIN labels USING (doc_id)",
    "role3": "SELECT conv_id, turn::INT AS turn, role AS v FROM conversations",
    "embed10": "SELECT vec_id, (embedding[1] > 0)::INT AS sign0, (embedding[2] > 0)::INT AS sign1, (embedding[3] > 0)::INT AS sign2, (embedding[4] > 0)::INT AS sign3, label AS v FROM embeddings",
}
