"""Removal of boilerplate lines by the number of distinct sites they stand on.

A line that stands on t sites occurs t times at least, so plain counts by line hash come first. Lines with enough
occurrences get a HyperLogLog sketch of their sites; sketches merge by aggregation. Where the estimate is near the
threshold, sites are counted exactly. Lines on ``min_sites`` sites and more go from every document.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import storage

MIN_SITES, LG_K = 10, 12


def _lines(docs: DataFrame, key: str, text: str, site: str) -> DataFrame:
    """(id, th, site, at, a, b): every line but blank ones, named by 96 bits of hashes."""
    rows = docs.select(F.col(key).cast("bigint").alias("id"), F.col(site).cast("string").alias("site"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    named = rows.select("id", "site", "t", F.xxhash64("t").alias("th"))  # before the lines part, as it would be taken of the text for every line after that
    cut = named.select("id", "site", "th", F.posexplode(F.split("t", "\n")).alias("at", "line")).withColumn("line", F.trim("line")).where("line <> ''")
    return cut.select("id", "th", "site", "at", F.xxhash64("line").alias("a"), F.hash("line").alias("b"))


def site_sketches(occurrences: DataFrame, lg_k: int = LG_K) -> DataFrame:
    """(a, b, sketch): a sketch of the distinct sites of each line; sketches of several corpora merge by ``hll_union_agg``."""
    return occurrences.where("site IS NOT NULL").groupBy("a", "b").agg(F.hll_sketch_agg("site", lg_k).alias("sketch"))


def boilerplate(occurrences: DataFrame, min_sites: int = MIN_SITES, lg_k: int = LG_K) -> DataFrame:
    """(a, b): lines on ``min_sites`` distinct sites and more. Estimates decide outside four standard errors of the threshold, exact counts inside."""
    margin = max(1.0, 4 * 1.04 / 2 ** (lg_k / 2) * min_sites)
    guess = storage.materialize(site_sketches(occurrences, lg_k).select("a", "b", F.hll_sketch_estimate("sketch").alias("n")), "site-estimates")
    near = guess.where(F.abs(F.col("n") - min_sites) <= margin).select("a", "b")
    exact = occurrences.where("site IS NOT NULL").join(near, ["a", "b"], "left_semi").groupBy("a", "b").agg(F.count_distinct("site").alias("n"))
    return guess.where(F.col("n") > min_sites + margin).select("a", "b").unionAll(exact.where(F.col("n") >= min_sites).select("a", "b"))


def remove_spread_lines(docs: DataFrame, key: str = "doc_id", text: str = "text", site: str = "source", min_sites: int = MIN_SITES) -> DataFrame:
    """``docs`` with ``text`` put in place of by what is left of it, and ``n_lines`` and ``n_removed``.

    Lines are compared without spaces at their ends; blank lines always stay and don't count as removed. A null text counts
    as one empty line and stays null; a null site is no site. Rows of the same key and text are treated alike.
    """
    lines = _lines(docs, key, text, site)
    heavy = storage.materialize(lines.groupBy("a", "b").agg(F.count(F.lit(1)).alias("c")).where(F.col("c") >= min_sites).select("a", "b"), "frequent-lines")
    found = storage.materialize(lines.join(heavy, ["a", "b"], "left_semi"), "frequent-occurrences")
    spread = storage.materialize(boilerplate(found, min_sites), "boilerplate")
    gone = found.join(spread, ["a", "b"], "left_semi").groupBy("id", "th").agg(F.array_sort(F.collect_set("at")).alias("gone"))
    own, th_of, lost, h = storage.fresh(docs, "_id", "_th", "_gone", "_h")
    gone = gone.withColumnsRenamed({"id": own, "th": th_of, "gone": lost}).hint("merge")  # grows with the corpus: never broadcast
    th = F.xxhash64(F.coalesce(F.col(text), F.lit("")))
    joined = docs.withColumn(h, th).join(gone, F.col(key).cast("bigint").eqNullSafe(F.col(own)) & (F.col(h) == F.col(th_of)), "left")
    whole = F.coalesce(F.col(text), F.lit(""))
    # a flag a line from the gaps between those that go, so that work is in proportion to the text, however many go
    gap = lambda i: F.get(F.col(lost), i) - F.coalesce(F.get(F.col(lost), i - 1), F.lit(-1)) - 1
    flags = F.transform(F.sequence(F.lit(0), F.size(lost) - 1), lambda i: F.concat(F.array_repeat(F.lit(True), gap(i)), F.array(F.lit(False))))
    rest = lambda parts: F.array(F.array_repeat(F.lit(True), F.size(parts) - F.get(F.col(lost), F.size(lost) - 1) - 1))
    both = F.array(F.struct(F.split(whole, "\n").alias("parts")))
    both = F.transform(both, lambda x: F.struct(x["parts"].alias("parts"), F.flatten(F.concat(flags, rest(x["parts"]))).alias("stay")))
    kept = F.get(F.transform(both, lambda x: F.array_join(F.filter(x["parts"], lambda _, i: F.get(x["stay"], i)), "\n")), 0)
    n_lines = F.length(whole) - F.length(F.replace(whole, F.lit("\n"), F.lit(""))) + 1
    out = {text: F.when(F.col(lost).isNull(), F.col(text)).otherwise(kept), "n_lines": n_lines.cast("bigint"), "n_removed": F.when(F.col(lost).isNull(), 0).otherwise(F.size(lost)).cast("bigint")}
    return joined.select(*[c for c in docs.columns if c not in out], *[v.alias(c) for c, v in out.items()])
