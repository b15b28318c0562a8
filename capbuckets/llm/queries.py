"""The queries of this subpackage: each applies one operator, with production parameters, to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontamination, jaccard_join, knn_join, line_spread, mixing, repeated_strings, token_counts, token_files, toxicity, warc
from .storage import shared_path, table


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_voronoi_knn_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 20 largest integer inner products of every twentieth vector with all others."""
    rows = table(spark, sf_dir, "embeddings").select("vec_id", knn_join.quantized("embedding").alias("v"))
    return knn_join.voronoi_top_k(rows, "vec_id", "v", F.pmod(F.col("vec_id"), F.lit(20)) == 0)


def op2_warc_transactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages written as WARC transactions, read back and put together."""
    path = shared_path(spark, "archives")
    warc.write_archives(table(spark, sf_dir, "pages"), path)
    return warc.capture_summary(warc.assemble_transactions(warc.read_records(spark, path)))


def op3_prefix_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact token counts of every whole text, from the last entry of its prefix table."""
    counts = token_counts.prefix_token_counts(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"), store=False)
    return counts.select("doc_id", "n_bytes", "n_tokens", token_counts.over_limit("n_tokens", 1024).alias("over_limit"))


def op4_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Class and number of links of every document: 0.8 or more on sets of five words."""
    return jaccard_join.jaccard_join(table(spark, sf_dir, "documents"))


def op5_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Token ids written as directly addressable codes and read back."""
    path = shared_path(spark, "token-files")
    token_files.write_token_files(table(spark, sf_dir, "documents"), path, tokenizer_path("word_bpe_49k.json"), end_id=2)
    return token_files.read_token_files(spark, path)


def op6_repeated_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents without the strings of 400 bytes that start in two places."""
    return repeated_strings.repeated_spans(table(spark, sf_dir, "documents"))


#: Levels and target weights of the mix: domains by the last character of the source, then language, then source.
MIX_WEIGHTS = {"domain": {"domain0": 4.0, "domain1": 3.0, "domain2": 2.0, "domain3": 1.0}, "lang": {"en": 5.0, "de": 2.0, "fr": 2.0, "es": 1.0}}
MIX_SEED = "mix0"


def mix_levels() -> dict:
    return {"domain": F.expr("'domain' || (ascii(right(source, 1)) % 4)"), "lang": F.col("lang"), "source": F.col("source")}


def op7_budget_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three fifths of all tokens, mixed to weights over domains, languages and sources, in two epochs at most."""
    mixed = mixing.mix(table(spark, sf_dir, "documents"), mix_levels(), MIX_WEIGHTS, F.expr("total * 3 div 5"), MIX_SEED, max_epochs=2)
    return mixed.select("doc_id", F.col("_epoch").alias("epoch"), "lang", "source", mixing.token_count(F.col("text")).alias("tokens"))


def op8_line_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents without the lines that stand on ten sites and more."""
    kept = line_spread.remove_spread_lines(table(spark, sf_dir, "documents"))
    return kept.select("doc_id", "n_lines", "n_removed", F.octet_length("text").cast("bigint").alias("kept_bytes"), F.sha2("text", 256).alias("kept_sha256"))


def op9_benchmark_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Benchmark items of which documents hold a similar window, for every document."""
    docs = table(spark, sf_dir, "documents")
    pairs = decontamination.contaminated(docs, table(spark, sf_dir, "benchmark"))
    held = pairs.groupBy("doc_id").agg(F.array_sort(F.collect_set("item_id")).alias("item_ids"))
    joined = docs.select("doc_id").join(held.withColumnRenamed("doc_id", "_id"), F.col("doc_id").eqNullSafe(F.col("_id")), "left")
    return joined.select("doc_id", F.col("_id").isNotNull().alias("contaminated"), F.coalesce("item_ids", F.array().cast("array<bigint>")).alias("item_ids"))


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity score of every whole text, learned from the labelled rows whose fold is not 0."""
    docs = table(spark, sf_dir, "documents")
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    scored = toxicity.score(docs, model, keep=["doc_id"])
    return scored.select("doc_id", (toxicity.fold(F.col("doc_id")) == 0).alias("held_out"), "score", "predicted")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_voronoi_knn_join, op2_warc_transactions, op3_prefix_token_counts, op4_jaccard_join, op5_token_files, op6_repeated_strings, op7_budget_mix, op8_line_spread, op9_benchmark_windows, op10_toxicity)
}
ORACLES: dict[str, str] = {
    "op1_voronoi_knn_join": """
        WITH v AS (SELECT vec_id, [floor(64 * x::DOUBLE) FOR x IN embedding] AS e FROM embeddings
                   WHERE embedding IS NOT NULL AND len([x FOR x IN embedding IF x IS NULL OR NOT isfinite(x)]) = 0),
        s AS (SELECT q.vec_id AS query_id, c.vec_id, list_dot_product(q.e, c.e)::BIGINT AS score
              FROM v q JOIN v c ON q.vec_id % 20 = 0 AND q.vec_id <> c.vec_id),
        r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank FROM s)
        SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 20""",
    "op2_warc_transactions": """
        WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
        d AS (SELECT page_id, strlen(h)::BIGINT AS payload_bytes, sha256(h) AS payload_digest FROM p),
        f AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS first FROM d)
        SELECT page_id, payload_bytes, payload_digest,
               CASE WHEN payload_bytes >= 100 AND page_id <> first THEN 'revisit' ELSE 'response' END AS record_type,
               CASE WHEN payload_bytes >= 100 AND page_id <> first THEN first END AS refers_to
        FROM f""",
    "op7_budget_mix": """
        WITH d AS (SELECT doc_id, lang, source, coalesce('domain' || (ascii(right(source, 1)) % 4), '(none)') AS l0, coalesce(lang, '(none)') AS l1,
                          coalesce(source, '(none)') AS l2, len(regexp_extract_all(coalesce(text, ''), '\\S+'))::BIGINT AS tokens FROM documents),
        leaf AS (SELECT l0, l1, l2, sum(tokens)::BIGINT AS tokens, 2.0::DOUBLE * sum(tokens) AS room FROM d GROUP BY l0, l1, l2),
        b AS (SELECT (sum(tokens)::BIGINT * 3 // 5)::DOUBLE AS budget FROM leaf),
        n0 AS (SELECT l0, sum(room) AS room, CASE l0 WHEN 'domain0' THEN 4.0 WHEN 'domain1' THEN 3.0 WHEN 'domain2' THEN 2.0 ELSE 1.0 END::DOUBLE AS w, (SELECT budget FROM b) AS budget FROM leaf GROUP BY l0),
        a0 AS (SELECT *, coalesce(sum(room) OVER p, 0) + room / w * (sum(w) OVER () - coalesce(sum(w) OVER p, 0)) <= budget AS fills FROM n0
               WINDOW p AS (ORDER BY room / w, l0 ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        s0 AS (SELECT l0, CASE WHEN fills THEN room ELSE (budget - coalesce(sum(room) FILTER (fills) OVER (), 0)) * w / sum(w) FILTER (NOT fills) OVER () END AS budget FROM a0),
        n1 AS (SELECT l0, l1, sum(room) AS room, CASE l1 WHEN 'en' THEN 5.0 WHEN 'de' THEN 2.0 WHEN 'fr' THEN 2.0 ELSE 1.0 END::DOUBLE AS w, any_value(s0.budget) AS budget FROM leaf JOIN s0 USING (l0) GROUP BY l0, l1),
        a1 AS (SELECT *, coalesce(sum(room) OVER p, 0) + room / w * (sum(w) OVER (PARTITION BY l0) - coalesce(sum(w) OVER p, 0)) <= budget AS fills FROM n1
               WINDOW p AS (PARTITION BY l0 ORDER BY room / w, l1 ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        s1 AS (SELECT l0, l1, CASE WHEN fills THEN room ELSE (budget - coalesce(sum(room) FILTER (fills) OVER q, 0)) * w / sum(w) FILTER (NOT fills) OVER q END AS budget FROM a1 WINDOW q AS (PARTITION BY l0)),
        n2 AS (SELECT l0, l1, l2, tokens, room, 1.0::DOUBLE AS w, s1.budget FROM leaf JOIN s1 USING (l0, l1)),
        a2 AS (SELECT *, coalesce(sum(room) OVER p, 0) + room / w * (sum(w) OVER (PARTITION BY l0, l1) - coalesce(sum(w) OVER p, 0)) <= budget AS fills FROM n2
               WINDOW p AS (PARTITION BY l0, l1 ORDER BY room / w, l2 ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        s2 AS (SELECT l0, l1, l2, tokens, floor(CASE WHEN fills THEN room ELSE (budget - coalesce(sum(room) FILTER (fills) OVER q, 0)) * w / sum(w) FILTER (NOT fills) OVER q END + 1e-6)::BIGINT AS quota
               FROM a2 WINDOW q AS (PARTITION BY l0, l1)),
        q AS (SELECT l0, l1, l2, quota // tokens AS whole, quota - quota // tokens * tokens AS rest FROM s2),
        o AS (SELECT d.*, whole, rest, md5('mix0:' || whole || ':' || doc_id) AS h FROM d JOIN q USING (l0, l1, l2)),
        c AS (SELECT *, sum(tokens) OVER (PARTITION BY l0, l1, l2 ORDER BY h) AS cum FROM o),
        t AS (SELECT *, whole + CASE WHEN cum <= rest AND rest > 0 THEN 1 ELSE 0 END AS times FROM c)
        SELECT doc_id, e::INTEGER AS epoch, lang, source, tokens FROM t, generate_series(0, 1) g(e) WHERE e < times""",
    "op8_line_spread": """
        WITH l AS (SELECT doc_id, source, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos FROM documents),
        b AS (SELECT trim(line) AS t FROM l WHERE trim(line) <> '' GROUP BY trim(line) HAVING count(DISTINCT source) >= 10),
        k AS (SELECT doc_id, count(*)::BIGINT AS n_lines, count(b.t)::BIGINT AS n_removed, string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE b.t IS NULL) AS kept
              FROM l LEFT JOIN b ON trim(l.line) = b.t GROUP BY doc_id)
        SELECT doc_id, n_lines, n_removed, strlen(coalesce(kept, ''))::BIGINT AS kept_bytes, sha256(coalesce(kept, '')) AS kept_sha256 FROM k""",
}
