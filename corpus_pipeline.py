"""A training corpus from ``documents``: toxic texts out, one of each near-duplicate class, no benchmark passages, mixed
to target weights, written as token ids.

Each stage takes (spark, docs, sf_dir); all but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from capbuckets.llm import decontamination, jaccard_join, mixing, queries, storage, token_files, toxicity


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose toxicity score is under one half; the model is fitted on the labelled rows among ``docs``."""
    model = toxicity.fit(docs, storage.table(spark, sf_dir, "labels"))
    names = tuple(storage.fresh(docs, "_score", "_predicted"))
    return toxicity.score(docs, model, names=names).where(F.col(names[1]) == 0).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of the Jaccard join: that of the smallest doc_id."""
    return jaccard_join.one_of_each_class(docs)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that hold no window similar to a benchmark item."""
    return decontamination.clean_documents(docs, storage.table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Four fifths of the tokens, mixed to the target weights, no document twice."""
    return mixing.mix(docs, queries.mix_levels(), queries.MIX_WEIGHTS, F.expr("total * 4 div 5"), queries.MIX_SEED, max_epochs=1, epoch=storage.fresh(docs, "_epoch")[0]).select(*docs.columns)


def write_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token files of what is left, read back: place, number and checksum of each document's ids."""
    path = storage.shared_path(spark, "corpus")
    token_files.write_token_files(docs, path, queries.tokenizer_path("word_bpe_49k.json"), end_id=2)
    return token_files.read_token_files(spark, path)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_benchmark),
    ("mixing", mix_sources),
    ("token_files", write_tokens),
]

#: Tokenizers and MinHash have no SQL form; tests hold the stages against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in a row, each over what the one before has written."""
    docs = storage.table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = storage.materialize(stage(spark, docs, sf_dir), name)
    return docs
