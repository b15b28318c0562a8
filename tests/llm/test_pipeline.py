"""The pipeline's stages, each against what it should keep."""

import sys
import zlib
from pathlib import Path

import numpy as np

sys.path.insert(0, str(Path(__file__).parent))
import helpers as H
from tokenizers import Tokenizer

import corpus_pipeline as P
from capbuckets.llm import queries, storage, toxicity


def test_stages_in_a_row(spark, sf):
    docs = storage.table(spark, sf, "documents")
    out = []
    for name, stage in P.STAGES:
        docs = storage.materialize(stage(spark, docs, sf), f"test-{name}")
        out.append(docs)
    toxic, near, clean, mixed, tokens = out
    first = storage.table(spark, sf, "documents")
    assert all(x.columns == first.columns for x in out[:-1])
    model = toxicity.fit(first, storage.table(spark, sf, "labels"))
    assert H.rows(toxic.select("doc_id")) == H.rows(toxicity.score(first, model).where("score < 0.5").select("doc_id"))
    had = [(r.doc_id, r.text) for r in toxic.collect()]
    assert {r.doc_id for r in near.collect()} == {c for _, c, _ in H.jaccard_classes(had)}
    had = [(r.doc_id, r.text) for r in near.collect()]
    bad = {k for k, _ in H.contaminated(had, [(r.item_id, r.text) for r in storage.table(spark, sf, "benchmark").collect()])}
    assert {r.doc_id for r in clean.collect()} == {k for k, _ in had} - bad
    size = lambda df: sum(len((r.text or "").split()) for r in df.collect())
    assert {r.doc_id for r in mixed.collect()} <= {r.doc_id for r in clean.collect()} and size(mixed) <= 0.8 * size(clean)
    lib, place = Tokenizer.from_file(queries.tokenizer_path("word_bpe_49k.json")), 0
    got = {r.doc_id: r for r in tokens.collect()}
    for r in sorted(mixed.collect(), key=lambda r: r.doc_id):
        ids = lib.encode(r.text or "", add_special_tokens=False).ids + [2]
        assert (got[r.doc_id].start, got[r.doc_id].n_tokens, got[r.doc_id].ids_crc32) == (place, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        place += len(ids)
    assert len(got) == mixed.count()


def test_awkward_corpus(spark, sf):
    """Nulls, repeats and clashing columns pass through every stage."""
    more = ["score", "predicted", "_epoch", "_score", "_id", "tokens", "k", "t", "class_id", "_level0"]
    data = [(1, None, None, None, None), (2, "", "en", "s1", 0), (3, "a b c d e f g", "en", "s1", 13), (3, "a b c d e f g", "en", "s1", 13), (None, "z y x w v u t", None, "s2", 13), (None, None, None, None, None)]
    docs = spark.createDataFrame(data, H.DOC)
    for c in more:
        docs = docs.withColumn(c, docs["n_chars"] + 1)
    names = docs.columns
    for name, stage in P.STAGES:
        docs = storage.materialize(stage(spark, docs, sf), f"odd-{name}")
        if name != "token_files":
            assert docs.columns == names
    assert docs.count() > 0


def test_empty_corpus(spark, sf):
    docs = storage.table(spark, sf, "documents").limit(0)
    for name, stage in P.STAGES:
        docs = storage.materialize(stage(spark, docs, sf), f"none-{name}")
        assert docs.count() == 0
