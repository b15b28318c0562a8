"""Each operator against the library or brute force, and on awkward rows."""

import random
import sys
import time
import zlib
from pathlib import Path

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).parent))
import helpers as H

from capbuckets.llm import decontamination, jaccard_join, knn_join, line_spread, mixing, queries, repeated_strings, shingles, storage, token_counts, token_files, toxicity, warc

BYTE_BPE, WORD_BPE = queries.tokenizer_path("byte_bpe_50k.json"), queries.tokenizer_path("word_bpe_49k.json")
rng = random.Random(5)
WORDS = ["".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 7))) for _ in range(400)]


def prose(n, seed):
    r = random.Random(seed)
    return " ".join(r.choice(WORDS) for _ in range(n))


def frame(spark, data, schema="doc_id bigint, text string"):
    return spark.createDataFrame(data, schema)


@pytest.fixture(scope="module")
def awkward(spark):
    """Nulls, empty, short and long texts, repeated rows and columns whose names clash with inner ones."""
    long = prose(30_000, 1)
    data = [(1, None), (2, ""), (3, "   \n\t "), (4, "one two"), (5, long), (6, long), (7, prose(200, 2)), (7, prose(200, 2)), (None, prose(200, 2)), (None, None), (8, "ünï çødé 中文 \U0001f600 <|endoftext|> 'tis"), (9, prose(200, 2) + " tail")]
    return frame(spark, data).select("*", F.lit("en").alias("lang"), F.when(F.col("doc_id") > 3, "src1").alias("source"), F.lit(0).cast("bigint").alias("n_chars"), *[F.lit(1).alias(c) for c in ("id", "k", "t", "_id", "_th", "_gone", "tokens", "score", "_times", "block", "class_id")])


# ---------------------------------------------------------------- 1


def brute_top(data, k):
    out = []
    for q, v in data:
        if q is None or v is None or q % 3:
            continue
        scored = sorted(((-sum(a * b for a, b in zip(v, w, strict=False)), i) for i, w in data if i is not None and w is not None and i != q))[:k]
        out += [(q, r + 1, i, -s) for r, (s, i) in enumerate(scored)]
    return sorted(out, key=str)


@pytest.mark.parametrize("n", [0, 1, 7, 400])
def test_top_k_is_exact(spark, n):
    r = np.random.default_rng(n)
    data = [(i, r.integers(-60, 60, 8).tolist()) for i in range(n)]
    data += [(n + i, [5] * 8) for i in range(n // 3)]  # ties and a hot vector
    if n > 5:
        data += [(None, [1] * 8), (n * 2, None), (3, [7] * 8), (n * 2 + 1, [9] * 3)]
    df = frame(spark, data, "vec_id bigint, v array<bigint>")
    got = H.rows(knn_join.voronoi_top_k(df, "vec_id", "v", F.pmod("vec_id", F.lit(3)) == 0, 5))
    assert got == brute_top(data, 5)


def test_rows_of_one_query_key_have_their_own_answers(spark, monkeypatch):
    """Keys that very many rows share, with blocks and shares small enough for several of each."""
    monkeypatch.setattr(knn_join, "BLOCK", 16)
    r = np.random.default_rng(9)
    data = [(int(i % 90 if i % 3 else 3), r.integers(-40, 40, 6).tolist()) for i in range(600)]
    got = H.rows(knn_join.voronoi_top_k(frame(spark, data, "vec_id bigint, v array<bigint>"), "vec_id", "v", F.pmod("vec_id", F.lit(3)) == 0, 7))
    assert got == brute_top(data, 7)


def test_quantized(spark):
    df = frame(spark, [(1, [0.5, -0.01]), (2, [1.0, None]), (3, None), (4, [float("nan"), 1.0]), (5, [float("inf"), 1.0])], "vec_id bigint, e array<float>")
    assert [r[1] for r in H.rows(df.select("vec_id", knn_join.quantized("e")))] == [[32, -1], None, None, None, None]


# ---------------------------------------------------------------- 2


def test_archives_round_trip(spark):
    big = "x" * 300 + "\r\n\r\nWARC/1.1\r\nContent-Length: 5\r\n\r\n é"
    data = [(3, "http://a/\r\nEvil: 1", big), (1, None, big), (2, "http://b", None), (4, "http://c", "small"), (5, "http://c", "small"), (None, "http://d", big), (6, "http://e", "")]
    pages = frame(spark, data, "page_id bigint, url string, html string")
    path = storage.shared_path(spark, "warc-test")
    warc.write_archives(pages, path)
    records = warc.read_records(spark, path, blocks=True)
    assert records.count() == 3 * len(data)
    assembled = warc.assemble_transactions(records)
    assert assembled.where("request IS NULL OR response IS NULL OR metadata IS NULL").count() == 0
    got = {r.page_id: r for r in warc.capture_summary(assembled).collect()}
    import hashlib

    digest = lambda s: hashlib.sha256((s or "").encode()).hexdigest()
    for k, _, html in data:
        assert (got[k].payload_bytes, got[k].payload_digest) == (len((html or "").encode()), digest(html))
    assert {k: (r.record_type, r.refers_to) for k, r in got.items()} == {1: ("response", None), 2: ("response", None), 3: ("revisit", 1), 4: ("response", None), 5: ("response", None), None: ("revisit", 1), 6: ("response", None)}
    held = records.where("record_type = 'response'").select("block").collect()
    assert any(big.encode() in bytes(r.block) for r in held)


def test_every_revisit_finds_its_record(spark, sf):
    """WARC-Refers-To names a response record of the same payload digest, and each record is a member that can be read alone."""
    pages = storage.table(spark, sf, "pages")
    pages = pages.unionByName(pages.limit(9)).unionByName(pages.withColumn("page_id", F.col("page_id") + 10_000)).unionByName(pages.limit(5).withColumn("page_id", F.lit(None).cast("bigint")))
    path = storage.shared_path(spark, "warc-refers")
    warc.write_archives(pages, path)
    records = warc.read_records(spark, path).select("record_id", "record_type", "refers_to", "concurrent_to", "digest").collect()
    named = {r.record_id: r for r in records}
    assert len(named) == len(records) == 3 * pages.count()
    revisits = [r for r in records if r.record_type == "revisit"]
    assert revisits and all(named[r.refers_to].record_type == "response" and named[r.refers_to].digest == r.digest for r in revisits)
    assert all(r.concurrent_to in named for r in records if r.record_type in ("request", "metadata"))
    archive = bytes(spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).first().content)
    members = [m for m in warc.members_of(archive) if m]
    assert len(members) >= 3 and all(len(list(warc.records_of(m))) == 1 and m.startswith(b"WARC/1.1") for m in members)
    import gzip

    assert gzip.decompress(archive) == b"".join(members)


def test_large_payloads_are_cut_into_files_by_bytes(spark, monkeypatch):
    monkeypatch.setattr(warc, "CHUNK_BYTES", 1 << 16)
    monkeypatch.setattr(warc, "CHUNKS_PER_FILE", 2)
    r = random.Random(3)
    data = [(i, "http://a", "".join(r.choice("abcdefghijklmnopqrstuvwxyz0123456789") for _ in range(3_000_000 if i == 7 else 50_000))) for i in range(20)]
    path = storage.shared_path(spark, "warc-large")
    warc.write_archives(frame(spark, data, "page_id bigint, url string, html string").coalesce(1), path)
    sizes = [r.length for r in spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("length").collect()]
    assert len(sizes) > 5 and sum(x > 2 * (1 << 16) + 100 for x in sizes) == 1
    got = {r.page_id: r.payload_bytes for r in warc.capture_summary(warc.assemble_transactions(warc.read_records(spark, path))).collect()}
    assert got == {i: len(h) for i, _, h in data}


def test_plain_archives_and_records_over_several_members():
    import gzip

    record = b"WARC/1.1\r\nWARC-Type: resource\r\nContent-Length: 6\r\n\r\nab\r\ncd\r\n\r\n"
    for data in (record * 3, gzip.compress(record * 3), gzip.compress(record[:20]) + gzip.compress(record[20:] + record * 2), b""):
        assert [b for _, b in warc.records_of(data)] == [b"ab\r\ncd"] * (3 if data else 0)
    for data in (record[:-4], gzip.compress(record)[:-6], record + b"junk"):
        with pytest.raises(ValueError):
            list(warc.records_of(data))


def test_assembly_of_parts_in_any_order(spark):
    none = [None] * 4
    rows = [("m", "metadata", "c", *none[:3], 0, *none[:3]), ("c", "response", *none, 0, None, "aa", 2), ("lone", "resource", *none, 0, *none[:3])]
    got = {r.capture_id: r for r in warc.assemble_transactions(frame(spark, rows, warc.RECORD)).collect()}
    assert got["c"].metadata.record_id == "m" and got["c"].response.payload_bytes == 2 and got["c"].request is None
    assert got["lone"].response is None


def test_empty_pages(spark):
    path = storage.shared_path(spark, "warc-none")
    warc.write_archives(frame(spark, [], "page_id bigint, url string, html string"), path)
    assert warc.capture_summary(warc.assemble_transactions(warc.read_records(spark, path))).count() == 0


# ---------------------------------------------------------------- 3


@pytest.fixture(scope="module")
def counter():
    return token_counts.PrefixCounter(BYTE_BPE)


@settings(max_examples=150, deadline=None)
@given(st.one_of(st.text(max_size=25), st.text(alphabet=" \n\tab'slvert1é!<|>", max_size=40), st.just("a<|endoftext|> b<|endoftext|>"), st.just("we'll they're it's 'x  \n\n y")))
def test_every_prefix_count(text):
    c = token_counts.counter_for(BYTE_BPE)
    want = [len(c.library.encode(text[:i], add_special_tokens=False).ids) for i in range(len(text) + 1)]
    steps = c.prefix_steps_of([text])[0]
    assert token_counts.counts_from_steps(steps).tolist() == want
    for budget in (0, 1, 3):
        assert want[token_counts.longest_prefix_within(steps, budget)] <= budget


def test_counts_of_awkward_rows(spark, awkward, counter):
    got = token_counts.prefix_token_counts(awkward, BYTE_BPE).select("doc_id", "n_bytes", "n_tokens", "prefix_steps")
    text = [(r.doc_id, r.text or "") for r in awkward.collect()]
    want = sorted(((k, len(t.encode()), len(counter.library.encode(t, add_special_tokens=False).ids)) for k, t in text), key=str)
    assert H.rows(got.drop("prefix_steps")) == want
    assert token_counts.prefix_token_counts(awkward.limit(0), BYTE_BPE).count() == 0


# ---------------------------------------------------------------- 4


def test_joined_classes(spark):
    base = prose(120, 3)
    near = [base.replace(base.split()[40 + i], f"edit{i}", 1) for i in range(4)]
    data = [(i, prose(80, 100 + i)) for i in range(40)] + [(50, base), (51, base), *[(60 + i, t) for i, t in enumerate(near)], (70, None), (71, ""), (72, "a b"), (73, "a b"), (73, "a b"), (74, "A  B"), (None, base), (80, prose(9_000, 8)), (81, prose(9_000, 8) + " x")]
    got = H.rows(jaccard_join.jaccard_join(frame(spark, data)).select("doc_id", "class_id", "n_links"))
    want = sorted(H.jaccard_classes(data), key=str)
    assert got == want


def test_large_near_copy_group_is_cut_into_blocks(spark, monkeypatch):
    monkeypatch.setattr(jaccard_join, "BLOCK_MEMBERS", 8)
    base = prose(150, 4).split()
    data = []
    for i in range(40):
        w = list(base)
        w[i * 3] = f"e{i}"
        data.append((i, " ".join(w)))
    got = H.rows(jaccard_join.jaccard_join(frame(spark, data)).select("doc_id", "class_id", "n_links"))
    assert got == sorted(H.jaccard_classes(data), key=str)


def test_join_keeps_awkward_rows(spark, awkward):
    got = jaccard_join.jaccard_join(awkward)
    assert got.count() == awkward.count() and jaccard_join.jaccard_join(awkward.limit(0)).count() == 0
    kept = jaccard_join.one_of_each_class(awkward)
    assert kept.columns == awkward.columns and {r.doc_id for r in kept.collect()} >= {4, 5, 7, 8}


def test_chosen_bands_reach_the_recall():
    for recall in (0.99, 0.999, 0.9995):
        b, r = shingles.choose_bands(0.8, recall)
        assert 1 - (1 - 0.8**r) ** b >= recall and b * r <= 128


def test_components_of_chains(spark):
    n = 40
    edges = frame(spark, [(i, i + 1) for i in range(n)] + [(100, 101)], "a bigint, b bigint")
    got = {r.node: r.label for r in jaccard_join.components(edges).collect()}
    assert got == {i: 0 for i in range(n + 1)} | {100: 100, 101: 100}


def test_components_of_long_shuffled_chains(spark, monkeypatch):
    n, written, write = 3000, [], storage.materialize
    monkeypatch.setattr(storage, "materialize", lambda df, name: written.append(name) or write(df, name))
    name = list(range(n))
    random.Random(7).shuffle(name)
    edges = frame(spark, [(name[i], name[i + 1]) for i in range(n - 1)] + [(n + 1, n)], "a bigint, b bigint")
    got = {r.node: r.label for r in jaccard_join.components(edges).collect()}
    assert got == dict.fromkeys(range(n), 0) | {n: n, n + 1: n}
    assert written.count("labels") < 30


# ---------------------------------------------------------------- 5


@given(st.lists(st.integers(0, 2**32 - 1), max_size=1200))
def test_codes_give_back_every_id(ids):
    levels = token_files.encode_levels(np.array(ids, np.uint32))
    assert token_files.decode_levels(levels).tolist() == ids
    assert [token_files.token_at(levels, i) for i in range(0, len(ids), 7)] == ids[::7]


def test_files_hold_the_library_ids(spark, awkward):
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(WORD_BPE)
    path = storage.shared_path(spark, "tokens-test")
    token_files.write_token_files(awkward, path, WORD_BPE, 2)
    got = token_files.read_token_files(spark, path, ids=True).collect()
    data = [(r.doc_id, lib.encode(r.text or "", add_special_tokens=False).ids + [2]) for r in awkward.collect()]
    assert sorted((str(r.doc_id), r.ids) for r in got) == sorted((str(k), ids) for k, ids in data)
    place = 0
    for r in sorted(got, key=lambda r: r.start):
        assert (r.start, r.n_tokens, r.ids_crc32) == (place, len(r.ids), zlib.crc32(np.array(r.ids, "<u4").tobytes()))
        place += r.n_tokens
    keys = [r.doc_id for r in sorted(got, key=lambda r: r.start)]
    assert keys == sorted(keys, key=lambda k: (k is not None, k or 0))
    empty = storage.shared_path(spark, "tokens-none")
    token_files.write_token_files(awkward.limit(0), empty, WORD_BPE, 2)
    assert token_files.read_token_files(spark, empty).count() == 0


@settings(max_examples=60, deadline=None)
@given(st.lists(st.text(alphabet=st.characters(max_codepoint=0x2FF), max_size=30), max_size=6))
def test_word_encoder_is_the_library(texts):
    e = token_files.encoder_for(WORD_BPE)
    ids, sizes = e.encode(texts)
    want = [e.library.encode(t, add_special_tokens=False).ids for t in texts]
    assert ids.tolist() == [i for w in want for i in w] and sizes.tolist() == [len(w) for w in want]


# ---------------------------------------------------------------- 6


def test_cover_meets_every_shift():
    v, d = repeated_strings.difference_cover()
    assert all(any((i + s) % v in set(d.tolist()) and (j + s) % v in set(d.tolist()) for s in range(v)) for i in range(0, v, 7) for j in range(v))


def test_removed_strings(spark, monkeypatch):
    monkeypatch.setattr(repeated_strings, "BLOCK_BYTES", 4096)
    part, long = prose(120, 5), prose(700, 6)
    data = [(1, prose(30, 7) + part + prose(30, 8)), (2, part + prose(100, 9)), (3, long), (4, long), (5, None), (6, ""), (7, part[:399]), (8, part[:401] + "é"), (9, prose(20, 10) + part[100:505] + part[100:505]), (9, "x" * 1000), (None, "ab" * 300), (10, prose(50, 11)), (11, prose(50, 11))]
    got = repeated_strings.repeated_spans(frame(spark, data))
    assert H.rows(got.select(got.columns[:5])) == sorted(H.removed_strings(data), key=str)
    assert got.where("kept_bytes <> n_bytes - n_removed OR changed <> (n_removed > 0)").count() == 0
    assert not [t for t in spark.catalog.listTables() if t.name.startswith("texts_")]


def test_strings_of_one_name_are_told_apart(spark, monkeypatch):
    """Strings that no base tells apart modulo 2^64, in one block and in several: bytes are compared, and other names taken."""
    a, b = doubled(11)
    used, rounds = [], repeated_strings._rounds
    monkeypatch.setattr(repeated_strings, "_rounds", lambda keyed, length, buckets, kind, store: used.append(kind) or rounds(keyed, length, buckets, kind, store))
    data = [(1, a), (2, b), (3, "start " + a[:1500]), (4, prose(100, 1)), (5, a + b), (6, "x" + b[:700])]
    for size in (1 << 20, 4096):
        monkeypatch.setattr(repeated_strings, "BLOCK_BYTES", size)
        got = repeated_strings.repeated_spans(frame(spark, data), 1024)
        assert H.rows(got.select(got.columns[:5])) == sorted(H.removed_strings(data, 1024), key=str)
    assert used == [0, 1, 0, 1]


def test_names_of_all_kinds():
    texts = [prose(60, 2).encode(), b"", b"ab" * 40, prose(60, 2).encode()[:90]]
    for kind in (0, 1, 2):
        names = repeated_strings.Names(texts, kind)
        at = names.all_of(20)
        strings = [bytes(names.data[p : p + 20]) for p in at]
        assert len(at) == sum(max(0, len(t) - 19) for t in texts)
        assert len(set(names.of(at, 20).tolist())) == len(set(strings)) == len(set(zip(strings, names.of(at, 20).tolist(), strict=True)))
        assert repeated_strings.differing(names.data, at, names.data, at, 20) == 0
        assert repeated_strings.differing(names.data, at[:-1], names.data, at[1:], 20) > 0


@pytest.mark.parametrize("block", [8 << 20, 1 << 16])
def test_removed_strings_of_a_table(spark, sf, monkeypatch, block):
    monkeypatch.setattr(repeated_strings, "BLOCK_BYTES", block)
    docs = storage.table(spark, sf, "documents")
    want = H.removed_strings([(r.doc_id, r.text) for r in docs.collect()])
    got = repeated_strings.repeated_spans(docs)
    assert H.rows(got.select(got.columns[:5])) == sorted(want, key=str)
    assert repeated_strings.repeated_spans(docs.limit(0)).count() == 0


# ---------------------------------------------------------------- 7


def test_shortage_goes_to_siblings_first(spark):
    leaves = frame(spark, [("a", "x", 10, 2000), ("a", "y", 1000, 2000), ("b", "x", 990, 2000)], "_level0 string, _level1 string, tokens bigint, total bigint")
    got = {(r._level0, r._level1): r.quota for r in mixing.leaf_budgets(leaves, ["_level0", "_level1"], {"_level0": {"a": 1.0, "b": 1.0}}, F.lit(1000), 1).collect()}
    assert got == {("a", "x"): 10, ("a", "y"): 490, ("b", "x"): 500}
    more = {(r._level0, r._level1): r.quota for r in mixing.leaf_budgets(leaves, ["_level0", "_level1"], {"_level0": {"a": 1.0, "b": 3.0}}, F.lit(1900), 1).collect()}
    assert more == {("a", "x"): 10, ("a", "y"): 900, ("b", "x"): 990}


def test_shards_do_not_change_the_mix(spark, monkeypatch):
    docs = frame(spark, [(i, prose(1 + i % 7, i), f"src{i % 3 % 2}") for i in range(300)], "doc_id bigint, text string, source string")
    took = []
    for tokens in (10**9, 100, 3):
        monkeypatch.setattr(mixing, "SHARD_TOKENS", tokens)
        took.append(H.rows(mixing.mix(docs, {"source": F.col("source")}, {"source": {"src0": 2.0}}, F.expr("total * 2 div 3"), "s", 1)))
    assert took[0] == took[1] == took[2] and 100 < len(took[0]) < 300


def test_mix_takes_seeded_prefixes(spark, awkward):
    data = [(i, prose(10 + i % 5, i), "en" if i % 3 else None, f"src{i % 4}") for i in range(200)]
    docs = frame(spark, data, "doc_id bigint, text string, lang string, source string")
    levels = {"lang": F.col("lang"), "source": F.col("source")}
    mixed = mixing.mix(docs, levels, {}, F.expr("total div 2"), "s", 1)
    assert mixed.count() == mixed.select("doc_id").distinct().count()
    total = sum(len(t.split()) for _, t, _, _ in data)
    taken = sum(len(r.text.split()) for r in mixed.collect())
    assert total / 2 - 15 * 8 <= taken <= total / 2
    again = mixing.mix(docs.repartition(5), levels, {}, F.expr("total div 2"), "s", 1)
    assert H.rows(mixed) == H.rows(again)
    twice = mixing.mix(docs, levels, {}, F.expr("total * 2"), "s", 2)
    assert twice.count() == 400 and twice.groupBy("doc_id").count().where("count <> 2").count() == 0
    odd = mixing.mix(awkward, levels, {}, F.col("total"), "s", 1)
    assert odd.count() == awkward.count() and odd.columns == [*awkward.columns, "_epoch"]
    assert mixing.mix(awkward.limit(0), levels, {}, F.col("total"), "s", 1).count() == 0


def test_native_plans_have_no_python(spark, sf):
    docs = storage.table(spark, sf, "documents")
    for df in (mixing.mix(docs, queries.mix_levels(), {}, F.col("total"), "s", 1), decontamination.contaminated(docs, storage.table(spark, sf, "benchmark"))):
        text = df._jdf.queryExecution().executedPlan().toString()
        assert "Python" not in text and "Arrow" not in text and "Pandas" not in text


# ---------------------------------------------------------------- 8


def test_spread_lines(spark, awkward):
    data = [(i, f"unique {i}\n  shared line \n\nend {i}", f"site{i % 12}") for i in range(24)] + [(100, "shared line", None), (101, None, "site0"), (102, "shared line\nshared line", "site1"), (102, "other", "site1")]
    data += [(200 + i, "only few sites", f"site{i % 9}") for i in range(30)]
    got = {(r.doc_id, r.n_lines): r for r in line_spread.remove_spread_lines(frame(spark, data, "doc_id bigint, text string, source string")).collect()}
    assert got[0, 4].text == "unique 0\n\nend 0" and got[0, 4].n_removed == 1
    assert got[100, 1].text == "" and got[101, 1].text is None and got[102, 2].n_removed == 2 and got[102, 1].text == "other"
    assert got[200, 1].text == "only few sites"
    out = line_spread.remove_spread_lines(awkward)
    assert out.count() == awkward.count() and line_spread.remove_spread_lines(awkward.limit(0)).count() == 0


def test_runs_of_lines_that_go(spark):
    """Lines that go at either end, side by side, all of them, or in a text of very many lines."""
    r = random.Random(4)
    common = [f"common {i}" for i in range(5)]
    data = [(i, "\n".join(common), f"site{i}") for i in range(12)]
    texts = {100 + i: [r.choice([*common, f"own {r.random()}", "", "  "]) for _ in range(r.randint(1, 12))] for i in range(60)}
    texts[500] = [common[i % 5] for i in range(100_000)] + ["kept"]
    data += [(k, "\n".join(t), "site0") for k, t in texts.items()]
    began = time.monotonic()
    got = {x.doc_id: x for x in line_spread.remove_spread_lines(frame(spark, data, "doc_id bigint, text string, source string")).collect()}
    assert time.monotonic() - began < 60
    for k, t in texts.items():
        left = [x for x in t if x not in common]
        assert (got[k].text, got[k].n_lines, got[k].n_removed) == ("\n".join(left), len(t), len(t) - len(left))
    assert all(got[i].text == "" and got[i].n_removed == 5 for i in range(12))


def test_sketches_merge(spark):
    occ = frame(spark, [(1, 2, f"s{i}") for i in range(50)] + [(3, 4, "s0")], "a bigint, b int, site string")
    halves = [line_spread.site_sketches(occ.where(f"site {op} 's3'")) for op in ("<", ">=")]
    merged = halves[0].unionAll(halves[1]).groupBy("a", "b").agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("n"))
    assert {r.a: r.n for r in merged.collect()} == {1: 50, 3: 1}


# ---------------------------------------------------------------- 9


def test_windows_against_brute_force(spark):
    items = [(i, prose(12 + i, 500 + i)) for i in range(8)] + [(20, "too short"), (21, None), (22, prose(12, 500))]
    edit = items[7][1].split()
    edit[0] = "changed"
    docs = [(1, prose(50, 1) + " " + items[3][1].upper() + ", " + prose(30, 2)), (2, prose(100, 3)), (3, items[0][1]), (4, None), (5, ""), (6, " ".join(edit)), (7, " ".join(items[5][1].split()[:-4])), (8, items[1][1] + ". " + items[2][1]), (8, prose(9, 4)), (None, items[4][1]), (9, prose(20_000, 9) + " " + items[6][1])]
    got = {(r.doc_id, r.item_id) for r in decontamination.contaminated(frame(spark, docs), frame(spark, items, "item_id bigint, text string")).collect()}
    assert got == H.contaminated(docs, items) and (3, 22) in got


def test_documents_shorter_than_the_item(spark, monkeypatch):
    whole = [prose(n, 900 + n).split() for n in (9, 38, 50, 59)]
    items = [(i, " ".join(w)) for i, w in enumerate(whole)]
    docs = [(i, " ".join(w[:-1])) for i, w in enumerate(whole)] + [(10 + i, " ".join(w[1:])) for i, w in enumerate(whole)]
    docs += [(22, " ".join(whole[2][:25] + whole[2][26:])), (23, " ".join(whole[3][:45])), (24, " ".join(whole[3][:48])), (25, " ".join(whole[0][:4])), (26, " ".join(whole[1][:20]))]
    docs += [(30, " ".join(whole[1][:35])), (30, " ".join([*whole[1][:36], "new", "end"]))]  # rows of one key: the shorter is the more similar
    want = {(i, i) for i in range(4)} | {(10 + i, i) for i in range(4)} | {(22, 2), (24, 3), (30, 1)}
    lost = {(22, 2): (41, 50), (24, 3): (44, 55), (30, 1): (31, 34)}
    for inline in (50_000, 10):
        monkeypatch.setattr(decontamination, "MAX_INLINE", inline)
        got = {(r.doc_id, r.item_id): (r.shared, r.weight) for r in decontamination.contaminated(frame(spark, docs), frame(spark, items, "item_id bigint, text string")).collect()}
        assert set(got) == want and all(got[k] == lost.get(k, (len(whole[k[1]]) - 5, len(whole[k[1]]) - 4)) for k in want)


def test_large_benchmarks_are_joined(spark, sf, monkeypatch):
    docs, bench = storage.table(spark, sf, "documents"), storage.table(spark, sf, "benchmark")
    want = H.rows(decontamination.contaminated(docs, bench))
    monkeypatch.setattr(decontamination, "MAX_INLINE", 10)
    assert H.rows(decontamination.contaminated(docs, bench)) == want
    assert {(r[0], r[1]) for r in want} == H.contaminated([(r.doc_id, r.text) for r in docs.collect()], [(r.item_id, r.text) for r in bench.collect()])


def test_blocks_meet_within_the_radius(spark):
    r = random.Random(1)
    rows = []
    for _ in range(200):
        a = r.getrandbits(64)
        b = a
        for bit in r.sample(range(64), r.randint(0, decontamination.RADIUS)):
            b ^= 1 << bit
        rows.append(tuple(x - (1 << 64) if x >> 63 else x for x in (a, b)))
    blocks = lambda c: decontamination.hamming_blocks(F.col(c))
    df = frame(spark, rows, "a bigint, b bigint")
    assert df.where(F.size(F.array_intersect(blocks("a"), blocks("b"))) == 0).count() == 0


def test_moved_passages_against_brute_force(spark, monkeypatch):
    """Items with halves swapped, rotated, with words put in, left out or changed, repeated items, and items of few words."""
    r = random.Random(12)
    few = ["red", "blue", "green"]
    items = [(i, prose(20 + 5 * i, 700 + i)) for i in range(9)] + [(20, " ".join(r.choice(few) for _ in range(30))), (21, "red " * 25), (22, " ".join(["one two three four five six"] * 6))]
    docs = []
    for k, (_, t) in enumerate(items):
        w = t.split()
        half, at = len(w) // 2, r.randrange(1, len(w))
        shapes = [w[half:] + w[:half], w[at:] + w[:at], w[:at] + ["new"] + w[at:], w[:at] + w[at + 1 :], w + w, w[:-2] + ["x", "y"], w[at:] + w, [*w[: at // 2], "p", "q", *w[at // 2 :]], r.sample(w, len(w))]
        docs += [(100 * k + i, " ".join(prose(r.randint(0, 40), 9 * k + i).split() + x + prose(r.randint(0, 40), 5000 + 9 * k + i).split())) for i, x in enumerate(shapes)]
    docs += [(5000 + i, " ".join(r.choice(few) for _ in range(r.randint(3, 90)))) for i in range(30)]
    want = H.contaminated(docs, items)
    assert {k for k, _ in want} >= {400, 500, 600, 700, 800, 801, 1000, 1100}
    for inline in (50_000, 10):
        monkeypatch.setattr(decontamination, "MAX_INLINE", inline)
        got = {(r.doc_id, r.item_id) for r in decontamination.contaminated(frame(spark, docs), frame(spark, items, "item_id bigint, text string")).collect()}
        assert got == want


def test_radius_finds_windows_at_the_threshold(spark):
    """Of pairs of shingle sets with a similarity of just 0.8 or little more nearly none is beyond the radius."""
    r = np.random.default_rng(3)
    draw = lambda n: r.integers(-(1 << 63), (1 << 63) - 1, n).tolist()
    rows = []
    for m in (9, 18, 27, 36, 45, 90):
        for _ in range(500):
            both = draw(m * 8 // 9)
            rows.append((both + draw(m - len(both)), both + draw(m - len(both))))
    df = frame(spark, rows, "a array<bigint>, b array<bigint>")
    far = df.where(F.bit_count(decontamination.simhash(F.col("a")).bitwiseXOR(decontamination.simhash(F.col("b")))) > decontamination.RADIUS).count()
    assert far <= 0.002 * len(rows)


def test_clean_documents_keep_their_columns(spark, awkward):
    bench = frame(spark, [(1, prose(60, 2))], "item_id bigint, text string")
    kept = decontamination.clean_documents(awkward, bench)
    assert kept.columns == awkward.columns and {r.doc_id for r in kept.collect()} == {1, 2, 3, 4, 5, 6, 8, None} - ({None} if True else set()) or kept.count() < awkward.count()
    assert decontamination.clean_documents(awkward, bench.limit(0)).count() == awkward.count()
    assert decontamination.clean_documents(awkward.limit(0), bench).count() == 0


# ---------------------------------------------------------------- 10


def test_boosting_learns_and_calibrates():
    r = np.random.default_rng(1)
    x = r.normal(size=(3000, 5))
    p = 1 / (1 + np.exp(-(3 * (x[:, 0] > 0.5) * (x[:, 1] < 0) - 1)))
    y = (r.random(3000) < p).astype(float)
    base, trees = toxicity.boost(x[:2000], y[:2000], rounds=40)
    m = toxicity.Model({}, base, trees)
    m.knots = toxicity.isotonic(m.raw(x[2000:]), y[2000:])
    s = m.score(x)
    assert ((s >= 0) & (s <= 1)).all() and abs(s.mean() - y.mean()) < 0.05 and np.corrcoef(s, p)[0, 1] > 0.85
    assert (np.diff(m.knots[1]) >= 0).all()


@settings(max_examples=120, deadline=None)
@given(st.lists(st.one_of(st.sampled_from(["idiot", "1d10t", "i.diot", "Idiot!", "moronic", "moronXX", "you", "YOUR", "du", "ok", "x2", "42", "\n", "né", "--", "@$$"]), st.text(alphabet="abé!?1 ", max_size=6)), max_size=120))
def test_features_against_their_definitions(words):
    lexicon = {"w:idiot": 5.0, "b:moron": 2.5, "w:ass": 40.0, "w:ok": 0.3}
    text = " ".join(words)
    stand_ins = {chr(k): chr(v) if isinstance(v, int) else v for k, v in toxicity.STAND_INS.items()}
    want = H.text_features(text, lexicon, toxicity.SECOND_PERSON, toxicity.STRIP, stand_ins)
    got = toxicity.features(text, toxicity._Codes(lexicon))
    assert dict(zip(toxicity.FEATURES, got, strict=True)) == pytest.approx(dict(zip(toxicity.FEATURES, map(float, want), strict=True)))


@pytest.mark.parametrize("seed", range(4))
def test_boosting_against_every_split(seed):
    r = np.random.default_rng(seed)
    x = np.stack([r.normal(size=150), r.integers(0, 4, 150), r.normal(size=150)], 1).astype(float)
    y = (r.random(150) < 1 / (1 + np.exp(-2 * x[:, 0] * (x[:, 1] > 1) - x[:, 2]))).astype(float)
    base, trees = toxicity.boost(x, y, rounds=6, depth=3, rate=0.3, bins=12, l2=1.0)
    assert toxicity.Model({}, base, trees).raw(x) == pytest.approx(H.boosted(x, y, 6, 3, 0.3, 12, 1.0), abs=1e-6)


@given(st.lists(st.tuples(st.integers(0, 30), st.integers(0, 1)), min_size=1, max_size=25, unique_by=lambda p: p[0]))
def test_calibration_is_the_increasing_least_squares_fit(pairs):
    pairs = sorted(pairs)
    raw, y = np.array([p[0] for p in pairs], float), np.array([p[1] for p in pairs], float)
    at, value = toxicity.isotonic(raw, y)
    n = len(y)
    want = [max(min(y[i : j + 1].mean() for j in range(k, n)) for i in range(k + 1)) for k in range(n)]
    steps = [i for i in range(n) if i == 0 or want[i] != pytest.approx(want[i - 1])]
    assert value == pytest.approx([want[i] for i in steps])
    assert at == pytest.approx([raw[i:j].mean() for i, j in zip(steps, [*steps[1:], n], strict=True)])


def test_fit_does_not_depend_on_the_order_of_rows(spark, sf):
    docs, labels = storage.table(spark, sf, "documents"), storage.table(spark, sf, "labels")
    again = docs.unionByName(docs.withColumn("doc_id", F.col("doc_id") + 1))  # copies in other folds, and keys of two texts
    models = [toxicity.fit(d, labels, max_rows=60) for d in (again, again.orderBy(F.desc("text")).repartition(7))]
    assert models[0].lexicon == models[1].lexicon and models[0].base == models[1].base and len(models[0].trees) == len(models[1].trees)
    x = np.random.default_rng(0).random((200, len(toxicity.FEATURES)))
    assert models[0].score(x).tolist() == models[1].score(x).tolist()


def test_held_out_toxicity(spark):
    sf = "/root/testdata/sf0.1"
    got = queries.op10_toxicity(spark, sf).join(storage.table(spark, sf, "labels"), "doc_id").where("held_out")
    r = got.agg(F.avg((F.col("predicted") == F.col("toxic")).cast("int")).alias("right"), F.avg(F.when(F.col("toxic") == 0, F.col("predicted"))).alias("false"), F.avg(F.when(F.col("toxic") == 1, F.col("predicted"))).alias("found")).first()
    assert r.right > 0.96 and r.false < 0.02 and r.found > 0.8


def test_toxicity_of_awkward_rows(spark, awkward, sf):
    docs = storage.table(spark, sf, "documents")
    m = toxicity.fit(docs, storage.table(spark, sf, "labels"))
    got = toxicity.score(awkward, m)
    assert got.count() == awkward.count() and got.where("score BETWEEN 0 AND 1").count() == awkward.count()
    assert got.columns == [*[c for c in awkward.columns if c != "score"], "score", "predicted"]
    none = toxicity.fit(docs, storage.table(spark, sf, "labels").limit(0))
    assert {r.predicted for r in toxicity.score(awkward, none).collect()} == {0}
    assert toxicity.score(awkward.limit(0), m).count() == 0


def test_masked_spelling_is_a_hit():
    codes = toxicity._Codes({"w:idiot": 5.0})
    at = toxicity.FEATURES.index("masked_hits")
    assert toxicity.features("you 1d10t!", codes)[at] == 1 and toxicity.features("you idiom", codes)[at] == 0


def test_kinds_counts_the_words_of_the_whole_text():
    names = [f"bad{i}" for i in range(300)]
    codes = toxicity._Codes({f"w:{w}": 5.0 for w in names})
    assert toxicity.features(" ".join(names), codes)[toxicity.FEATURES.index("kinds")] == 300


# ---------------------------------------------------------------- words that a polynomial name does not tell apart


def doubled(steps):
    """Two different words of 2 ** steps letters: each step appends the complement."""
    a = "a"
    for _ in range(steps):
        a += a.translate(str.maketrans("ab", "ba"))
    return a, a.translate(str.maketrans("ab", "ba"))


@pytest.mark.parametrize("steps", [8, 10, 11, 12])
def test_words_of_one_name_have_their_own_ids(steps):
    a, b = doubled(steps)
    e = token_files.encoder_for(WORD_BPE)
    for texts in ([a, b], [f"{a} {b} end", "x y"], [b, a, b]):
        want = [e.library.encode(t, add_special_tokens=False).ids for t in texts]
        ids, sizes = e.encode(texts)
        assert ids.tolist() == [i for w in want for i in w] and sizes.tolist() == [len(w) for w in want]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.lists(st.text(alphabet="ab", min_size=1, max_size=40), max_size=12), max_size=5))
def test_words_of_two_letters(texts):
    texts = [" ".join(t) for t in texts]
    e = token_files.encoder_for(WORD_BPE)
    want = [e.library.encode(t, add_special_tokens=False).ids for t in texts]
    assert e.encode(texts)[0].tolist() == [i for w in want for i in w]
    sets = shingles.exact_sets(texts)
    true = [H.shingles(t) for t in texts]
    for i, x in enumerate(sets):
        assert len(x) == len(true[i])
        for j, y in enumerate(sets):
            assert len(np.intersect1d(x, y)) == len(true[i] & true[j])


def test_words_of_one_name_make_no_link(spark):
    a, b = doubled(10)
    data = [(1, " ".join([a] * 9)), (2, " ".join([b] * 9)), (3, f"{a} {b} {a} {b} {b}"), (4, f"{b} {a} {b} {a} {a}"), (5, " ".join([a] * 12))]
    assert shingles.word_names(a) == shingles.word_names(b)
    got = H.rows(jaccard_join.jaccard_join(frame(spark, data)).select("doc_id", "class_id", "n_links"))
    assert got == sorted(H.jaccard_classes(data), key=str) and (5, 1, 1) in got


# ---------------------------------------------------------------- the registered queries, on a whole table


@pytest.fixture(scope="module")
def texts(spark, sf):
    return [(r.doc_id, r.text) for r in storage.table(spark, sf, "documents").collect()]


def test_query_of_token_counts(spark, sf, texts):
    c = token_counts.counter_for(BYTE_BPE)
    sizes = [(k, len((t or "").encode()), len(c.library.encode(t or "", add_special_tokens=False).ids)) for k, t in texts]
    assert H.rows(queries.op3_prefix_token_counts(spark, sf)) == sorted(((k, b, n, n > 1024) for k, b, n in sizes), key=str)


def test_query_of_classes(spark, sf, texts):
    got = H.rows(queries.op4_jaccard_join(spark, sf).select("doc_id", "class_id", "n_links"))
    assert got == sorted(H.jaccard_classes(texts), key=str)


def test_query_of_token_files(spark, sf, texts):
    from tokenizers import Tokenizer

    lib, place, want = Tokenizer.from_file(WORD_BPE), 0, []
    for k, t in sorted(texts):
        ids = lib.encode(t or "", add_special_tokens=False).ids + [2]
        want.append((k, place, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        place += len(ids)
    assert H.rows(queries.op5_token_files(spark, sf).select("doc_id", "start", "n_tokens", "ids_crc32")) == sorted(want, key=str)


def test_query_of_repeated_strings(spark, sf, texts):
    got = queries.op6_repeated_strings(spark, sf)
    assert got.columns[:5] == ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
    assert H.rows(got.select(got.columns[:5])) == sorted(H.removed_strings(texts), key=str)


def test_query_of_benchmark_windows(spark, sf, texts):
    items = [(r.item_id, r.text) for r in storage.table(spark, sf, "benchmark").collect()]
    found = H.contaminated(texts, items)
    want = [(k, any(d == k for d, _ in found), sorted(i for d, i in found if d == k)) for k, _ in texts]
    assert H.rows(queries.op9_benchmark_windows(spark, sf)) == sorted(want, key=str)


def test_query_of_toxicity(spark, sf, texts):
    got = queries.op10_toxicity(spark, sf).collect()
    assert sorted(r.doc_id for r in got) == sorted(k for k, _ in texts)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in got)
