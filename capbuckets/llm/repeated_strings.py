"""Removal of long strings that occur more than once, by blockwise suffix work over a difference-cover sample.

A suffix array over the whole corpus would rank every byte. To find strings of ``length`` bytes that start in two places
only ties of that depth matter, and these are resolved in two rounds, each a blockwise sort of suffix names:

1. *Cover sample.* A difference cover D modulo v has, for any two places i and j, a shift d < v such that i + d and j + d both
   fall into D. Strings of ``length - v + 1`` bytes at sampled places are named; only names that occur twice can lie in a
   repeated string, so all suffixes without such a sample in their first v places are decided at once.
2. *Tied suffixes.* What is left is named to the full depth, and sorted by name, bucket by bucket: ties stand side by side.
3. *Bytes.* Equal names are no proof. Each tie is held byte for byte against the one before it in its bucket's order, in
   the block itself or through runs of text sent to that block. If any two differ, all is done again under names of another kind.

Names are 64-bit polynomial hashes. A block of documents sends each bucket its distinct names
alone, as packed arrays, and gets back which of them are tied, and with which block, so memory is that of a block or of one
bucket's arrays, and a passage that a third of all documents share counts once a block and is compared along a chain. The
texts are dealt out to blocks by the hash of the text once, in a bucketed table; all rounds read it without moving it
again, and equal texts are one entry.
"""

from __future__ import annotations

import hashlib
import uuid
from functools import cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import storage

LENGTH = 400
#: Kinds of names that are tried in turn; each but the first holds any two strings apart with a chance of over 1 - 2^-50.
KINDS = 4
#: Bytes of text in a block on average (up to four times as much for very large corpora), and of a bucket's arrays.
BLOCK_BYTES, BUCKET_BYTES = 8 << 20, 64 << 20
_U = np.uint64
_VALUE = np.random.default_rng(31).integers(1, 1 << 63, 256, dtype=np.uint64) * _U(2) + _U(1)
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
#: The largest primes under 2^31 and 2^32.
PRIMES = (2147483647, 4294967291)


@cache
def difference_cover(r: int = 2) -> tuple[int, np.ndarray]:
    """(v, D): the known family of covers with v = 24 r^2 + 36 r + 13 and 6 r + 4 members, from its gaps."""
    v = 24 * r * r + 36 * r + 13
    gaps = [1] * r + [r + 1] + [2 * r + 1] * r + [4 * r + 3] * (2 * r + 1) + [2 * r + 2] * (r + 1) + [1] * r
    members = np.concatenate([[0], np.cumsum(gaps)])
    if len({(a - b) % v for a in members for b in members}) != v:
        raise ValueError("the gaps do not make a cover")
    return v, members


def _powers(n: int, base: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


def _powers_modulo(n: int, base: int, prime: int) -> np.ndarray:
    out = np.ones(n, np.uint64)
    done = 1
    while done < n:  # doubles what is known
        more = min(done, n - done)
        out[done : done + more] = out[:more] * _U(pow(base, done, prime)) % _U(prime)
        done += more
    return out


class Names:
    """Names of the strings of one block: its texts stand in a row, in the order of their keys.

    ``kind`` 0 counts modulo 2^64, which is quick but tells some strings of two letters apart under no base; other kinds
    count modulo two primes, over bases that follow from the kind.
    """

    def __init__(self, texts: list[bytes], kind: int = 0):
        self.size = np.array([len(t) for t in texts], np.int64)
        self.end = np.cumsum(self.size)
        self.begin = self.end - self.size
        self.data = np.frombuffer(b"".join(texts), np.uint8)
        most = int(self.size.max(initial=0)) + 1
        self.inside = np.arange(len(self.data)) - np.repeat(self.begin, self.size)
        self.parts = []
        if not kind:
            self._add(_VALUE[self.data] * _powers(most, _BASE)[self.inside], _powers(most, _INVERSE), None)
            return
        rng = np.random.default_rng(kind)
        for prime in PRIMES:
            base, value = int(rng.integers(256, prime - 1)), rng.integers(1, prime, 256, dtype=np.uint64)
            self._add(value[self.data] * _powers_modulo(most, base, prime)[self.inside] % _U(prime), _powers_modulo(most, pow(base, -1, prime), prime), prime)

    def _add(self, terms: np.ndarray, back: np.ndarray, prime: int | None) -> None:
        total = np.zeros(len(terms) + 1, np.uint64)
        np.cumsum(terms, out=total[1:])
        self.parts.append((total, back, prime))

    def of(self, at: np.ndarray, length: int) -> np.ndarray:
        """Names of the strings of ``length`` bytes at ``at``; the same string has the same name in every block."""
        x = np.zeros(len(at), np.uint64)
        for total, back, prime in self.parts:
            own = total[at + length] - total[at]
            shift = back[self.inside[at]]
            x = own * shift if prime is None else (x << _U(32)) + own % _U(prime) * shift % _U(prime)
        x = (x ^ (x >> _U(29))) * _U(0xBF58476D1CE4E5B9)
        return x ^ (x >> _U(32))

    def all_of(self, length: int) -> np.ndarray:
        """Every place with ``length`` bytes of its text after it."""
        return np.flatnonzero(np.repeat(self.end, self.size) - np.arange(len(self.data)) >= length)

    def sampled(self, length: int) -> np.ndarray:
        """Places of the cover sample that have ``length`` bytes of their text after them."""
        v, members = difference_cover()
        chosen = np.zeros(v, bool)
        chosen[members] = True
        at = np.flatnonzero(chosen[self.inside % v])
        return at[at + length <= self.end[np.searchsorted(self.end, at, side="right")]] if len(at) else at

    def candidates(self, flagged: np.ndarray, length: int) -> np.ndarray:
        """Places with a full string after them and a flagged sample within the first v places."""
        v, _ = difference_cover()
        mark = np.zeros(len(self.inside) + 1, np.int32)
        text = np.searchsorted(self.end, flagged, side="right")
        np.add.at(mark, np.maximum(flagged - v + 1, self.begin[text]), 1)
        np.add.at(mark, flagged + 1, -1)
        at = np.flatnonzero(np.cumsum(mark[:-1]) > 0)
        return at[at + length <= self.end[np.searchsorted(self.end, at, side="right")]] if len(at) else at


def _buckets(names: np.ndarray, count: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct names in ascending order, and where each of ``count`` buckets (ranges of names) begins."""
    distinct = np.unique(names)
    edges = (np.arange(1, count, dtype=object) * (1 << 64) // count).astype(np.uint64) if count > 1 else np.zeros(0, np.uint64)
    return distinct, np.concatenate([[0], np.searchsorted(distinct, edges), [len(distinct)]])


def _sent(block: int, names: np.ndarray, count: int) -> list[tuple[int, int, bytes]]:
    distinct, cut = _buckets(names, count)
    out = []
    for b in range(count):
        part = distinct[cut[b] : cut[b + 1]]
        if len(part):
            out.append((b, block, _packed(part)))
    return out


def _packed(ascending: np.ndarray) -> bytes:
    """Ascending 64-bit names as gaps, by byte planes with only as many planes as the largest gap needs."""
    gaps = np.diff(ascending, prepend=_U(0)).astype("<u8")
    first, gaps = int(ascending[0]), gaps[1:]
    planes = gaps.view(np.uint8).reshape(-1, 8).T if len(gaps) else np.zeros((8, 0), np.uint8)
    kept = max([p + 1 for p in range(8) if planes[p].any()], default=0)
    return first.to_bytes(8, "little") + len(gaps).to_bytes(8, "little") + bytes([kept]) + planes[:kept].tobytes()


def _unpacked(data: bytes) -> np.ndarray:
    first, n, kept = int.from_bytes(data[:8], "little"), int.from_bytes(data[8:16], "little"), data[16]
    planes = np.zeros((n + 1, 8), np.uint8)
    planes[1:, :kept] = np.frombuffer(data, np.uint8, n * kept, 17).reshape(kept, n).T
    gaps = planes.view("<u8").ravel().astype(np.uint64)
    gaps[0] = first
    return np.cumsum(gaps, dtype=np.uint64)


def _tied(group: pd.DataFrame, neighbours: bool) -> pd.DataFrame:
    """For each block of a bucket: a bitmap over the names it sent, of those that another block sent too.

    With ``neighbours``, for each of these, in order: the nearest block before that sent it (0: none, else its number + 1), and a bitmap of
    those that a later block sent.
    """
    group = group.sort_values("block")
    sent = [_unpacked(x) for x in group["names"]]
    owner = np.repeat(group["block"].to_numpy(np.int64) + 1, [len(x) for x in sent])
    every = np.concatenate(sent)
    order = np.argsort(every, kind="stable")  # of one name, blocks in ascending order
    name, block = every[order], owner[order]
    same = name[1:] == name[:-1]
    before, after = np.zeros(len(name), np.int64), np.zeros(len(name), bool)
    before[order[1:][same]] = block[:-1][same]
    after[order[:-1][same]] = True
    kind = next(t for t in ("<u1", "<u2", "<u4") if int(owner.max()) < 1 << 8 * np.dtype(t).itemsize)
    out, at = [], 0
    for part in sent:
        b, a = before[at : at + len(part)], after[at : at + len(part)]
        hit = (b > 0) | a
        out.append((len(part), np.packbits(hit).tobytes(), b[hit].astype(kind).tobytes() if neighbours else b"", np.packbits(a[hit]).tobytes() if neighbours else b""))
        at += len(part)
    n, bits, before, after = zip(*out, strict=True)
    return pd.DataFrame({"block": group["block"], "bucket": group["bucket"], "n": n, "bits": bits, "before": before, "after": after})


def _flagged(names: np.ndarray, answers: pd.DataFrame) -> np.ndarray:
    """Which of a block's names occur twice: in the block itself or, by the answers of the buckets, in another."""
    distinct, which, counts = np.unique(names, return_inverse=True, return_counts=True)
    tied = (counts > 1) | (_told(len(distinct), answers)[0])
    return tied[which]


def _told(n: int, answers: pd.DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(tied with another block, block before or -1, whether one is after) of a block's ``n`` distinct names, in order."""
    tied, before, after, at = np.zeros(n, bool), np.full(n, -1, np.int64), np.zeros(n, bool), 0
    for row in answers.sort_values("bucket").itertuples():
        hit = np.flatnonzero(np.unpackbits(np.frombuffer(row.bits, np.uint8), count=row.n)) + at
        tied[hit] = True
        if len(row.before):
            before[hit] = np.frombuffer(row.before, f"<u{len(row.before) // len(hit)}").astype(np.int64) - 1
            after[hit] = np.unpackbits(np.frombuffer(row.after, np.uint8), count=len(hit)).astype(bool)
        at += row.n
    if at != n:
        raise ValueError("the answers are not those of this block")
    return tied, before, after


def differing(a: np.ndarray, p: np.ndarray, b: np.ndarray, q: np.ndarray, length: int) -> int:
    """How many of the strings at ``p`` in ``a`` differ from those at ``q`` in ``b``; none, only if all are equal.

    Where both places follow on those before, all but the last byte has been compared.
    """
    if not len(p):
        return 0
    follows = np.append(False, (p[1:] == p[:-1] + 1) & (q[1:] == q[:-1] + 1))
    bad = int((a[p[follows] + length - 1] != b[q[follows] + length - 1]).sum())
    p, q, inside = p[~follows], q[~follows], np.arange(length)
    for at in range(0, len(p), 8192):
        bad += int((a[p[at : at + 8192, None] + inside] != b[q[at : at + 8192, None] + inside]).any(1).sum())
    return bad


def _runs(data: np.ndarray, at: np.ndarray, to: np.ndarray, length: int) -> dict[int, list[bytes]]:
    """For each target: the texts of the runs of places that go there."""
    if not len(at):
        return {}
    cut = np.flatnonzero((np.diff(at) != 1) | (np.diff(to) != 0)) + 1
    out: dict[int, list[bytes]] = {}
    for a, b in zip(np.concatenate([[0], cut]), np.concatenate([cut, [len(at)]]), strict=True):
        out.setdefault(int(to[a]), []).append(data[at[a] : at[b - 1] + length].tobytes())
    return out


def _cut(row) -> list[bytes]:
    ends = np.cumsum(row.sizes)
    return [row.runs[e - n : e] for e, n in zip(ends.tolist(), row.sizes, strict=True)]


def _checked(group: pd.DataFrame, length: int, kind: int) -> int:
    """Strings in the runs sent to a block by blocks after it that are not in its own runs."""
    target = int(group["target"].iloc[0])
    own = Names([r for row in group[group["block"] == target].itertuples() for r in _cut(row)], kind)
    at = own.all_of(length)
    known, first = np.unique(own.of(at, length), return_index=True)
    at, bad = at[first], 0
    for row in group[group["block"] != target].itertuples():
        other = Names(_cut(row), kind)
        p = other.all_of(length)
        name = other.of(p, length)
        place = np.minimum(np.searchsorted(known, name), max(0, len(known) - 1))
        hit = known[place] == name if len(known) else np.zeros(len(name), bool)
        bad += int((~hit).sum()) + differing(other.data, p[hit], own.data, at[place[hit]], length)
    return bad


def repeated_spans(docs: DataFrame, length: int = LENGTH, key: str = "doc_id", text: str = "text", store_text: bool = False) -> DataFrame:
    """One row per row of ``docs``: key, ``n_bytes``, ``n_removed``, ``n_spans``, ``kept_sha256``, ``kept_bytes``, ``changed`` (and ``kept``).

    Every byte that lies in a string of ``length`` bytes that also starts elsewhere, in the same document or another, is
    removed; strings are compared on the input, as UTF-8 bytes, and never cross documents. Null texts count as empty, keys may
    be null or repeat. Of rows with one text each counts as elsewhere of the others, so such a text goes as a whole if it
    has ``length`` bytes.
    """
    spark = docs.sparkSession
    v, _ = difference_cover()
    if length < 2 * v:
        raise ValueError(f"strings must have {2 * v} bytes at least")
    rows = docs.select(F.col(key).cast("bigint").alias("id"), F.coalesce(F.col(text), F.lit("")).cast("binary").alias("t")).withColumn("k", F.unhex(F.substring(F.sha2("t", 256), 1, 32)))
    total = storage.plan_bytes(docs, text)
    texts_bytes = 2 * total  # files are compressed
    blocks = max(1, -(-texts_bytes // min(4 * BLOCK_BYTES, max(BLOCK_BYTES, texts_bytes >> 16))))
    buckets = max(min(64, blocks), total // BUCKET_BYTES)
    parts = storage.shuffle_partitions(spark, total, 8 << 20)
    # equal texts are one entry; blocks are given by the hash of the text, so all rounds see the same ones
    name = f"texts_{uuid.uuid4().hex}"
    by_block = rows.withColumn("block", F.pmod(F.xxhash64("k"), F.lit(blocks)).cast("int")).repartition(parts, "block").groupBy("block", "k").agg(F.first("t").alias("t"), F.count(F.lit(1)).alias("copies"))
    try:
        by_block.write.option("path", storage.shared_path(spark, "texts")).option("compression", "zstd").bucketBy(parts, "block").format("parquet").saveAsTable(name)
        keyed = spark.table(name).select("block", "k", "t", "copies").groupBy("block")
        for kind in range(KINDS):
            result, bad = _rounds(keyed, length, buckets, kind, store_text)
            if not bad:
                break
        else:
            raise RuntimeError(f"different strings had equal names under {KINDS} kinds of names")
    finally:
        spark.sql(f"DROP TABLE IF EXISTS {name}")  # the files go with the session
    left = (F.col("n_bytes") - F.col("n_removed")).alias("kept_bytes")
    return rows.select("id", "k").join(result, "k").select(F.col("id").alias(key), "n_bytes", "n_removed", "n_spans", "kept_sha256", left, (F.col("n_removed") > 0).alias("changed"), *["kept"] * store_text)


def _rounds(keyed, length: int, buckets: int, kind: int, store_text: bool) -> tuple[DataFrame, int]:
    """(rows by text, strings that differ though their names are equal); the rows are right if there are none of the latter."""
    v, _ = difference_cover()
    depth = length - v + 1
    sent_schema = "bucket int, block int, names binary"
    answer_schema = "block int, bucket int, n bigint, bits binary, before binary, after binary"

    def opened(group: pd.DataFrame) -> tuple[pd.DataFrame, Names]:
        group = group.sort_values("k").reset_index(drop=True)
        return group, Names(group["t"].tolist(), kind)

    def sample(group: pd.DataFrame) -> pd.DataFrame:
        group, names = opened(group)
        return pd.DataFrame(_sent(int(group["block"].iloc[0]), names.of(names.sampled(depth), depth), buckets), columns=["bucket", "block", "names"])

    def suspects(group: pd.DataFrame, answers: pd.DataFrame) -> tuple[pd.DataFrame, Names, np.ndarray]:
        group, names = opened(group)
        at = names.sampled(depth)
        if len(at):
            at = at[_flagged(names.of(at, depth), answers)]
        return group, names, names.candidates(at, length)

    def tied(group: pd.DataFrame, answers: pd.DataFrame) -> pd.DataFrame:
        if not len(group):
            return pd.DataFrame({"bucket": [], "block": [], "names": []})
        group, names, at = suspects(group, answers)
        return pd.DataFrame(_sent(int(group["block"].iloc[0]), names.of(at, length), buckets), columns=["bucket", "block", "names"])

    columns = ("k", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept", "block", "target", "runs", "sizes", "bad")

    def removed(group: pd.DataFrame, answers: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(group):
            group, names, at = suspects(group, answers[answers["round"] == 1])
            block, bad = int(group["block"].iloc[0]), 0
            if len(at):
                distinct, first, which, counts = np.unique(names.of(at, length), return_index=True, return_inverse=True, return_counts=True)
                again, before, after = _told(len(distinct), answers[answers["round"] == 2])
                later = first[which] != np.arange(len(at))
                bad = differing(names.data, at[later], names.data, at[first[which[later]]], length)
                order = np.argsort(first)  # one place a name, in the order of the text
                place, before, after = at[first[order]], before[order], after[order]
                sent = _runs(names.data, place[before >= 0], before[before >= 0], length)
                sent |= _runs(names.data, place[after], np.full(int(after.sum()), block), length)
                for target, runs in sent.items():
                    out.append((None, None, None, None, None, None, block, target, b"".join(runs), [len(r) for r in runs], None))
                at = at[((counts > 1) | again)[which]]
            out.append((None, None, None, None, None, None, block, None, None, None, bad))
            cover = np.zeros(len(names.inside) + 1, np.int32)
            np.add.at(cover, at, 1)
            np.add.at(cover, at + length, -1)
            gone = np.cumsum(cover[:-1]) > 0
            for k, t, copies, a, b in zip(group["k"], group["t"], group["copies"], names.begin, names.end, strict=True):
                own = np.ones(b - a, bool) if copies > 1 and b - a >= length else gone[a:b]
                kept = np.frombuffer(t, np.uint8)[~own].tobytes()
                out.append((k, b - a, int(own.sum()), int(own[:1].sum() + (own[1:] & ~own[:-1]).sum()), hashlib.sha256(kept).hexdigest(), kept if store_text else None, *[None] * 5))
        return pd.DataFrame(dict(zip(columns, zip(*out, strict=True), strict=True)) if out else {c: [] for c in columns}, dtype=object)

    by_bucket = lambda sent, neighbours: sent.groupBy("bucket").applyInPandas(lambda group: _tied(group, neighbours), answer_schema)
    first = storage.materialize(by_bucket(keyed.applyInPandas(sample, sent_schema), False), "cover-answers")
    sent = keyed.cogroup(first.groupBy("block")).applyInPandas(tied, sent_schema)
    second = storage.materialize(by_bucket(sent, True), "tie-answers")
    both = first.withColumn("round", F.lit(1)).unionAll(second.withColumn("round", F.lit(2)))
    schema = "k binary, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string, kept binary, block int, target int, runs binary, sizes array<int>, bad bigint"
    result = storage.materialize(keyed.cogroup(both.groupBy("block")).applyInPandas(removed, schema), "removed-strings")
    runs = result.where("target IS NOT NULL").select("block", "target", "runs", "sizes").groupBy("target")
    checked = runs.applyInPandas(lambda group: pd.DataFrame({"bad": [_checked(group, length, kind)]}), "bad bigint")
    bad = result.where("bad > 0").select("bad").unionAll(checked).agg(F.coalesce(F.sum("bad"), F.lit(0))).first()[0]
    return result.where("k IS NOT NULL").select("k", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"), int(bad)
