"""Token-id files with directly addressable codes.

A file is a row of segments. A segment holds the ids of some whole documents, cut into eight-bit levels: level 0 has the
low byte of every id, level 1 the second byte of the ids that are over 255, and so on. A bitmap beside each level but the
last says which of its ids go on, and a directory has the number of set bits before every 512th bit, so that the place
of an id in the next level, and with it any id, is found by one look-up a level; nothing else is decoded.

Files are written by Spark's own committed text writer (each row is one segment, its line end is part of the format)
and read by its binary-file source, so they can lie in any store that Spark reads, and a lost task leaves nothing behind.
"""

from __future__ import annotations

import os
import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import storage
from .token_counts import byte_alphabet

#: Fixed values of the format: mark, header layout (partition, sequence, documents, ids, levels), bits between directory entries.
MARK = b"DACTOK1\0"
HEADER = struct.Struct("<8sQQQQB")
STRIDE = 512
SEGMENT_CHARS = 1 << 20
CACHE_WORDS = 300_000
#: Texts of these characters alone are cut by array operations as the library cuts them; all others go through the library.
PLAIN = re.compile("[\\t\\n\\r\\x20-&(-;=-~\\u00a1-\\u012f\\u0131-\\u017f]*")


# ---------------------------------------------------------------- directly addressable codes


def encode_levels(ids: np.ndarray) -> list[tuple[np.ndarray, np.ndarray | None, np.ndarray | None]]:
    """(bytes, packed continuation bitmap, rank directory) for each level; the last level has no bitmap."""
    levels, rest = [], np.asarray(ids, np.uint32)
    while True:
        low, more = (rest & 255).astype(np.uint8), rest > 255
        if not more.any():
            return [*levels, (low, None, None)]
        bits = np.packbits(more, bitorder="little")
        counts = np.add.reduceat(more, np.arange(0, len(more), STRIDE), dtype=np.uint32)
        levels.append((low, bits, np.concatenate([[0], np.cumsum(counts)[:-1]]).astype(np.uint32)))
        rest = rest[more] >> 8


def decode_levels(levels) -> np.ndarray:
    """All ids of a segment."""
    ids = None
    for low, bits, _ in reversed(levels):
        value = low.astype(np.uint32)
        if bits is not None:
            more = np.unpackbits(bits, count=len(low), bitorder="little").astype(bool)
            value[more] |= ids << np.uint32(8)
        ids = value
    return ids if ids is not None else np.zeros(0, np.uint32)


def token_at(levels, i: int) -> int:
    """The id at place ``i``: one bitmap and one directory look-up a level, no block is decoded."""
    value, shift = 0, 0
    for low, bits, ranks in levels:
        value |= int(low[i]) << shift
        if bits is None or not bits[i >> 3] >> (i & 7) & 1:
            return value
        block = i // STRIDE
        between = np.unpackbits(bits[block * STRIDE // 8 : (i >> 3) + 1], bitorder="little")[: i - block * STRIDE]
        i, shift = int(ranks[block]) + int(between.sum()), shift + 8
    return value


def pack_segment(partition: int, sequence: int, doc_ids: list[int | None], sizes: np.ndarray, ids: np.ndarray) -> bytes:
    """A segment as bytes; the document directory has an id, a null flag and a number of tokens for each."""
    levels = encode_levels(ids)
    out = [HEADER.pack(MARK, partition, sequence, len(doc_ids), len(ids), len(levels))]
    out.append(np.array([d or 0 for d in doc_ids], "<i8").tobytes())
    out.append(bytes(d is None for d in doc_ids))
    out.append(np.asarray(sizes, "<u8").tobytes())
    for low, bits, ranks in levels:
        out.append(struct.pack("<QB", len(low), bits is not None))
        out.append(low.tobytes())
        if bits is not None:
            out += [bits.tobytes(), ranks.astype("<u4").tobytes()]
    return b"".join(out)


def segments(data: bytes) -> Iterator[tuple[int, int, list[int | None], np.ndarray, list]]:
    """(partition, sequence, document ids, sizes, levels) of every segment of a file."""
    at, view = 0, memoryview(data)
    while at < len(data):
        mark, partition, sequence, docs, _, depth = HEADER.unpack_from(data, at)
        if mark != MARK:
            raise ValueError(f"no segment starts at byte {at}")
        at += HEADER.size
        keys = np.frombuffer(view, "<i8", docs, at)
        nulls = np.frombuffer(view, np.uint8, docs, at + 8 * docs)
        sizes = np.frombuffer(view, "<u8", docs, at + 9 * docs)
        at, levels = at + 17 * docs, []
        for _ in range(depth):
            n, more = struct.unpack_from("<QB", data, at)
            low, at = np.frombuffer(view, np.uint8, n, at + 9), at + 9 + n
            bits = ranks = None
            if more:
                bits = np.frombuffer(view, np.uint8, -(-n // 8), at)
                ranks = np.frombuffer(view, "<u4", -(-n // STRIDE), at + len(bits))
                at += len(bits) + 4 * len(ranks)
            levels.append((low, bits, ranks))
        yield partition, sequence, [None if z else int(k) for k, z in zip(keys, nulls, strict=True)], sizes.astype(np.int64), levels
        if data[at : at + 1] != b"\n":
            raise ValueError(f"no segment ends at byte {at}")
        at += 1


# ---------------------------------------------------------------- encoding


_ENCODERS: dict[str, WordEncoder] = {}


def encoder_for(path: str) -> WordEncoder:
    """The encoder of this worker process: its cache of words lives on from task to task."""
    os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
    if path not in _ENCODERS:
        _ENCODERS[path] = WordEncoder(path)
    return _ENCODERS[path]


class WordEncoder:
    """Ids of whole texts, as the library gives them: distinct words are encoded by the library's model, once each while cached.

    The tokenizer lower-cases, drops white space and encodes runs of letters, single digits and runs of other characters
    apart, so the ids of a text are those of its words. Texts with characters outside :data:`PLAIN` are encoded whole.
    """

    def __init__(self, path: str):
        import json

        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        kinds = [x["type"] for x in (spec["pre_tokenizer"] or {}).get("pretokenizers", [])]
        lower = [x["type"] for x in (spec["normalizer"] or {}).get("normalizers", [])]
        self.by_word = kinds == ["Split", "ByteLevel"] and lower == ["NFC", "Replace", "Lowercase"] and bool(spec["model"].get("end_of_word_suffix"))
        point = np.arange(0x180)
        letter = np.array([chr(p).isalpha() for p in point])
        digit = np.array([chr(p).isnumeric() for p in point])
        self.kind = np.where(letter, 1, np.where(digit, 2, 3)).astype(np.uint8)
        self.kind[[9, 10, 11, 12, 13, 32]] = 0
        self.model = self.library.model
        self.alphabet = {b: c for c, b in byte_alphabet().items()}
        rng = np.random.default_rng(7)
        self.mark = rng.integers(1, 1 << 63, 0x180, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.reset()

    def reset(self) -> None:
        self.place: dict[str, int] = {}
        self.flat, self.starts, self.used = np.zeros(1 << 16, np.uint32), np.zeros(CACHE_WORDS * 2, np.int64), 0

    def _learn(self, words: list[str]) -> None:
        if len(self.place) + len(words) > CACHE_WORDS:
            self.reset()
        if len(words) + 1 >= len(self.starts):
            self.starts = np.zeros(2 * len(words) + 2, np.int64)
        tokenize, alphabet, ids, ends = self.model.tokenize, self.alphabet, [], []
        for word in words:
            ids += [t.id for t in tokenize(word if word.isascii() else word.encode().decode("latin-1").translate(alphabet))]
            ends.append(len(ids))
        if self.used + len(ids) > len(self.flat):
            self.flat = np.concatenate([self.flat, np.zeros(len(self.flat) + len(ids), np.uint32)])
        self.flat[self.used : self.used + len(ids)] = ids
        n = len(self.place)
        self.starts[n + 1 : n + 1 + len(words)] = self.used + np.array(ends, np.int64)
        self.place.update(zip(words, range(n, n + len(words)), strict=True))
        self.used += len(ids)

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts in a row, number of ids of each)."""
        plain = [self.by_word and bool(PLAIN.fullmatch(t)) for t in texts]
        sizes, parts = np.zeros(len(texts), np.int64), [None] * len(texts)
        rest = [i for i, p in enumerate(plain) if not p]
        for i, code in zip(rest, self.library.encode_batch([texts[i] for i in rest], add_special_tokens=False), strict=True):
            parts[i] = np.array(code.ids, np.uint32)
        common = [i for i, p in enumerate(plain) if p]
        if common:
            for i, ids in zip(common, self._plain([texts[i].lower() for i in common]), strict=True):
                parts[i] = ids
        for i, ids in enumerate(parts):
            sizes[i] = len(ids)
        return np.concatenate(parts) if parts else np.zeros(0, np.uint32), sizes

    def _plain(self, texts: list[str]) -> list[np.ndarray]:
        joined = "\n".join(texts) + "\n"
        try:  # a byte a character, where that will do
            points = np.frombuffer(joined.encode("latin-1"), np.uint8)
        except UnicodeEncodeError:
            points = np.frombuffer(joined.encode("utf-32-le"), np.uint32)
        kind = self.kind[points]
        start = kind != 0
        start[1:] &= (kind[1:] != kind[:-1]) | (kind[1:] == 2)
        at = np.flatnonzero(start)
        if not len(at):
            return [np.zeros(0, np.uint32)] * len(texts)
        stop = np.flatnonzero((kind != 0) & np.append((kind[1:] != kind[:-1]) | (kind[1:] == 2), True)) + 1
        length = stop - at
        power = np.ones(int(length.max()), np.uint64)
        power[1:] = np.uint64(0x9E3779B97F4A7C15)
        power = np.multiply.accumulate(power)
        inside = np.arange(length.sum()) - np.repeat(np.cumsum(length) - length, length)
        chars, base = points[kind != 0], np.cumsum(length) - length
        name = np.add.reduceat(self.mark[chars] * power[inside], base)
        _, first, which = np.unique(name, return_index=True, return_inverse=True)
        like = first[which]
        if (length != length[like]).any() or (chars != chars[np.arange(len(chars)) + np.repeat(base[like] - base, length)]).any():
            # two words of one name: the names are only a short way to equal words
            return [np.array(code.ids, np.uint32) for code in self.library.encode_batch(texts, add_special_tokens=False)]
        words = [joined[a:b] for a, b in zip(at[first].tolist(), stop[first].tolist(), strict=True)]
        new = [w for w in words if w not in self.place]
        if len(self.place) + len(new) > CACHE_WORDS:
            new = words
            self.reset()
        self._learn(new)
        code = np.fromiter(map(self.place.__getitem__, words), np.int64, len(words))[which]
        begin, size = self.starts[code], self.starts[code + 1] - self.starts[code]
        before = np.cumsum(size) - size
        ids = self.flat[np.arange(size.sum()) - np.repeat(before - begin, size)]
        ends = np.cumsum([len(t) + 1 for t in texts])
        cut = np.append(before, len(ids))[np.searchsorted(at, ends)]
        return np.split(ids, cut[:-1])


def write_token_files(docs: DataFrame, path: str, tokenizer: str, end_id: int, key: str = "doc_id", text: str = "text") -> None:
    """Writes the ids of every whole text, ``end_id`` after each, into files below ``path`` in ascending order of ``key``.

    Null keys come first; a null text has the end id alone; rows of the same key stand side by side, ordered by text.
    Texts are dealt out once, by ranges of (key, hash of the text), so a key that many rows share is split over files.
    A document is in one segment; memory is that of a segment, or of the longest document.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col(key).cast("bigint").alias("k"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    parts = storage.shuffle_partitions(spark, storage.plan_bytes(docs, text))
    dealt = rows.withColumn("h", F.xxhash64("t")).repartitionByRange(parts, F.asc_nulls_first("k"), "h").sortWithinPartitions(F.asc_nulls_first("k"), "h", "t")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encoder, part, sequence = encoder_for(tokenizer), TaskContext.get().partitionId(), 0

        def segment(keys, texts):
            ids, sizes = encoder.encode(texts)
            ends = np.cumsum(sizes)
            whole = np.insert(ids, ends, np.uint32(end_id)).astype(np.uint32)
            return pa.RecordBatch.from_arrays([pa.array([pack_segment(part, sequence, keys, sizes + 1, whole)], pa.binary())], names=["segment"])

        keys, texts, held = [], [], 0
        for batch in batches:
            for k, t in zip(batch.column("k").to_pylist(), batch.column("t").to_pylist(), strict=True):
                if held and held + len(t) > SEGMENT_CHARS:
                    yield segment(keys, texts)
                    keys, texts, held, sequence = [], [], 0, sequence + 1
                keys.append(k)
                texts.append(t)
                held += len(t)
        if keys:
            yield segment(keys, texts)

    dealt.select("k", "t").mapInArrow(pack, "segment binary").select(F.col("segment").cast("string").alias("value")).write.text(path, lineSep="\n")


def read_token_files(spark: SparkSession, path: str, ids: bool = False) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32), and with ``ids`` the ids themselves, of every document in the files.

    ``start`` is the number of ids before the document: its place in its file, and the ids of all files before; the
    latter are summed over one row a file. The checksum is taken over little-endian unsigned 32-bit ids.
    """
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("content")
    schema = "part bigint, doc_id bigint, place bigint, n_tokens bigint, ids_crc32 bigint, ids array<bigint>"

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for value in batch.column("content"):
                place = 0
                for part, _, keys, sizes, levels in segments(value.as_py()):
                    tokens = decode_levels(levels).astype("<u4")
                    ends = np.cumsum(sizes)
                    cut = np.split(tokens, ends[:-1])
                    yield pa.RecordBatch.from_arrays([pa.array([part] * len(keys), pa.int64()), pa.array(keys, pa.int64()), pa.array(place + ends - sizes, pa.int64()), pa.array(sizes, pa.int64()), pa.array([zlib.crc32(c.tobytes()) for c in cut], pa.int64()), pa.array([c.astype(np.int64) for c in cut] if ids else [None] * len(cut), pa.list_(pa.int64()))], names=["part", "doc_id", "place", "n_tokens", "ids_crc32", "ids"])
                    place += int(ends[-1])

    docs = storage.materialize(files.mapInArrow(unpack, schema), "token-rows")
    sums = docs.groupBy("part").agg(F.sum("n_tokens").alias("n"))
    before = sums.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    out = docs.join(before, "part").select("doc_id", (F.col("before") + F.col("place")).cast("bigint").alias("start"), "n_tokens", "ids_crc32", *["ids"] * ids)
    return out
