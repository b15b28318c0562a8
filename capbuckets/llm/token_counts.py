"""Exact token counts at every prefix of a text, by dynamic programming over byte-pair tokens.

In a byte-pair vocabulary whose merges are all proper, the encoding of a byte string is the only split into tokens
whose neighbours are *compatible*: encoding two neighbours together gives back just those two. So the last token of a
prefix is the one vocabulary suffix that is compatible with the last token of what stands before it, and

    count[i] = count[i - len(last[i])] + 1

gives the count at every prefix in one pass. The pre-tokenizer cuts a text into pieces that are encoded apart, so the
table of a text is put together from the tables of its pieces; these are cached by piece. Where a cut inside the text
would make the pre-tokenizer cut otherwise (runs of white space, contractions, added tokens) the table has the count
that the library gives for that prefix.
"""

from __future__ import annotations

import json
import os
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Texts of these characters alone are cut by the ``regex`` module as by the library; all others are cut by the library.
PLAIN = re.compile("[\\t\\n\\r\\x20-\\x7e\\u00a1-\\u012f\\u0131-\\u017f]*")
#: Fixed value: the splitting pattern that byte-level byte-pair tokenizers of this kind publish.
BYTE_LEVEL_SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
CONTRACTIONS = ("'re", "'ve", "'ll")
CACHE_PIECES = 250_000


def byte_alphabet() -> dict[str, int]:
    """The printable character that stands for each byte in vocabulary files: printable Latin-1 bytes stand for themselves, the rest follow from U+0100."""
    own = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(rest)}


class _Pieces(dict):
    """Piece -> its table of count steps; two generations, so memory is bounded and common pieces stay."""

    def __init__(self, make, room: int = CACHE_PIECES):
        super().__init__()
        self.make, self.room, self.old = make, room, {}

    def __missing__(self, piece):
        value = self.old.get(piece)
        if value is None:
            value = self.make(piece)
        self.keep(piece, value)
        return value

    def keep(self, piece, value) -> None:
        if len(self) >= self.room:
            self.old = dict(self)
            self.clear()
        if len(piece) <= 256:
            self[piece] = value


class PrefixCounter:
    """Count tables for one tokenizers-library file with a byte-level pre-tokenizer and a plain byte-pair model."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        pre, model = spec["pre_tokenizer"], spec["model"]
        if spec["normalizer"] or pre["type"] != "ByteLevel" or pre["add_prefix_space"] or model.get("end_of_word_suffix") or model.get("dropout"):
            raise ValueError("prefix counts need a byte-level pre-tokenizer, no normalizer and plain merges")
        to_byte = byte_alphabet()
        raw = lambda token: bytes(to_byte[c] for c in token)
        self.vocab = {raw(t) for t in model["vocab"] if all(c in to_byte for c in t)}
        merges = (m.split(" ") if isinstance(m, str) else m for m in model["merges"])
        self.rank = {(raw(a), raw(b)): i for i, (a, b) in enumerate(merges)}
        self.longest = max(map(len, self.vocab))
        if self.longest > 128:
            raise ValueError("a step of the table would not fit into a signed byte")
        self.ends: dict[bytes, tuple[int, ...]] = {}
        lengths: dict[bytes, set[int]] = {}
        for t in self.vocab:  # lengths of the tokens of two bytes and more that end in the same three bytes, or two
            if len(t) > 1:
                lengths.setdefault(t[-2:], set()).add(len(t))
            if len(t) > 2:
                lengths.setdefault(t[-3:], set()).add(len(t))
        for t in [t for t in lengths if len(t) == 3]:
            lengths[t] |= {2} & lengths.get(t[-2:], set())
        # three bytes that end no longer token leave the token of their last two
        self.ends = {k: tuple(sorted(v if len(k) == 3 else v & {2}, reverse=True)) for k, v in lengths.items()}
        self.fits: dict[tuple[bytes, bytes], bool] = {}
        self.steps = _Pieces(self._steps)
        self.cut = regex.compile(BYTE_LEVEL_SPLIT).findall
        self.added = [a["content"] for a in spec["added_tokens"]]
        if any(a["single_word"] or a["lstrip"] or a["rstrip"] for a in spec["added_tokens"]):
            raise ValueError("added tokens that take in their surroundings are not supported")
        self.added_at = re.compile("|".join(map(re.escape, sorted(self.added, key=len, reverse=True)))) if self.added else None

    def encode(self, piece: bytes) -> list[bytes]:
        """Byte-pair encoding by rank, for short byte strings."""
        parts = [piece[i : i + 1] for i in range(len(piece))]
        while len(parts) > 1:
            best = min(range(len(parts) - 1), key=lambda i: self.rank.get((parts[i], parts[i + 1]), 1 << 40))
            if (parts[best], parts[best + 1]) not in self.rank:
                break
            parts[best : best + 2] = [parts[best] + parts[best + 1]]
        return parts

    def _fits(self, left: bytes, right: bytes) -> bool:
        key = (left, right)
        known = self.fits.get(key)
        if known is None:
            if len(self.fits) > 400_000:
                self.fits.clear()
            known = self.fits[key] = self.encode(left + right) == ([left, right] if left else [right])
        return known

    def table(self, piece: bytes, count: list[int] | None = None, last: list[bytes] | None = None, start: int = 0) -> list[int]:
        """Token counts of all prefixes of a piece, by bytes: entry i is the count of its first i bytes.

        ``count`` and ``last`` are the tables of a piece that has its first ``start`` bytes in common with this one.
        """
        n, vocab, ends, fits, known = len(piece), self.vocab, self.ends, self._fits, self.fits
        count, last = ([0], [b""]) if count is None else (count, last)
        del count[start + 1 :], last[start + 1 :]
        for i in range(start + 1, n + 1):
            for size in ends.get(piece[i - 3 : i] if i > 2 else piece[:i], ends.get(piece[i - 2 : i], ())) if i > 1 else ():
                if size <= i and (t := piece[i - size : i]) in vocab:
                    left = last[i - size]
                    ok = known.get((left, t))
                    if ok or ok is None and fits(left, t):
                        break
            else:
                size, t = 1, piece[i - 1 : i]
            count.append(count[i - size] + 1)
            last.append(t)
        return count

    def warm(self, pieces: set[str]) -> None:
        """Makes the tables of new pieces in sorted order, so that each takes over what it has in common with the one before."""
        steps, count, last, before = self.steps, [0], [b""], b""
        for piece in sorted(p for p in pieces if p not in steps and p not in steps.old):
            data, k = piece.encode(), 0
            for x, y in zip(before, data, strict=False):
                if x != y:
                    break
                k += 1
            self.table(data, count, last, k)
            before = data
            steps.keep(piece, self._packed(piece, data, count))

    def _steps(self, piece: str) -> bytes:
        data = piece.encode()
        return self._packed(piece, data, self.table(data))

    @staticmethod
    def _packed(piece: str, data: bytes, count: list[int]) -> bytes:
        """Differences of the counts at successive characters of a piece, a signed byte each."""
        if piece in CONTRACTIONS:  # a cut inside leaves an apostrophe and a letter, which are pieces of their own
            return bytes([1, 1, (count[3] - 2) & 255])
        if len(data) == len(piece):
            return bytes([(b - a) & 255 for a, b in zip(count, count[1:], strict=False)])
        out, was = [], 0
        for i, b in enumerate(data[1:], 1):
            if b & 0xC0 != 0x80:
                out.append((count[i] - was) & 255)
                was = count[i]
        return bytes([*out, (count[-1] - was) & 255])

    def _plain(self, text: str, pieces: list[str] | None = None) -> bytes:
        """Steps of a text without added tokens."""
        if pieces is not None:
            pass
        elif PLAIN.fullmatch(text):
            pieces = self.cut(text)
        else:
            pieces = [text[a:b] for _, (a, b) in self.library.pre_tokenizer.pre_tokenize_str(text)]
        out = b"".join(map(self.steps.__getitem__, pieces))
        if not re.search(r"\s\s", text):
            return out
        steps, at = np.frombuffer(out, np.int8).copy(), 0
        for a, b in zip(pieces, pieces[1:], strict=False):  # a prefix that ends in a run of white space has the run as one piece
            at += len(a)
            if a.isspace() and b[0].isspace():
                whole = int(np.frombuffer(self.steps[a + b[0]], np.int8).sum(dtype=np.int64)) - int(np.frombuffer(self.steps[a], np.int8).sum(dtype=np.int64))
                change = whole - int(steps[at])
                steps[at] += change
                if at + 1 < len(steps):
                    steps[at + 1] -= change
        return steps.tobytes()

    def prefix_steps_of(self, texts: list[str]) -> list[bytes]:
        """:meth:`prefix_steps` of several texts."""
        cut = [self.cut(t) if PLAIN.fullmatch(t) and not (self.added_at and self.added_at.search(t)) else None for t in texts]
        self.warm(set().union(*[c for c in cut if c]))
        return [self.prefix_steps(t) if c is None else self._plain(t, c) for t, c in zip(texts, cut, strict=True)]

    def prefix_steps(self, text: str) -> bytes:
        """One signed byte per character: by how much the token count changes when the prefix takes in that character."""
        if not self.added_at or not self.added_at.search(text):
            return self._plain(text)
        out, at = [], 0
        for m in self.added_at.finditer(text):
            out.append(self._plain(text[at : m.start()]))
            inner = np.frombuffer(self._plain(text[at : m.end()]), np.int8)[len(text[at : m.start()]) :].copy()
            before = int(np.frombuffer(out[-1], np.int8).sum(dtype=np.int64))
            open_count = int(np.frombuffer(self._plain(text[at : m.end() - 1]), np.int8).sum(dtype=np.int64))
            inner[-1] = before + 1 - open_count
            # up to its last character the added token is common text, which joins on to what stands before it
            head = np.frombuffer(self._plain(text[at : m.end() - 1]), np.int8)
            out[-1] = head.tobytes() + inner[-1:].tobytes()
            at = m.end()
        out.append(self._plain(text[at:]))
        return b"".join(out)


_COUNTERS: dict[str, PrefixCounter] = {}


def counter_for(path: str) -> PrefixCounter:
    """The counter of this worker process: its tables live on from task to task."""
    os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
    if path not in _COUNTERS:
        _COUNTERS[path] = PrefixCounter(path)
    return _COUNTERS[path]


def counts_from_steps(steps: bytes) -> np.ndarray:
    """Token counts of the prefixes of 0, 1, 2, ... characters."""
    return np.concatenate([[0], np.cumsum(np.frombuffer(steps, np.int8), dtype=np.int64)])


def longest_prefix_within(steps: bytes, budget: int) -> int:
    """Characters of the longest prefix with at most ``budget`` tokens, without encoding again."""
    return int(np.flatnonzero(counts_from_steps(steps) <= budget)[-1]) if budget >= 0 else 0


def prefix_token_counts(docs: DataFrame, tokenizer: str, text: str = "text", keep: tuple[str, ...] = ("doc_id",), store: bool = True) -> DataFrame:
    """Adds to the columns ``keep`` of ``docs``: ``n_bytes`` (UTF-8), ``n_tokens`` and, with ``store``, ``prefix_steps``.

    ``prefix_steps`` has a signed byte per character (see :func:`counts_from_steps`); ``n_tokens`` is the table's last
    entry. A null text counts as empty: no bytes, no tokens, no steps. Repeated rows give repeated rows; other columns of
    ``docs`` don't take part. Nothing is shuffled; memory is that of the longest text and a bounded cache.
    """
    fields = [docs.schema[c] for c in keep]
    plain = docs.select(*[F.col(c).alias(f"k{i}") for i, c in enumerate(keep)], F.coalesce(F.col(text), F.lit("")).alias("t"))
    kept = plain.schema.names[:-1]
    schema = ", ".join([*[f"k{i} {f.dataType.simpleString()}" for i, f in enumerate(fields)], "n_bytes bigint", "n_tokens bigint", *["prefix_steps binary"] * store])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = counter_for(tokenizer)
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                sizes, tokens, steps = [], [], []
                texts = part.column("t").to_pylist()
                for t, row in zip(texts, counter.prefix_steps_of(texts), strict=True):
                    sizes.append(len(t) if t.isascii() else len(t.encode()))
                    tokens.append(int(np.frombuffer(row, np.int8).sum(dtype=np.int64)))
                    if store:
                        steps.append(row)
                yield pa.RecordBatch.from_arrays([*[part.column(c) for c in kept], pa.array(sizes, pa.int64()), pa.array(tokens, pa.int64()), *[pa.array(steps, pa.binary())] * store], names=[*kept, "n_bytes", "n_tokens", *["prefix_steps"] * store])

    return plain.mapInArrow(count, schema).withColumnsRenamed({f"k{i}": c for i, c in enumerate(keep)})


def over_limit(n_tokens: Column | str, limit: int) -> Column:
    """Whether a text has more tokens than ``limit``."""
    return (F.col(n_tokens) if isinstance(n_tokens, str) else n_tokens) > F.lit(limit)
