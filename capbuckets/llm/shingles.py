"""Word shingles of texts, and MinHash sketches of their sets, by array operations.

Sketches rest on 64-bit names of shingles, as candidates may be too many but not too few. Decisions rest on
:func:`exact_sets`, which numbers the words and shingles of some texts by comparing the words themselves.
"""

from __future__ import annotations

import numpy as np

WIDTH = 5
_U = np.uint64
_BYTE = np.random.default_rng(11).integers(1, 1 << 63, 256, dtype=np.uint64) * _U(2) + _U(1)
_STEP = _U(0x9E3779B97F4A7C15)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every input bit (the finalizer of a public generator)."""
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def word_names(text: str) -> np.ndarray:
    """A 64-bit name for each word: lower case, split at white space."""
    data = np.frombuffer((" ".join(text.lower().split()) + " ").encode("utf-8", "replace"), np.uint8)
    if len(data) < 2:
        return np.zeros(0, np.uint64)
    stop = np.flatnonzero(data == 32)
    start = np.concatenate([[0], stop[:-1] + 1])
    length = stop - start + 1
    power = np.full(int(length.max()), _STEP)
    power[0] = 1
    power = np.multiply.accumulate(power)
    inside = np.arange(len(data)) - np.repeat(start, length)
    return mix(np.add.reduceat(_BYTE[data] * power[inside], start))


def shingle_set(text: str, width: int = WIDTH) -> np.ndarray:
    """Sorted distinct names of the runs of ``width`` words; a shorter text has one shingle of all its words, or none."""
    words = word_names(text)
    width = min(width, len(words))
    if not width:
        return words
    n = len(words) - width + 1
    total, factor = np.zeros(n, np.uint64), _U(1)
    for i in range(width):
        total += words[i : i + n] * factor
        factor = _U((int(factor) * 0xD6E8FEB86659FD93) & (1 << 64) - 1)
    return np.unique(mix(total))


def _numbered(high: np.ndarray, low: np.ndarray, low_count: int) -> tuple[np.ndarray, int]:
    """Numbers from 0 for the distinct pairs (high, low), and how many there are."""
    if int(high.max(initial=0)) < (1 << 62) // max(1, low_count):
        distinct, which = np.unique(high * low_count + low, return_inverse=True)
    else:
        distinct, which = np.unique(np.stack([high, low], 1), axis=0, return_inverse=True)
    return which.reshape(-1).astype(np.int64), len(distinct)


def exact_sets(texts: list[str], width: int = WIDTH) -> list[np.ndarray]:
    """For each text the sorted numbers of its distinct shingles; equal numbers are equal words, in any of the texts.

    Texts of fewer words have one shingle of all their words (unlike any of another length), or none.
    """
    number: dict[str, int] = {}
    words = [np.fromiter((number.setdefault(w, len(number)) for w in t.lower().split()), np.int64) for t in texts]
    count, sizes = len(number), np.array([len(w) for w in words], np.int64)
    out: list[np.ndarray] = [np.zeros(0, np.int64)] * len(texts)
    used = 0
    for n in sorted({min(width, int(x)) for x in sizes} - {0}):
        own = np.flatnonzero(sizes == n if n < width else sizes >= width)
        flat = np.concatenate([words[i] for i in own])
        ends = np.cumsum(sizes[own])
        begin = np.concatenate([np.arange(e - k, e - n + 1) for e, k in zip(ends, sizes[own], strict=True)])
        name, names = flat[begin], count
        for j in range(1, n):
            name, names = _numbered(name, flat[begin + j], count)
        for i, part in zip(own, np.split(name + used, np.cumsum(sizes[own] - n + 1)[:-1]), strict=True):
            out[i] = np.unique(part)
        used += names
    return out


def choose_bands(threshold: float, recall: float, most_hashes: int = 128) -> tuple[int, int]:
    """(bands, rows): the most rows a band, within ``most_hashes`` in all, that find a pair at ``threshold`` with ``recall``."""
    for rows in range(16, 0, -1):
        bands = int(np.ceil(np.log(1 - recall) / np.log(1 - threshold**rows)))
        if bands * rows <= most_hashes:
            return bands, rows
    raise ValueError("no banding within that many hashes has the recall")


def band_names(shingles: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """A 64-bit name for each band of the MinHash sketch; empty for an empty set."""
    if not len(shingles):
        return np.zeros(0, np.uint64)
    factors = np.random.default_rng(23).integers(1, 1 << 63, bands * rows, dtype=np.uint64) * _U(2) + _U(1)
    least = None
    for at in range(0, len(shingles), 2048):
        part = ((shingles[at : at + 2048, None] * factors) >> _U(32)).min(axis=0)
        least = part if least is None else np.minimum(least, part)
    least = least.reshape(bands, rows)
    name = np.arange(bands, dtype=np.uint64) + _U(1)
    for i in range(rows):
        name = mix(name * _STEP + least[:, i])
    return name
