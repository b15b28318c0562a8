"""Toxicity scores: gradient-boosted trees over dense text features, with isotonic calibration.

Features are densities of lexicon words and word beginnings, their nearness to second-person words, capitals,
punctuation and obfuscated spellings. The lexicon is learned from the labelled training rows by document-frequency lift;
a bounded sample of rows (``max_rows``) is all that the fit sees. Scoring reads every whole text once and shuffles nothing.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import storage

#: Most labelled rows that the fit takes, and most entries of the lexicon.
MAX_ROWS, MAX_TERMS = 16_000, 600
BEGINNING = 5
#: Second-person words of the four languages, and the letters that stand-in characters replace.
SECOND_PERSON = frozenset("you your yours yourself u ur du dich dir dein deine ihr euch euer tu te toi ton ta tes vous votre vos ti tú usted ustedes vosotros tuyo".split())
STAND_INS = str.maketrans("013457@$!|", "oieastasil")
STRIP = "".join(chr(c) for c in range(33, 127) if not chr(c).isalnum() and chr(c) not in "@$") + "«»“”‘’„…–—¡¿"
WORD, BEGIN, YOU, MASKED, MASKED_HIT = 1, 2, 4, 8, 16
FEATURES = ["hit_density", "hits", "weight_density", "top_weight", "kinds", "begin_density", "begins", "near_you", "you_density", "capitals", "punctuation", "shouting", "masked_rate", "masked_hits", "digits", "words", "word_length", "lines", "window_hits", "first_hit"]


def bare(word: str) -> str:
    return word.strip(STRIP)


def unmasked(word: str) -> str:
    """A spelling with stand-in characters and separators put right."""
    return re.sub(r"[^\w]|[\d_]", "", word.translate(STAND_INS))


def terms_of(text: str) -> set[str]:
    """Distinct words, and beginnings of longer words, marked ``w:`` and ``b:``."""
    words = {bare(w) for w in text.lower().split()}
    return {f"w:{w}" for w in words if 2 < len(w) <= 30} | {f"b:{w[:BEGINNING]}" for w in words if BEGINNING < len(w) <= 60}


class _Codes(dict):
    """Word -> flags and lexicon weight; cleared when full, so memory is bounded."""

    def __init__(self, lexicon: dict[str, float]):
        super().__init__()
        self.lexicon = lexicon

    def __missing__(self, word: str) -> int:
        w, flags, weight = bare(word), 0, 0.0
        if w in SECOND_PERSON:
            flags |= YOU
        if (x := self.lexicon.get(f"w:{w}")) is not None:
            flags, weight = flags | WORD, x
        elif len(w) > BEGINNING and (x := self.lexicon.get(f"b:{w[:BEGINNING]}")) is not None:
            flags, weight = flags | BEGIN, x
        elif w and not w.isalpha() and not w.isnumeric() and re.search(r"[^\W\d_]", w):
            flags |= MASKED
            u = unmasked(w)
            x = self.lexicon.get(f"w:{u}")
            if x is not None:
                flags, weight = flags | MASKED_HIT | WORD, x
        code = flags | int(min(weight, 30.0) * 64) << 5
        if len(self) > 400_000:
            self.clear()
        if len(word) < 80:
            self[word] = code
        return code


_UPPER, _LETTER, _PUNCT, _SHOUT, _DIGIT = (np.zeros(256, np.int64) for _ in range(5))
_UPPER[65:91] = 1
_LETTER[65:91] = _LETTER[97:123] = 1
_LETTER[0xC3] = 1
_DIGIT[48:58] = 1
for _c in range(33, 127):
    _PUNCT[_c] = not chr(_c).isalnum()
_SHOUT[[33, 63]] = 1


def features(text: str, codes: _Codes) -> list[float]:
    """The dense features of one whole text, in the order of :data:`FEATURES`."""
    words = text.lower().split()
    n = len(words)
    code = np.fromiter(map(codes.__getitem__, words), np.int64, n)
    counts = np.bincount(np.frombuffer(text.encode("utf-8", "replace"), np.uint8), minlength=256)
    chars, letters = max(1, int(counts.sum())), max(1, int(counts @ _LETTER))
    flagged = np.flatnonzero(code)
    fl = code[flagged]
    hit = flagged[(fl & WORD) > 0]
    begin = flagged[(fl & BEGIN) > 0]
    you = flagged[(fl & YOU) > 0]
    weights = (code[hit] >> 5) / 64
    both = np.sort(np.concatenate([hit, begin]))
    near = 0.0
    if len(both) and len(you):
        at = np.searchsorted(you, both)
        gap = np.minimum(np.abs(you[np.minimum(at, len(you) - 1)] - both), np.abs(both - you[np.maximum(at - 1, 0)]))
        near = float((gap <= 5).mean())
    window = int((np.searchsorted(both, both + 50) - np.arange(len(both))).max()) if len(both) else 0
    d = max(1, n)
    return [
        len(hit) / d, float(np.log1p(len(hit))), float(weights.sum()) / d, float(weights.max()) if len(hit) else 0.0, float(len({words[i] for i in hit})),
        len(begin) / d, float(np.log1p(len(begin))), near, len(you) / d, float(counts @ _UPPER) / letters, float(counts @ _PUNCT) / chars, float(counts @ _SHOUT) / chars,
        float(((fl & MASKED) > 0).sum()) / d, float(((fl & MASKED_HIT) > 0).sum()), float(counts @ _DIGIT) / chars, float(np.log1p(n)), chars / d, float(np.log1p(counts[10])), float(window), float(both[0]) / d if len(both) else 1.0,
    ]


# ---------------------------------------------------------------- boosted trees and calibration


@dataclass
class Model:
    """Trees as arrays: for each, (feature, threshold, left, right, value) by node; knots of the calibration; the lexicon."""

    lexicon: dict[str, float]
    base: float = 0.0
    trees: list[tuple[np.ndarray, ...]] = field(default_factory=list)
    knots: tuple[np.ndarray, np.ndarray] | None = None
    constant: float | None = None

    def raw(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.base)
        rows = np.arange(len(x))
        for feature, threshold, left, right, value in self.trees:
            node = np.zeros(len(x), np.int64)
            while (inner := left[node] >= 0).any():
                go = x[rows, np.maximum(feature[node], 0)] <= threshold[node]
                node = np.where(inner, np.where(go, left[node], right[node]), node)
            out += value[node]
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(x), self.constant)
        raw = self.raw(x)
        plain = 1 / (1 + np.exp(-np.clip(raw, -30, 30)))
        if self.knots is None:
            return plain
        return np.clip(0.98 * np.interp(raw, *self.knots) + 0.02 * plain, 0.0, 1.0)  # the small share keeps the order inside level steps


def boost(x: np.ndarray, y: np.ndarray, rounds: int = 80, depth: int = 3, rate: float = 0.15, bins: int = 48, l2: float = 1.0) -> tuple[float, list]:
    """Second-order boosting on binned features with logistic loss; returns the base and the trees."""
    cuts = [np.unique(np.quantile(c, np.linspace(0, 1, bins + 1)[1:-1])) for c in x.T]
    binned = np.stack([np.searchsorted(c, v, side="left") for c, v in zip(cuts, x.T, strict=True)], axis=1)
    n, f = x.shape
    p = np.clip(y.mean(), 1e-4, 1 - 1e-4)
    base, trees, least = float(np.log(p / (1 - p))), [], max(3, n // 1000)
    raw = np.full(n, base)
    offset = np.arange(f) * bins
    for _ in range(rounds):
        prob = 1 / (1 + np.exp(-raw))
        g, h = prob - y, np.maximum(prob * (1 - prob), 1e-6)
        feature, threshold, left, right, value = [-1], [0.0], [-1], [-1], [0.0]
        members = {0: np.arange(n)}
        for _ in range(depth):
            grown = {}
            for node, own in members.items():
                at = (binned[own] + offset).ravel()
                gs, hs, cs = (np.bincount(at, np.repeat(w, f), f * bins).reshape(f, bins).cumsum(1) for w in (g[own], h[own], np.ones(len(own))))
                G, H, C = gs[0, -1], hs[0, -1], len(own)
                gain = gs**2 / (hs + l2) + (G - gs) ** 2 / (H - hs + l2) - G * G / (H + l2)
                gain[(cs < least) | (C - cs < least)] = -1
                j, b = divmod(int(gain.argmax()), bins)
                if gain[j, b] <= 1e-6 or b >= len(cuts[j]):
                    continue
                go = binned[own, j] <= b
                feature[node], threshold[node], left[node], right[node] = j, float(cuts[j][b]), len(left), len(left) + 1
                for part in (own[go], own[~go]):
                    grown[len(left)] = part
                    feature.append(-1), threshold.append(0.0), left.append(-1), right.append(-1)
                    value.append(float(-rate * g[part].sum() / (h[part].sum() + l2)))
            members = grown
            if not grown:
                break
        tree = (np.array(feature), np.array(threshold), np.array(left), np.array(right), np.array(value))
        trees.append(tree)
        raw += Model({}, 0.0, [tree]).raw(x)
    return base, trees


def isotonic(raw: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Knots of the increasing step fit (pool-adjacent-violators), joined linearly between the middles of the steps."""
    order = np.argsort(raw, kind="stable")
    blocks: list[list[float]] = []  # sum of y, rows, sum of raw
    for r, v in zip(raw[order].tolist(), y[order].tolist(), strict=True):
        blocks.append([v, 1.0, r])
        while len(blocks) > 1 and blocks[-2][0] * blocks[-1][1] >= blocks[-1][0] * blocks[-2][1]:
            last = blocks.pop()
            blocks[-1] = [a + b for a, b in zip(blocks[-1], last, strict=True)]
    return np.array([b[2] / b[1] for b in blocks]), np.array([b[0] / b[1] for b in blocks])


# ---------------------------------------------------------------- on DataFrames


def fold(key: Column, folds: int = 5) -> Column:
    """crc32 of the key as text, modulo ``folds``; a null key counts as empty text."""
    return F.pmod(F.crc32(F.coalesce(key.cast("string"), F.lit("")).cast("binary")), F.lit(folds))


def fit(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "toxic", max_rows: int = MAX_ROWS, max_terms: int = MAX_TERMS) -> Model:
    """Fits lexicon, trees and calibration on the labelled rows of all folds but 0.

    At most ``max_rows`` labelled keys, and texts of them, take part, those with the smallest hash; this bounds what is
    broadcast and collected, however often keys repeat. The lexicon has the ``max_terms`` terms with the largest product of
    lift and number of toxic texts. Rows with a null label or key are left out; of several labels of a key, or a text, the
    largest counts; copies of a text count once, in the fold of their smallest key. Fold 1 calibrates. Without rows of
    both labels the model is constant: the share of the label, or 0. The fit is the same in whatever order rows arrive.
    """
    known = labels.select(F.col(key).alias("k"), F.col(label).cast("int").alias("y")).where(F.col("y").isNotNull() & F.col("k").isNotNull()).groupBy("k").agg(F.max("y").alias("y"))
    sample = known.where(fold(F.col("k")) != 0).orderBy(F.xxhash64("k"), "k").limit(max_rows)
    rows = docs.select(F.col(key).alias("k"), F.coalesce(F.col(text), F.lit("")).alias("t")).join(F.broadcast(sample), "k")
    rows = storage.materialize(rows.select("k", "y", fold(F.col("k")).alias("fold"), F.sha2("t", 256).alias("h"), "t"), "labelled-rows")
    chosen = rows.groupBy("h").agg(F.max("y").alias("y"), F.min(F.struct("k", "fold")).alias("at")).orderBy("h").limit(max_rows).select("h", "y", "at.fold")
    rows = storage.materialize(rows.groupBy("h").agg(F.first("t").alias("t")).join(F.broadcast(chosen), "h").select("t", "y", "fold"), "labelled-texts")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = (Counter(), Counter())
        for batch in batches:
            for t, y in zip(batch.column("t").to_pylist(), batch.column("y").to_pylist(), strict=True):
                seen[y > 0].update(terms_of(t))
            if len(seen[0]) + len(seen[1]) > 500_000:
                yield from told(seen)
                seen = (Counter(), Counter())
        yield from told(seen)

    def told(seen) -> Iterator[pa.RecordBatch]:
        terms = list(set(seen[0]) | set(seen[1]))
        for at in range(0, len(terms), 50_000):
            some = terms[at : at + 50_000]
            yield pa.RecordBatch.from_arrays([pa.array(some), *[pa.array([seen[k][t] for t in some], pa.int64()) for k in (0, 1)]], names=["term", "clean", "toxic"])

    counts = rows.where("fold <> 1").select("t", "y").mapInArrow(count, "term string, clean bigint, toxic bigint").groupBy("term").agg(F.sum("clean").alias("clean"), F.sum("toxic").alias("toxic"))
    clean, toxic = rows.where("fold <> 1").agg(F.count_if(F.col("y") <= 0), F.count_if(F.col("y") > 0)).first()
    lift = F.log((F.col("toxic") + 0.5) / (toxic + 1)) - F.log((F.col("clean") + 0.5) / (clean + 1))
    strong = counts.where((F.col("toxic") >= 5) & (F.col("toxic") > F.col("clean") / 4)).withColumn("lift", lift).where("lift >= 1.5")
    model = Model({r.term: r.lift for r in strong.orderBy(F.desc(F.col("lift") * F.col("toxic")), "term").limit(max_terms).collect()})
    data = rows.mapInArrow(_featurizer(model.lexicon, ["y", "fold"]), "y int, fold bigint, x array<double>").toPandas()
    if data["y"].nunique() < 2:
        model.constant = float(data["y"].mean()) if len(data) else 0.0
        return model
    x, y, held = np.stack(data["x"].to_numpy()), (data["y"] > 0).to_numpy(float), (data["fold"] == 1).to_numpy()
    order = np.lexsort([*x.T, y])  # the rows' order of arrival must not matter
    x, y, held = x[order], y[order], held[order]
    own = ~held if 0 < y[~held].sum() < (~held).sum() else np.ones(len(y), bool)
    model.base, model.trees = boost(x[own], y[own])
    if held.sum() >= 200 and min(y[held].sum(), (1 - y[held]).sum()) >= 20:
        model.knots = isotonic(model.raw(x[held]), y[held])
    return model


def _featurizer(lexicon: dict[str, float], keep: list[str], model: Model | None = None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes = _Codes(lexicon)
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                x = [features(v.as_py(), codes) for v in part.column("t")]
                out = pa.array(x, pa.list_(pa.float64())) if model is None else pa.array(model.score(np.array(x)))
                yield pa.RecordBatch.from_arrays([*[part.column(c) for c in keep], out], names=[*keep, "x"])

    return run


def score(docs: DataFrame, model: Model, text: str = "text", keep: list[str] | None = None, threshold: float = 0.5, names: tuple[str, str] = ("score", "predicted")) -> DataFrame:
    """``keep`` (all columns, if None) of ``docs`` with ``score`` (0 to 1) and ``predicted`` (1 from ``threshold`` on), or ``names``.

    A null text counts as empty; every row gets a score. Columns that clash with the new ones are replaced.
    """
    keep = [c for c in (docs.columns if keep is None else keep) if c not in names]
    inner = docs.select(*[F.col(c).alias(f"c{i}") for i, c in enumerate(keep)], F.coalesce(F.col(text), F.lit("")).alias("t"))
    kept = inner.columns[:-1]
    schema = ", ".join([*[f"{f.name} {f.dataType.simpleString()}" for f in inner.schema.fields[:-1]], "x double"])
    out = inner.mapInArrow(_featurizer(model.lexicon, kept, model), schema)
    return out.select(*[F.col(n).alias(c) for n, c in zip(kept, keep, strict=True)], F.col("x").alias(names[0]), (F.col("x") >= threshold).cast("int").alias(names[1]))
