"""Count queries: a random pool, exact answers, and answers estimated from a release.

A query asks for rows whose value is in a list, for each of d quasi-identifiers and for the sensitive column. A pool is a
long table (query_id, d, attr, value) with attr ``v`` for the sensitive list; values are strings.
"""

from __future__ import annotations

import json
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from capbuckets.functions.exact import order_key, pick

#: Most rows of a pool that are collected, and most cells of the tables of a chunk.
MAX_POOL_ROWS, MAX_CELLS = 5_000_000, 1 << 26
#: Rows that a task holds a pool against at once, about, most cells of the compositions' values by queries, and most values of an
#: attribute that has its rows by sets of values.
CHUNK_ROWS, MAX_SHARES, NARROW = 1 << 18, 1 << 22, 64


def domains(df: DataFrame, columns: Sequence[str]) -> DataFrame:
    """(attr, value): distinct values of each column, in one pass."""
    long = df.select(F.explode(F.array(*[F.struct(F.lit(c).alias("attr"), F.col(c).cast("string").alias("value")) for c in columns])).alias("x"))
    return long.select("x.attr", "x.value").distinct()


def width(size: Column, d: Column, selectivity: float) -> Column:
    """Values in a list, so that d + 1 lists together let ``selectivity`` of evenly spread rows through."""
    return F.greatest(F.lit(1), F.ceil(F.round(size * F.pow(F.lit(selectivity), F.lit(1.0) / (d + 1)), 9)).cast("int"))


def query_pool(dom: DataFrame, qi: Sequence[str], n_queries: int, selectivity: float, seed: str, v: str = "v") -> DataFrame:
    """(query_id, d, attr, value): d from 1 to the number of quasi-identifiers, that many of them, and the sensitive list."""
    spark = dom.sparkSession
    q = F.col("query_id")
    queries = spark.range(n_queries).select(F.col("id").cast("int").alias("query_id")).withColumn("d", (pick(f"{seed}d", len(qi), q) + 1).cast("int"))
    names = [F.struct(order_key(f"{seed}a", q, F.lit(a)).alias("h"), F.lit(a).alias("a")) for a in qi]
    chosen = F.slice(F.transform(F.array_sort(F.array(*names)), lambda s: s["a"]), F.lit(1), F.col("d"))
    attrs = queries.select("query_id", "d", F.explode(F.concat(chosen, F.array(F.lit(v)))).alias("attr"))
    sized = dom.withColumn("size", F.count(F.lit(1)).over(Window.partitionBy("attr")))
    grid = attrs.join(sized, "attr")  # the pool grows with the queries, the domains with the table: Spark sizes them
    rank = F.row_number().over(Window.partitionBy("query_id", "attr").orderBy(order_key(f"{seed}v", q, F.col("attr"), F.col("value"))))
    return grid.withColumn("r", rank).where(F.col("r") <= width(F.col("size"), F.col("d"), selectivity)).select("query_id", "d", "attr", "value")


@dataclass
class PoolBits:
    """A pool on the driver: for each attribute, which queries allow a value, and which leave the attribute free."""

    ids: list[int]
    allowed: dict[str, dict[str, np.ndarray]]
    free: dict[str, np.ndarray]

    def chunks(self) -> Iterator[PoolBits]:
        """Parts of the pool whose tables have ``MAX_CELLS`` cells at most: these are what every task holds."""
        values = max(1, sum(len(x) for x in self.allowed.values()))
        step = max(1, MAX_CELLS // values)
        for at in range(0, len(self.ids), step):
            own = slice(at, at + step)
            yield PoolBits(self.ids[own], {a: {v: x[own] for v, x in m.items()} for a, m in self.allowed.items()}, {a: x[own] for a, x in self.free.items()})


def pool_bits(pool: DataFrame) -> PoolBits:
    """The pool collected; its size is that of the workload, not of the data, and is checked."""
    rows = pool.select("query_id", "attr", "value").limit(MAX_POOL_ROWS + 1).collect()
    if len(rows) > MAX_POOL_ROWS:
        raise ValueError("the pool is too large for the driver; answer it in parts")
    ids = sorted({r.query_id for r in rows})
    place = {q: i for i, q in enumerate(ids)}
    allowed: dict[str, dict[str, np.ndarray]] = {}
    free: dict[str, np.ndarray] = {}
    for r in rows:
        free.setdefault(r.attr, np.ones(len(ids), bool))[place[r.query_id]] = False
        allowed.setdefault(r.attr, {}).setdefault(r.value, np.zeros(len(ids), bool))[place[r.query_id]] = True
    return PoolBits(ids, allowed, free)


def weights_of(values: Column | str, counts: Column | str) -> Column:
    """The sensitive values that a row may have and their counts as text: what the rows of one composition share."""
    return F.to_json(F.struct(F.transform(values, lambda x: x.cast("string")).alias("v"), F.transform(counts, lambda x: x.cast("bigint")).alias("n")))


def pool_answers(df: DataFrame, pool: DataFrame | PoolBits, qi: Sequence[str], weights: str, shares: bool = False) -> DataFrame:
    """(query_id, answer) of a pool in one pass over weighted rows: a bit a row, for each value of each attribute.

    ``weights`` is a column of :func:`weights_of`. A row counts as often under each value as its count says or, with ``shares``,
    for the count's share of all counts. Rows are read once for each chunk of the pool.
    """
    pool = pool if isinstance(pool, PoolBits) else pool_bits(pool)
    plain = ("string", "tinyint", "smallint", "int", "bigint")  # other kinds are written out by Spark, as in the pool
    kinds = dict(df.dtypes)
    rows_in = df.select(*[F.col(c) if kinds[c] in plain else F.col(c).cast("string").alias(c) for c in qi], F.col(weights).alias("_weights"))
    out = None
    for part in pool.chunks():
        one = rows_in.mapInArrow(_evaluator(part, qi, shares), "query_id int, answer double")
        out = one if out is None else out.unionAll(one)
    if out is None:
        return df.sparkSession.createDataFrame([], "query_id int, answer double")
    return out.groupBy("query_id").agg(F.sum("answer").alias("answer"))


def _codes(column: pa.Array, place: dict[str, int], other: int) -> np.ndarray:
    """The place of each row's value, written out as text; ``other`` for nulls and for values without one."""
    held = column.dictionary_encode()
    table = np.array([*[place.get(str(x), other) for x in held.dictionary.to_pylist()], other], np.int32)
    return table[held.indices.fill_null(len(held.dictionary)).to_numpy(zero_copy_only=False)]


def _packed(mask: np.ndarray) -> np.ndarray:
    return np.packbits(mask).view(np.uint64)


class _Attribute:
    """A quasi-identifier's lists of a pool, and the rows of a chunk that each list allows, as bits."""

    def __init__(self, allowed: dict[str, np.ndarray], free: np.ndarray):
        self.place = {v: i for i, v in enumerate(allowed)}
        self.size, self.free = len(allowed), free
        self.member = np.array(list(allowed.values())).T  # query by value
        self.narrow = self.size <= NARROW
        if self.narrow:  # a list is one of 32 sets in each group of five values
            groups = -(-self.size // 5)
            bits = np.zeros((len(free), 5 * groups), np.int64)
            bits[:, : self.size] = self.member
            codes = bits.reshape(len(free), groups, 5) @ (1 << np.arange(5)) + 32 * np.arange(groups)
            self.sets = [x[x % 32 > 0].tolist() for x in codes]

    def hold(self, codes: np.ndarray) -> None:
        """``codes``: a place for each row; rows in no list and rows that are not there have ``size``."""
        self.codes = codes
        if not self.narrow:
            return
        self.rows = np.zeros((32 * -(-self.size // 5), len(codes) // 64), np.uint64)
        for i in range(self.size):
            group, bit = 32 * (i // 5), 1 << i % 5
            self.rows[group + bit] = _packed(codes == i)
            for x in range(1, bit):  # sets with this value as the last one
                np.bitwise_or(self.rows[group + bit], self.rows[group + x], out=self.rows[group + bit + x])

    def rows_of(self, query: int, out: np.ndarray) -> np.ndarray:
        """The rows that the list of ``query`` allows; ``out`` may be overwritten."""
        if not self.narrow:
            return _packed(np.append(self.member[query], False)[self.codes])
        sets = self.sets[query]
        if len(sets) < 2:
            return self.rows[sets[0] if sets else 0]
        np.bitwise_or(self.rows[sets[0]], self.rows[sets[1]], out=out)
        for x in sets[2:]:
            np.bitwise_or(out, self.rows[x], out=out)
        return out


def _evaluator(pool: PoolBits, qi: Sequence[str], shares: bool):
    n = len(pool.ids)
    used = [c for c in qi if c in pool.allowed]

    def evaluate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        attributes = [_Attribute(pool.allowed[c], pool.free[c]) for c in used]
        asked = [[a for a in attributes if not a.free[i]] for i in range(n)]
        sens_free = pool.free.get("v", np.ones(n, bool))
        sens = {v: x | sens_free for v, x in pool.allowed.get("v", {}).items()}

        def shares_of(texts: Sequence[str]) -> Iterator[tuple[int, np.ndarray]]:
            """(first query, what a row of each composition counts for) of blocks of queries."""
            parts = [json.loads(x) for x in texts]
            values = {v: i for i, v in enumerate(dict.fromkeys(v for x in parts for v in x["v"]))}
            entry = np.array([values[v] for x in parts for v in x["v"]])
            weight = np.concatenate([np.array(x["n"], float) / (sum(x["n"]) if shares else 1) for x in parts])
            start = np.cumsum([0, *[len(x["v"]) for x in parts[:-1]]])
            table = np.array([sens.get(v, sens_free) for v in values]).T  # query by value
            step = max(1, MAX_SHARES // len(entry))
            for first in range(0, n, step):
                yield first, np.add.reduceat(table[first : first + step, entry] * weight, start, axis=1)

        def answers(held: list[list[np.ndarray]], texts: Sequence[str]) -> np.ndarray:
            *codes, kind = [np.concatenate(x) for x in zip(*held, strict=True)]
            # rows of a composition lie together and fill whole words
            count = np.bincount(kind, minlength=len(texts))
            words = -(-count // 64)
            start = np.cumsum(words) - words
            order = np.argsort(kind, kind="stable")
            at = np.arange(len(kind)) + np.repeat(64 * start - (np.cumsum(count) - count), count)
            there = np.zeros(64 * int(words.sum()), bool)
            there[at] = True
            there = _packed(there)
            for a, x in zip(attributes, codes, strict=True):
                own = np.full(64 * len(there), a.size, np.min_scalar_type(a.size))
                own[at] = x[order]
                a.hold(own)
            out, one, rows = np.zeros(n), np.empty_like(there), np.empty_like(there)
            for first, block in shares_of(texts):
                for i, own in enumerate(block, first):
                    np.copyto(rows, there)
                    for a in asked[i]:
                        np.bitwise_and(rows, a.rows_of(i, one), out=rows)
                    out[i] = np.add.reduceat(np.bitwise_count(rows), start, dtype=np.int64) @ own
            return out

        total, held, size, texts = np.zeros(n), [], 0, {}
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                part = batch.slice(at, 4096)
                for text in part.column("_weights").unique().to_pylist():
                    texts.setdefault(text, len(texts))
                held.append([*[_codes(part.column(c), a.place, a.size) for c, a in zip(used, attributes, strict=True)], _codes(part.column("_weights"), texts, -1)])
                size += part.num_rows
                if size + 64 * len(texts) >= CHUNK_ROWS:  # a composition fills a word at least
                    total += answers(held, list(texts))
                    held, size, texts = [], 0, {}
        if size:
            total += answers(held, list(texts))
        yield pa.RecordBatch.from_arrays([pa.array(pool.ids, pa.int32()), pa.array(total)], names=["query_id", "answer"])

    return evaluate


def pool_exact(df: DataFrame, pool: DataFrame | PoolBits, qi: Sequence[str], v: str = "v") -> DataFrame:
    """(query_id, act) of a pool, from the rows: each counts once, under its own value."""
    rows = df.select(*qi, weights_of(F.array(v), F.array(F.lit(1))).alias("_w"))
    return pool_answers(rows, pool, qi, "_w").select("query_id", F.round("answer").cast("bigint").alias("act"))


def pool_estimate(qi_side: DataFrame, sa: DataFrame, pool: DataFrame | PoolBits, qi: Sequence[str]) -> DataFrame:
    """(query_id, est) of a pool, from the release alone: each row takes its bucket's values and counts along.

    Buckets of the same values and counts are of one composition; a task holds the pool against the rows of each composition.
    """
    held = sa.groupBy("bucket").agg(F.array_sort(F.collect_list(F.struct("v", "cnt"))).alias("_x"))
    met = qi_side.join(held.select("bucket", weights_of("_x.v", "_x.cnt").alias("_w")), "bucket")
    return pool_answers(met, pool, qi, "_w", shares=True).withColumnRenamed("answer", "est")


def relative_error(exact: DataFrame, estimate: DataFrame) -> DataFrame:
    """(query_id, act, est, re): re is null where the true answer is 0."""
    return exact.join(estimate, "query_id").select("query_id", "act", "est", F.when(F.col("act") > 0, F.abs(F.col("act") - F.col("est")) / F.col("act")).alias("re"))


def mean_error(errors: DataFrame) -> DataFrame:
    """One row (queries, skipped, mean_re): queries with a true answer of 0 are skipped and counted."""
    return errors.agg(F.count(F.lit(1)).alias("queries"), F.count_if(F.col("re").isNull()).alias("skipped"), F.avg("re").alias("mean_re"))


def rewrite_on_release(qi_side: DataFrame, sa: DataFrame, lists: dict[str, list], sensitive: list) -> DataFrame:
    """A count query over the raw table (values allowed by attribute, and sensitive values) turned into one over the release."""
    ok = F.lit(True)
    for attr, values in lists.items():
        ok = ok & F.col(attr).isin(*values)
    return estimate_count(qi_side, sa, ok, F.col("v").isin(*sensitive))


def estimate_count(qi_side: DataFrame, sa: DataFrame, qi_predicate: Column, sa_predicate: Column) -> DataFrame:
    """One row (est): a single count query, answered from the release."""
    q = qi_side.where(qi_predicate).groupBy("bucket").agg(F.count(F.lit(1)).alias("q"))
    s = sa.groupBy("bucket").agg(F.sum("cnt").alias("size"), F.sum(F.when(sa_predicate, F.col("cnt")).otherwise(0)).alias("s"))
    return q.join(s, "bucket").agg(F.coalesce(F.sum(F.col("q") * F.col("s") / F.col("size")), F.lit(0.0)).alias("est"))
