"""Exact top-k search by inner product: a Voronoi kNN join.

Largest inner product is nearest neighbour after one added coordinate: with M the largest norm, a candidate x gets
sqrt(M^2 - |x|^2) and a query 0, so that |q - x|^2 = |q|^2 + M^2 - 2 q.x. Pivots cut that space into cells. Summaries of
the cells (sizes, radii, the k smallest distances to the pivot) bound the k-th distance of every query cell; a block of
candidates goes only to the query cells whose bound its ring can reach; each (query block, candidate blocks) is solved
by matrix products that keep a running top k.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import storage

#: Most pivots (they, and summaries of as many cells, are all that is collected), rings a cell, rows of a block.
MAX_PIVOTS, RINGS, BLOCK = 256, 8, 2048
#: Score of no partner: under every score, and safe to negate.
NONE = -(1 << 62)


def quantized(vector: Column | str, scale: int = 64) -> Column:
    """floor(scale * x) of every component as bigint; null for vectors that are null or hold null or non-finite components."""
    v = F.col(vector) if isinstance(vector, str) else vector
    ok = v.isNotNull() & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.when(ok, F.transform(v, lambda x: F.floor(x.cast("double") * scale).cast("bigint")))


def _matrix(column: pa.ListArray, dim: int) -> np.ndarray:
    lists = column.to_pylist() if column.null_count else None
    flat, offsets = column.flatten().to_numpy(zero_copy_only=False), np.asarray(column.offsets)
    if lists is None and len(flat) == dim * len(column) and (np.diff(offsets) == dim).all():
        return flat.reshape(-1, dim).astype(np.int64)
    out = np.zeros((len(column), dim), np.int64)
    for i in range(len(column)):
        row = np.asarray(column[i].as_py(), np.int64)
        out[i, : len(row)] = row
    return out


def _lifted(x: np.ndarray, top: float) -> np.ndarray:
    x = x.astype(np.float64)
    return np.concatenate([x, np.sqrt(np.maximum(top - (x * x).sum(1), 0))[:, None]], axis=1)


def _distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum((a * a).sum(1)[:, None] + (b * b).sum(1) - 2 * a @ b.T, 0))


def _products(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Exact integer inner products; by floating-point matrix product where that is exact."""
    if float(np.abs(q).max(initial=0)) * float(np.abs(x).max(initial=0)) * q.shape[1] < 2**52:
        return (q.astype(np.float64) @ x.T.astype(np.float64)).astype(np.int64)
    return q @ x.T


def voronoi_top_k(rows: DataFrame, key: str, vector: str, is_query: Column, k: int = 20) -> DataFrame:
    """(query_id, rank, vec_id, score): for every query row the ``k`` rows of other keys with the largest inner product.

    ``vector`` holds arrays of bigint; null vectors and null keys take no part, shorter vectors count as ended by zeros.
    Ties go to the smaller key; a query with fewer than ``k`` partners gets all of them. Rows that repeat a key count as
    partners of their own, but never of their own key; each row of a repeated query key has its own ``k`` answers. Pivots are
    a sample by hash, bounded by ``MAX_PIVOTS``, as they and k + 1 distances of each are collected; every row is
    searched. Cells are cut into rings by distance and into blocks of about ``BLOCK`` rows by hash, so a cell of any size
    is spread out; blocks, not rows, are matched with cells. Blocks are dealt out to shares, and a block of queries goes only
    to shares that hold a block which its cell can need. A vector is copied to the cells that need it and a query to no more
    shares than make as many copies, so what is moved grows in proportion to the rows.
    """
    spark = rows.sparkSession
    own = rows.select(F.col(key).cast("bigint").alias("id"), F.col(vector).alias("v"), is_query.alias("q")).where(F.col("v").isNotNull() & F.col("id").isNotNull())
    own = storage.materialize(own.withColumn("q", F.coalesce("q", F.lit(False))).withColumn("row", F.monotonically_increasing_id()), "vectors")
    square = F.aggregate("v", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    facts = own.agg(F.count(F.lit(1)).alias("n"), F.max(F.size("v")).alias("dim"), F.max(square).alias("top"), F.max(F.aggregate("v", F.lit(0).cast("bigint"), lambda a, x: F.greatest(a, F.abs(x)))).alias("widest"), F.count_if("q").alias("asked")).first()
    out_schema = "query_id bigint, rank int, vec_id bigint, score bigint"
    if not facts.n or not facts.dim:
        return spark.createDataFrame([], out_schema)
    dim, top = int(facts.dim), float(facts.top)
    small = next(t for t in (np.int8, np.int16, np.int32, np.int64) if facts.widest <= np.iinfo(t).max)
    spare = k + 1  # of so many different keys one at most is a query's own
    pivots = min(MAX_PIVOTS, max(4, facts.asked * 2 // BLOCK))  # a query cell should fill half a block
    sample = own.select("id", "v").orderBy(F.xxhash64("id"), "id").limit(pivots).collect()
    centre = np.zeros((len(sample), dim), np.int64)
    for i, r in enumerate(sample):
        centre[i, : len(r.v)] = r.v
    centre = _lifted(centre, top)
    apart = _distances(centre, centre)
    width = max(1e-9, 2 * top**0.5 / RINGS)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                part = batch.slice(at, 4096)
                x = _matrix(part.column("v"), dim)
                lifted, q = _lifted(x, top), np.asarray(part.column("q").to_pylist(), bool)
                data = pa.array([r.tobytes() for r in x.astype(small)], pa.binary())
                for chosen, kind in ((np.ones(len(x), bool), False), (q, True)):
                    if not chosen.any():
                        continue
                    z = lifted[chosen].copy()
                    if kind:
                        z[:, -1] = 0
                    d = _distances(z, centre)
                    cell = d.argmin(1)
                    near = d[np.arange(len(z)), cell]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(z), kind)), pa.array(cell.astype(np.int32)), pa.array(near), part.column("row").filter(pa.array(chosen)), part.column("id").filter(pa.array(chosen)), data.filter(pa.array(chosen))], names=["q", "cell", "d", "row", "id", "x"])

    placed = storage.materialize(own.mapInArrow(place, "q boolean, cell int, d double, row bigint, id bigint, x binary"), "placed")
    queries, data = placed.where("q"), placed.where("NOT q").withColumn("ring", F.floor(F.col("d") / width).cast("int"))

    # Summaries: a row a cell, or a ring of a cell; their number is bounded by that of the pivots.
    q_cells = queries.groupBy("cell").agg(F.count(F.lit(1)).alias("n"), F.max("d").alias("far")).collect()
    rings = data.groupBy("cell", "ring").agg(F.count(F.lit(1)).alias("n"), F.min("d").alias("lo"), F.max("d").alias("hi")).collect()
    by_key = data.groupBy("cell", "id").agg(F.min("d").alias("d"))
    nearest = by_key.select("cell", "id", "d", F.row_number().over(Window.partitionBy("cell").orderBy("d")).alias("r")).where(F.col("r") <= spare).select("cell", "id", "d").collect()
    if not q_cells or not rings:
        return spark.createDataFrame([], out_schema)
    cells, dist, keys = np.array([r.cell for r in nearest]), np.array([r.d for r in nearest]), np.array([r.id for r in nearest])
    bound = {}
    for r in q_cells:  # the k-th distance of any query of the cell, its own key left out
        upper = r.far + apart[r.cell, cells] + dist
        order = np.argsort(upper, kind="stable")
        _, first = np.unique(keys[order], return_index=True)
        upper = np.sort(upper[order][first])
        bound[r.cell] = float(upper[spare - 1]) if len(upper) >= spare else float("inf")
    slack = 1e-6 * (1 + top**0.5)
    reach = [(r.cell, r.ring, -(-r.n // BLOCK), t.cell, max(0.0, apart[t.cell, r.cell] - t.far - r.hi, r.lo - apart[t.cell, r.cell] - t.far)) for r in rings for t in q_cells]
    reach = [x for x in reach if x[4] <= bound[x[3]] + slack]
    routes = spark.createDataFrame(_grouped(reach), "cell int, ring int, parts bigint, targets array<struct<q_cell:int,least:double>>")
    held = {(r.cell, r.ring): r.n for r in rings}
    copies = sum(held[x[0], x[1]] for x in reach)  # rows of vectors that are moved
    shares = max(1, min(int(facts.n) // (16 * BLOCK), copies // max(1, facts.asked)))
    packed = data.join(F.broadcast(routes), ["cell", "ring"]).withColumn("part", F.pmod(F.xxhash64("id"), F.col("parts")))
    blocks = packed.groupBy("cell", "ring", "part").agg(F.first("targets").alias("targets"), F.collect_list(F.struct("id", "x")).alias("rows"))
    share = F.pmod(F.xxhash64("cell", "ring", "part"), F.lit(shares))
    blocks = blocks.withColumn("share", share).select("share", "rows", F.inline("targets"))
    sizes = F.broadcast(spark.createDataFrame([(r.cell, -(-r.n // BLOCK)) for r in q_cells], "q_cell int, parts bigint"))
    asked = queries.withColumnRenamed("cell", "q_cell").join(sizes, "q_cell").withColumn("q_part", F.pmod(F.xxhash64("id"), F.col("parts")))
    asked = asked.groupBy("q_cell", "q_part").agg(F.collect_list(F.struct("id", "x", "row")).alias("queries"))
    wanted = routes.select("cell", "ring", "targets", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("parts") - 1)).alias("part")).select(share.alias("share"), F.inline("targets")).select("share", "q_cell").distinct()
    asked = asked.join(wanted, "q_cell")
    tasks = blocks.join(asked, ["share", "q_cell"]).select("q_cell", "q_part", "least", "queries", "rows").sortWithinPartitions("q_cell", "q_part", "least")

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, qid, row, q, far, score, ids = None, None, None, None, None, None, None

        def told():
            if current is None:
                return
            keep = ids >= 0
            at = keep.ravel()
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(row, k)[at]), pa.array(np.repeat(qid, k)[at]), pa.array(ids[keep]), pa.array(score[keep])], names=["row", "query_id", "vec_id", "score"])

        for batch in batches:
            for i in range(batch.num_rows):
                name = (batch.column("q_cell")[i].as_py(), batch.column("q_part")[i].as_py())
                if name != current:
                    yield from told()
                    qid, q, row = _unpacked(batch.column("queries")[i], dim, small)
                    score, ids = np.full((len(qid), k), NONE), np.full((len(qid), k), -1, np.int64)
                    current, far = name, (q.astype(float) ** 2).sum(1) + top
                least = batch.column("least")[i].as_py()
                if (ids[:, -1] >= 0).all() and (least > np.sqrt(np.maximum(far - 2.0 * score[:, -1], 0)) + slack).all():
                    continue
                xid, x, _ = _unpacked(batch.column("rows")[i], dim, small)
                for at in range(0, len(xid), BLOCK):
                    some, its = x[at : at + BLOCK], xid[at : at + BLOCK]
                    s = _products(q, some)
                    ours = np.where(its[None, :] == qid[:, None], -1, its[None, :])
                    s = np.where(ours < 0, NONE, s)
                    if s.shape[1] > k:  # ties to the smaller id: ids ascend within a block
                        kth = -np.partition(-s, k - 1, axis=1)[:, k - 1]
                        keep = np.flatnonzero((s >= np.maximum(kth, score[:, -1])[:, None]).any(0))
                        s, ours = s[:, keep], ours[:, keep]
                    s, ours = np.concatenate([score, s], 1), np.concatenate([ids, ours], 1)
                    order = np.lexsort((np.where(ours < 0, np.iinfo(np.int64).max, ours), -s.astype(np.float64)), axis=1)[:, :k] if np.abs(s[s > NONE]).max(initial=0) < 2**52 else np.array([sorted(range(s.shape[1]), key=lambda j, r=r: (-int(s[r, j]), int(ours[r, j]) if ours[r, j] >= 0 else 2**63))[:k] for r in range(len(s))])
                    score, ids = np.take_along_axis(s, order, 1), np.take_along_axis(ours, order, 1)
        yield from told()

    local = tasks.mapInArrow(solve, "row bigint, query_id bigint, vec_id bigint, score bigint")
    ranked = local.withColumn("rank", F.row_number().over(Window.partitionBy("row").orderBy(F.desc("score"), "vec_id")))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _grouped(reach: list[tuple]) -> list[tuple]:
    out: dict[tuple, list] = {}
    for cell, ring, parts, target, least in reach:
        out.setdefault((cell, ring, parts), []).append((target, float(least)))
    return [(*k, v) for k, v in sorted(out.items())]


def _unpacked(value: pa.Scalar, dim: int, kind: type) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """(ids in ascending order, vectors, row numbers if there are any) of a block."""
    rows = value.values
    ids = rows.field(0).to_numpy(zero_copy_only=False).astype(np.int64)
    x = np.frombuffer(b"".join(rows.field(1).to_pylist()), kind).reshape(len(ids), dim).astype(np.int64)
    order = np.argsort(ids, kind="stable")
    row = rows.field(2).to_numpy(zero_copy_only=False).astype(np.int64)[order] if rows.type.num_fields > 2 else None
    return ids[order], x[order], row
