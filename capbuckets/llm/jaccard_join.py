"""Self-join of documents on the Jaccard similarity of their word n-gram sets, by MinHash banding.

Copies of a text are one node. Nodes that share a band name meet in a bucket; buckets with the same members as one of an
earlier band are dropped, as no pair meets there first. A pair is judged on its full n-gram sets, words against words, in
the first band in which it meets and nowhere else, so links are counted once without any table of pairs: each bucket returns, for each of
its members, a weight of links and one partner that leads to the rest of its component. A bucket of any size is cut into
blocks, and each pair of blocks is a task of bounded size.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import storage
from .shingles import WIDTH, band_names, choose_bands, exact_sets, shingle_set

#: Members, and shingles, of a block at most (on average, as blocks are dealt out by hash).
BLOCK_MEMBERS, BLOCK_SHINGLES = 1024, 4 << 20


def similar(a: np.ndarray, b: np.ndarray, both: np.ndarray, num: int, den: int) -> np.ndarray:
    """both / (a + b - both) >= num / den, in whole numbers."""
    return (both > 0) & (both * den >= (a + b - both) * num)


def linked_pairs(sets: list[np.ndarray], names: np.ndarray, band: int, left: np.ndarray, num: int, den: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (i, j) that first meet in ``band`` and are similar; if ``left`` is mixed, only pairs of its two sides."""
    size = np.array([len(s) for s in sets])
    found_i, found_j = [], []
    cross = left.any() and not left.all()
    for at in range(0, len(sets), 128):
        rows = np.arange(at, min(at + 128, len(sets)))
        same = names[rows, None, :] == names[None, :, :]
        ok = same[:, :, band] & ~same[:, :, :band].any(2)
        ok &= (left[rows, None] & ~left[None, :]) if cross else (rows[:, None] < np.arange(len(sets))[None, :])
        ok &= np.minimum(size[rows, None], size[None, :]) * den >= np.maximum(size[rows, None], size[None, :]) * num
        i, j = np.nonzero(ok)
        found_i.append(rows[i])
        found_j.append(j)
    i, j = np.concatenate(found_i), np.concatenate(found_j)
    if len(i) <= 8 * len(sets):
        both = np.array([len(np.intersect1d(sets[a], sets[b], assume_unique=True)) for a, b in zip(i, j, strict=True)], np.int64)
    else:
        both = _common(sets)[i, j]
    keep = similar(size[i], size[j], both, num, den) if len(i) else np.zeros(0, bool)
    return i[keep], j[keep]


def _common(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of all intersections, by products of membership matrices, some thousand shingles at a time."""
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    _, which, counts = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    keep = counts[which] > 1
    place = np.cumsum(counts > 1) - 1
    owner, which = owner[keep], place[which[keep]]
    out = np.zeros((len(sets), len(sets)), np.float32)
    order = np.argsort(which, kind="stable")
    owner, which = owner[order], which[order]
    for at in range(0, int(which[-1]) + 1 if len(which) else 0, 2048):
        a, b = np.searchsorted(which, [at, at + 2048])
        member = np.zeros((len(sets), 2048), np.float32)
        member[owner[a:b], which[a:b] - at] = 1
        out += member @ member.T
    return out.astype(np.int64)


def roots(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """The smallest member of each member's component."""
    root = np.arange(n)
    while True:
        low = np.minimum(root[i], root[j])
        after = root.copy()
        np.minimum.at(after, root[i], low)
        np.minimum.at(after, root[j], low)
        after = after[after]
        if (after == root).all():
            return root
        root = after


def components(edges: DataFrame) -> DataFrame:
    """(node, label): the smallest node of each component of ``edges`` (a, b), by label exchange with hooks and pointer jumps.

    A smaller label that a node hears goes to the node and to the node that its old label names, so that whole trees move at
    once and the rounds grow with the logarithm of a component's length. Rounds go on until no label changes; each
    lowers a label, so they end. Each is written to the shared folder. Nothing is collected but a count.
    """
    both = edges.where("a <> b").select("a", "b").unionAll(edges.where("a <> b").select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct()
    both = storage.materialize(both, "edges")
    labels = storage.materialize(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("label")), "labels")
    while True:
        heard = both.join(labels.select(F.col("node").alias("b"), F.col("label").alias("heard")), "b").groupBy(F.col("a").alias("node")).agg(F.min("heard").alias("heard"))
        near = labels.join(heard, "node").select("node", "label", F.least("label", "heard").alias("near"))
        own = F.struct("node", "label", "near")
        hook = F.struct(F.col("label").alias("node"), F.lit(None).cast(labels.schema["label"].dataType).alias("label"), "near")
        told = near.select(F.inline(F.when(F.col("near") < F.col("label"), F.array(own, hook)).otherwise(F.array(own))))
        new = told.groupBy("node").agg(F.max("label").alias("label"), F.min("near").alias("near"))
        jump = new.join(labels.select(F.col("node").alias("near"), F.col("label").alias("far")), "near").select("node", "label", F.least("near", "far").alias("next"))
        jump = storage.materialize(jump, "labels")
        labels = jump.select("node", F.col("next").alias("label"))
        if jump.where("label <> next").isEmpty():
            return labels


def jaccard_join(docs: DataFrame, key: str = "doc_id", text: str = "text", num: int = 4, den: int = 5, recall: float = 0.9995, width: int = WIDTH) -> DataFrame:
    """One row per row of ``docs``: key, ``class_id``, ``n_links`` and ``n_copies``.

    Two documents are linked if the Jaccard similarity of their sets of ``width``-word shingles is ``num/den`` or more.
    ``n_links`` counts the other rows that a row is linked to, copies of its text among them; ``class_id`` is the smallest
    key of its component; ``n_copies`` the rows with the very same text. Null texts count as empty; texts without a word
    are linked to rows of the same text only; a null key is a row like any other, and a class of null keys alone has a null
    id. Bands and rows are chosen so that a pair just at the threshold is met with probability ``recall``.
    """
    bands, rows = choose_bands(num / den, recall)
    base = docs.select(F.col(key).cast("bigint").alias("id"), F.coalesce(F.col(text), F.lit("")).alias("t")).withColumn("k", F.unhex(F.substring(F.sha2("t", 256), 1, 32)))

    def sketch(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                sets = [shingle_set(v.as_py(), width) for v in part.column("t")]
                named = [band_names(s, bands, rows).view(np.int64) for s in sets]
                yield pa.RecordBatch.from_arrays([part.column("id"), part.column("k"), pa.array([len(s) for s in sets], pa.int64()), pa.array(named, pa.list_(pa.int64()))], names=["id", "k", "n", "names"])

    sketches = storage.materialize(base.select("id", "k", "t").mapInArrow(sketch, "id bigint, k binary, n bigint, names array<bigint>"), "sketches")
    # rows of one text are one node; its smallest key stands for it
    nodes = sketches.groupBy("k").agg(F.min("id").alias("rep"), F.count(F.lit(1)).alias("copies"))
    first = sketches.groupBy("k").agg(F.min("n").alias("n"), F.min("names").alias("names"))
    met = first.select("k", "n", F.posexplode("names").alias("band", "name"))
    buckets = met.groupBy("band", "name").agg(F.count(F.lit(1)).alias("c"), F.sum("n").alias("total"), F.bit_xor(F.xxhash64("k")).alias("x"), F.bit_xor(F.xxhash64("k", F.lit(1))).alias("y")).where("c > 1")
    kept = buckets.groupBy("c", "x", "y").agg(F.min(F.struct("band", "name")).alias("at"), F.first("total").alias("total")).select("at.band", "at.name", "c", "total")
    kept = storage.materialize(kept.withColumn("blocks", F.greatest(F.ceil(F.col("c") / BLOCK_MEMBERS), F.ceil(F.col("total") / BLOCK_SHINGLES))).select("band", "name", "blocks"), "buckets")
    members = storage.materialize(met.select("k", "band", "name").join(kept, ["band", "name"]), "members")
    # every member meets every block of its bucket once
    own = F.pmod(F.xxhash64("k"), F.col("blocks"))
    dealt = members.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1).cast("array<bigint>")))
    dealt = dealt.select("k", "band", "name", "own", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"))
    known = nodes.join(first.select("k", "names"), "k").select("k", F.col("rep").alias("id"), "copies", "names")
    wanted = dealt.join(known, "k").select("k", "id", "copies", "names", "band", "name", "own", "lo", "hi")
    texts = base.select("id", "k", "t")
    full = wanted.join(texts, (wanted["k"] == texts["k"]) & wanted["id"].eqNullSafe(texts["id"])).select(wanted["k"], "t", "copies", "names", "band", "name", "own", "lo", "hi")

    def judge(group: pd.DataFrame) -> pd.DataFrame:
        group = group.drop_duplicates("k").sort_values("k")
        if len(group) < 2:
            return pd.DataFrame({"a": [], "b": [], "links": []})
        sets = exact_sets(group["t"].tolist(), width)
        names = np.stack(group["names"].to_list()).astype(np.int64)
        lo, hi = int(group["lo"].iloc[0]), int(group["hi"].iloc[0])
        left = np.ones(len(group), bool) if lo == hi else (group["own"] == lo).to_numpy()
        i, j = linked_pairs(sets, names, int(group["band"].iloc[0]), left, num, den)
        copies, links = group["copies"].to_numpy(), np.zeros(len(group), np.int64)
        np.add.at(links, i, copies[j])
        np.add.at(links, j, copies[i])
        k, on = group["k"].to_numpy(), links > 0
        return pd.DataFrame({"a": k[on], "b": k[roots(len(group), i, j)][on], "links": links[on]})

    judged = storage.materialize(full.groupBy("band", "name", "lo", "hi").applyInPandas(judge, "a binary, b binary, links bigint"), "links")
    links = judged.groupBy(F.col("a").alias("k")).agg(F.sum("links").alias("links"))
    labels = components(judged).withColumnsRenamed({"node": "k"})
    told = nodes.join(links, "k", "left").join(labels, "k", "left").withColumn("label", F.coalesce("label", "k"))
    told = storage.materialize(told, "nodes")
    classes = told.groupBy("label").agg(F.min("rep").alias("class_id"))
    per_node = told.join(classes, "label").select("k", "class_id", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.col("copies").alias("n_copies"))
    return sketches.select("id", "k").join(per_node, "k").select(F.col("id").alias(key), "class_id", "n_links", "n_copies")


def one_of_each_class(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of ``docs`` that stand for their class: those of the smallest key; repeated rows of that key all stay."""
    (own,) = storage.fresh(docs, "_id")
    joined = jaccard_join(docs, key, text)
    stay = joined.where(F.col(key).eqNullSafe(F.col("class_id"))).select(F.col(key).alias(own)).distinct()
    return docs.join(stay, F.col(key).cast("bigint").eqNullSafe(F.col(own)), "left_semi")
