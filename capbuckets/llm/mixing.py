"""Mixing sources to target weights under a token budget, by DataFrame functions alone.

Levels (say domain, language, source) make a tree. From the root down, the budget of a node is shared out among its
children by weight; a child gets no more than its subtree holds (in all its epochs), and what it leaves goes to its
siblings by weight before anything is lost to the parent. A leaf with room for whole epochs takes them; what remains is
a prefix of the next epoch, whose order is a seeded hash. The prefix's end is found from sums over hash shards, so a leaf
of any size is never sorted as a whole, and texts are not moved.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import storage

#: Tokens of a shard at most, about: a leaf has 16, 256, ... of them as its own tokens ask for.
SHARD_TOKENS = 1_000_000


def token_count(text: Column) -> Column:
    """Words, as runs of non-space characters; none for null."""
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(r"\S+")).cast("bigint")


def epoch_order(seed: str, epoch: Column, key: Column) -> Column:
    """Order of a key in an epoch: hexadecimal, as many engines can compute it."""
    return F.md5(F.concat_ws(":", F.lit(seed), epoch.cast("string"), F.coalesce(key.cast("string"), F.lit("null"))))


def shard_digits(tokens: Column, shard_tokens: int) -> Column:
    """Leading hexadecimal digits of the hash that name a leaf's shards, none for a leaf of one shard."""
    steps = [F.when(tokens > F.lit(shard_tokens).cast("double") * 16.0**i, 1).otherwise(0) for i in range(12)]
    return sum(steps[1:], steps[0])


def shared_out(nodes: DataFrame, parent: list[str], order: list[str]) -> DataFrame:
    """Adds ``share``: the node's part of ``budget`` among its siblings by ``weight``, at most ``room``.

    With siblings in order of room / weight, those that fill up are a prefix: one fills up if, after all before it have,
    its own ratio times the weight still open fits into what is left. A weight of 0 gets nothing.
    """
    ratio = F.when(F.col("weight") > 0, F.col("room") / F.col("weight")).otherwise(F.lit(float("inf")))
    same = [F.col(c) for c in parent] or [F.lit(1)]
    before = Window.partitionBy(*same).orderBy("ratio", *order).rowsBetween(Window.unboundedPreceding, -1)
    family = Window.partitionBy(*same)
    sums = nodes.withColumn("ratio", ratio).withColumn("open", F.sum("weight").over(family) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))).withColumn("gone", F.coalesce(F.sum(F.when(F.col("weight") > 0, F.col("room")).otherwise(0.0)).over(before), F.lit(0.0)))
    full = sums.withColumn("full", (F.col("weight") > 0) & (F.col("gone") + F.col("ratio") * F.col("open") <= F.col("budget")))
    left = full.withColumn("rest", F.col("budget") - F.coalesce(F.sum(F.when(F.col("full"), F.col("room"))).over(family), F.lit(0.0))).withColumn("heavy", F.sum(F.when(~F.col("full"), F.col("weight")).otherwise(0.0)).over(family))
    share = F.when(F.col("full"), F.col("room")).when((F.col("weight") > 0) & (F.col("heavy") > 0), F.col("rest") * F.col("weight") / F.col("heavy")).otherwise(0.0)
    return left.withColumn("share", share).select(*nodes.columns, "share")


def leaf_budgets(leaves: DataFrame, levels: list[str], weights: dict[str, dict[str, float]], budget: Column, max_epochs: int) -> DataFrame:
    """(levels..., tokens, quota): whole tokens that each leaf may give; ``leaves`` has the levels and ``tokens``."""
    tree = leaves.withColumn("room", (F.col("tokens") * max_epochs).cast("double"))
    known, parent = None, []
    for i, level in enumerate(levels):
        own = levels[: i + 1]
        weight = F.lit(1.0)
        for value, w in sorted(weights.get(level, {}).items()):
            weight = F.when(F.col(level) == value, F.lit(float(w))).otherwise(weight)
        nodes = tree.groupBy(*own).agg(F.sum("room").alias("room"), F.first("total").alias("total"))
        nodes = (nodes.withColumn("budget", budget.cast("double")) if known is None else nodes.join(known, parent)).withColumn("weight", weight)
        known = shared_out(nodes, parent, [level]).select(*own, F.col("share").alias("budget"))
        parent = own
    return tree.join(known, parent).select(*levels, "tokens", F.floor(F.col("budget") + 1e-6).cast("bigint").alias("quota"))


def mix(docs: DataFrame, levels: dict[str, Column], weights: dict[str, dict[str, float]], budget: Column, seed: str, max_epochs: int = 1, key: str = "doc_id", text: str = "text", epoch: str = "_epoch") -> DataFrame:
    """Rows of ``docs`` that the mix takes, with ``epoch`` (0, 1, ...): a row once for each epoch that takes it.

    ``levels`` names the tree's levels from the root down, null values are a child of their own; ``weights`` has weights by
    level and value, 1 where none is named; ``budget`` is a column over ``total``, the tokens of all rows. A leaf's last
    epoch ends before the first key that would pass its quota; rows of one key are taken together. An empty table gives
    an empty mix; a column of the input by the name of ``epoch`` is replaced. The leaf table is joined by whatever way its written size allows.
    """
    own = storage.fresh(docs, *[f"_level{i}" for i in range(len(levels))])
    times, whole, rest, digits, shard, last_h = storage.fresh(docs, "_times", "_whole", "_rest", "_digits", "_shard", "_last")
    by_own = {o: weights.get(name, {}) for o, name in zip(own, levels, strict=True)}
    placed = docs.select("*", *[F.coalesce(c, F.lit("(none)")).alias(o) for o, c in zip(own, levels.values(), strict=True)])
    light = storage.materialize(placed.select(F.col(key).alias("k"), *own, token_count(F.col(text)).alias("tokens")), "mix-rows")
    leaves = light.groupBy(*own).agg(F.sum("tokens").alias("tokens"))
    leaves = leaves.withColumn("total", F.sum("tokens").over(Window.partitionBy(F.lit(1))))
    plan = storage.materialize(leaf_budgets(leaves, own, by_own, budget, max_epochs).withColumn("whole", F.when(F.col("tokens") > 0, F.floor(F.col("quota") / F.col("tokens"))).otherwise(F.lit(max_epochs)).cast("bigint")).withColumn("rest", F.when(F.col("tokens") > 0, F.col("quota") - F.col("whole") * F.col("tokens")).otherwise(F.lit(0)).cast("bigint")).withColumn("digits", shard_digits(F.col("tokens"), SHARD_TOKENS)), "mix-leaves")
    ordered = light.join(plan.where("rest > 0").select(*own, "whole", "rest", "digits"), own).withColumn("h", epoch_order(seed, F.col("whole"), F.col("k"))).withColumn("shard", F.substr("h", F.lit(1), F.col("digits")))
    sums = ordered.groupBy(*own, "rest", "shard").agg(F.sum("tokens").alias("n"))
    sums = sums.withColumn("before", F.coalesce(F.sum("n").over(Window.partitionBy(*own).orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    edge = storage.materialize(sums.where((F.col("before") <= F.col("rest")) & (F.col("before") + F.col("n") > F.col("rest"))).select(*own, "shard", "before"), "mix-edges")
    inside = ordered.join(edge, [*own, "shard"]).withColumn("sum", F.col("before") + F.sum("tokens").over(Window.partitionBy(*own, "shard").orderBy("h")))
    last = inside.where("sum <= rest").groupBy(*own).agg(F.max("h").alias("last"))
    cuts = plan.join(edge, own, "left").join(last, own, "left").select(*own, F.col("whole").alias(whole), F.col("rest").alias(rest), F.col("digits").alias(digits), F.col("shard").alias(shard), F.col("last").alias(last_h))
    cuts = storage.materialize(cuts, "mix-cuts")
    h = epoch_order(seed, F.col(whole), F.col(key))
    taken = F.coalesce((F.col(rest) > 0) & (F.substr(h, F.lit(1), F.col(digits)) < F.col(shard)), F.lit(False)) | F.coalesce(h <= F.col(last_h), F.lit(False))
    chosen = placed.join(cuts, own).withColumn(times, F.col(whole) + taken.cast("int")).where(F.col(times) > 0)
    return chosen.select(*[c for c in docs.columns if c != epoch], F.explode(F.sequence(F.lit(0), F.col(times).cast("int") - 1)).alias(epoch))
