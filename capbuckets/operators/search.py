"""The least-loss layout of two bucket sizes under a cap policy.

The *plan* engine is one Spark job over all pairs of sizes: fill thresholds once a size, privacy intervals in closed form
for each pair and value class, and the least (loss, s1, s2) of the first valid positions. The *driver* engine works on the
collected classes, pair by pair, with the best loss so far as a cutoff; it also has the baselines without prunings and
counts the work that each strategy does.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from capbuckets.functions.exact import ceil_div, div, quota
from capbuckets.operators.lattice import lattice, lattice_grid, loss_of, size_pairs
from capbuckets.operators.policy import classes

#: Most value classes that are collected to the driver, and most layouts that the plan without prunings lists.
MAX_CLASSES, MAX_LAYOUTS = 2_000_000, 50_000_000
#: Layouts up to which the driver looks at all of them itself, positions of a range in a task, and (positions x values) held at once.
DRIVER_LAYOUTS, RANGE, CHUNK_CELLS = 1 << 21, 1 << 18, 1 << 18
#: Positions of a range that are looked at together, and positions below which all values of a run are tested at once.
STRIP, FEW = 1 << 14, 1 << 10


@dataclass
class Layout:
    """A layout as (size, buckets) pairs; empty with a reason if there is none."""

    classes: list[tuple[int, int]] = field(default_factory=list)
    loss: int | None = None
    reason: str = ""
    counters: dict[str, int] = field(default_factory=dict)


def loss_of_layout(layout: Sequence[tuple[int, int]]) -> int:
    return sum(b * (s - 1) ** 2 for s, b in layout)


# ---------------------------------------------------------------- plan engine


def max_fill(grid: DataFrame) -> DataFrame:
    """(s, fill): the most buckets of size s that the values can fill, from (s, cnt, quota, mult).

    b buckets can be filled if A + b Q >= s b for every split of the values into those that give all their rows (A) and
    those that give their quota Q in each bucket; splits in order of cnt / quota are enough.
    """
    order = Window.partitionBy("s").orderBy("ratio").rowsBetween(Window.unboundedPreceding, 0)
    all_of = Window.partitionBy("s")
    g = grid.where("quota > 0").withColumn("ratio", F.col("cnt") / F.col("quota"))
    g = g.withColumn("all_q", F.sum(F.col("quota") * F.col("mult")).over(all_of)).withColumn("a", F.sum(F.col("cnt") * F.col("mult")).over(order)).withColumn("q", F.col("all_q") - F.sum(F.col("quota") * F.col("mult")).over(order))
    limit = F.when(F.col("q") < F.col("s"), div(F.col("a"), F.greatest(F.col("s") - F.col("q"), F.lit(1).cast("bigint"))))
    fill = F.when(F.first("all_q") < F.first("s"), F.lit(0).cast("bigint")).otherwise(F.min(limit))
    filled = g.groupBy("s").agg(fill.alias("fill"))
    sizes = grid.select("s").distinct()
    return sizes.join(filled, "s", "left").select("s", F.coalesce("fill", F.lit(0).cast("bigint")).alias("fill"))


def quota_classes(caps: DataFrame, low: int, high: int) -> DataFrame:
    """(s, cnt, quota, mult) for all sizes and value classes."""
    sizes = classes(caps).select("*", F.explode(F.sequence(F.lit(low).cast("bigint"), F.lit(high).cast("bigint"))).alias("s"))
    return sizes.select("s", "cnt", "cap_num", "cap_den", quota(F.col("s"), F.col("cap_num"), F.col("cap_den")).alias("quota"), "mult")


def valid_intervals(caps: DataFrame, low: int, high: int, n: int) -> DataFrame:
    """(s1, s2, b1_0, b2_0, d1, d2, lo, hi): positions of each lattice that are valid; none if lo > hi."""
    spark = caps.sparkSession
    grid = quota_classes(caps, low, high)
    fill = F.broadcast(max_fill(grid))
    lat = F.broadcast(lattice_grid(size_pairs(spark, low, high), n))  # bounded by the number of size pairs
    both = classes(caps).crossJoin(lat)
    q1, q2 = (quota(F.col(s), F.col("cap_num"), F.col("cap_den")) for s in ("s1", "s2"))
    both = both.select("s1", "s2", "b1_0", "b2_0", "d1", "d2", "k", (q1 * F.col("b1_0") + q2 * F.col("b2_0") - F.col("cnt")).alias("c"), (q2 * F.col("d2") - q1 * F.col("d1")).alias("m"))
    zero, none = F.lit(0).cast("bigint"), F.col("k") + 1
    lo = F.when(F.col("c") >= 0, zero).when(F.col("m") > 0, ceil_div(F.greatest(-F.col("c"), zero), F.greatest(F.col("m"), F.lit(1).cast("bigint")))).otherwise(none)
    hi = F.when((F.col("m") < 0) & (F.col("c") >= 0), F.least(F.col("k"), div(F.greatest(F.col("c"), zero), F.greatest(-F.col("m"), F.lit(1).cast("bigint"))))).otherwise(F.col("k"))
    privacy = both.groupBy("s1", "s2", "b1_0", "b2_0", "d1", "d2").agg(F.max(lo).alias("lo"), F.min(hi).alias("hi"))
    f1, f2 = fill.select(F.col("s").alias("s1"), F.col("fill").alias("fill1")), fill.select(F.col("s").alias("s2"), F.col("fill").alias("fill2"))
    out = privacy.join(F.broadcast(f1), "s1").join(F.broadcast(f2), "s2")
    lo_fill = ceil_div(F.greatest(F.col("b1_0") - F.col("fill1"), zero), F.col("d1"))
    hi_fill = F.when(F.col("fill2") >= F.col("b2_0"), div(F.greatest(F.col("fill2") - F.col("b2_0"), zero), F.col("d2"))).otherwise(F.lit(-1).cast("bigint"))
    return out.select("s1", "s2", "b1_0", "b2_0", "d1", "d2", F.greatest("lo", lo_fill).alias("lo"), F.least("hi", hi_fill).alias("hi"))


def search_range(caps: DataFrame) -> tuple[int, int]:
    """(rows, smallest useful size) of a policy: one row from the caps table."""
    r = caps.agg(F.coalesce(F.sum("cnt"), F.lit(0)).cast("bigint").alias("n"), F.coalesce(F.min(ceil_div(F.col("cap_den"), F.col("cap_num"))), F.lit(1)).cast("bigint").alias("low")).first()
    return r.n, r.low


def plan_search(caps: DataFrame, m_max: int = 50) -> DataFrame:
    """One row (s1, b1, s2, b2, loss) of the optimum, or none; ties go to the smaller sizes."""
    n, low = search_range(caps)
    v = valid_intervals(caps, low, m_max, n).where("lo <= hi").select("s1", (F.col("b1_0") - F.col("lo") * F.col("d1")).alias("b1"), "s2", (F.col("b2_0") + F.col("lo") * F.col("d2")).alias("b2"))
    row = F.struct("loss", "s1", "s2", "b1", "b2")
    best = v.withColumn("loss", loss_of(F.col("s1"), F.col("b1"), F.col("s2"), F.col("b2"))).agg(F.min(row).alias("r")).where("r IS NOT NULL")
    return best.select("r.s1", "r.b1", "r.s2", "r.b2", "r.loss")


def plan_search_one_size(caps: DataFrame, m_max: int = 50) -> DataFrame:
    """One row (s1, b1, loss): the least-loss layout of equal buckets, or none."""
    grid = quota_classes(caps, 1, m_max).crossJoin(F.broadcast(caps.agg(F.sum("cnt").alias("n")))).where("n % s = 0").withColumn("b", div(F.col("n"), F.col("s")))
    ok = grid.groupBy("s", "b").agg(F.bool_and(F.col("cnt") <= F.col("quota") * F.col("b")).alias("ok")).where("ok")
    return ok.agg(F.min(F.struct((F.col("b") * (F.col("s") - 1) * (F.col("s") - 1)).alias("loss"), "s", "b")).alias("r")).where("r IS NOT NULL").select(F.col("r.s").alias("s1"), F.col("r.b").alias("b1"), F.col("r.loss").alias("loss"))


# ---------------------------------------------------------------- driver engine


@dataclass(frozen=True)
class Counts:
    """Value classes on the driver: counts, cap ratios and multiplicities."""

    cnt: np.ndarray
    num: np.ndarray
    den: np.ndarray
    mult: np.ndarray

    @property
    def n(self) -> int:
        return int((self.cnt * self.mult).sum())

    def quota(self, s: int) -> np.ndarray:
        return np.minimum(s, s * self.num // self.den)


def collect_classes(caps: DataFrame) -> Counts:
    rows = classes(caps).orderBy("cnt", "cap_num", "cap_den").limit(MAX_CLASSES + 1).collect()
    if len(rows) > MAX_CLASSES:
        raise ValueError("too many value classes for the driver; use plan_search")
    at = lambda f: np.array([r[f] for r in rows], np.int64)
    return Counts(at("cnt"), at("cap_num"), at("cap_den"), at("mult"))


def fill_threshold(c: Counts, s: int) -> int:
    """Binary search for the most buckets of size s that can be filled."""
    q, low, high = c.quota(s), 0, c.n // s
    while low < high:
        b = (low + high + 1) // 2
        low, high = (b, high) if int((c.mult * np.minimum(q * b, c.cnt)).sum()) >= s * b else (low, b - 1)
    return low


def privacy_interval(c: Counts, lat, method: str = "linear") -> tuple[int, int]:
    """Positions at which every value fits into both classes together: one interval."""
    q1, q2 = c.quota(lat.s1), c.quota(lat.s2)
    if method == "three_part":
        return _three_part(c, lat, q1, q2)
    short, slope = q1 * lat.b1 + q2 * lat.b2 - c.cnt, q2 * lat.d2 - q1 * lat.d1
    if ((short < 0) & (slope <= 0)).any():
        return 0, -1
    up, down = (short < 0), (short >= 0) & (slope < 0)
    lo = int((-(short[up] // slope[up])).max(initial=0))
    hi = int((short[down] // -slope[down]).min(initial=lat.last))
    return lo, min(hi, lat.last)


def _three_part(c: Counts, lat, q1: np.ndarray, q2: np.ndarray) -> tuple[int, int]:
    """The same by parts: where the first class alone takes a value, where the second does, and between, by bisection."""
    lo, hi = 0, lat.last
    for o, x, y in zip(c.cnt.tolist(), q1.tolist(), q2.tolist(), strict=True):
        test = lambda i, o=o, x=x, y=y: min(x * lat.at(i)[0], o) + min(y * lat.at(i)[1], o) >= o
        slope = y * lat.d2 - x * lat.d1
        first, last = 0, lat.last
        if slope >= 0:  # false ... true
            a, b = 0, lat.last + 1
            while a < b:
                mid = (a + b) // 2
                a, b = (a, mid) if test(mid) else (mid + 1, b)
            first = a
        else:  # true ... false
            a, b = -1, lat.last
            while a < b:
                mid = (a + b + 1) // 2
                a, b = (mid, b) if test(mid) else (a, mid - 1)
            last = a
        lo, hi = max(lo, first), min(hi, last)
    return lo, hi


def valid_positions(c: Counts, lat, positions: np.ndarray) -> np.ndarray:
    """The conditions for many positions of a lattice, without any of their monotone structure."""
    return judged_positions(c, lat, positions)[0]


def fits_all(slope: np.ndarray, short: np.ndarray, positions: np.ndarray) -> np.ndarray:
    """Whether slope * position >= short for all values: a value at a time, or all at once where positions are few."""
    if len(positions) < FEW:
        return (slope[:, None] * positions >= short[:, None]).all(0)
    ok, held = np.ones(len(positions), bool), np.empty_like(positions)
    for a, b in zip(slope.tolist(), short.tolist(), strict=True):
        ok &= np.multiply(positions, a, out=held) >= b
    return ok


def rows_taken(c: Counts, q: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Rows that values of quota ``q`` can give to ``b`` buckets, for many numbers of buckets."""
    if len(b) < FEW:
        return (c.mult[:, None] * np.minimum(q[:, None] * b, c.cnt[:, None])).sum(0)
    out, held = np.zeros(len(b), np.int64), np.empty(len(b), np.int64)
    for quota_of, cnt, mult in zip(q.tolist(), c.cnt.tolist(), c.mult.tolist(), strict=True):
        np.minimum(np.multiply(b, quota_of, out=held), cnt, out=held)
        out += np.multiply(held, mult, out=held)
    return out


def judged_positions(c: Counts, lat, positions: np.ndarray) -> tuple[np.ndarray, int]:
    """(valid or not, values tested): a position is done with at the first run of values, each twice as long, that has one too many."""
    q1, q2 = c.quota(lat.s1), c.quota(lat.s2)
    short, slope = c.cnt - q1 * lat.b1 - q2 * lat.b2, q2 * lat.d2 - q1 * lat.d1  # a value fits where slope * position >= short
    left, tests, at, run = np.arange(len(positions)), 0, 0, 4
    while at < len(short) and len(left):
        v = slice(at, at + run)
        tests += len(short[v]) * len(left)
        left = left[fits_all(slope[v], short[v], positions[left])]
        at, run = at + run, 2 * run
    for q, s, first, step in ((q1, lat.s1, lat.b1, -lat.d1), (q2, lat.s2, lat.b2, lat.d2)):
        b = first + positions[left] * step
        left = left[rows_taken(c, q, b) >= s * b]
    ok = np.zeros(len(positions), bool)
    ok[left] = True
    return ok, tests


def judged_range(c: Counts, lat, start: int, stop: int) -> tuple[int | None, int]:
    """(first valid position, values tested) of the positions from ``start`` up to ``stop``, all of which are looked at."""
    first, tests, step = None, 0, max(64, min(CHUNK_CELLS, STRIP))
    for at in range(start, stop, step):
        valid, more = judged_positions(c, lat, np.arange(at, min(at + step, stop)))
        tests += more
        if first is None and valid.any():
            first = at + int(valid.argmax())
    return first, tests


def judge_all(spark: SparkSession, c: Counts, lats: Sequence) -> dict[tuple[int, int], tuple[int | None, int]]:
    """:func:`judged_range` of every whole list as a Spark job over ranges of positions, by pair of sizes."""
    ranges = [(i, at, min(at + RANGE, lat.last + 1)) for i, lat in enumerate(lats) for at in range(0, lat.last + 1, RANGE)]
    slots = max(1, min(len(ranges), 8 * spark.sparkContext.defaultParallelism))
    held = list(lats)

    def judge(batches):
        for batch in batches:
            for slot in batch["id"]:  # ranges are dealt in turn, as the first lists are the longest
                rows = [(i, *judged_range(c, held[i], start, stop)) for i, start, stop in ranges[slot::slots]]
                yield pd.DataFrame({"i": [r[0] for r in rows], "first": pd.array([r[1] for r in rows], "Int64"), "tests": [r[2] for r in rows]})

    out: dict[tuple[int, int], tuple[int | None, int]] = {}
    for i, first, tests in spark.range(0, slots, 1, slots).mapInPandas(judge, "i bigint, first bigint, tests bigint").collect():
        key = (held[i].s1, held[i].s2)
        least, sum_of = out.get(key, (None, 0))
        out[key] = (first if least is None else least if first is None else min(least, first), sum_of + tests)
    return out


def bounds_of(c: Counts) -> tuple[int, int]:
    need = -(-c.den // c.num)
    return int(need.min()), int(need.max())


def driver_search(c: Counts, m_max: int = 50, strategy: str = "full", low: int | None = None, spark: SparkSession | None = None) -> Layout:
    """``full``: loss cutoff, fill and privacy intervals. ``loss``: loss cutoff, positions one after another.
    ``none``: every position, as a job of ``spark`` where they are many. ``ilp``: an integer program for each pair, with the best
    loss so far as a bound. All give the same layout."""
    best = Layout(reason="no valid layout in the size range", counters=dict.fromkeys(("pairs", "positions", "tests", "listed"), 0))
    if not len(c.cnt):
        return best
    n = c.n
    smallest, ell = bounds_of(c)
    low = smallest if low is None else low
    if ell > m_max:
        best.reason = f"the strictest cap needs buckets of {ell}"
        return best
    fills: dict[int, int] = {}
    count = best.counters
    m = len(c.cnt)
    judged = None
    if strategy == "none":
        lats = [x for s1 in range(low, m_max + 1) for s2 in range(s1 + 1, m_max + 1) if (x := lattice(n, s1, s2))]
        if spark is not None and sum(x.last + 1 for x in lats) > DRIVER_LAYOUTS:
            judged = judge_all(spark, c, lats)
    for s1 in range(low, m_max + 1):
        for s2 in range(max(s1 + 1, ell if strategy in ("full", "loss") else s1 + 1), m_max + 1):
            lat = lattice(n, s1, s2)
            if lat is None:
                continue
            count["pairs"] += 1
            count["listed"] += lat.last + 1
            cut = lat.last if strategy == "none" else lat.cutoff(best.loss)
            if cut < 0:
                continue
            first = None
            if strategy == "full":
                for s in (s1, s2):
                    if s not in fills:
                        fills[s] = fill_threshold(c, s)
                        count["tests"] += m * max(1, n.bit_length())
                lo = max(0, -((fills[s1] - lat.b1) // lat.d1))
                hi = min(cut, (fills[s2] - lat.b2) // lat.d2)
                count["positions"] += 1
                if lo <= hi:
                    a, b = privacy_interval(c, lat)
                    count["tests"] += m
                    first = max(lo, a) if max(lo, a) <= min(hi, b) else None
            elif strategy == "ilp":
                first, nodes = ilp_first(c, lat, cut)
                count["tests"] += nodes * m
                count["positions"] += nodes
            elif strategy == "none":
                first, tests = judged[s1, s2] if judged is not None else judged_range(c, lat, 0, lat.last + 1)
                count["positions"] += lat.last + 1
                count["tests"] += tests
            else:
                step = max(64, CHUNK_CELLS // m)
                for at in range(0, cut + 1, step):
                    positions = np.arange(at, min(at + step, cut + 1))
                    valid, tests = judged_positions(c, lat, positions)
                    count["tests"] += tests
                    if valid.any():
                        first = at + int(valid.argmax())
                        count["positions"] += first - at + 1
                        break
                    count["positions"] += len(positions)
            if first is not None and (best.loss is None or lat.loss(first) < best.loss):
                b1, b2 = lat.at(first)
                best.classes, best.loss, best.reason = [(s1, b1), (s2, b2)], lat.loss(first), ""
    return best


def ilp_first(c: Counts, lat, last: int | None = None) -> tuple[int | None, int]:
    """(least position up to ``last`` at which an integer program has a solution, nodes looked at).

    Unknown are the position i and, for each value, its rows in the first class; they must fit into both classes and fill
    the first one. Given i the rest is a transport problem, whose corners are whole, so the linear relaxation is held as
    cuts on i alone: one a value, and for each class the one of the values that are short of its buckets. A node solves the
    relaxation at its lower end; the most demanding violated cut gives a new end, and as positions are whole, the branch
    below the next whole number is empty.
    """
    q1, q2 = c.quota(lat.s1), c.quota(lat.s2)
    at, last, nodes = 0, lat.last if last is None else min(last, lat.last), 0
    own, own_slope = c.cnt - q1 * lat.b1 - q2 * lat.b2, q1 * lat.d1 - q2 * lat.d2
    while at <= last:
        nodes += 1
        b1, b2 = lat.at(at)
        cuts = []  # (constant, slope): constant + slope * i <= 0
        short = own + own_slope * at > 0
        cuts += zip(own[short].tolist(), own_slope[short].tolist(), strict=True)
        for q, s, b, start, step in ((q1, lat.s1, b1, lat.b1, -lat.d1), (q2, lat.s2, b2, lat.b2, lat.d2)):
            few = q * b < c.cnt
            open_room = s - int((q * c.mult)[few].sum())  # room of a bucket that the values outside must fill
            constant, slope = open_room * start - int((c.cnt * c.mult)[~few].sum()), open_room * step
            if constant + slope * at > 0:
                cuts.append((constant, slope))
        if not cuts:
            return at, nodes
        if any(slope >= 0 for _, slope in cuts):
            return None, nodes
        at = max(-(constant // slope) for constant, slope in cuts)
    return None, nodes


def ilp_rows(c: Counts, lat, position: int) -> np.ndarray:
    """Whole rows of each value class (one value each) in the first class: a solution at ``position``."""
    b1, b2 = lat.at(position)
    low, high = np.maximum(0, c.cnt - c.quota(lat.s2) * b2), np.minimum(c.cnt, c.quota(lat.s1) * b1)
    left = lat.s1 * b1 - int(low.sum())
    room = high - low
    before = np.cumsum(room) - room
    return low + np.clip(left - before, 0, room)


def search_one_size(c: Counts, m_max: int = 50) -> Layout:
    """The least-loss layout of equal buckets: sizes that divide the rows, smallest first."""
    n = c.n
    for s in range(1, m_max + 1):
        if n and n % s == 0 and (c.cnt <= c.quota(s) * (n // s)).all():
            return Layout([(s, n // s)], n // s * (s - 1) ** 2)
    return Layout(reason="no valid layout in the size range")


def search_two_size(caps: DataFrame, m_max: int = 50, strategy: str = "full") -> Layout:
    """The driver engine over the collected classes of ``caps``."""
    return driver_search(collect_classes(caps), m_max, strategy, spark=caps.sparkSession)


def layout_row(spark: SparkSession, layout: Layout) -> DataFrame:
    """(s1, b1, s2, b2, loss) of a two-size layout, as :func:`plan_search` gives it."""
    rows = [(*layout.classes[0], *layout.classes[1], layout.loss)] if layout.classes else []
    return spark.createDataFrame(rows, "s1 bigint, b1 bigint, s2 bigint, b2 bigint, loss bigint")


def counters_row(spark: SparkSession, results: dict[str, Layout]) -> DataFrame:
    """(strategy, loss, pairs, positions, tests, listed) for each strategy."""
    rows = [(k, r.loss, *[r.counters[x] for x in ("pairs", "positions", "tests", "listed")]) for k, r in results.items()]
    return spark.createDataFrame(rows, "strategy string, loss bigint, pairs bigint, positions bigint, tests bigint, listed bigint")


def brute_force_plan(caps: DataFrame, low: int, high: int, n: int) -> DataFrame:
    """The search without prunings as a distributed job: every layout times every value class; refused beyond ``MAX_LAYOUTS``."""
    grid = lattice_grid(size_pairs(caps.sparkSession, low, high), n)
    if (grid.agg(F.sum(F.col("k") + 1)).first()[0] or 0) > MAX_LAYOUTS:
        raise ValueError("too many layouts for a search without prunings")
    from capbuckets.operators.lattice import enumerate_layouts

    every = enumerate_layouts(grid)
    both = every.crossJoin(F.broadcast(classes(caps)))
    q1, q2 = (quota(F.col(s), F.col("cap_num"), F.col("cap_den")) for s in ("s1", "s2"))
    u1, u2 = q1 * F.col("b1"), q2 * F.col("b2")
    keys = ["s1", "s2", "pos", "b1", "b2", "loss"]
    ok = both.groupBy(*keys).agg(F.bool_and(u1 + u2 >= F.col("cnt")).alias("p"), F.sum(F.col("mult") * F.least(u1, F.col("cnt"))).alias("f1"), F.sum(F.col("mult") * F.least(u2, F.col("cnt"))).alias("f2")).where((F.col("p")) & (F.col("f1") >= F.col("s1") * F.col("b1")) & (F.col("f2") >= F.col("s2") * F.col("b2")))
    return ok.agg(F.min(F.struct("loss", "s1", "s2", "b1", "b2")).alias("r")).where("r IS NOT NULL").select("r.s1", "r.b1", "r.s2", "r.b2", "r.loss")
