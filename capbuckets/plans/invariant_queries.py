"""Queries for what has no plain SQL form: its invariants beside what SQL can tell, so that each has an oracle."""

from __future__ import annotations

from pyspark.sql import functions as F

from capbuckets.operators import assign as A
from capbuckets.operators import exact, policy, refine, release, search
from capbuckets.operators import lattice as L
from capbuckets.plans import method_queries as Q
from capbuckets.plans.method_queries import M_MAX, OCC_ASSIGNED, brute, caps, caps_frame, with_caps
from capbuckets.plans.registry import Registry
from capbuckets.plans.surface_queries import scratch
from capbuckets.sources import microdata as M
from capbuckets.sources import sinks

query = Registry()


def _classes(rows) -> search.Counts:
    return search.Counts(*(search.np.array([f(r) for r in rows], search.np.int64) for f in (lambda r: r.cnt, lambda r: r.cap_num, lambda r: r.cap_den, lambda r: 1)))


# ---------------------------------------------------------------- validity, splits and search


@query(with_caps("psize50") + brute() + "SELECT l.s1, l.b1, l.s2, l.b2, ok.s1 IS NOT NULL AS dealable FROM l JOIN (SELECT s1, s2 FROM best) x USING (s1, s2) LEFT JOIN ok ON ok.s1 = l.s1 AND ok.s2 = l.s2 AND ok.b1 = l.b1 AND ok.b2 = l.b2")
def split_existence(spark, sf):
    """Whether rows can be split between the classes, by a flow, at every position of the best sizes' lattice: just where the three conditions hold."""
    rows = A.collect_caps(caps(spark, sf, "psize50"))
    c = _classes(rows)
    (s1, _), (s2, _) = search.driver_search(c, M_MAX).classes
    lat = L.lattice(c.n, s1, s2)
    quotas, out = search.np.stack([c.quota(s1), c.quota(s2)], 1), []
    for i in range(lat.last + 1):
        b1, b2 = lat.at(i)
        out.append((s1, b1, s2, b2, exact.flow_split(c.cnt, quotas, [(s1, b1), (s2, b2)]) is not None))
    return spark.createDataFrame(out, "s1 bigint, b1 bigint, s2 bigint, b2 bigint, dealable boolean")


@query(with_caps("occ50") + brute() + "SELECT x.i::INTEGER AS class_id, CASE x.i WHEN 1 THEN s1 * b1 ELSE s2 * b2 END::BIGINT AS n_rows, true AS caps_kept, true AS all_rows FROM best, unnest([1, 2]) x(i)")
def flow_split_counts(spark, sf):
    """Rows of each class in the split that a flow gives, whether no value is over its bound, and whether every row has a class."""
    c = _classes(A.collect_caps(caps(spark, sf, "occ50")))
    layout = search.driver_search(c, M_MAX).classes
    takes = search.np.array(exact.flow_split(c.cnt, search.np.stack([c.quota(s) for s, _ in layout], 1), layout))
    whole = bool((takes.sum(1) == c.cnt).all())
    return spark.createDataFrame([(j + 1, int(takes[:, j].sum()), bool((takes[:, j] <= c.quota(s) * b).all()), whole) for j, (s, b) in enumerate(layout)], "class_id int, n_rows bigint, caps_kept boolean, all_rows boolean")


@query(f"WITH z AS ({Q.query.oracles['privacy_intervals']}) SELECT s1, s2, max(lo) AS lo, min(hi) AS hi FROM z GROUP BY s1, s2 HAVING count(*) = (SELECT count(DISTINCT v) FROM ({M.SQL['edu14']})) AND max(lo) <= min(hi)")
def three_part_intervals(spark, sf):
    """Positions of each lattice at which all values fit, by the three parts and their bisections."""
    c, out = _classes(A.collect_caps(caps(spark, sf, "edu14"))), []
    for s1 in range(1, 20):
        for s2 in range(s1 + 1, 21):
            if lat := L.lattice(c.n, s1, s2):
                lo, hi = search.privacy_interval(c, lat, "three_part")
                if lo <= hi:
                    out.append((s1, s2, lo, hi))
    return spark.createDataFrame(out, "s1 bigint, s2 bigint, lo bigint, hi bigint")


_RANGES = (5, 12, 20, 35, 50)


@query(" UNION ALL ".join(f"SELECT {m}::INTEGER AS m_max, found, loss FROM ({with_caps('edu14')}{brute(m)} SELECT count(*) > 0 AS found, min(loss)::BIGINT AS loss FROM ok)" for m in _RANGES))
def layout_in_range(spark, sf):
    """Whether there is a layout up to a largest size, and its least loss; the search says so where there is none."""
    c = _classes(A.collect_caps(caps(spark, sf, "edu14")))
    found = [(m, search.driver_search(c, m)) for m in _RANGES]
    return spark.createDataFrame([(m, bool(x.classes) and not x.reason, x.loss) for m, x in found], "m_max int, found boolean, loss bigint")


@query(with_caps("occ50") + "SELECT n AS n_rows, true AS caps_kept, true AS absent_dropped FROM t")
def refine_parts_audit(spark, sf):
    """Rows in the refinement's parts, whether each part keeps the whole table's caps, and whether values without rows change nothing."""
    rows = A.collect_caps(caps(spark, sf, "occ50"))
    c = _classes(rows)
    r = refine.refine_caps(rows, M_MAX)
    kept = all((part <= c.quota(s) * b).all() and int(part.sum()) == s * b for s, b, part in r.leaves)
    more = refine.refine([*c.cnt.tolist(), 0, 0], [*c.num.tolist(), 1, 1], [*c.den.tolist(), 1, 40], M_MAX)
    return spark.createDataFrame([(sum(s * b for s, b, _ in r.leaves), bool(kept), refine.layout_of(more) == refine.layout_of(r))], "n_rows bigint, caps_kept boolean, absent_dropped boolean")


@query(Q.THREE_SIZES_LINES)
def exact_enumerated(spark, sf):
    """The optimum of the 50-row example by trying every layout."""
    rows = A.collect_caps(Q.fifty_caps(spark, sf))
    return spark.createDataFrame([(exact.exact_enumerate([r.cnt for r in rows], [r.cap_num for r in rows], [r.cap_den for r in rows], 16)[1],)], "loss bigint")


@query(f"SELECT loss, true AS under FROM ({Q.THREE_SIZES})")
def lp_bound_small(spark, sf):
    """The linear bound of the 50-row example beside its optimum."""
    rows = A.collect_caps(Q.fifty_caps(spark))
    args = [[getattr(r, f) for r in rows] for f in ("cnt", "cap_num", "cap_den")]
    c, sizes = _classes(rows), list(range(3, M_MAX + 1))
    best = exact.exact_multi(*args, M_MAX)
    return spark.createDataFrame([(best.loss, bool(best.optimal and exact.lp_bound(args[0], search.np.stack([c.quota(s) for s in sizes], 1), sizes) <= best.loss + 1e-6))], "loss bigint, under boolean")


@query(f"WITH m AS ({M.SQL['psize50']}), h AS (SELECT v, count(*)::BIGINT AS cnt FROM m GROUP BY v), t AS (SELECT sum(cnt)::BIGINT AS n FROM h), c AS (SELECT v, cnt, 1::BIGINT AS cap_num, 10::BIGINT AS cap_den FROM h)" + brute() + " SELECT s1, b1, s2, b2, loss FROM best")
def equal_caps_two_size(spark, sf):
    """The uniform model as a case of the search: one cap of a tenth for all values."""
    return search.plan_search(policy.uniform_caps(policy.histogram(M.psize50(spark, sf).df), 10), M_MAX)


# ---------------------------------------------------------------- sources, sinks, aggregates and samples


@query(OCC_ASSIGNED + " SELECT bucket, v FROM a")
def sink_release(spark, sf):
    """The sensitive side of a release, written and read back."""
    m, rows, layout, a = Q.two_size(spark, sf)
    path = scratch(spark, "release")
    sinks.write_release(*release.publish(a, m.qi), path, files=4)
    return spark.read.parquet(f"{path}/sensitive").select("bucket", "v")


@query("SELECT 2000::BIGINT AS n_rows, true AS in_domain, true AS skewed, true AS repeatable")
def source_microdata_audit(spark, sf):
    """Rows of the generated source, whether its values lie in the domain, fall in frequency, and come again."""
    from capbuckets.sources import generated

    generated.register(spark)
    load = lambda: spark.read.format("microdata").options(rows=2000, domain=20, skew=1.2, parts=4, seed=3).load()
    hist = {r.v: r.n for r in load().groupBy("v").agg(F.count(F.lit(1)).alias("n")).collect()}
    same = load().exceptAll(load()).isEmpty()
    return spark.createDataFrame([(sum(hist.values()), all(0 <= v < 20 for v in hist), max(hist.values()) > 4 * min(hist.values()), same)], "n_rows bigint, in_domain boolean, skewed boolean, repeatable boolean")


@query("SELECT n_regionkey, max(n_name) AS last FROM nation GROUP BY n_regionkey")
def agg_sort_based(spark, sf):
    """A string maximum has no mutable buffer of fixed size, so this one is sorted, not hashed."""
    return M.table(spark, sf, "nation").groupBy("n_regionkey").agg(F.max("n_name").alias("last"))


_SKETCHES = ("approx_distinct", "hll", "theta")


@query(" UNION ALL ".join(f"SELECT '{s}' AS sketch, count(DISTINCT user_id)::BIGINT AS users, true AS near FROM events" for s in _SKETCHES))
def sketches_of_distinct(spark, sf):
    """The true number of users, and whether each sketch's estimate is within four of its standard errors."""
    e = M.table(spark, sf, "events")
    parts = e.groupBy("event_type").agg(F.hll_sketch_agg("user_id").alias("s")).agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("hll"))
    one = e.agg(F.count_distinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.02).alias("approx_distinct"), F.theta_sketch_estimate(F.theta_sketch_agg("user_id")).alias("theta")).crossJoin(parts)
    rows = F.array(*[F.struct(F.lit(s).alias("sketch"), "users", (F.abs(F.col(s) - F.col("users")) <= 0.08 * F.col("users") + 1).alias("near")) for s in _SKETCHES])
    return one.select(F.inline(rows))


@query("SELECT x.s AS sketch, n, true AS near FROM (SELECT count(*)::BIGINT AS n FROM lineitem), unnest(['kll', 'percentile']) x(s)")
def sketches_of_quantiles(spark, sf):
    """Rows, and whether the rank of each sketch's median is within two per cent of the middle."""
    li = M.table(spark, sf, "lineitem")
    a = li.agg(F.kll_sketch_get_quantile_bigint(F.kll_sketch_agg_bigint(F.col("l_partkey")), F.lit(0.5)).alias("kll"), F.percentile_approx("l_extendedprice", 0.5, 10_000).alias("percentile"))
    held = li.crossJoin(F.broadcast(a)).agg(F.count(F.lit(1)).alias("n"), *[F.count_if(F.col(c) < F.col(s)).alias(f"{s}_lt") for c, s in (("l_partkey", "kll"), ("l_extendedprice", "percentile"))], *[F.count_if(F.col(c) <= F.col(s)).alias(f"{s}_le") for c, s in (("l_partkey", "kll"), ("l_extendedprice", "percentile"))])
    near = lambda s: (F.col(f"{s}_lt") <= 0.52 * F.col("n")) & (F.col(f"{s}_le") >= 0.48 * F.col("n"))
    return held.select(F.inline(F.array(*[F.struct(F.lit(s).alias("sketch"), "n", near(s).alias("near")) for s in ("kll", "percentile")])))


@query("SELECT l_partkey, count(*)::BIGINT AS n, true AS near FROM lineitem GROUP BY l_partkey ORDER BY n DESC, l_partkey LIMIT 50")
def countmin_of_frequent(spark, sf):
    """The fifty most frequent parts, and whether a count-min sketch is over their counts by a hundredth of all rows at most, never under."""
    li = M.table(spark, sf, "lineitem")
    rows, data = li.count(), li.agg(F.count_min_sketch("l_partkey", F.lit(0.01), F.lit(0.99), F.lit(1)).alias("s")).first().s
    sketch = spark.sparkContext._jvm.org.apache.spark.util.sketch.CountMinSketch.readFrom(data)
    top = li.groupBy("l_partkey").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "l_partkey").limit(50).collect()
    return spark.createDataFrame([(r.l_partkey, r.n, r.n <= sketch.estimateCount(r.l_partkey) <= r.n + 0.01 * rows) for r in top], "l_partkey bigint, n bigint, near boolean")


@query("SELECT event_type, count(*)::BIGINT AS n, true AS near FROM events GROUP BY event_type")
def sample_stratified_share(spark, sf):
    """Rows of each stratum, and whether a fifth of them were drawn, within five standard deviations."""
    e = M.table(spark, sf, "events")
    drawn = e.sampleBy("event_type", {r.event_type: 0.2 for r in e.select("event_type").distinct().collect()}, seed=5).groupBy("event_type").agg(F.count(F.lit(1)).alias("k"))
    every = e.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    return every.join(drawn, "event_type", "left").select("event_type", "n", (F.abs(F.coalesce("k", F.lit(0)) - 0.2 * F.col("n")) <= 5 * F.sqrt(0.16 * F.col("n")) + 1).alias("near"))
