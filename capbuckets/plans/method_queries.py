"""Queries for the methods, measures, baselines and worked examples, each with the same question as DuckDB text.

The oracles share no logic with the engine: searches list every layout, ranks are plain windows, totals plain sums.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from capbuckets.operators import assign as A
from capbuckets.operators import attacks as X
from capbuckets.operators import exact, fixed_ell, noise, policy, refine, release, risk, search, validity, workload
from capbuckets.operators import lattice as L
from capbuckets.plans.registry import Registry
from capbuckets.sources import microdata as M

query = Registry()
THETA, M_MAX = 8, 50
THETAS = (2, 4, 8, 16, 32)
STRATEGIES = ("full", "loss", "none", "ilp")


def caps(spark, sf, name: str, theta: int = THETA) -> DataFrame:
    return policy.linear_caps(policy.histogram(M.MICRODATA[name](spark, sf).df), theta, 2, 100)


# ---------------------------------------------------------------- oracle text


def with_caps(name: str, a: str = "8", num: int = 2, den: int = 100, a_den: int = 1, extra: str = "") -> str:
    return f"""WITH m AS ({M.SQL[name]}), h AS (SELECT v, count(*)::BIGINT AS cnt FROM m GROUP BY v), t AS (SELECT sum(cnt)::BIGINT AS n FROM h),
        c AS (SELECT v, cnt, least(cnt * {a} * {den} + n * {num * a_den}, n * {den * a_den})::BIGINT AS cap_num, (n * {den * a_den})::BIGINT AS cap_den FROM h, t){extra} """


def quota_sql(s: str) -> str:
    return f"least({s}, {s} * cap_num // cap_den)"


def brute(m_max: int = 50, low: str = "(SELECT min((cap_den + cap_num - 1) // cap_num) FROM c)", table: str = "c") -> str:
    """CTEs l (all layouts) and ok (the valid ones), from caps c and total t."""
    return f""", p AS (SELECT s1, s2 FROM generate_series(1, {m_max}) a(s1), generate_series(1, {m_max}) b(s2) WHERE s1 < s2 AND s1 >= {low}),
        l0 AS (SELECT s1, s2, n, unnest(generate_series(0, n // s2)) AS b2 FROM p, t),
        l AS (SELECT s1, (n - s2 * b2) // s1 AS b1, s2, b2 FROM l0 WHERE (n - s2 * b2) % s1 = 0),
        ok AS (SELECT s1, b1, s2, b2, (b1 * (s1 - 1) * (s1 - 1) + b2 * (s2 - 1) * (s2 - 1))::BIGINT AS loss FROM l, {table}
               GROUP BY s1, b1, s2, b2
               HAVING bool_and({quota_sql('s1')} * b1 + {quota_sql('s2')} * b2 >= cnt) AND sum(least({quota_sql('s1')} * b1, cnt)) >= s1 * b1 AND sum(least({quota_sql('s2')} * b2, cnt)) >= s2 * b2),
        best AS (SELECT s1, b1, s2, b2, loss FROM ok ORDER BY loss, s1, s2 LIMIT 1)"""


def assigned_sql(key: str, salt: str = "s0") -> str:
    """CTE a: rows with class and bucket of the best two-size layout, split with rare values first."""
    keys = [k.strip() for k in key.split(",")]
    text = " || '|' || ".join(keys)
    return f""", k AS (SELECT v, cnt, least({quota_sql('s1')} * b1, cnt) AS u1, least({quota_sql('s2')} * b2, cnt) AS u2, s1, b1, s2, b2 FROM c, best),
        z AS (SELECT *, u1 + u2 - cnt AS slack, sum(u1) OVER () - s1 * b1 AS surplus FROM k),
        g AS (SELECT *, (u1 - greatest(0, least(slack, surplus - coalesce(sum(slack) OVER (ORDER BY cnt, v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))))::BIGINT AS take1 FROM z),
        w AS (SELECT *, cnt - take1 AS take2, coalesce(sum(take1) OVER o, 0) AS p1, coalesce(sum(cnt - take1) OVER o, 0) AS p2 FROM g WINDOW o AS (ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        r AS (SELECT *, row_number() OVER (PARTITION BY v ORDER BY md5('{salt}|' || {text}), {key}) AS t FROM m),
        a AS (SELECT r.*, CASE WHEN t <= take1 THEN 1 ELSE 2 END::INTEGER AS class_id,
                     (CASE WHEN t <= take1 THEN (p1 + t) % greatest(b1, 1) ELSE b1 + (p2 + t - take1) % greatest(b2, 1) END)::BIGINT AS bucket FROM r JOIN w USING (v)),
        sa AS (SELECT bucket, v, count(*)::BIGINT AS cnt FROM a GROUP BY bucket, v),
        bs AS (SELECT bucket, sum(cnt)::BIGINT AS size FROM sa GROUP BY bucket)"""


OCC_ASSIGNED = with_caps("occ50") + brute() + assigned_sql("event_id")


def two_size(spark, sf, name: str = "occ50", theta: int = THETA, salt: str = "s0", order: str = "rare_first", rows=None):
    """(microdata, caps rows, layout, assigned rows) of the two-size optimum."""
    m = M.MICRODATA[name](spark, sf)
    rows = A.collect_caps(policy.linear_caps(policy.histogram(m.df), theta, 2, 100)) if rows is None else rows
    layout = search.search_two_size(spark.createDataFrame(rows, "v int, cnt bigint, cap_num bigint, cap_den bigint"), M_MAX)
    return m, rows, layout, A.assign(m.df, "v", m.key, A.two_size_cuts(rows, layout.classes, order), salt)


def many_size(spark, sf, name: str = "occ50", theta: int = THETA, salt: str = "s0", order: str = "rare_first"):
    """(microdata, caps rows, refinement, assigned rows)."""
    m = M.MICRODATA[name](spark, sf)
    rows = A.collect_caps(policy.linear_caps(policy.histogram(m.df), theta, 2, 100))
    r = refine.refine_caps(rows, M_MAX, order)
    return m, rows, r, A.assign(m.df, "v", m.key, refine.leaf_cuts(r, [x.v for x in rows]), salt)


def caps_frame(spark, rows) -> DataFrame:
    return spark.createDataFrame(rows, "v int, cnt bigint, cap_num bigint, cap_den bigint")


# ---------------------------------------------------------------- policies


@query(with_caps("occ50") + "SELECT v, cnt FROM h")
def sa_histogram(spark, sf):
    return policy.histogram(M.occ50(spark, sf).df)


@query(with_caps("occ50") + "SELECT v, cnt, cap_num, cap_den FROM c")
def caps_linear(spark, sf):
    return caps(spark, sf, "occ50")


@query(with_caps("occ50") + "SELECT v, cnt, CASE WHEN v >= 40 THEN 1 WHEN v <= 1 THEN 1 ELSE cap_num END::BIGINT AS cap_num, CASE WHEN v >= 40 THEN 1 WHEN v <= 1 THEN 10 ELSE cap_den END::BIGINT AS cap_den FROM c")
def caps_mixed(spark, sf):
    return policy.mixed_caps(policy.histogram(M.occ50(spark, sf).df), {0: (1, 10), 1: (1, 10)}, list(range(40, 50)), THETA, 2, 100)


@query(with_caps("occ50") + "SELECT v, cnt, 1::BIGINT AS cap_num, 10::BIGINT AS cap_den FROM h")
def caps_uniform(spark, sf):
    return policy.uniform_caps(policy.histogram(M.occ50(spark, sf).df), 10)


@query(f"""SELECT * FROM ({with_caps('occ50')} SELECT 'linear' AS policy, bool_and(cap_num * n >= cnt * cap_den) AS feasible, count(*) FILTER (NOT cap_num * n >= cnt * cap_den)::BIGINT AS offenders FROM c, t)
        UNION ALL SELECT * FROM ({with_caps('edu14')} SELECT 'uniform' AS policy, bool_and(n >= cnt * 10) AS feasible, count(*) FILTER (NOT n >= cnt * 10)::BIGINT AS offenders FROM c, t)""")
def policy_feasible(spark, sf):
    a = policy.caps_feasible(caps(spark, sf, "occ50")).select(F.lit("linear").alias("policy"), "*")
    b = policy.caps_feasible(policy.uniform_caps(policy.histogram(M.edu14(spark, sf).df), 10)).select(F.lit("uniform").alias("policy"), "*")
    return a.unionByName(b)


@query(with_caps("occ50") + "SELECT min((cap_den + cap_num - 1) // cap_num)::BIGINT AS m_min, max((cap_den + cap_num - 1) // cap_num)::BIGINT AS ell FROM c")
def size_bounds(spark, sf):
    return policy.size_bounds(caps(spark, sf, "occ50"))


@query(with_caps("bigdom") + "SELECT cnt, cap_num, cap_den, count(*)::BIGINT AS mult FROM c GROUP BY cnt, cap_num, cap_den")
def cap_classes(spark, sf):
    return policy.classes(caps(spark, sf, "bigdom"))


# ---------------------------------------------------------------- validity


@query(with_caps("occ50") + f"SELECT s::INTEGER AS s, v, {quota_sql('s')}::BIGINT AS quota FROM c, generate_series(1, 50) g(s)")
def quota_grid(spark, sf):
    return validity.quota_table(caps(spark, sf, "occ50"), 1, 50)


@query(with_caps("occ50") + f"SELECT v, cnt, ({quota_sql('7')} * 1174)::BIGINT AS free_1, least({quota_sql('7')} * 1174, cnt)::BIGINT AS held_1, ({quota_sql('33')} * 54)::BIGINT AS free_2, least({quota_sql('33')} * 54, cnt)::BIGINT AS held_2 FROM c")
def class_bounds(spark, sf):
    return validity.class_bounds(caps(spark, sf, "occ50"), [(7, 1174), (33, 54)])


@query(with_caps("occ50") + "SELECT bool_and((cnt + n // 40 - 1) // (n // 40) * cap_den <= 40 * cap_num) AND any_value(n % 40 = 0) AS valid FROM c, t")
def valid_one_size(spark, sf):
    c = caps(spark, sf, "occ50")
    n, _ = search.search_range(c)
    return validity.valid_one_size(c, 40, n // 40, "ceil")


@query(with_caps("occ50") + f"""SELECT s::INTEGER AS s, (n // s)::BIGINT AS b, bool_and((cnt + n // s - 1) // (n // s) * cap_den <= s * cap_num) AS form_ceil, bool_and(cnt <= {quota_sql('s')} * (n // s)) AS form_quota
        FROM c, t, generate_series(1, 50) g(s) WHERE n % s = 0 GROUP BY s, n""")
def valid_one_size_all(spark, sf):
    c = policy.with_total(caps(spark, sf, "occ50")).select("*", F.explode(F.sequence(F.lit(1), F.lit(50))).alias("s")).where("n % s = 0")
    s, b = F.col("s").cast("bigint"), F.expr("n div s")
    return c.withColumn("b", b).groupBy("s", "b").agg(F.bool_and(validity.fits_one_size(s, F.col("b"), "ceil")).alias("form_ceil"), F.bool_and(validity.fits_one_size(s, F.col("b"))).alias("form_quota"))


_LAYOUTS = [(7, 1174, 33, 54), (7, 1207, 33, 47), (7, 1141, 33, 61), (2, 2000, 3, 2000)]


@query(with_caps("occ50") + f"""SELECT s1, b1, s2, b2, bool_and({quota_sql('s1')} * b1 + {quota_sql('s2')} * b2 >= cnt) AS privacy_ok, sum(least({quota_sql('s1')} * b1, cnt)) >= s1 * b1 AS fill1_ok,
        sum(least({quota_sql('s2')} * b2, cnt)) >= s2 * b2 AS fill2_ok, s1 * b1 + s2 * b2 = n AS room_ok,
        bool_and({quota_sql('s1')} * b1 + {quota_sql('s2')} * b2 >= cnt) AND sum(least({quota_sql('s1')} * b1, cnt)) >= s1 * b1 AND sum(least({quota_sql('s2')} * b2, cnt)) >= s2 * b2 AND s1 * b1 + s2 * b2 = n AS valid
        FROM c, t, (VALUES {', '.join(f'({a}::BIGINT, {b}::BIGINT, {x}::BIGINT, {y}::BIGINT)' for a, b, x, y in _LAYOUTS)}) y(s1, b1, s2, b2) GROUP BY s1, b1, s2, b2, n""")
def valid_two_size(spark, sf):
    return validity.valid_two_size(caps(spark, sf, "occ50"), spark.createDataFrame(_LAYOUTS, "s1 bigint, b1 bigint, s2 bigint, b2 bigint"))


_THREE = "WITH x AS (SELECT 5 AS cnt, [0, 0, 5] AS ub FROM range(10) UNION ALL SELECT 20, [20, 20, 20])"


@query(f"{_THREE} SELECT bool_and(list_sum(ub) >= cnt) AND sum(least(ub[1], cnt)) >= 20 AND sum(least(ub[2], cnt)) >= 20 AND sum(least(ub[3], cnt)) >= 30 AND sum(cnt) = 70 AS valid FROM x")
def naive_three_size_counterexample(spark, sf):
    return validity.valid_naive_multi(validity.three_class_bounds(spark), validity.THREE_CLASS_ROOMS)


@query(f"""{_THREE}, s AS (SELECT k AS mask, sum(least((k & 1) * ub[1] + (k >> 1 & 1) * ub[2] + (k >> 2) * ub[3], cnt))::BIGINT AS supply, any_value((k & 1) * 20 + (k >> 1 & 1) * 20 + (k >> 2) * 30)::BIGINT AS room
        FROM x, generate_series(1, 7) g(k) GROUP BY k) SELECT mask, supply, room, supply >= room AS ok FROM s""")
def valid_multi_subsets(spark, sf):
    return validity.subset_tests(validity.three_class_bounds(spark), validity.THREE_CLASS_ROOMS)


# ---------------------------------------------------------------- lattices


def _pairs(spark, low=2, high=12):
    return L.size_pairs(spark, low, high)


_ENUM = """WITH p AS (SELECT s1, s2 FROM generate_series(2, 12) a(s1), generate_series(2, 12) b(s2) WHERE s1 < s2),
        e AS (SELECT s1, s2, unnest(generate_series(0, 10000 // s2)) AS b2 FROM p),
        l AS (SELECT s1, s2, row_number() OVER (PARTITION BY s1, s2 ORDER BY b2) - 1 AS pos, (10000 - s2 * b2) // s1 AS b1, b2 FROM e WHERE (10000 - s2 * b2) % s1 = 0) """


@query(_ENUM + "SELECT s1, s2, pos, b1, b2, b1 * (s1 - 1) * (s1 - 1) + b2 * (s2 - 1) * (s2 - 1) AS loss FROM l")
def lattice_enumeration(spark, sf):
    return L.enumerate_layouts(L.lattice_grid(_pairs(spark), 10_000))


@query(_ENUM + "SELECT s1, s2, max(b1)::BIGINT AS b1_0, min(b2)::BIGINT AS b2_0, (max(b1) - max(b1) FILTER (pos = 1))::BIGINT AS d1, (min(b2) FILTER (pos = 1) - min(b2))::BIGINT AS d2, max(pos)::BIGINT AS k FROM l GROUP BY s1, s2")
def lattice_grid(spark, sf):
    return L.lattice_grid(_pairs(spark), 10_000)


@query("WITH e AS (SELECT b2 FROM generate_series(0, 7) g(b2) WHERE (28 - 4 * b2) % 2 = 0) SELECT row_number() OVER (ORDER BY b2) - 1 AS pos, (28 - 4 * b2) // 2 AS b1, b2 FROM e")
def lattice_worked_list(spark, sf):
    return L.enumerate_layouts(L.lattice_grid(spark.sql("SELECT 2L AS s1, 4L AS s2"), 28)).select("pos", "b1", "b2")


@query(_ENUM + "SELECT s1, s2, b1, b2 FROM l WHERE pos = 3")
def lattice_at_position(spark, sf):
    return L.lattice_at(L.lattice_grid(_pairs(spark), 10_000), F.lit(3).cast("bigint")).select("s1", "s2", "b1", "b2")


@query("""WITH p AS (SELECT s1, s2 FROM generate_series(1, 50) a(s1), generate_series(1, 50) b(s2) WHERE s1 < s2), n AS (SELECT DISTINCT count(*) AS n FROM events GROUP BY event_type),
        e AS (SELECT n, s1, s2, unnest(generate_series(0, n // s2)) AS b2 FROM p, n) SELECT n::BIGINT AS n, count(*)::BIGINT AS layouts FROM e WHERE (n - s2 * b2) % s1 = 0 GROUP BY n""")
def feasible_count(spark, sf):
    """Layouts of as many rows as an event type has, for each number of them."""
    rows = M.table(spark, sf, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n")).select("n").distinct()
    pairs = L.size_pairs(spark, 1, 50).crossJoin(rows)
    e = L.lattice_columns(F.col("n"), F.col("s1"), F.col("s2"))
    g = pairs.withColumn("g", e["g"]).withColumn("b2", e["b2_0"]).where("b2 IS NOT NULL AND s2 * b2 <= n")
    return g.groupBy("n").agg(F.sum(F.expr("((n - s2 * b2) div s1) div (s2 div g) + 1")).alias("layouts"))


@query(_ENUM + ", f AS (SELECT s1, s2, pos, b1 * (s1 - 1) * (s1 - 1) + b2 * (s2 - 1) * (s2 - 1) AS loss FROM l) SELECT count(*)::BIGINT AS steps, count(*) FILTER (a.loss >= b.loss)::BIGINT AS not_rising FROM f a JOIN f b ON a.s1 = b.s1 AND a.s2 = b.s2 AND b.pos = a.pos + 1")
def loss_monotone(spark, sf):
    e = L.enumerate_layouts(L.lattice_grid(_pairs(spark), 10_000))
    step = F.lead("loss").over(Window.partitionBy("s1", "s2").orderBy("pos"))
    return e.withColumn("next", step).where("next IS NOT NULL").agg(F.count(F.lit(1)).alias("steps"), F.count_if(F.col("loss") >= F.col("next")).alias("not_rising"))


@query(_ENUM + "SELECT s1, s2, coalesce(max(pos) FILTER (b1 * (s1 - 1) * (s1 - 1) + b2 * (s2 - 1) * (s2 - 1) < 30000), -1)::BIGINT AS cut FROM l GROUP BY s1, s2")
def loss_cutoff(spark, sf):
    return L.loss_cutoff(L.lattice_grid(_pairs(spark), 10_000), F.lit(30_000).cast("bigint"))


# ---------------------------------------------------------------- search


@query(with_caps("edu14") + f""", f AS (SELECT s, b, sum(least({quota_sql('s')} * b, cnt)) >= s * b AS ok FROM c, generate_series(1, 20) g(s), generate_series(0, 10000) i(b), t WHERE s * b <= n GROUP BY s, b)
        SELECT s, max(b) FILTER (ok)::BIGINT AS fill FROM f GROUP BY s""")
def max_fill(spark, sf):
    c = caps(spark, sf, "edu14")
    n, _ = search.search_range(c)
    return search.max_fill(search.quota_classes(c, 1, 20)).withColumn("fill", F.least("fill", F.expr(f"{n} div s")))


@query(with_caps("edu14") + brute(20, "1") + f""", y AS (SELECT s1, s2, b1, b2, row_number() OVER (PARTITION BY s1, s2 ORDER BY b2) - 1 AS pos FROM l),
        z AS (SELECT s1, s2, pos, bool_and({quota_sql('s1')} * b1 + {quota_sql('s2')} * b2 >= cnt) AND sum(least({quota_sql('s1')} * b1, cnt)) >= s1 * b1 AND sum(least({quota_sql('s2')} * b2, cnt)) >= s2 * b2 AS ok FROM y, c GROUP BY s1, s2, b1, b2, pos)
        SELECT s1, s2, min(pos)::BIGINT AS lo, max(pos)::BIGINT AS hi, count(*)::BIGINT AS valid FROM z WHERE ok GROUP BY s1, s2""")
def valid_intervals(spark, sf):
    c = caps(spark, sf, "edu14")
    n, _ = search.search_range(c)
    return search.valid_intervals(c, 1, 20, n).where("lo <= hi").select("s1", "s2", "lo", "hi", (F.col("hi") - F.col("lo") + 1).alias("valid"))


@query(with_caps("edu14") + brute(20, "1") + f""", y AS (SELECT s1, s2, b1, b2, row_number() OVER (PARTITION BY s1, s2 ORDER BY b2) - 1 AS pos FROM l)
        SELECT v, s1, s2, min(pos)::BIGINT AS lo, max(pos)::BIGINT AS hi FROM y, c WHERE {quota_sql('s1')} * b1 + {quota_sql('s2')} * b2 >= cnt GROUP BY v, s1, s2""")
def privacy_intervals(spark, sf):
    """Intervals of each value alone: the search over a policy that has just that value's condition."""
    rows = A.collect_caps(caps(spark, sf, "edu14"))
    n = sum(r.cnt for r in rows)
    out = []
    for r in rows:
        c = search.Counts(*(search.np.array([x], search.np.int64) for x in (r.cnt, r.cap_num, r.cap_den, 1)))
        for s1 in range(1, 20):
            for s2 in range(s1 + 1, 21):
                lat = L.lattice(n, s1, s2)
                if lat:
                    lo, hi = search.privacy_interval(c, lat, "three_part" if (s1 + s2) % 2 else "linear")
                    if lo <= hi:
                        out.append((r.v, s1, s2, lo, hi))
    return spark.createDataFrame(out, "v int, s1 bigint, s2 bigint, lo bigint, hi bigint")


_BEST = "SELECT s1, b1, s2, b2, loss FROM best"


@query(with_caps("occ50") + brute() + _BEST)
def two_size_optimal(spark, sf):
    return search.plan_search(caps(spark, sf, "occ50"), M_MAX)


@query(with_caps("edu14") + brute() + _BEST)
def two_size_edu(spark, sf):
    return search.plan_search(caps(spark, sf, "edu14"), M_MAX)


@query(with_caps("psize50") + brute() + _BEST)
def two_size_full(spark, sf):
    return search.layout_row(spark, search.search_two_size(caps(spark, sf, "psize50"), M_MAX))


@query(with_caps("occ50") + brute() + _BEST)
def two_size_loss(spark, sf):
    return search.layout_row(spark, search.search_two_size(caps(spark, sf, "occ50"), M_MAX, "loss"))


@query(with_caps("occ50") + brute() + _BEST)
def two_size_none(spark, sf):
    return search.layout_row(spark, search.search_two_size(caps(spark, sf, "occ50"), M_MAX, "none"))


@query(with_caps("psize50") + brute() + _BEST)
def two_size_none_plan(spark, sf):
    c = caps(spark, sf, "psize50")
    n, low = search.search_range(c)
    return search.brute_force_plan(c, low, M_MAX, n)


_FIFTY = "WITH h AS (SELECT * FROM (VALUES " + ", ".join(f"({i + 1}, {c}::BIGINT)" for i, c in enumerate(M.FIFTY)) + ") f(v, cnt)), t AS (SELECT 50::BIGINT AS n), c AS (SELECT v, cnt, least(cnt * 40 + 50, 1000)::BIGINT AS cap_num, 1000::BIGINT AS cap_den FROM h)"


#: The same from the quantities of the line items, see :func:`M.fifty_rows`.
_FIFTY_LINES = "WITH h AS (SELECT (CASE WHEN i < 8 THEN i + 1 WHEN i < 32 THEN 9 + (i - 8) // 6 ELSE 13 + (i - 32) // 9 END)::INTEGER AS v, count(*)::BIGINT AS cnt FROM (SELECT DISTINCT l_quantity::INTEGER - 1 AS i FROM lineitem) GROUP BY 1), t AS" + _FIFTY.split(", t AS")[1]


def fifty_caps(spark, sf: str | None = None) -> DataFrame:
    return policy.linear_caps(policy.histogram(M.fifty_rows(spark, sf).df), 2, 5, 100)


@query(_FIFTY + brute(14) + _BEST)
def two_size_ilp_small(spark, sf):
    return search.layout_row(spark, search.search_two_size(fifty_caps(spark), 14, "ilp"))


@query(_FIFTY_LINES + brute(50) + _BEST)
def fifty_rows_search(spark, sf):
    return search.plan_search(fifty_caps(spark, sf), M_MAX)


@query(with_caps("qty50") + f", y AS (SELECT s, n // s AS b FROM generate_series(1, 50) g(s), t WHERE n % s = 0), z AS (SELECT s, b FROM y, c GROUP BY s, b HAVING bool_and(cnt <= {quota_sql('s')} * b)) SELECT s AS s1, b AS b1, b * (s - 1) * (s - 1) AS loss FROM z ORDER BY loss LIMIT 1")
def one_size_optimal(spark, sf):
    return search.plan_search_one_size(caps(spark, sf, "qty50"), M_MAX)


@query(with_caps("occ50") + brute() + "SELECT u AS strategy, loss FROM best, unnest(['full', 'loss', 'none', 'ilp']) x(u)")
def strategies_agree(spark, sf):
    c = search.collect_classes(caps(spark, sf, "occ50"))
    return search.counters_row(spark, {s: search.driver_search(c, M_MAX, s, spark=spark) for s in STRATEGIES}).select("strategy", "loss")


@query()
def work_counters(spark, sf):
    """Pairs, positions, tests and list lengths of each strategy."""
    c = search.collect_classes(caps(spark, sf, "occ50"))
    return search.counters_row(spark, {s: search.driver_search(c, M_MAX, s, spark=spark) for s in STRATEGIES})


@query(with_caps("occ50") + brute() + "SELECT u AS strategy, loss, (SELECT count(*) FROM l)::BIGINT AS listed, true AS in_order FROM best, unnest(['full', 'loss', 'none']) x(u)")
def work_counters_order(spark, sf):
    """Each pruning looks at no more positions than the search with one pruning less; all lists together have every layout."""
    c = search.collect_classes(caps(spark, sf, "occ50"))
    found = {s: search.driver_search(c, M_MAX, s, spark=spark) for s in ("full", "loss", "none")}
    seen = {s: found[s].counters["positions"] for s in found}
    least = {"full": 0, "loss": seen["full"], "none": seen["loss"]}
    listed = found["none"].counters["listed"]
    return spark.createDataFrame([(s, f.loss, listed, least[s] <= seen[s] <= listed) for s, f in found.items()], "strategy string, loss bigint, listed bigint, in_order boolean")


# ---------------------------------------------------------------- assignment and releases


_DEAL = f"""WITH m AS ({M.SQL['psize50']}), r AS (SELECT *, row_number() OVER (PARTITION BY v ORDER BY md5('s0|' || p_partkey), p_partkey) AS t FROM m),
        h AS (SELECT v, count(*) AS cnt FROM m GROUP BY v), o AS (SELECT v, coalesce(sum(cnt) OVER (ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS p FROM h),
        nb AS (SELECT count(*) // 10 AS k FROM m), a AS (SELECT r.*, ((p + t) % k)::BIGINT AS bucket FROM r JOIN o USING (v), nb), sa AS (SELECT bucket, v, count(*)::BIGINT AS cnt FROM a GROUP BY bucket, v)"""


def dealt(spark, sf):
    """``psize50`` dealt over a tenth as many buckets."""
    m = M.psize50(spark, sf)
    return m, A.deal(m.df, "v", m.key, m.df.count() // 10, "s0")


@query(_DEAL + " SELECT p_partkey, v, bucket FROM a")
def deal_one_size(spark, sf):
    return dealt(spark, sf)[1].select("p_partkey", "v", "bucket")


@query(_DEAL + ", s AS (SELECT v, max(cnt) AS most, sum(cnt) AS cnt, count(*) AS held FROM sa GROUP BY v) SELECT v, (cnt // k)::BIGINT AS floor, most::BIGINT AS most, most <= (cnt + k - 1) // k AS ok FROM s, nb")
def deal_spread(spark, sf):
    m, d = dealt(spark, sf)
    k = m.df.count() // 10
    s = release.compact(d).groupBy("v").agg(F.max("cnt").alias("most"), F.sum("cnt").alias("cnt"))
    return s.select("v", F.expr(f"cnt div {k}").alias("floor"), "most", (F.col("most") <= F.expr(f"(cnt + {k} - 1) div {k}")).alias("ok"))


@query(OCC_ASSIGNED + " SELECT v, cnt, take1, take2 FROM w")
def split_counts(spark, sf):
    rows = A.collect_caps(caps(spark, sf, "occ50"))
    layout = search.plan_search(caps_frame(spark, rows), M_MAX).first()
    return A.split_plan(caps_frame(spark, rows), [(layout.s1, layout.b1), (layout.s2, layout.b2)])


@query(OCC_ASSIGNED + " SELECT class_id, v, count(*)::BIGINT AS cnt FROM a GROUP BY class_id, v")
def split_rows_counts(spark, sf):
    return two_size(spark, sf)[3].groupBy("class_id", "v").agg(F.count(F.lit(1)).alias("cnt"))


@query(OCC_ASSIGNED + " SELECT event_id, v, class_id, bucket FROM a")
def assign_two_size(spark, sf):
    return two_size(spark, sf)[3].select("event_id", "v", "class_id", "bucket")


@query(with_caps("occ50") + "SELECT n AS n_rows, 0::BIGINT AS violations, true AS ok, 0::BIGINT AS bag_diff FROM t")
def assign_multi(spark, sf):
    m, rows, r, a = many_size(spark, sf)
    got = release.audit(a, caps_frame(spark, rows)).select("n_rows", "violations", "ok")
    return got.crossJoin(release.bag_difference(a.select("v", *m.qi), m.df.select("v", *m.qi)).withColumnRenamed("difference", "bag_diff"))


@query(OCC_ASSIGNED + " SELECT sum(size)::BIGINT AS n_rows, count(*)::BIGINT AS buckets, 0::BIGINT AS violations, true AS ok FROM bs")
def audit_two_size(spark, sf):
    _, rows, _, a = two_size(spark, sf)
    return release.audit(a, caps_frame(spark, rows))


@query(with_caps("edu14") + "SELECT n AS n_rows, 0::BIGINT AS violations, true AS ok FROM t")
def audit_multi(spark, sf):
    _, rows, _, a = many_size(spark, sf, "edu14")
    return release.audit(a, caps_frame(spark, rows)).select("n_rows", "violations", "ok")


@query(OCC_ASSIGNED + " SELECT event_type, bucket, count(*)::BIGINT AS cnt FROM a GROUP BY event_type, bucket")
def qi_side_counts(spark, sf):
    m, _, _, a = two_size(spark, sf)
    return release.publish(a, m.qi)[0].groupBy("event_type", "bucket").agg(F.count(F.lit(1)).alias("cnt"))


@query(OCC_ASSIGNED + " SELECT bucket, v FROM a")
def sa_side(spark, sf):
    m, _, _, a = two_size(spark, sf)
    return release.publish(a, m.qi)[1]


@query(OCC_ASSIGNED + " SELECT bucket, v, cnt, size, round(cnt / size, 6) AS prob FROM sa JOIN bs USING (bucket)")
def bucket_risk(spark, sf):
    return release.bucket_risk(release.compact(two_size(spark, sf)[3])).withColumn("prob", F.round("prob", 6))


@query(OCC_ASSIGNED + " SELECT event_type, hour, v, round(max(cnt / size), 6) AS prob FROM (SELECT DISTINCT event_type, hour, bucket FROM a) JOIN sa USING (bucket) JOIN bs USING (bucket) GROUP BY event_type, hour, v")
def person_risk(spark, sf):
    _, _, _, a = two_size(spark, sf)
    qi_side, sa = release.publish(a, ("event_type", "hour"))
    return release.person_risk(qi_side, release.compact(sa), ("event_type", "hour")).withColumn("prob", F.round("prob", 6))


@query("""WITH a AS (SELECT c_nationkey, c_acctbal, c_mktsegment AS v, c_custkey // 2 AS bucket FROM customer), sa AS (SELECT bucket, v, count(*) AS cnt FROM a GROUP BY bucket, v), bs AS (SELECT bucket, count(*) AS size FROM a GROUP BY bucket)
        SELECT c_nationkey, c_acctbal, v, max(cnt / size) AS prob FROM (SELECT DISTINCT c_nationkey, c_acctbal, bucket FROM a) JOIN sa USING (bucket) JOIN bs USING (bucket) GROUP BY c_nationkey, c_acctbal, v""")
def four_rows_risk(spark, sf):
    """The smallest buckets, of two people each, here of customers: two different values have probability one half each."""
    qi = ("c_nationkey", "c_acctbal")
    dealt_by_two = M.table(spark, sf, "customer").select(*qi, F.col("c_mktsegment").alias("v"), F.expr("c_custkey div 2").alias("bucket"))
    qi_side, sa = release.publish(dealt_by_two, qi)
    return release.person_risk(qi_side, release.compact(sa), qi)


@query(OCC_ASSIGNED + " SELECT sum(size)::BIGINT AS n_rows, sum((size - 1) * (size - 1))::BIGINT AS loss, round(sum((size - 1) * (size - 1)) / (sum(size) - 1), 6) AS mse FROM bs")
def mse_of_release(spark, sf):
    return release.release_loss(release.compact(two_size(spark, sf)[3])).withColumn("mse", F.round("mse", 6))


@query(with_caps("edu14") + brute() + "SELECT loss, round(loss / (n - 1), 6) AS mse FROM best, t")
def loss_of_layout(spark, sf):
    c = caps(spark, sf, "edu14")
    n, _ = search.search_range(c)
    found = search.search_two_size(c, M_MAX)
    return spark.createDataFrame([(search.loss_of_layout(found.classes), round(release.layout_mse(found.loss, n), 6))], "loss bigint, mse double")


@query("SELECT 'raw' AS which, 0::BIGINT AS loss, 0::DOUBLE AS mse UNION ALL SELECT 'one_bucket', ((count(*) - 1) * (count(*) - 1))::BIGINT, (count(*) - 1)::DOUBLE FROM events")
def mse_extremes(spark, sf):
    n = M.table(spark, sf, "events").count()
    return spark.createDataFrame([(k, *v) for k, v in release.extreme_losses(n).items()], "which string, loss bigint, mse double")


# ---------------------------------------------------------------- many sizes


@query()
def multi_size_layout(spark, sf):
    """Classes of the refinement, equal sizes merged."""
    r = refine.refine_caps(A.collect_caps(caps(spark, sf, "occ50")), M_MAX)
    return spark.createDataFrame(refine.layout_of(r), "s int, b bigint")


@query(with_caps("occ50") + "SELECT n AS n_rows, true AS dealable, true AS within FROM t")
def multi_size_audit(spark, sf):
    """Rows that the refinement's classes hold, whether the caps allow them (by a flow), and whether the sizes are in range."""
    rows = A.collect_caps(caps(spark, sf, "occ50"))
    layout = refine.layout_of(refine.refine_caps(rows, M_MAX))
    quotas = [[min(s, s * r.cap_num // r.cap_den) for s, _ in layout] for r in rows]
    low = min(-(-r.cap_den // r.cap_num) for r in rows)
    return spark.createDataFrame([(sum(s * b for s, b in layout), exact.flow_split([r.cnt for r in rows], quotas, layout) is not None, all(low <= s <= M_MAX for s, _ in layout))], "n_rows bigint, dealable boolean, within boolean")


@query(with_caps("occ50") + brute() + "SELECT loss AS two_size, true AS not_more, n AS n_rows FROM best, t")
def multi_size_loss_le_two(spark, sf):
    rows = A.collect_caps(caps(spark, sf, "occ50"))
    r, two = refine.refine_caps(rows, M_MAX), search.search_two_size(caps_frame(spark, rows), M_MAX)
    held = sum(s * b for s, b in refine.layout_of(r))
    return spark.createDataFrame([(two.loss, r.loss <= two.loss, held)], "two_size bigint, not_more boolean, n_rows bigint")


THREE_SIZES = (
    _FIFTY
    + """, q AS (SELECT s, list(least(s, s * cap_num // cap_den) ORDER BY v) AS q FROM c, generate_series(3, 16) g(s) GROUP BY s), o AS (SELECT list(cnt ORDER BY v) AS o FROM c),
        e AS (SELECT a.s AS s1, b.s AS s2, d.s AS s3, unnest(generate_series(0, 50 // a.s)) AS b1, a.q AS q1, b.q AS q2, d.q AS q3 FROM q a, q b, q d WHERE a.s < b.s AND b.s < d.s),
        f AS (SELECT *, unnest(generate_series(0, (50 - s1 * b1) // s2)) AS b2 FROM e), k AS (SELECT *, (50 - s1 * b1 - s2 * b2) // s3 AS b3 FROM f WHERE (50 - s1 * b1 - s2 * b2) % s3 = 0),
        j AS (SELECT b1 * (s1 - 1) * (s1 - 1) + b2 * (s2 - 1) * (s2 - 1) + b3 * (s3 - 1) * (s3 - 1) AS loss, *, list_zip(q1, q2, q3, o) AS z FROM k, o),
        w AS (SELECT loss FROM j WHERE loss < 260 AND list_bool_and([x[1] * b1 + x[2] * b2 + x[3] * b3 >= x[4] FOR x IN z])
              AND list_sum([least(x[1] * b1, x[4]) FOR x IN z]) >= s1 * b1 AND list_sum([least(x[2] * b2, x[4]) FOR x IN z]) >= s2 * b2 AND list_sum([least(x[3] * b3, x[4]) FOR x IN z]) >= s3 * b3
              AND list_sum([least(x[1] * b1 + x[2] * b2, x[4]) FOR x IN z]) >= s1 * b1 + s2 * b2 AND list_sum([least(x[1] * b1 + x[3] * b3, x[4]) FOR x IN z]) >= s1 * b1 + s3 * b3
              AND list_sum([least(x[2] * b2 + x[3] * b3, x[4]) FOR x IN z]) >= s2 * b2 + s3 * b3)
        SELECT min(loss)::BIGINT AS loss FROM w"""
)

THREE_SIZES_LINES = THREE_SIZES.replace(_FIFTY, _FIFTY_LINES)


@query(THREE_SIZES_LINES)
def exact_small(spark, sf):
    """The exact many-size optimum of the 50-row example."""
    rows = A.collect_caps(fifty_caps(spark, sf))
    e = exact.exact_multi([r.cnt for r in rows], [r.cap_num for r in rows], [r.cap_den for r in rows], M_MAX)
    if not e.optimal:
        raise ValueError("the exact search was stopped")
    return spark.createDataFrame([(e.loss,)], "loss bigint")


@query()
def optimality_gap(spark, sf):
    """Two-size, many-size and exact loss, the linear bound, and whether it proves the exact one, on the education stand-in."""
    rows = A.collect_caps(caps(spark, sf, "edu14"))
    r, two = refine.refine_caps(rows, M_MAX), search.search_two_size(caps_frame(spark, rows), M_MAX)
    e = exact.exact_multi([x.cnt for x in rows], [x.cap_num for x in rows], [x.cap_den for x in rows], M_MAX, (refine.layout_of(r), r.loss))
    return spark.createDataFrame([(two.loss, r.loss, e.loss, float(e.bound), e.optimal)], "two_size bigint, many_size bigint, exact bigint, bound double, optimal boolean")


# ---------------------------------------------------------------- uniform baseline


_THETAS_SQL = "unnest([2, 4, 8, 16, 32]) th(theta)"


@query(with_caps("occ50") + f"SELECT theta, max((n * 50 + x - 1) // x)::BIGINT AS ell FROM (SELECT theta, n, least(theta * cnt * 50 + n, n * 50) AS x FROM h, t, {_THETAS_SQL}) GROUP BY theta")
def ell_vs_theta(spark, sf):
    hist = policy.histogram(M.occ50(spark, sf).df)
    out = None
    for t in THETAS:
        one = policy.ell_for(policy.linear_caps(hist, t, 2, 100)).select(F.lit(t).alias("theta"), "ell")
        out = one if out is None else out.unionAll(one)
    return out


@query(with_caps("edu14") + f", e AS (SELECT theta, max((n * 50 + x - 1) // x)::BIGINT AS ell FROM (SELECT theta, n, least(theta * cnt * 50 + n, n * 50) AS x FROM h, t, {_THETAS_SQL}) GROUP BY theta), y AS (SELECT min(n // cnt)::BIGINT AS max_ell FROM h, t) SELECT theta, ell, max_ell, ell <= max_ell AS eligible FROM e, y")
def ell_eligibility(spark, sf):
    hist = policy.histogram(M.edu14(spark, sf).df)
    out = None
    for t in THETAS:
        one = policy.ell_eligible(policy.linear_caps(hist, t, 2, 100)).select(F.lit(t).alias("theta"), "*")
        out = one if out is None else out.unionAll(one)
    return out


@query(with_caps("occ50") + f""", e AS (SELECT theta, max((n * 50 + x - 1) // x)::BIGINT AS ell, any_value(n) AS n FROM (SELECT theta, n, least(theta * cnt * 50 + n, n * 50) AS x FROM h, t, {_THETAS_SQL}) GROUP BY theta),
        f AS (SELECT *, n // ell AS b FROM e) SELECT theta, ell, round(((b - n % b) * (n // b - 1) * (n // b - 1) + n % b * (n // b) * (n // b)) / (n - 1), 6) AS mse FROM f""")
def fixed_ell_mse(spark, sf):
    c = None
    hist = policy.histogram(M.occ50(spark, sf).df)
    for t in THETAS:
        one = policy.ell_for(policy.linear_caps(hist, t, 2, 100)).crossJoin(hist.agg(F.sum("cnt").alias("n"))).select(F.lit(t).alias("theta"), "ell", "n")
        c = one if c is None else c.unionAll(one)
    return c.select("theta", "ell", F.round(fixed_ell.fixed_ell_loss(F.col("n"), F.col("ell")) / (F.col("n") - 1), 6).alias("mse"))


@query(f"WITH m AS ({M.SQL['psize50']}) SELECT count(*)::BIGINT AS n_rows, (count(*) // 10)::BIGINT AS buckets, 0::BIGINT AS violations, true AS ok, 10::BIGINT AS least_size FROM m")
def fixed_ell_audit(spark, sf):
    m = M.psize50(spark, sf)
    a = fixed_ell.fixed_ell_assign(m.df, "v", m.key, 10, "s0")
    sizes = release.bucket_sizes(release.compact(a)).agg(F.min("size").alias("least_size"))
    return release.audit(a, policy.uniform_caps(policy.histogram(m.df), 10)).crossJoin(sizes)


# ---------------------------------------------------------------- rules and noise


_ACCT = f"WITH m AS ({M.SQL['acct']}), y AS (SELECT n_regionkey, c_mktsegment, v, count(*)::BIGINT AS y FROM m GROUP BY n_regionkey, c_mktsegment, v), x AS (SELECT n_regionkey, c_mktsegment, sum(y)::BIGINT AS x FROM y GROUP BY n_regionkey, c_mktsegment), r AS (SELECT n_regionkey, c_mktsegment, v, x, y, y / x AS conf FROM y JOIN x USING (n_regionkey, c_mktsegment) WHERE x >= 5)"
_QI = ("n_regionkey", "c_mktsegment")


def _rules(spark, sf):
    return risk.rule_confidence(M.acct(spark, sf).df, _QI, "v", 5)


@query(_ACCT + " SELECT n_regionkey, c_mktsegment, v, x, y, round(conf, 6) AS conf FROM r WHERE conf >= 0.1")
def rule_confidence(spark, sf):
    return risk.rule_confidence(M.acct(spark, sf).df, _QI, "v", 5, 0.1).withColumn("conf", F.round("conf", 6))


@query(f"""WITH m AS ({M.SQL['acct']}), g AS (SELECT n_regionkey, c_mktsegment, v, count(*) AS y, grouping(n_regionkey) * 2 + grouping(c_mktsegment) AS level FROM m GROUP BY GROUPING SETS ((n_regionkey, c_mktsegment, v), (n_regionkey, v), (c_mktsegment, v), (v))),
        x AS (SELECT n_regionkey, c_mktsegment, count(*) AS x, grouping(n_regionkey) * 2 + grouping(c_mktsegment) AS level FROM m GROUP BY GROUPING SETS ((n_regionkey, c_mktsegment), (n_regionkey), (c_mktsegment), ()))
        SELECT g.n_regionkey, g.c_mktsegment, v, g.level::BIGINT AS level, x::BIGINT AS x, y::BIGINT AS y, round(y / x, 6) AS conf FROM g JOIN x ON g.level = x.level AND g.n_regionkey IS NOT DISTINCT FROM x.n_regionkey AND g.c_mktsegment IS NOT DISTINCT FROM x.c_mktsegment WHERE x >= 5""")
def rule_cube(spark, sf):
    return risk.rule_cube(M.acct(spark, sf).df, _QI, "v", 5).withColumn("conf", F.round("conf", 6))


@query(_ACCT + " SELECT n_regionkey, c_mktsegment, CASE WHEN v IN (0, 1, 2) THEN NULL ELSE v END AS v, x, sum(y)::BIGINT AS y, round(sum(y) / x, 6) AS conf FROM r GROUP BY n_regionkey, c_mktsegment, x, CASE WHEN v IN (0, 1, 2) THEN NULL ELSE v END")
def rule_useful_outcome(spark, sf):
    return risk.useful_outcome(_rules(spark, sf), [0, 1, 2]).withColumn("conf", F.round("conf", 6))


@query(_ACCT + " SELECT n_regionkey, c_mktsegment, v, round(conf, 6) AS conf, round((y - 1) / (x - 1), 6) AS conf_without FROM r WHERE x > 1")
def leave_one_out(spark, sf):
    return risk.leave_one_out(_rules(spark, sf)).select(*_QI, "v", F.round("conf", 6).alias("conf"), F.round("conf_without", 6).alias("conf_without"))


def _uniform_sql(text: str) -> str:
    return f"((('0x' || substr(md5({text}), 1, 13))::BIGINT + 0.5::DOUBLE) / 4503599627370496.0::DOUBLE)"


def _laplace_sql(text: str, epsilon: float) -> str:
    u = f"({_uniform_sql(text)} - 0.5::DOUBLE)"
    return f"(-sign({u}) * ln(1 - 2 * abs({u})) / {epsilon}::DOUBLE)"


@query(f"WITH h AS (SELECT event_type, count(*)::BIGINT AS cnt FROM events GROUP BY event_type) SELECT event_type, cnt, round(cnt + {_laplace_sql(chr(39) + 'n0|' + chr(39) + ' || event_type', 0.1)}, 6) AS noisy FROM h")
def noisy_counts(spark, sf):
    h = M.table(spark, sf, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("cnt"))
    return h.withColumn("noisy", F.round(noise.laplace_count(F.col("cnt"), 0.1, "n0", F.col("event_type")), 6))


@query(_ACCT + f""", z AS (SELECT *, x + {_laplace_sql("'n0x|' || n_regionkey || '|' || c_mktsegment", 0.1)} AS noisy_x, y + {_laplace_sql("'n0y|' || n_regionkey || '|' || c_mktsegment || '|' || v", 0.1)} AS noisy_y FROM r)
        SELECT n_regionkey, c_mktsegment, v, x, y, round(noisy_x, 6) AS noisy_x, round(noisy_y, 6) AS noisy_y, round(CASE WHEN abs(noisy_x) >= 1 THEN noisy_y / noisy_x END, 5) AS noisy_conf FROM z""")
def noisy_confidence(spark, sf):
    n = noise.noisy_rule_confidence(M.acct(spark, sf).df, _QI, 0.1, "v", "n0", 5)
    return n.select(*_QI, "v", "x", "y", F.round("noisy_x", 6).alias("noisy_x"), F.round("noisy_y", 6).alias("noisy_y"), F.round("noisy_conf", 5).alias("noisy_conf"))


_KEYX, _KEYY = "'w2x|' || n_regionkey || '|' || c_mktsegment", "'w2y|' || n_regionkey || '|' || c_mktsegment || '|' || v"


@query(_ACCT + " SELECT eps, rules, near, worst FROM (" + " UNION ALL ".join(f"""SELECT {e}::DOUBLE AS eps, count(*)::BIGINT AS rules, count(*) FILTER (abs(d) <= 0.1)::BIGINT AS near, round(max(abs(d)), 4) AS worst
        FROM (SELECT (y + {_laplace_sql(_KEYY, e)}) / (x + {_laplace_sql(_KEYX, e)}) - conf AS d, x + {_laplace_sql(_KEYX, e)} AS nx FROM r) WHERE abs(nx) >= 1""" for e in (0.01, 0.1, 1.0)) + ")")
def w_noise_ratio(spark, sf):
    """How near noisy ratios stay to the true confidence, for three noise levels: rules, those within a tenth, the worst."""
    out = None
    for e in (0.01, 0.1, 1.0):
        d = F.col("noisy_conf") - F.col("conf")
        n = noise.noisy_rule_confidence(M.acct(spark, sf).df, _QI, e, "v", "w2", 5).where("noisy_conf IS NOT NULL")
        one = n.agg(F.count(F.lit(1)).alias("rules"), F.count_if(F.abs(d) <= 0.1).alias("near"), F.round(F.max(F.abs(d)), 4).alias("worst")).select(F.lit(e).alias("eps"), "*")
        out = one if out is None else out.unionAll(one)
    return out


@query("SELECT x, y, eps, round(1 + 2 / (eps * eps) / (x * x), 6) AS factor, round(y / x * (1 + 2 / (eps * eps) / (x * x)), 6) AS mean, round(2 / (eps * eps) / (x * x) * (1 + (y / x) * (y / x)), 8) AS var FROM (VALUES (100::BIGINT, 99::BIGINT), (1000, 990)) v(x, y), unnest([0.01::DOUBLE, 0.1::DOUBLE, 1.0::DOUBLE]) e(eps)")
def ratio_moments(spark, sf):
    base = spark.createDataFrame([(100, 99), (1000, 990)], "x bigint, y bigint")
    out = None
    for eps in (0.01, 0.1, 1.0):
        m = noise.ratio_moments(F.col("x"), F.col("y"), eps)
        one = base.select("x", "y", F.lit(eps).alias("eps"), F.round(m["factor"], 6).alias("factor"), F.round(m["mean"], 6).alias("mean"), F.round(m["var"], 8).alias("var"))
        out = one if out is None else out.unionAll(one)
    return out


@query(f"""WITH g AS (SELECT x, rep, x + {_laplace_sql("'r0x|' || x || '|' || rep", 0.1)} AS a, x * 0.99::DOUBLE + {_laplace_sql("'r0y|' || x || '|' || rep", 0.1)} AS b FROM unnest([1000::BIGINT, 10000::BIGINT, 100000::BIGINT]) u(x), range(2000) r(rep))
        SELECT x, round(avg(b / a), 4) AS mean, round(var_pop(b / a), 6) AS var FROM g WHERE abs(a) >= 1 GROUP BY x""")
def ratio_convergence(spark, sf):
    return noise.ratio_convergence(spark, (1000, 10_000, 100_000), 0.99, 0.1, 2000).select("x", F.round("mean", 4).alias("mean"), F.round("var", 6).alias("var"))


@query("SELECT a AS answer, round(exp(0.1::DOUBLE * (abs(a - 101) - abs(a - 100))), 6) AS ratio, exp(0.1::DOUBLE * (abs(a - 101) - abs(a - 100))) <= exp(0.1::DOUBLE) + 1e-12 AS bounded FROM (SELECT DISTINCT count(*)::BIGINT AS a FROM events GROUP BY user_id)")
def dp_ratio_bound(spark, sf):
    """Answers are the counts of events that users have."""
    answers = M.table(spark, sf, "events").groupBy("user_id").agg(F.count(F.lit(1)).alias("id")).select("id").distinct()
    ratio = noise.density_ratio(F.col("id"), F.lit(100), F.lit(101), 0.1)
    return answers.select(F.col("id").alias("answer"), F.round(ratio, 6).alias("ratio"), (ratio <= F.exp(F.lit(0.1)) + 1e-12).alias("bounded"))


# ---------------------------------------------------------------- attacks and decoys


@query("SELECT g AS size, q AS known, s AS sigma, round((g - q) / (g - q + s), 6) AS share FROM (SELECT DISTINCT count(*)::BIGINT AS g FROM lineitem GROUP BY l_orderkey) a, (SELECT unnest(generate_series(0, g - 1)) AS q, g AS k FROM (SELECT DISTINCT count(*)::BIGINT AS g FROM lineitem GROUP BY l_orderkey)) b, unnest([0, 1, 2, 4]) c(s) WHERE k = g")
def corruption_closed_form(spark, sf):
    """Orders are the buckets: every size that one has, and every number of its rows that may be known."""
    sizes = M.table(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("size")).select("size").distinct()
    g = sizes.select("size", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("size") - 1)).alias("known")).select("*", F.explode(F.array(*[F.lit(s) for s in (0, 1, 2, 4)])).alias("sigma"))
    return g.withColumn("share", F.round(X.corrupted_share(F.col("size"), F.col("known"), F.col("sigma")), 6))


@query("SELECT s AS sigma, round(1.0 / (1 + s), 6)::DOUBLE AS certainty FROM unnest([0, 1, 2, 4]) c(s)")
def worst_certainty(spark, sf):
    return spark.createDataFrame([(s,) for s in (0, 1, 2, 4)], "sigma int").withColumn("certainty", F.round(X.worst_certainty(F.col("sigma")), 6))


@query(_DEAL + """, i AS (SELECT bucket, v, row_number() OVER (PARTITION BY bucket, v) AS i FROM a), od AS (SELECT bucket, v, row_number() OVER (PARTITION BY bucket ORDER BY md5('c0|' || bucket || '|' || v || '|' || i)) AS r FROM i),
        l AS (SELECT bucket, v, count(*) AS c FROM od WHERE r > 3 GROUP BY bucket, v) SELECT bucket, v, round(c / (sum(c) OVER (PARTITION BY bucket) + 2), 6) AS prob FROM l""")
def corruption_empirical(spark, sf):
    return X.corruption_attack(dealt(spark, sf)[1], 3, 2, "c0").withColumn("prob", F.round("prob", 6))


_DECOYS = _DEAL + """, dom AS (SELECT v, row_number() OVER (ORDER BY md5('d0|' || v), v) - 1 AS i, count(*) OVER () AS d FROM (SELECT DISTINCT v FROM m)), bk AS (SELECT DISTINCT bucket FROM a),
        cand AS (SELECT bucket, v, row_number() OVER (PARTITION BY bucket ORDER BY (i - ('0x' || substr(md5('d0|' || bucket), 1, 13))::BIGINT % d + d) % d) AS r FROM bk, dom WHERE NOT EXISTS (SELECT 1 FROM sa WHERE sa.bucket = bk.bucket AND sa.v = dom.v)),
        dec AS (SELECT bucket, v FROM cand WHERE r <= 2), pub AS (SELECT bucket, v, cnt FROM sa UNION ALL SELECT bucket, v, 1 FROM dec)"""


@query(_DECOYS + " SELECT bucket, v FROM dec")
def decoys_per_bucket(spark, sf):
    return X.decoys(release.compact(dealt(spark, sf)[1]), 2, "d0")


@query(_DECOYS + " SELECT bucket, count(*)::BIGINT AS vals, count(DISTINCT v)::BIGINT AS distinct_vals, sum(cnt)::BIGINT AS size FROM pub GROUP BY bucket")
def decoys_distinct(spark, sf):
    p = X.inject_decoys(release.compact(dealt(spark, sf)[1]), 2, "d0")
    return p.groupBy("bucket").agg(F.count(F.lit(1)).alias("vals"), F.count_distinct("v").alias("distinct_vals"), F.sum("cnt").cast("bigint").alias("size"))


@query(_DECOYS + " SELECT v, sum(cnt) FILTER (NOT d)::BIGINT AS cnt, sum(cnt)::BIGINT AS published, coalesce(sum(cnt) FILTER (d), 0)::BIGINT AS excess FROM (SELECT v, cnt, false AS d FROM sa UNION ALL SELECT v, 1, true FROM dec) GROUP BY v")
def decoy_distortion(spark, sf):
    sa = release.compact(dealt(spark, sf)[1])
    return X.decoy_distortion(sa, X.inject_decoys(sa, 2, "d0"))


def role_release(spark, sf):
    m = M.role3(spark, sf)
    rows = A.collect_caps(policy.linear_caps(policy.histogram(m.df), 3, 2, 100, a_den=2))
    frame = spark.createDataFrame(rows, "v string, cnt bigint, cap_num bigint, cap_den bigint")
    layout = search.search_two_size(frame, M_MAX)
    a = A.assign(m.df, "v", m.key, A.two_size_cuts(rows, layout.classes), "s0")
    qi_side, sa = release.publish(a, m.qi)
    return qi_side, release.compact(sa)


_ROLE = with_caps("role3", "3", 2, 100, 2) + brute() + assigned_sql("conv_id, turn, v") + """, zs AS (SELECT bucket, turn AS z, count(*) AS nz FROM a GROUP BY bucket, turn),
        pr AS (SELECT z, sa.v, sum(nz * sa.cnt / size) AS pairs FROM zs JOIN sa USING (bucket) JOIN bs USING (bucket) GROUP BY z, sa.v),
        lf AS (SELECT z, hv.v, nz, coalesce(pairs, 0) / (nz * hv.cnt / n) AS lift FROM (SELECT z, sum(nz) AS nz FROM zs GROUP BY z) CROSS JOIN h hv CROSS JOIN t LEFT JOIN pr USING (z, v)),
        na AS (SELECT z, v, round(lift, 6) AS lift FROM lf WHERE lift <= 0.9 AND nz >= 5)"""


@query(_ROLE + " SELECT z, v, lift FROM na")
def negative_assoc(spark, sf):
    qi_side, sa = role_release(spark, sf)
    return X.negative_associations(qi_side, sa, F.col("turn"), 0.9, 5).withColumn("lift", F.round("lift", 6))


@query(_ROLE + """, ex AS (SELECT zs.bucket, zs.z, sa.v, sa.cnt, size, CASE WHEN na.v IS NULL THEN sa.cnt ELSE 0 END AS kept FROM zs JOIN sa USING (bucket) JOIN bs USING (bucket) LEFT JOIN na ON na.z = zs.z AND na.v = sa.v)
        SELECT bucket, z, v, round(cnt / size, 6) AS prob, round(coalesce(kept / nullif(sum(kept) OVER (PARTITION BY bucket, z), 0), 0), 6) AS prob_after FROM ex""")
def exclusion_attack(spark, sf):
    qi_side, sa = role_release(spark, sf)
    e = X.exclusion_attack(qi_side, sa, F.col("turn"), X.negative_associations(qi_side, sa, F.col("turn"), 0.9, 5))
    return e.select("bucket", "z", "v", F.round("prob", 6).alias("prob"), F.round("prob_after", 6).alias("prob_after"))


@query("SELECT 0::BIGINT AS ruled_out, true AS all_served")
def decoys_safe(spark, sf):
    """No decoy that a row of its bucket can rule out: associations of brand and size in the dealt parts."""
    m, d = dealt(spark, sf)
    qi_side, sa = release.publish(d, m.qi)
    sa = release.compact(sa)
    assoc = X.negative_associations(qi_side, sa, F.col("p_brand"), 0.6, 1)
    forbidden = X.forbidden_values(qi_side, F.col("p_brand"), assoc)
    chosen = X.decoys(sa, 1, "d0", forbidden)
    bad = chosen.join(forbidden, "bucket").where(F.array_contains("values", F.col("v"))).agg(F.count(F.lit(1)).alias("ruled_out"))
    served = chosen.agg(F.count_distinct("bucket").alias("c")).crossJoin(sa.agg(F.count_distinct("bucket").alias("k"))).select((F.col("c") == F.col("k")).alias("all_served"))
    return bad.crossJoin(served)


# ---------------------------------------------------------------- count workload


N_QUERIES, SELECTIVITY, SEED = 50, 0.01, "p0"
_QIS = M.EVENT_QI
_DOM = "dom AS (" + " UNION ".join(f"SELECT '{c}' AS attr, {c}::VARCHAR AS value FROM m" for c in (*_QIS, "v")) + ")"
_POOL = f""", {_DOM}, qd AS (SELECT i::INTEGER AS query_id, (('0x' || substr(md5('p0d|' || i), 1, 13))::BIGINT % 7 + 1)::INTEGER AS d FROM range({N_QUERIES}) g(i)),
        at0 AS (SELECT query_id, d, attr, row_number() OVER (PARTITION BY query_id ORDER BY md5('p0a|' || query_id || '|' || attr)) AS r FROM qd, (SELECT DISTINCT attr FROM dom WHERE attr <> 'v')),
        at1 AS (SELECT query_id, d, attr FROM at0 WHERE r <= d UNION ALL SELECT query_id, d, 'v' FROM qd), sz AS (SELECT attr, count(*) AS size FROM dom GROUP BY attr),
        p0 AS (SELECT query_id, d, attr, value, size, row_number() OVER (PARTITION BY query_id, attr ORDER BY md5('p0v|' || query_id || '|' || attr || '|' || value)) AS r FROM at1 JOIN dom USING (attr) JOIN sz USING (attr)),
        pool AS (SELECT query_id, d, attr, value FROM p0 WHERE r <= greatest(1, ceil(round(size * pow(0.01, 1.0 / (d + 1)), 9))))"""
_MATCH = f""", lg AS (SELECT event_id, bucket, attr, value FROM a, LATERAL (SELECT unnest([{', '.join(f"'{c}'" for c in (*_QIS, 'v'))}]) AS attr, unnest([{', '.join(f'{c}::VARCHAR' for c in (*_QIS, 'v'))}]) AS value)),
        hit AS (SELECT query_id, event_id, bucket, any_value(d) AS d, count(*) FILTER (attr <> 'v') AS q, count(*) FILTER (attr = 'v') AS s FROM lg JOIN pool USING (attr, value) GROUP BY query_id, event_id, bucket),
        act AS (SELECT query_id, count(*) FILTER (q = d AND s = 1)::BIGINT AS act FROM hit GROUP BY query_id),
        es0 AS (SELECT query_id, bucket, count(*) FILTER (q = d) AS q, count(*) FILTER (s = 1) AS s FROM hit GROUP BY query_id, bucket),
        est AS (SELECT query_id, sum(q * s / size) AS est FROM es0 JOIN bs USING (bucket) GROUP BY query_id)"""


def event_pool(spark, sf, n: int = N_QUERIES, name: str = "occ50"):
    m = M.MICRODATA[name](spark, sf)
    return workload.query_pool(workload.domains(m.df, [*m.qi, "v"]), m.qi, n, SELECTIVITY, SEED)


@query(f"WITH m AS ({M.SQL['occ50']}), {_DOM} SELECT attr, value FROM dom")
def attribute_domains(spark, sf):
    m = M.occ50(spark, sf)
    return workload.domains(m.df, [*m.qi, "v"])


@query(f"WITH m AS ({M.SQL['occ50']}){_POOL} SELECT query_id, d, attr, value FROM pool")
def pool_shape(spark, sf):
    return event_pool(spark, sf)


@query("SELECT s AS size, d, greatest(1, ceil(round(s * pow(0.01, 1.0 / (d + 1)), 9)))::INTEGER AS width FROM unnest([2, 4, 5, 10, 24, 30, 50]) a(s), generate_series(1, 7) b(d)")
def pool_width(spark, sf):
    g = spark.createDataFrame([(s, d) for s in (2, 4, 5, 10, 24, 30, 50) for d in range(1, 8)], "size int, d bigint")
    return g.withColumn("width", workload.width(F.col("size"), F.col("d"), SELECTIVITY))


@query(OCC_ASSIGNED + _POOL + _MATCH + " SELECT query_id, coalesce(act, 0)::BIGINT AS act FROM qd LEFT JOIN act USING (query_id)")
def pool_exact(spark, sf):
    m = M.occ50(spark, sf)
    return workload.pool_exact(m.df, event_pool(spark, sf), m.qi)


@query(OCC_ASSIGNED + _POOL + _MATCH + " SELECT query_id, coalesce(act, 0)::BIGINT AS act FROM qd LEFT JOIN act USING (query_id)")
def map_in_arrow_pool(spark, sf):
    m = M.occ50(spark, sf)
    return workload.pool_exact(m.df, event_pool(spark, sf), m.qi)


@query(OCC_ASSIGNED + _POOL + _MATCH + " SELECT query_id, round(coalesce(est, 0), 4) AS est FROM qd LEFT JOIN est USING (query_id)")
def pool_estimate(spark, sf):
    m, _, _, a = two_size(spark, sf)
    qi_side, sa = release.publish(a, m.qi)
    return workload.pool_estimate(qi_side, release.compact(sa), event_pool(spark, sf), m.qi).withColumn("est", F.round("est", 4))


@query(OCC_ASSIGNED + _POOL + _MATCH + " SELECT count(*)::BIGINT AS queries, count(*) FILTER (coalesce(act, 0) = 0)::BIGINT AS skipped, round(avg(CASE WHEN act > 0 THEN abs(act - coalesce(est, 0)) / act END), 4) AS mean_re FROM qd LEFT JOIN act USING (query_id) LEFT JOIN est USING (query_id)")
def re_pool(spark, sf):
    m, _, _, a = two_size(spark, sf)
    qi_side, sa = release.publish(a, m.qi)
    pool = workload.pool_bits(event_pool(spark, sf))
    return workload.mean_error(workload.relative_error(workload.pool_exact(m.df, pool, m.qi), workload.pool_estimate(qi_side, release.compact(sa), pool, m.qi))).withColumn("mean_re", F.round("mean_re", 4))


@query(OCC_ASSIGNED + ", q AS (SELECT bucket, count(*) AS q FROM a WHERE event_type = (SELECT min(event_type) FROM events) AND hour BETWEEN 6 AND 11 GROUP BY bucket), s AS (SELECT bucket, sum(cnt) FILTER (v < 5) AS s FROM sa GROUP BY bucket) SELECT round(sum(q * coalesce(s, 0) / size), 4) AS est FROM q JOIN s USING (bucket) JOIN bs USING (bucket)")
def estimate_single(spark, sf):
    m, _, _, a = two_size(spark, sf)
    qi_side, sa = release.publish(a, m.qi)
    kind = M.table(spark, sf, "events").agg(F.min("event_type")).first()[0]
    return workload.estimate_count(qi_side, release.compact(sa), (F.col("event_type") == kind) & F.col("hour").between(6, 11), F.col("v") < 5).withColumn("est", F.round("est", 4))

