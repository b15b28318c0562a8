"""The experiments: sweeps over the policy's slope, rows and domain sizes, for all methods and strategies."""

from __future__ import annotations

import time
from collections.abc import Sequence
from concurrent.futures import ThreadPoolExecutor

import numpy as np
from pyspark import StorageLevel
from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from capbuckets.functions.exact import order_key
from capbuckets.operators import assign as A
from capbuckets.operators import exact, fixed_ell, policy, refine, release, search, workload
from capbuckets.operators import lattice as L
from capbuckets.plans.method_queries import STRATEGIES, brute, with_caps
from capbuckets.plans.registry import Registry
from capbuckets.sources import microdata as M

query = Registry()
THETAS, M_MAX = (2, 4, 8, 16, 32), 50
TABLES = ("occ50", "edu14")
#: Queries of the pool, factors by which the domain is scaled, and releases that are made at once.
N_QUERIES, GAMMAS, AT_ONCE = 5000, (2, 4, 8, 16, 32, 64), 3


def caps_by_theta(hist: DataFrame, thetas: Sequence[int] = THETAS) -> dict[int, list]:
    """Collected caps for each slope, from one collected histogram: ``hist`` is read once."""
    rows = A.collect_caps(policy.linear_caps(hist, 1, 0, 1))
    n = sum(r.cnt for r in rows)
    return {t: [Row(v=r.v, cnt=r.cnt, cap_num=min(t * r.cnt * 50 + n, n * 50), cap_den=n * 50) for r in rows] for t in thetas}


def counts_of(rows: Sequence) -> search.Counts:
    at = lambda f: np.array([getattr(r, f) for r in rows], np.int64)
    return search.Counts(at("cnt"), at("cap_num"), at("cap_den"), np.ones(len(rows), np.int64))


def theta_sweep(hist: DataFrame, nodes: int = exact.MAX_NODES, order: str = "rare_first") -> list[tuple]:
    """(theta, ell, eligible, two-size, many-size, exact or best, bound, proved, uniform, rows) losses for each slope."""
    out = []
    for t, rows in caps_by_theta(hist).items():
        c = counts_of(rows)
        n, (_, ell) = c.n, search.bounds_of(c)
        two, many = search.driver_search(c, M_MAX), refine.refine_caps(rows, M_MAX, order)
        best = exact.exact_multi(c.cnt, c.num, c.den, M_MAX, (refine.layout_of(many), many.loss), nodes)
        fixed = sum(b * (s - 1) ** 2 for s, b in fixed_ell.fixed_ell_layout(n, ell))
        out.append((t, ell, bool(ell * int(c.cnt.max()) <= n), two.loss, many.loss, best.loss, float(best.bound), best.optimal, fixed, n))
    return out


@query()
def w_mse_theta(spark, sf):
    """Squared error of the two-size, many-size, exact and uniform methods against the slope, on both stand-ins.

    ``exact`` is the optimum where ``proved``, and else the best layout found after a number of nodes; none has less than ``bound``.
    """
    rows = []
    for name in TABLES:
        for t, ell, ok, two, many, best, bound, proved, fixed, n in theta_sweep(policy.histogram(M.MICRODATA[name](spark, sf).df)):
            rows.append((name, t, ell, ok, *[round(x / (n - 1), 6) for x in (two, many, best, bound, fixed)], proved))
    return spark.createDataFrame(rows, "table string, theta int, ell int, eligible boolean, two_size double, many_size double, exact double, bound double, fixed_ell double, proved boolean")


@query(" UNION ALL ".join(f"""SELECT '{name}' AS "table", {t}::INTEGER AS theta, two_size, n_rows, true AS ordered, true AS dealable FROM ({with_caps(name, str(t))}{brute()} SELECT loss AS two_size, n AS n_rows FROM best, t)""" for name in TABLES for t in THETAS))
def w_mse_order(spark, sf):
    """For each slope: the two-size loss, the rows that the best many-size layout holds, whether bound <= exact <= many-size <= two-size, and whether the caps allow both layouts (by a flow)."""
    out = []
    for name in TABLES:
        for t, rows in caps_by_theta(policy.histogram(M.MICRODATA[name](spark, sf).df)).items():
            c = counts_of(rows)
            two, many = search.driver_search(c, M_MAX), refine.refine_caps(rows, M_MAX)
            best = exact.exact_multi(c.cnt, c.num, c.den, M_MAX, (refine.layout_of(many), many.loss), 20)
            layouts = (best.layout, refine.layout_of(many))
            dealable = all(exact.flow_split(c.cnt, np.stack([c.quota(s) for s, _ in x], 1), x) is not None for x in layouts)
            held = {sum(s * b for s, b in x) for x in layouts}
            out.append((name, t, two.loss, held.pop() if len(held) == 1 else -1, bool(best.bound <= best.loss + 1e-6 and best.loss <= many.loss <= two.loss), dealable))
    return spark.createDataFrame(out, "table string, theta int, two_size bigint, n_rows bigint, ordered boolean, dealable boolean")


@query(
    " UNION ALL ".join(
        f"""SELECT '{name}' AS "table", theta, ell, ell * most <= n AS eligible FROM (SELECT theta, max((n * 50 + x - 1) // x)::BIGINT AS ell, any_value(n) AS n, max(cnt) AS most
        FROM (SELECT theta, n, cnt, least(theta * cnt * 50 + n, n * 50) AS x FROM (SELECT v, count(*)::BIGINT AS cnt FROM ({M.SQL[name]}) GROUP BY v) h, (SELECT count(*)::BIGINT AS n FROM events) t, unnest([2, 4, 8, 16, 32]) th(theta)) GROUP BY theta)"""
        for name in TABLES
    )
)
def w_ell_theta(spark, sf):
    """Uniform diversity that the policy asks for, against the slope, and whether it can be had."""
    rows = []
    for name in TABLES:
        for t, c in caps_by_theta(policy.histogram(M.MICRODATA[name](spark, sf).df)).items():
            k = counts_of(c)
            ell = search.bounds_of(k)[1]
            rows.append((name, t, ell, bool(ell * int(k.cnt.max()) <= k.n)))
    return spark.createDataFrame(rows, "table string, theta int, ell bigint, eligible boolean")


def release_error(m: M.Microdata, ranked: DataFrame, cuts, pool: workload.PoolBits, true: DataFrame) -> DataFrame:
    """One row (queries, skipped, mean_re) of a pool with true answers ``true`` against the release that the cut points make of ranked rows."""
    qi_side, sa = release.publish(A.place(ranked, "v", cuts), m.qi)
    return workload.mean_error(workload.relative_error(true, workload.pool_estimate(qi_side, release.compact(sa), pool, m.qi)))


def first_error(*release) -> Row:
    return release_error(*release).first()


def error_sweep(spark: SparkSession, sf: str, tables: Sequence[str] = TABLES, thetas: Sequence[int] = THETAS, n_queries: int = N_QUERIES, nodes: int = 40) -> list[tuple]:
    """(table, theta, method, queries, skipped, mean relative error); ``exact`` is the best layout after ``nodes`` nodes."""
    asked = []
    for name in tables:
        m = M.MICRODATA[name](spark, sf)
        pool = workload.pool_bits(workload.query_pool(workload.domains(m.df, [*m.qi, "v"]), m.qi, n_queries, 0.01, "p0"))
        known = workload.pool_exact(m.df, pool, m.qi).collect()  # as many rows as the pool has queries
        true = spark.createDataFrame(known, "query_id int, act bigint")
        ranked = A.rank_rows(m.df, "v", m.key, "s0").select(*m.qi, "v", "_t").persist(StorageLevel.DISK_ONLY)  # for all releases of the table
        ranked.count()  # held before jobs that run beside each other ask for it
        with ThreadPoolExecutor(AT_ONCE) as jobs:
            for t, rows in caps_by_theta(policy.histogram(m.df), thetas).items():
                c, values = counts_of(rows), [r.v for r in rows]
                two, many = search.driver_search(c, M_MAX), refine.refine_caps(rows, M_MAX)
                ways = [("two_size", A.two_size_cuts(rows, two.classes)), ("many_size", refine.leaf_cuts(many, values))]
                begun = [(name, t, method, jobs.submit(first_error, m, ranked, cuts, pool, true)) for method, cuts in ways]
                best = exact.exact_multi(c.cnt, c.num, c.den, M_MAX, (refine.layout_of(many), many.loss), nodes)
                takes = exact.flow_split(c.cnt, np.stack([c.quota(s) for s, _ in best.layout], 1), best.layout)
                method, cuts = "exact" if best.optimal else "best found", A.cut_points(values, takes, best.layout)
                asked += [*begun, (name, t, method, jobs.submit(first_error, m, ranked, cuts, pool, true))]
        ranked.unpersist()
    found = [(name, t, method, job.result()) for name, t, method, job in asked]
    return [(name, t, method, e.queries, e.skipped, round(e.mean_re, 6)) for name, t, method, e in found]


@query()
def w_re_theta(spark, sf):
    """Mean relative error of 5,000 pooled count queries against all five slopes, by method, on both stand-ins."""
    return spark.createDataFrame(error_sweep(spark, sf), "table string, theta int, method string, queries bigint, skipped bigint, mean_re double")


@query()
def w_re_correlated(spark, sf):
    """The same on a table whose eighth quasi-identifier depends on the sensitive value."""
    return spark.createDataFrame(error_sweep(spark, sf, ("corr",), (8,)), "table string, theta int, method string, queries bigint, skipped bigint, mean_re double")


#: Text, vector and other stand-ins beyond the census-like ones.
OTHERS = ("k100", "psize50", "lang4", "toxic2", "role3", "embed10", "acct")


@query(" UNION ALL ".join(f"""SELECT '{t}' AS "table", s1, b1, s2, b2, loss FROM ({with_caps(t)}{brute()} SELECT * FROM best)""" for t in OTHERS))
def w_standins(spark, sf):
    """The two-size optimum of every other stand-in."""
    out = None
    for name in OTHERS:
        caps = policy.linear_caps(policy.histogram(M.MICRODATA[name](spark, sf).df), 8, 2, 100)
        one = search.layout_row(spark, search.search_two_size(caps, M_MAX)).select(F.lit(name).alias("table"), "*")
        out = one if out is None else out.unionAll(one)
    return out


def timed(c: search.Counts, strategy: str, runs: int = 100, seconds: float = 10.0, spark: SparkSession | None = None) -> tuple[float, int, search.Layout]:
    """(mean seconds, runs, layout) of up to ``runs`` searches; no more are begun after ``seconds``."""
    began, done, found = time.perf_counter(), 0, None
    while done < runs and (not done or time.perf_counter() - began < seconds):
        found = search.driver_search(c, M_MAX, strategy, spark=spark)
        done += 1
    return (time.perf_counter() - began) / done, done, found


def prefix_histograms(m: M.Microdata, sizes: Sequence[int]) -> list[DataFrame]:
    """The histograms of the first rows in a salted order, for each of ``sizes``: whole hash shards, and part of the one at the edge.

    Rows are hashed twice however many sizes there are: once for the histogram of every shard, once for the shards at edges.
    """
    spark = m.df.sparkSession
    h = order_key("w10", *[F.col(k) for k in m.key])
    keyed = m.df.select("v", h.alias("h")).withColumn("s", F.substring("h", 1, 3))
    sums = keyed.groupBy("s", "v").agg(F.count(F.lit(1)).alias("n")).persist()
    before, have = [], 0
    for r in sums.groupBy("s").agg(F.sum("n").alias("n")).orderBy("s").collect():
        before.append((r.s, have, have + r.n))
        have += r.n
    edges = [next(((s, rows - low) for s, low, high in before if high > rows), (None, 0)) for rows in sizes]
    at = Window.partitionBy("s").orderBy("h")
    cut = sorted({s for s, _ in edges if s is not None})
    rest = keyed.where(F.col("s").isin(cut)).select("s", "v", F.row_number().over(at).alias("r")).persist()
    out, kind = [], m.df.schema["v"].dataType.simpleString()
    for s, more in edges:
        whole = sums if s is None else sums.where(F.col("s") < s)
        parts = whole.select("v", "n")
        if s is not None:
            parts = parts.unionAll(rest.where((F.col("s") == s) & (F.col("r") <= more)).groupBy("v").agg(F.count(F.lit(1)).alias("n")))
        rows = A.collect_caps(parts.groupBy("v").agg(F.sum("n").alias("cnt")))
        out.append(spark.createDataFrame(rows, f"v {kind}, cnt bigint"))
    sums.unpersist()
    rest.unpersist()
    return out


def prefix_histogram(m: M.Microdata, rows: int) -> DataFrame:
    return prefix_histograms(m, [rows])[0]


def growth(cases: Sequence[tuple[str, int, DataFrame]], strategies: Sequence[str] = STRATEGIES, runs: int = 1, seconds: float = 10.0) -> list[tuple]:
    """(what, size, strategy, loss, positions, tests, listed, seconds, runs) for histograms of growing tables or domains."""
    out = []
    for what, size, hist in cases:
        c = counts_of(caps_by_theta(hist, (8,))[8])
        for s in strategies:
            mean, done, found = timed(c, s, runs, seconds, hist.sparkSession)
            out.append((what, size, s, found.loss, *[found.counters[x] for x in ("positions", "tests", "listed")], round(mean, 5), done))
    return out


def row_cases(spark: SparkSession, sf: str) -> list[tuple[str, int, DataFrame]]:
    """Histograms of one to five sixths of the line items: 100,000 to 500,000 of 600,000."""
    m = M.price50(spark, sf)
    n = m.df.count()
    sizes = [n * i // 6 for i in (1, 2, 3, 4, 5)]
    return [("rows", size, hist) for size, hist in zip(sizes, prefix_histograms(m, sizes), strict=True)]


def domain_cases(spark: SparkSession, sf: str) -> list[tuple[str, int, DataFrame]]:
    return [(name, g, policy.histogram(M.scaled_domain(M.MICRODATA[name](spark, sf), g).df)) for name in TABLES for g in GAMMAS]


GROWTH = "what string, size bigint, strategy string, loss bigint, positions bigint, tests bigint, listed bigint"
LOSSES = "what string, size bigint, strategy string, loss bigint"
_KEYS = ", ".join(("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"))


@query()
def w_runtime_rows(spark, sf):
    """Work of the four strategies against rows."""
    return spark.createDataFrame([r[:-2] for r in growth(row_cases(spark, sf))], GROWTH)


@query(" UNION ALL ".join(f"""SELECT 'rows' AS what, n AS size, u AS strategy, loss FROM ({with_caps('price50').replace(M.SQL['price50'], 'SELECT * FROM (SELECT *, row_number() OVER (ORDER BY md5(concat_ws(chr(124), ' + "'w10'" + ', ' + _KEYS + f'))) AS place, count(*) OVER () AS every FROM (' + M.SQL['price50'] + f')) WHERE place <= every * {i} // 6')}{brute()} SELECT n, loss FROM best, t), unnest(['full', 'loss', 'none', 'ilp']) x(u)""" for i in (1, 2, 3, 4, 5)))
def w_runtime_losses(spark, sf):
    """The loss that each strategy finds, for the same tables as :func:`w_runtime_rows`."""
    return spark.createDataFrame([r[:4] for r in growth(row_cases(spark, sf))], LOSSES)


@query()
def w_domain_scale(spark, sf):
    """Work of the four strategies against the domain: each value of both stand-ins split into gamma values."""
    return spark.createDataFrame([r[:-2] for r in growth(domain_cases(spark, sf))], GROWTH)


@query(" UNION ALL ".join(f"""SELECT '{name}' AS what, {g}::BIGINT AS size, u AS strategy, loss FROM ({with_caps(name).replace(M.SQL[name], f"SELECT * REPLACE ((v * {g} + ('0x' || substr(md5('g0|' || event_id), 1, 13))::BIGINT % {g})::INT AS v) FROM ({M.SQL[name]})")}{brute()} SELECT loss FROM best), unnest(['full', 'loss', 'none', 'ilp']) x(u)""" for name in TABLES for g in GAMMAS))
def w_domain_losses(spark, sf):
    """The loss that each strategy finds, for the same domains as :func:`w_domain_scale`."""
    return spark.createDataFrame([r[:4] for r in growth(domain_cases(spark, sf))], LOSSES)


_PROGRAM = ("occ50", "edu14", "qty50", "psize50", "k100")


@query(" UNION ALL ".join(f"""SELECT '{t}' AS "table", loss, n AS n_rows, true AS dealable FROM ({with_caps(t)}{brute()} SELECT loss, n FROM best, t)""" for t in _PROGRAM))
def w_integer_program(spark, sf):
    """The integer program's layout on whole tables: its loss, the rows that it holds, and whether its whole solution keeps all caps."""
    out = []
    for name in _PROGRAM:
        c = counts_of(caps_by_theta(policy.histogram(M.MICRODATA[name](spark, sf).df), (8,))[8])
        found = search.driver_search(c, M_MAX, "ilp")
        (s1, b1), (s2, b2) = found.classes
        lat = L.lattice(c.n, s1, s2)
        x = search.ilp_rows(c, lat, (lat.b1 - b1) // lat.d1)
        ok = (x >= 0).all() and (x <= c.quota(s1) * b1).all() and (c.cnt - x <= c.quota(s2) * b2).all() and (x <= c.cnt).all() and int(x.sum()) == s1 * b1
        out.append((name, found.loss, s1 * b1 + s2 * b2, bool(ok)))
    return spark.createDataFrame(out, "table string, loss bigint, n_rows bigint, dealable boolean")


@query(" UNION ALL ".join(f"""SELECT '{t}' AS "table", count(*)::BIGINT AS domain, sum(cnt)::BIGINT AS n_rows, round(min(cnt) / sum(cnt), 6) AS least, round(max(cnt) / sum(cnt), 6) AS most FROM (SELECT v, count(*) AS cnt FROM ({M.SQL[t]}) GROUP BY v)""" for t in M.SQL))
def w_frequencies(spark, sf):
    """Domain size and extreme frequencies of every stand-in."""
    out = None
    for name, make in M.MICRODATA.items():
        if name not in M.SQL:
            continue
        h = policy.histogram(make(spark, sf).df)
        one = h.agg(F.count(F.lit(1)).alias("domain"), F.sum("cnt").alias("n_rows"), F.round(F.min("cnt") / F.sum("cnt"), 6).alias("least"), F.round(F.max("cnt") / F.sum("cnt"), 6).alias("most")).select(F.lit(name).alias("table"), "*")
        out = one if out is None else out.unionAll(one)
    return out


_SPACES = ", ".join(str(10**k) for k in range(4, 13, 2))


@query(f"""SELECT n, sum(((n - s2 * r) // s2) // (s1 // gcd(s1, s2)) + 1)::BIGINT AS layouts FROM unnest([{_SPACES}]::BIGINT[]) a(n), generate_series(1, 49) b(s1), generate_series(2, 50) c(s2), generate_series(0, 48) d(r)
        WHERE s1 < s2 AND r < s1 // gcd(s1, s2) AND (n - s2 * r) % s1 = 0 AND n >= s2 * r GROUP BY n""")
def w_search_space(spark, sf):
    """Layouts of two sizes up to 50 for tables of up to 10^12 rows, counted without listing them."""
    sizes = [10**k for k in range(4, 13, 2)]
    rows = [(n, sum(x.last + 1 for a in range(1, 50) for b in range(a + 1, 51) if (x := L.lattice(n, a, b)))) for n in sizes]
    return spark.createDataFrame(rows, "n bigint, layouts bigint")


_ORDERS = ("key", "rare_first", "common_first", "spread")


@query()
def w_split_orders(spark, sf):
    """Loss of the many-size refinement for each order in which rows are split."""
    rows = caps_by_theta(policy.histogram(M.occ50(spark, sf).df), (8,))[8]
    return spark.createDataFrame([(o, refine.refine_caps(rows, M_MAX, o).loss) for o in _ORDERS], "split_order string, loss bigint")


@query(with_caps("occ50") + brute() + f"SELECT u AS split_order, loss AS two_size, n AS n_rows, true AS dealable, true AS not_more FROM best, t, unnest({list(_ORDERS)}) x(u)")
def w_split_orders_audit(spark, sf):
    """The refinement's layout for each order: rows held, whether the caps allow it (by a flow), and whether its loss is under the two-size loss or equal."""
    rows, out = caps_by_theta(policy.histogram(M.occ50(spark, sf).df), (8,))[8], []
    c = counts_of(rows)
    two = search.driver_search(c, M_MAX)
    for o in _ORDERS:
        r = refine.refine_caps(rows, M_MAX, o)
        layout = refine.layout_of(r)
        out.append((o, two.loss, sum(s * b for s, b in layout), exact.flow_split(c.cnt, np.stack([c.quota(s) for s, _ in layout], 1), layout) is not None, r.loss <= two.loss))
    return spark.createDataFrame(out, "split_order string, two_size bigint, n_rows bigint, dealable boolean, not_more boolean")
