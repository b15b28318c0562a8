"""Releases, plans, workloads, streams and edge cases on small tables."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from capbuckets.operators import assign, attacks, fixed_ell, policy, refine, release, search, validity, workload
from capbuckets.plans import method_queries as Q
from capbuckets.sources import generated, microdata, sinks


def plan_of(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    got = entry.entry(spark)
    assert got.columns == ["bucket", "v", "cnt", "size", "prob"] and got.count() > 0


def test_release_keeps_bags_and_hides_keys(spark, sf):
    m, rows, layout, a = Q.two_size(spark, sf)
    qi_side, sa = release.publish(a, m.qi, salt="x")
    assert qi_side.columns == [*m.qi, "bucket"] and sa.columns == ["bucket", "v"]
    assert release.bag_difference(qi_side.select(*m.qi), m.df.select(*m.qi)).first().difference == 0
    assert release.bag_difference(sa.select("v"), m.df.select("v")).first().difference == 0
    sizes = sorted(r["size"] for r in release.bucket_sizes(release.compact(sa)).collect())
    assert sizes == sorted(s for s, b in layout.classes for _ in range(b))


def test_partitioning_does_not_change_the_release(spark, sf):
    m, rows, layout, a = Q.two_size(spark, sf)
    other = assign.assign(m.df.repartition(7), "v", m.key, assign.two_size_cuts(rows, layout.classes), "s0")
    assert release.bag_difference(a, other).first().difference == 0


def test_plan_and_driver_engines_agree(spark, sf):
    for theta in (2, 8, 32):
        c = Q.caps(spark, sf, "edu14", theta)
        row, found = search.plan_search(c).first(), search.search_two_size(c)
        assert (row.loss, [(row.s1, row.b1), (row.s2, row.b2)]) == (found.loss, found.classes)


def test_empty_table(spark):
    empty = spark.createDataFrame([], "id int, v int")
    hist = policy.histogram(empty)
    caps = policy.linear_caps(hist, 8, 2, 100)
    assert hist.count() == 0 and policy.caps_feasible(caps).first().feasible
    assert search.search_two_size(caps).loss is None and search.plan_search(caps).count() == 0
    assert refine.refine_caps([]).reason


def test_null_is_a_value_or_an_error(spark):
    df = spark.createDataFrame([(1, 1), (2, None), (3, None), (4, 2)], "id int, v int")
    hist = policy.histogram(df)
    assert {(r.v, r.cnt) for r in hist.collect()} == {(1, 1), (None, 2), (2, 1)}
    with pytest.raises(Exception, match="null in the sensitive"):
        policy.histogram(df, nulls="reject").collect()
    dealt = assign.deal(df, "v", ("id",), 2, "s")
    assert dealt.count() == 4 and {r.bucket for r in dealt.collect()} == {0, 1}


def test_one_value_only(spark):
    df = spark.createDataFrame([(i, 1) for i in range(6)], "id int, v int")
    caps = policy.linear_caps(policy.histogram(df), 8, 2, 100)
    assert search.search_two_size(caps).loss == 0


def test_duplicate_rows_are_dealt(spark):
    df = spark.createDataFrame([(1, 1)] * 5 + [(2, 2)] * 3, "id int, v int")
    assert sorted(r["size"] for r in release.bucket_sizes(release.compact(assign.deal(df, "v", ("id",), 4, "s"))).collect()) == [2, 2, 2, 2]


def test_fixed_ell_rejects_a_frequent_value(spark):
    df = spark.createDataFrame([(i, min(i, 3)) for i in range(20)], "id int, v int")
    with pytest.raises(ValueError, match="rules out"):
        fixed_ell.fixed_ell_assign(df, "v", ("id",), 4, "s")
    assert fixed_ell.fixed_ell_assign(df, "v", ("id",), 4, "s", ignore_privacy=True).count() == 20


def test_decoys_need_room(spark):
    sa = spark.createDataFrame([(0, 1, 1), (0, 2, 1)], "bucket bigint, v int, cnt bigint")
    with pytest.raises(Exception, match="too few values"):
        attacks.decoys(sa, 1, "s").collect()


def test_pool_answers_are_those_of_each_query(spark, sf, monkeypatch):
    """Every query of a pool asked on its own, in one chunk of the pool and in many."""
    m, _, _, a = Q.two_size(spark, sf)
    qi_side, sa = release.publish(a, m.qi)
    sa, pool = release.compact(sa), Q.event_pool(spark, sf, 20)
    lists = {}
    for r in pool.collect():
        lists.setdefault(r.query_id, {}).setdefault(r.attr, set()).add(r.value)
    rows, side = m.df.select(*m.qi, "v").collect(), qi_side.collect()
    buckets = {}
    for r in sa.collect():
        buckets.setdefault(r.bucket, []).append((str(r.v), r.cnt))
    fits = lambda r, q, columns: all(c not in q or str(r[c]) in q[c] for c in columns)
    share = lambda b, q: sum(n for v, n in buckets[b] if v in q["v"]) / sum(n for _, n in buckets[b])
    act = {i: sum(fits(r, q, [*m.qi, "v"]) for r in rows) for i, q in lists.items()}
    est = {i: sum(share(r.bucket, q) for r in side if fits(r, q, m.qi)) for i, q in lists.items()}
    for cells in (1 << 26, 400):
        monkeypatch.setattr(workload, "MAX_CELLS", cells)
        assert {r.query_id: r.act for r in workload.pool_exact(m.df, pool, m.qi).collect()} == act
        assert {r.query_id: r.est for r in workload.pool_estimate(qi_side, sa, pool, m.qi).collect()} == pytest.approx(est)
    assert len(list(workload.pool_bits(pool).chunks())) > 1


def test_pool_is_checked(spark, sf, monkeypatch):
    monkeypatch.setattr(workload, "MAX_POOL_ROWS", 10)
    with pytest.raises(ValueError, match="too large"):
        workload.pool_bits(Q.event_pool(spark, sf, 20))


def test_relative_error_skips_zero(spark):
    e = spark.createDataFrame([(0, 0), (1, 4)], "query_id int, act bigint")
    x = spark.createDataFrame([(0, 1.0), (1, 5.0)], "query_id int, est double")
    r = workload.mean_error(workload.relative_error(e, x)).first()
    assert (r.queries, r.skipped, r.mean_re) == (2, 1, 0.25)


def test_scan_is_pruned_and_pushed(spark, sf):
    text = plan_of(entry.queries()["scan_parquet_pruned"](spark, sf))
    assert "PushedFilters: [IsNotNull(l_quantity)" in text and "l_orderkey" not in text.split("ReadSchema")[1]


def test_histogram_counts_on_each_task_first(spark, sf):
    text = plan_of(policy.histogram(microdata.price50(spark, sf).df))
    assert "partial_count" in text and "l_orderkey" not in text


def test_ranking_is_sharded(spark, sf):
    m = microdata.occ50(spark, sf)
    text = plan_of(assign.rank_rows(m.df, "v", m.key, "s"))
    assert "hashpartitioning(v" in text and "_shard" in text and "Python" not in text


def test_shards_follow_from_the_commonest_value(spark, sf, monkeypatch):
    assert [assign.shard_digits(n) for n in (0, 1 << 18, (1 << 18) + 1, 1 << 22, 1 << 40)] == [0, 0, 1, 1, 6]
    m = microdata.occ50(spark, sf)
    ranks = []
    for rows in (1 << 18, 20, 1):
        monkeypatch.setattr(assign, "SHARD_ROWS", rows)
        ranks.append(sorted((r.event_id, r._t) for r in assign.rank_rows(m.df, "v", m.key, "s").collect()))
    assert ranks[0] == ranks[1] == ranks[2]
    assert [r.t for r in assign.rank_rows(m.df, "v", m.key, "s", 5).where("v = 0").selectExpr("_t AS t").orderBy("t").collect()] == list(range(1, m.df.where("v = 0").count() + 1))


def test_decoys_against_the_ring(spark):
    """Each bucket takes the first free values from its place on, whatever is forbidden; all of a small domain, if need be."""
    sa = spark.createDataFrame([(b, v, 1) for b in range(12) for v in range(30) if (b * 7 + v) % 5 == 0], "bucket bigint, v int, cnt bigint")
    forbidden = spark.createDataFrame([(b, [v for v in range(30) if v % 3 == b % 3] + [99]) for b in range(0, 12, 2)] + [(77, [1])], "bucket bigint, values array<int>")
    held = {b: {v for v in range(30) if (b * 7 + v) % 5 == 0} for b in range(12)}
    ruled = {b: {v for v in range(30) if v % 3 == b % 3} if b % 2 == 0 else set() for b in range(12)}
    for sigma in (1, 3, 14):
        got = {}
        for r in attacks.decoys(sa, sigma, "s", forbidden).collect():
            got.setdefault(r.bucket, []).append(r.v)
        assert set(got) == set(range(12))
        assert all(len(vs) == len(set(vs)) == sigma and not set(vs) & (held[b] | ruled[b]) for b, vs in got.items())
    assert len({tuple(sorted(vs)) for vs in got.values()}) > 3


def test_no_python_on_the_row_path(spark, sf):
    m, _, _, a = Q.two_size(spark, sf)
    text = plan_of(release.audit(a, policy.linear_caps(policy.histogram(m.df), 8, 2, 100)))
    assert "Python" not in text and "Pandas" not in text and "CartesianProduct" not in text


def test_generated_source(spark):
    generated.register(spark)
    df = spark.read.format("microdata").options(rows=1000, domain=5, skew=1.5, parts=3).load()
    assert df.count() == 1000 and df.rdd.getNumPartitions() == 3
    top = policy.histogram(df).orderBy(F.desc("cnt")).first()
    assert top.v == 0 and top.cnt > 400


def test_sink_sorts_sides_apart(spark, sf, tmp_path):
    m, _, _, a = Q.two_size(spark, sf)
    qi_side, sa = release.publish(a, m.qi)
    sinks.write_release(qi_side, sa, f"file://{tmp_path}/r", files=2)
    back = spark.read.parquet(f"file://{tmp_path}/r/sensitive")
    assert back.count() == m.df.count() and spark.read.parquet(f"file://{tmp_path}/r/qi").columns == [*m.qi, "bucket"]
    sinks.write_release(qi_side, sa, f"file://{tmp_path}/r", mode="overwrite")


@pytest.mark.parametrize("name", ["agg_approx_distinct", "agg_hll_sketch", "agg_theta_sketch"])
def test_sketches_are_near(spark, sf, name):
    true = microdata.table(spark, sf, "events").agg(F.count_distinct("user_id")).first()[0]
    got = entry.queries()[name](spark, sf).first()[0]
    assert abs(got - true) <= 0.1 * true


def test_multi_size_beats_two_size_and_fixed(spark, sf):
    for r in entry.queries()["w_mse_theta"](spark, sf).collect():
        assert r.bound <= r.exact + 1e-6 and r.exact <= r.many_size <= r.two_size < r.fixed_ell


def test_policy_monitor_and_bucket_fill(spark, sf):
    from capbuckets.streaming import events as S

    seen = []
    S.policy_monitor(S.stream_histogram(S.event_stream(spark, sf)), 8, lambda layout, ok: seen.append((layout.loss, ok))).awaitTermination()
    want = search.search_two_size(Q.caps(spark, sf, "occ50"))
    assert seen[-1] == (want.loss, True)
    filled = S.run_available(S.bucket_fill(S.event_stream(spark, sf), 6, 2))
    sizes = filled.groupBy("part", "bucket").agg(F.count(F.lit(1)).alias("n"))
    assert sizes.count() > 100 and sizes.where("n <> 6").count() == 0
    assert filled.groupBy("part", "bucket", "v").count().agg(F.max("count")).first()[0] <= 2


class _State:
    """A state variable on its own, as a handle gives it."""

    def __init__(self):
        self.held = None

    def exists(self):
        return self.held is not None

    def get(self):
        return self.held

    put = update = lambda self, x: setattr(self, "held", list(x))

    def clear(self):
        self.held = None


def _fill(frames, size=6, quota=2):
    """(bucket, event_id, v) of the frames, each a batch of its own, and what waits in the end."""
    import pandas as pd
    from capbuckets.streaming.events import BucketFiller

    filler, out = BucketFiller(size, quota), []
    filler.waiting, filler.made = _State(), _State()
    for rows in frames:
        frame = pd.DataFrame(rows, columns=["event_id", "v"])
        for got in filler.handleInputRows(("0",), iter([frame[:7], frame[7:]]), None):
            out += [(int(b), int(i), None if pd.isna(v) else int(v)) for b, i, v in zip(got["bucket"], got["event_id"], got["v"], strict=True)]
    return out, list(filler.waiting.held or [])


def test_bucket_filler_takes_the_earliest_rows_and_loses_none():
    import random

    rng = random.Random(5)
    rows = [(i // 2, rng.choice([None, 0, 0, 0, 1, 2, 3])) for i in range(300)]  # each id twice, some values null
    pool, want, n = list(rows), [], 0
    while True:
        taken, counts = [], {}
        for at, (_, v) in enumerate(pool):
            if len(taken) < 6 and counts.get(v, 0) < 2:
                counts[v] = counts.get(v, 0) + 1
                taken.append(at)
        if len(taken) < 6:
            break
        want += [(n, *pool[at]) for at in taken]
        pool, n = [r for at, r in enumerate(pool) if at not in taken], n + 1
    assert n > 20 and pool
    assert _fill([rows]) == (want, pool) == _fill([rows[:101], rows[101:102], rows[102:]])


def test_bucket_filler_costs_its_rows_however_many_wait():
    import time

    rows = [(i, 0) for i in range(60_000)] + [(60_000 + i, i % 3 + 1) for i in range(60_000)]
    began = time.process_time()
    out, left = _fill([rows])
    assert len(out) + len(left) == 120_000 and len(out) == 6 * 15_000
    assert time.process_time() - began < 20  # some minutes when each bucket looked at all rows that wait


def test_late_rows_are_dropped(spark, tmp_path):
    from capbuckets.streaming.events import checkpoint_path

    for i, (name, stamp) in enumerate([("a", "2024-01-02 00:00:00"), ("b", "2024-01-02 00:30:00"), ("c", "2024-01-01 00:00:00")]):
        spark.sql(f"SELECT TIMESTAMP'{stamp}' AS ts, '{name}' AS k").coalesce(1).write.mode("append").parquet(f"file://{tmp_path}/in/{i}")
    stream = spark.readStream.schema("ts timestamp, k string").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"file://{tmp_path}/in")
    counts = stream.withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    run = counts.writeStream.outputMode("append").option("checkpointLocation", checkpoint_path(spark, "late")).format("memory").queryName("late_rows").trigger(availableNow=True).start()
    run.awaitTermination()
    dropped = sum(s.get("numRowsDroppedByWatermark", 0) for p in run.recentProgress for s in p["stateOperators"])
    assert dropped == 1


def test_sort_based_aggregate(spark, sf):
    df = microdata.table(spark, sf, "nation").groupBy("n_regionkey").agg(F.max("n_name").alias("last"))
    assert "SortAggregate" in plan_of(df) and df.count() == 5


def test_one_size_engines_agree(spark, sf):
    c = Q.caps(spark, sf, "qty50")
    row, found = search.plan_search_one_size(c).first(), search.search_one_size(search.collect_classes(c))
    assert (row is None) == (found.loss is None)
    assert row is None or (row.loss, [(row.s1, row.b1)]) == (found.loss, found.classes)


def test_broadcasts_of_small_tables_only(spark, sf):
    text = plan_of(search.valid_intervals(Q.caps(spark, sf, "occ50"), 1, 20, 1000))
    assert "BroadcastNestedLoopJoin" in text and "CartesianProduct" not in text


def test_work_of_the_strategies(spark, sf):
    """Each pruning saves work; the integer program looks at fewer positions than no pruning, and its work grows with the domain while the list falls."""
    seen = {r.strategy: r.positions for r in entry.queries()["work_counters"](spark, sf).collect()}
    assert seen["full"] < seen["loss"] < seen["none"] and seen["full"] < seen["ilp"] < seen["none"]
    work = {(r.what, r.strategy, r.size): r for r in entry.queries()["w_domain_scale"](spark, sf).collect()}
    for name in ("occ50", "edu14"):
        assert work[name, "none", 64].listed < work[name, "none", 2].listed
        assert len({work[name, s, 8].loss for s in ("full", "loss", "none", "ilp")}) == 1
    assert work["edu14", "ilp", 16].tests > 4 * work["edu14", "ilp", 2].tests


def test_integer_program_against_every_position():
    """The least position with a solution, and a whole solution there, for random counts, caps and lattices."""
    import numpy as np

    from capbuckets.operators import lattice

    r = np.random.default_rng(5)
    found = 0
    for _ in range(400):
        m = int(r.integers(2, 9))
        den = int(r.integers(2, 12))
        c = search.Counts(r.integers(1, 30, m), r.integers(1, den + 1, m), np.full(m, den), np.ones(m, np.int64))
        lat = lattice.lattice(c.n, *sorted(r.choice(np.arange(1, 13), 2, replace=False).tolist()))
        if lat is None:
            continue
        ok = np.flatnonzero(search.valid_positions(c, lat, np.arange(lat.last + 1)))
        first, _ = search.ilp_first(c, lat)
        assert first == (int(ok[0]) if len(ok) else None)
        if first is not None:
            found += 1
            x, (b1, b2) = search.ilp_rows(c, lat, first), lat.at(first)
            assert (0 <= x).all() and (x <= np.minimum(c.cnt, c.quota(lat.s1) * b1)).all() and (c.cnt - x <= c.quota(lat.s2) * b2).all() and int(x.sum()) == lat.s1 * b1
    assert found > 20


def test_positions_are_judged_run_by_run_as_at_once():
    import numpy as np

    from capbuckets.operators import lattice

    r = np.random.default_rng(11)
    seen = [0, 0]
    for _ in range(300):
        m, den = int(r.integers(1, 40)), int(r.integers(2, 30))
        c = search.Counts(r.integers(1, 40, m), r.integers(1, den + 1, m), np.full(m, den), r.integers(1, 4, m))
        lat = lattice.lattice(c.n, *sorted(r.choice(np.arange(1, 20), 2, replace=False).tolist()))
        if lat is None:
            continue
        ok, tests = search.judged_positions(c, lat, np.arange(lat.last + 1))
        assert tests <= m * (lat.last + 1)
        for i in range(lat.last + 1):
            (b1, b2), q1, q2 = lat.at(i), c.quota(lat.s1), c.quota(lat.s2)
            fits = all(x * b1 + y * b2 >= o for o, x, y in zip(c.cnt, q1, q2, strict=True))
            fills = all(sum(k * min(x * b, o) for o, x, k in zip(c.cnt, q, c.mult, strict=True)) >= s * b for q, s, b in ((q1, lat.s1, b1), (q2, lat.s2, b2)))
            assert ok[i] == (fits and fills)
            seen[int(ok[i])] += 1
    assert min(seen) > 50


def test_exact_search_stops_by_nodes_and_says_so():
    from capbuckets.operators import exact

    o, n = [40, 31, 17, 9, 5, 3, 2, 1], 108
    num, den = [min(2 * x * 50 + 3 * n, n * 50) for x in o], [n * 50] * 8
    best, few = exact.exact_multi(o, num, den, 20), exact.exact_multi(o, num, den, 20, max_nodes=0)
    assert best.optimal and not best.stopped and few.bound <= best.loss and (few.optimal or few.stopped == "nodes")
    assert exact.exact_multi(o, num, den, 20).layout == best.layout
    import numpy as np

    with pytest.raises(exact.SimplexStopped):
        exact.simplex(np.array([1.0, 1.0]), np.array([[1.0, 2.0], [3.0, 1.0]]), np.array([4.0, 5.0]), np.array([False, False]), steps=1)
    with pytest.raises(exact.SimplexStopped):
        exact.simplex(np.array([-1.0]), np.array([[1.0]]), np.array([1.0]), np.array([False]))


def test_rewritten_query_is_the_estimate(spark, sf):
    m, _, _, a = Q.two_size(spark, sf)
    qi_side, sa = release.publish(a, m.qi)
    sa = release.compact(sa)
    one = workload.rewrite_on_release(qi_side, sa, {"hour": [6, 7, 8]}, [0, 1]).first().est
    two = workload.estimate_count(qi_side, sa, F.col("hour").between(6, 8), F.col("v") < 2).first().est
    assert abs(one - two) < 1e-9 and one > 0


def test_large_domains_are_searched_by_class(spark, sf):
    c = Q.caps(spark, sf, "bigdom")
    row, found = search.plan_search(c).first(), search.search_two_size(c)
    assert len(search.collect_classes(c).cnt) < policy.histogram(microdata.bigdom(spark, sf).df).count()
    assert (row is None) == (found.loss is None) and (row is None or row.loss == found.loss)


def test_bucketed_sides_join_without_exchange(spark, sf):
    m, _, _, a = Q.two_size(spark, sf)
    qi_side, sa = release.publish(a, m.qi)
    sinks.write_bucketed(qi_side, "side_q", 4)
    sinks.write_bucketed(release.compact(sa), "side_s", 4)
    joined = spark.table("side_q").join(spark.table("side_s").hint("merge"), "bucket")
    assert "Exchange" not in plan_of(joined) and joined.count() > m.df.count()
    spark.sql("DROP TABLE side_q")
    spark.sql("DROP TABLE side_s")


def test_best_layout_is_valid_for_every_set_of_classes(spark):
    caps = Q.fifty_caps(spark)
    assert validity.valid_multi(caps, [(4, 7), (5, 2), (12, 1)]).first().valid
    assert not validity.valid_multi(caps, [(3, 9), (11, 1), (12, 1)]).first().valid


def test_safe_decoys_avoid_associations(spark):
    qi_side = spark.createDataFrame([(0, "a"), (0, "b"), (1, "b"), (1, "b")], "bucket bigint, z string")
    sa = spark.createDataFrame([(0, 1, 1), (0, 2, 1), (1, 3, 1), (1, 4, 1)], "bucket bigint, v int, cnt bigint")
    assoc = spark.createDataFrame([("a", 3, 0.0), ("b", 9, 0.0)], "z string, v int, lift double")
    got = attacks.safe_decoys(qi_side, sa, F.col("z"), assoc, 1, "s")
    assert got.count() == 6 and {r.v for r in got.where("bucket = 0").collect()} == {1, 2, 4}


def test_map_of_a_bucket(spark):
    sa = spark.createDataFrame([(0, 2, 3), (0, 1, 1)], "bucket bigint, v int, cnt bigint")
    assert release.map_histogram(sa).first()["values"] == {1: 1, 2: 3}


def test_outer_joins_keep_every_row_of_whole_tables(spark, sf):
    import duckdb

    customers, orders = (spark.read.parquet(f"{sf}/{t}.parquet").count() for t in ("customer", "orders"))
    con = duckdb.connect()
    for t in ("customer", "orders"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    for how, left, right in (("left", True, False), ("right", False, True), ("full", True, True)):
        name = f"join_{how}_outer_whole"
        got = [tuple(r) for r in entry.queries()[name](spark, sf).collect()]
        assert sorted(got, key=str) == sorted(con.execute(entry.oracle_sql()[name]).fetchall(), key=str)
        assert not left or len({c for c, _ in got} - {None}) == customers and any(o is None for _, o in got)
        assert not right or len({o for _, o in got} - {None}) == orders and any(c is None for c, _ in got)


def test_search_without_prunings_looks_at_any_number_of_layouts(spark, sf, monkeypatch):
    c = search.collect_classes(Q.caps(spark, sf, "occ50"))
    want = search.driver_search(c, 50, "none")
    for name, most in (("MAX_LAYOUTS", 10), ("DRIVER_LAYOUTS", 10), ("RANGE", 7), ("CHUNK_CELLS", 1)):
        monkeypatch.setattr(search, name, most, raising=False)
    got = search.driver_search(c, 50, "none", spark=spark)
    assert got.classes and got == want and got.counters["positions"] == got.counters["listed"] > 1000


def test_prefix_histograms_are_of_the_first_rows(spark, sf):
    from capbuckets.functions.exact import order_key
    from capbuckets.plans import experiments as E

    m = microdata.price50(spark, sf)
    rows = [r.v for r in m.df.select("v", order_key("w10", *[F.col(k) for k in m.key]).alias("h")).orderBy("h").collect()]
    sizes = [0, 1, 1000, len(rows) - 1, len(rows)]
    for n, hist in zip(sizes, E.prefix_histograms(m, sizes), strict=True):
        assert sorted((r.v, r.cnt) for r in hist.collect()) == sorted((v, rows[:n].count(v)) for v in set(rows[:n]))


def test_lateral_puts_missing_order_keys_last_as_sql_does(spark, tmp_path):
    spark.sql("SELECT 1L AS c_custkey").write.parquet(f"file://{tmp_path}/customer.parquet")
    orders = "(1L, NULL, 5D), (1L, 7L, 5D), (1L, 8L, 5D), (1L, 9L, NULL)"
    spark.sql(f"SELECT * FROM VALUES {orders} AS t(o_custkey, o_orderkey, o_totalprice)").write.parquet(f"file://{tmp_path}/orders.parquet")
    got = entry.queries()["sub_lateral"](spark, str(tmp_path))
    assert sorted(r.o_orderkey for r in got.collect()) == [7, 8]


#: Queries that once made up all their rows.
OF_TABLES = ["corruption_closed_form", "cte_recursive_lattice", "dp_ratio_bound", "exact_enumerated", "exact_small", "feasible_count", "fifty_rows_search", "four_rows_risk"]


def test_queries_take_their_rows_from_a_given_table(spark, sf, tmp_path):
    from pyspark.errors import AnalysisException

    for name in OF_TABLES:
        assert entry.queries()[name](spark, sf).count() > 0
        with pytest.raises(AnalysisException):
            entry.queries()[name](spark, str(tmp_path)).collect()


def test_pool_estimate_keeps_null_values_in_their_places(spark):
    qi_side = spark.createDataFrame([("x", 0)] * 3 + [(None, 1)], "a string, bucket bigint")
    sa = spark.createDataFrame([(0, None, 2), (0, 1, 1), (1, 1, 1)], "bucket bigint, v int, cnt bigint")
    pool = spark.createDataFrame([(0, 1, "a", "x"), (0, 1, "v", "1"), (1, 1, "v", "1")], "query_id int, d int, attr string, value string")
    assert {r.query_id: round(r.est, 9) for r in workload.pool_estimate(qi_side, sa, pool, ["a"]).collect()} == {0: 1.0, 1: 2.0}


def test_place_makes_what_assign_makes(spark, sf):
    m, rows, layout, a = Q.two_size(spark, sf, "edu14", 16)
    ranked = assign.rank_rows(m.df, "v", m.key, "s0")
    assert a.columns == assign.place(ranked, "v", assign.two_size_cuts(rows, layout.classes)).columns
    assert a.exceptAll(assign.place(ranked, "v", assign.two_size_cuts(rows, layout.classes))).isEmpty() and a.count() > 0


def with_long_lists(spark, sf, monkeypatch, name):
    """(rows, rows where every list without prunings is longer than the driver looks at itself) of a query."""
    rows = lambda: sorted(entry.queries()[name](spark, sf).collect(), key=str)
    want, jobs, judge = rows(), [], getattr(search, "judge_all", None)
    for limit in ("MAX_LAYOUTS", "DRIVER_LAYOUTS"):
        monkeypatch.setattr(search, limit, 10, raising=False)
    monkeypatch.setattr(search, "judge_all", lambda *a: jobs.append(1) or judge(*a), raising=False)
    got = rows()
    assert jobs, "no job looked at the list"
    return want, got


def test_w_runtime_rows_of_long_lists(spark, sf, monkeypatch):
    want, got = with_long_lists(spark, sf, monkeypatch, "w_runtime_rows")
    assert len(got) == 20 and got == want
    assert all(r.positions == r.listed for r in got if r.strategy == "none")


def test_positions_are_judged_alike_many_or_few_at_once(monkeypatch):
    import numpy as np

    from capbuckets.operators import lattice

    r, some = np.random.default_rng(7), 0
    for m in (1, 5, 40):
        cnt, mult = r.integers(1, 60, m), r.integers(1, 4, m)
        c = search.Counts(cnt, r.integers(1, 9, m), np.full(m, 9), mult)
        for s1, s2 in ((2, 5), (3, 4), (6, 10)):
            lat = lattice.lattice(c.n, s1, s2)
            if lat is None:
                continue
            at, q1, q2 = range(lat.last + 1), c.quota(s1), c.quota(s2)
            held = lambda q, b: np.minimum(q * b, cnt)
            want = [bool((q1 * x + q2 * y >= cnt).all() and (mult * held(q1, x)).sum() >= s1 * x and (mult * held(q2, y)).sum() >= s2 * y) for x, y in map(lat.at, at)]
            seen = []
            for few in (0, 1 << 30):
                monkeypatch.setattr(search, "FEW", few)
                valid, tests = search.judged_positions(c, lat, np.arange(lat.last + 1))
                assert valid.tolist() == want
                seen.append(tests)
            assert seen[0] == seen[1]
            some += sum(want)
    assert some


def test_strategies_agree_of_long_lists(spark, sf, monkeypatch):
    want, got = with_long_lists(spark, sf, monkeypatch, "strategies_agree")
    assert got == want and len(got) == 4 and len({r.loss for r in got}) == 1


def test_two_size_none_of_long_lists(spark, sf, monkeypatch):
    want, got = with_long_lists(spark, sf, monkeypatch, "two_size_none")
    assert got == want == entry.queries()["two_size_optimal"](spark, sf).collect() and got


def test_work_counters_of_long_lists(spark, sf, monkeypatch):
    want, got = with_long_lists(spark, sf, monkeypatch, "work_counters")
    assert got == want and [r.positions == r.listed > 1000 for r in got if r.strategy == "none"] == [True]


def test_work_counters_order_of_long_lists(spark, sf, monkeypatch):
    want, got = with_long_lists(spark, sf, monkeypatch, "work_counters_order")
    assert got == want and len(got) == 3 and all(r.in_order for r in got)


def test_w_domain_scale_of_long_lists(spark, sf, monkeypatch):
    want, got = with_long_lists(spark, sf, monkeypatch, "w_domain_scale")
    assert got == want and len(got) == 48
    assert all(r.positions == r.listed for r in got if r.strategy == "none")


def test_w_domain_losses_of_long_lists(spark, sf, monkeypatch):
    want, got = with_long_lists(spark, sf, monkeypatch, "w_domain_losses")
    assert got == want and len(got) == 48 and len({(r.what, r.size, r.loss) for r in got}) == 12


def test_a_release_meets_the_pool_by_bucket_alone(spark, sf):
    """No shuffle by quasi-identifiers and no row a value: rows of the release move by bucket, and once."""
    m, _, _, a = Q.two_size(spark, sf)
    qi_side, sa = release.publish(a, m.qi)
    text = plan_of(workload.pool_estimate(qi_side, release.compact(sa), workload.pool_bits(Q.event_pool(spark, sf, 20)), m.qi))
    after = text.split("MapInArrow")[1]
    assert "hashpartitioning(bucket" in after and "hashpartitioning(event_type" not in after


def test_pool_of_wide_attributes_nulls_and_other_kinds(spark, monkeypatch):
    """Every query asked on its own, whatever the chunks of rows and compositions are."""
    rows = [(None if i % 11 == 0 else i * 37 % 90, i % 3 == 0, None if i % 7 == 0 else f'"{i % 5},', i // 4 % 25) for i in range(700)]
    side = spark.createDataFrame(rows, "wide int, flag boolean, name string, bucket int")
    shares = {b: [(None, 1), (b % 3, 1 + b % 2)] for b in range(25)}
    sa = spark.createDataFrame([(b, v, n) for b, x in shares.items() for v, n in x], "bucket int, v int, cnt bigint")
    lists = {0: {"wide": range(0, 70), "v": (0, 1)}, 1: {"flag": ("true",), "name": ('"1,', '"4,'), "v": (2,)}, 2: {"wide": range(30, 95), "flag": ("false",), "name": ('"0,', '"9,')}, 3: {"v": (1, 2)}, 4: {"name": ("none",), "v": (0,)}}
    pool = spark.createDataFrame([(q, 1, a, str(x)) for q, own in lists.items() for a, values in own.items() for x in values], "query_id int, d int, attr string, value string")
    text = lambda x: str(x).lower() if isinstance(x, bool) else str(x)
    fits = lambda q, a, x: a not in q or (x is not None and text(x) in {str(y) for y in q[a]})
    want = {}
    for i, q in lists.items():
        inside = [r[3] for r in rows if all(fits(q, a, x) for a, x in zip(("wide", "flag", "name"), r, strict=False))]
        want[i] = sum(sum(n for v, n in shares[b] if fits(q, "v", v)) / sum(n for _, n in shares[b]) for b in inside)
    assert want[4] == 0 and all(want[i] > 0 for i in range(4))
    for chunk, cells, narrow in ((1 << 18, 1 << 22, 64), (100, 7, 64), (1 << 18, 1 << 22, 2), (1 << 18, 1 << 22, 100)):
        for name, value in (("CHUNK_ROWS", chunk), ("MAX_SHARES", cells), ("NARROW", narrow)):
            monkeypatch.setattr(workload, name, value)
        evaluate = workload._evaluator(workload.pool_bits(pool), ("wide", "flag", "name"), True)  # as a task does, with these limits
        weights = sa.groupBy("bucket").agg(F.collect_list(F.struct("v", "cnt")).alias("x")).select("bucket", workload.weights_of("x.v", "x.cnt").alias("_weights"))
        table = side.join(weights, "bucket").select("wide", F.col("flag").cast("string").alias("flag"), "name", "_weights").toArrow()
        (got,) = evaluate(iter(table.to_batches(max_chunksize=64)))
        assert dict(zip(*[c.to_pylist() for c in got.columns], strict=True)) == pytest.approx(want)
    assert {r.query_id: r.est for r in workload.pool_estimate(side, sa, pool, ["wide", "flag", "name"]).collect()} == pytest.approx(want)


def test_releases_of_the_error_sweep_are_made_beside_each_other(spark, sf, monkeypatch):
    import threading

    from capbuckets.plans import experiments

    now, most, lock, old = [0], [0], threading.Lock(), experiments.release_error

    def counted(*a):
        with lock:
            now[0] += 1
            most[0] = max(most[0], now[0])
        try:
            out = old(*a).localCheckpoint()
        finally:
            with lock:
                now[0] -= 1
        return out

    monkeypatch.setattr(experiments, "release_error", counted)
    out = experiments.error_sweep(spark, sf, ("edu14",), (4, 8), 40)
    assert [(r[0], r[1], r[3]) for r in out] == [("edu14", t, 40) for t in (4, 8) for _ in range(3)] and most[0] > 1
