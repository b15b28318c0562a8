"""Worked examples with known results."""

from fractions import Fraction

import numpy as np
import pytest

from capbuckets.operators import assign, exact, fixed_ell, noise, policy, refine, release, search, validity
from capbuckets.operators.lattice import interval_and, lattice
from capbuckets.plans.method_queries import fifty_caps
from capbuckets.sources import microdata as M

FIFTY = M.FIFTY
NUM, DEN = [2 * o * 20 + 50 for o in FIFTY], [1000] * 14
COUNTS = search.Counts(np.array(FIFTY), np.array(NUM), np.array(DEN), np.ones(14, np.int64))


def test_worked_list_of_28_rows():
    lat = lattice(28, 2, 4)
    assert [lat.at(i) for i in range(lat.last + 1)] == [(14 - 2 * i, i) for i in range(8)]
    assert (lat.d1, lat.d2, lat.last) == (2, 1, 7)


def test_empty_lattice():
    assert lattice(7, 2, 4) is None
    assert lattice(1, 2, 3) is None


def test_worked_layout_bounds_and_split():
    q1, q2 = COUNTS.quota(4), COUNTS.quota(14)
    b1, b2 = np.minimum(q1 * 9, FIFTY), np.minimum(q2 * 1, FIFTY)
    assert b1.tolist() == [0] * 8 + [6] * 4 + [9] * 2 and b1.sum() == 42
    assert b2.tolist() == [1] * 8 + [4] * 4 + [5] * 2
    takes = assign.split_counts(FIFTY, q1, q2, [(4, 9), (14, 1)], "spread")
    moved = [int(b) - t for b, (t, _) in zip(b1, takes, strict=True)]
    assert moved == [0] * 8 + [1] * 6  # one row of each of six values


@pytest.mark.parametrize("order", ["key", "rare_first", "common_first", "spread"])
def test_split_reaches_room_and_respects_bounds(order):
    q1, q2 = COUNTS.quota(4), COUNTS.quota(14)
    takes = np.array(assign.split_counts(FIFTY, q1, q2, [(4, 9), (14, 1)], order))
    assert takes.sum(0).tolist() == [36, 14]
    assert (takes[:, 0] <= q1 * 9).all() and (takes[:, 1] <= q2).all() and (takes.sum(1) == FIFTY).all()


@pytest.mark.parametrize(("m_max", "loss", "layout"), [(50, 250, [(4, 9), (14, 1)]), (13, 342, [(4, 6), (13, 2)]), (12, 435, [(7, 2), (12, 3)])])
@pytest.mark.parametrize("strategy", ["full", "loss", "none"])
def test_fifty_rows_optimum(m_max, loss, layout, strategy):
    found = search.driver_search(COUNTS, m_max, strategy)
    assert (found.loss, found.classes) == (loss, layout)


def test_exact_many_size_is_216():
    e = exact.exact_multi(FIFTY, NUM, DEN, 50)
    assert e.optimal and e.loss == 216 and e.layout == [(4, 7), (5, 2), (12, 1)]
    assert exact.exact_enumerate(FIFTY, NUM, DEN, 16)[1] == 216
    assert refine.refine(FIFTY, NUM, DEN).loss == 250
    quotas = np.array([[min(s, s * a // b) for s in range(3, 51)] for a, b in zip(NUM, DEN, strict=True)])
    assert exact.lp_bound(FIFTY, quotas, range(3, 51)) <= 216


def test_three_class_counterexample(spark):
    bounds = validity.three_class_bounds(spark)
    assert validity.valid_naive_multi(bounds, validity.THREE_CLASS_ROOMS).first().valid
    failed = validity.subset_tests(bounds, validity.THREE_CLASS_ROOMS).where("NOT ok").collect()
    assert (3, 20, 40) in [(r.mask, r.supply, r.room) for r in failed]


@pytest.mark.parametrize(("least", "ells"), [(Fraction(18, 10_000), [43, 37, 30, 21, 13]), (Fraction(44, 10_000), [35, 27, 19, 12, 7])])
def test_diversity_that_a_slope_asks_for(least, ells):
    got = [-(-1 // min(Fraction(1), t * least + Fraction(1, 50))) for t in (2, 4, 8, 16, 32)]
    assert got == ells


def test_largest_diversity(spark):
    for most, want in ((75, 13), (273, 3)):
        hist = spark.createDataFrame([(0, most), (1, 1000 - most)], "v int, cnt bigint").where("v = 0").unionAll(spark.createDataFrame([(i, 1) for i in range(1, 1001 - most)], "v int, cnt bigint"))
        assert policy.max_ell(hist).first().max_ell == want


def test_ratio_factors(spark):
    from pyspark.sql import functions as F

    rows = spark.createDataFrame([(100, 99), (1000, 990)], "x bigint, y bigint")
    m = noise.ratio_moments(F.col("x"), F.col("y"), 0.1)
    got = rows.select(m["factor"].alias("f"), m["var"].alias("v")).collect()
    assert [round(r.f, 6) for r in got] == [1.02, 1.0002]
    assert [round(r.v, 8) for r in got] == [0.039602, 0.00039602]


def test_smallest_release(spark):
    m = M.four_rows(spark)
    qi_side, sa = release.publish(m.df, m.qi)
    risk = release.person_risk(qi_side, release.compact(sa), m.qi).where("gender = 'F' AND zip = '61434'").collect()
    assert {(r.v, r.prob) for r in risk} == {("Cancer", 0.5), ("HIV", 0.5)}


def test_quota_is_exact(spark):
    from pyspark.sql import functions as F

    from capbuckets.functions.exact import quota

    assert spark.range(1).select(quota(F.lit(49), F.lit(1).cast("bigint"), F.lit(49).cast("bigint")).alias("q")).first().q == 1


def test_extremes_and_intervals():
    assert release.extreme_losses(101) == {"raw": (0, 0.0), "one_bucket": (10_000, 100.0)}
    assert interval_and((0, 9), (3, 12), (1, 5)) == (3, 5)
    assert fixed_ell.fixed_ell_layout(1000, 46) == [(47, 13), (48, 8)] or sum(s * b for s, b in fixed_ell.fixed_ell_layout(1000, 46)) == 1000


def test_dealt_bucket_holds_distinct_values(spark):
    m = M.fifty_rows(spark)
    rows = assign.collect_caps(fifty_caps(spark))
    a = assign.assign(m.df, "v", m.key, assign.two_size_cuts(rows, [(4, 9), (14, 1)]), "s0")
    sa = release.compact(a)
    sizes = {r.bucket: r["size"] for r in release.bucket_sizes(sa).collect()}
    assert sorted(sizes.values()) == [4] * 9 + [14]
    assert sa.join(release.bucket_sizes(sa), "bucket").where("size = 4").agg({"cnt": "max"}).first()[0] == 1
    assert release.audit(a, fifty_caps(spark)).first().violations == 0
