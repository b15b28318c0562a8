"""The lemmas as properties, against brute force on small random instances."""

from itertools import combinations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from capbuckets.operators import assign, exact, refine, search
from capbuckets.operators.lattice import lattice

counts_ = st.lists(st.integers(1, 12), min_size=2, max_size=6)
caps_ = st.tuples(st.integers(1, 4), st.integers(0, 30))


def instance(counts, rule):
    a, b = rule
    o, n = np.array(counts, np.int64), sum(counts)
    return search.Counts(o, np.minimum(o * a * 100 + n * b, n * 100), np.full(len(o), n * 100), np.ones(len(o), np.int64))


@given(st.integers(1, 200), st.integers(1, 12), st.integers(1, 12))
def test_lattice_lists_all_layouts(n, a, b):
    s1, s2 = min(a, b), max(a, b) + 1
    want = [((n - s2 * y) // s1, y) for y in range(n // s2 + 1) if (n - s2 * y) % s1 == 0]
    lat = lattice(n, s1, s2)
    got = [] if lat is None else [lat.at(i) for i in range(lat.last + 1)]
    assert got == want
    if lat:
        losses = [lat.loss(i) for i in range(lat.last + 1)]
        assert losses == sorted(set(losses))
        for best in (None, losses[0], losses[-1], losses[len(losses) // 2] + 1):
            assert lat.cutoff(best) == max([i for i, x in enumerate(losses) if best is None or x < best], default=-1)


@settings(max_examples=60, deadline=None)
@given(counts_, caps_)
def test_strategies_agree(counts, rule):
    c = instance(counts, rule)
    found = [search.driver_search(c, 12, s) for s in ("full", "loss", "none", "ilp")]
    if search.bounds_of(c)[1] <= 12:
        assert len({(f.loss, tuple(f.classes)) for f in found}) == 1
        assert found[0].counters["positions"] <= found[2].counters["positions"]


@settings(max_examples=80, deadline=None)
@given(counts_, caps_, st.integers(1, 8), st.integers(1, 8))
def test_intervals(counts, rule, a, b):
    c = instance(counts, rule)
    lat = lattice(c.n, min(a, b), max(a, b) + 1)
    if lat is None:
        return
    assert {i for i in range(lat.last + 1) if _private(c, lat, i)} == set(_span(search.privacy_interval(c, lat)))
    assert list(_span(search.privacy_interval(c, lat))) == list(_span(search.privacy_interval(c, lat, "three_part")))
    for s in (lat.s1, lat.s2):
        ok = [x for x in range(c.n // s + 1) if (np.minimum(c.quota(s) * x, c.cnt)).sum() >= s * x]
        assert search.fill_threshold(c, s) == max(ok) and ok == list(range(max(ok) + 1))


def _span(x):
    return range(x[0], x[1] + 1)


def _private(c, lat, i):
    b1, b2 = lat.at(i)
    return bool((c.quota(lat.s1) * b1 + c.quota(lat.s2) * b2 >= c.cnt).all())


@settings(max_examples=100, deadline=None)
@given(counts_, caps_, st.lists(st.tuples(st.integers(1, 8), st.integers(1, 4)), min_size=1, max_size=4, unique_by=lambda x: x[0]))
def test_subset_rule_is_the_flow(counts, rule, layout):
    layout = sorted(layout)
    n = sum(s * b for s, b in layout)
    counts = [*counts, n - sum(counts)] if sum(counts) < n else counts
    if sum(counts) != n:
        return
    c = instance(counts, rule)
    q = np.stack([c.quota(s) for s, _ in layout], 1)
    rooms, b = np.array([s * x for s, x in layout]), np.array([x for _, x in layout])
    subsets = all(np.minimum((q * b)[:, list(k)].sum(1), c.cnt).sum() >= rooms[list(k)].sum() for r in range(1, len(layout) + 1) for k in combinations(range(len(layout)), r))
    split = exact.flow_split(c.cnt, q, layout)
    assert (split is not None) == subsets
    if split is not None:
        take = np.array(split)
        assert (take <= q * b).all() and (take.sum(1) == c.cnt).all() and (take.sum(0) == rooms).all()


@settings(max_examples=40, deadline=None)
@given(counts_, caps_)
def test_refinement_is_between_exact_and_two_size(counts, rule):
    c = instance(counts, rule)
    if (c.cnt * c.den > c.num * c.n).any() or search.bounds_of(c)[1] > 12:
        return
    two = search.driver_search(c, 12)
    many = refine.refine(c.cnt, c.num, c.den, 12)
    best = exact.exact_enumerate(c.cnt.tolist(), c.num.tolist(), c.den.tolist(), 12)
    if two.loss is None:
        return
    assert many.loss <= two.loss
    assert best[1] <= many.loss
    lp = exact.exact_multi(c.cnt, c.num, c.den, 12, (refine.layout_of(many), many.loss))
    assert lp.optimal and lp.loss == best[1]
    values = list(range(len(counts)))
    cuts = refine.leaf_cuts(many, values)
    assert sum(x.hi - x.lo for x in cuts) == c.n


@given(st.lists(st.integers(0, 9), min_size=1, max_size=8), st.integers(1, 6))
def test_dealing_spreads_evenly(counts, buckets):
    cuts = assign.cut_points(range(len(counts)), [[c] for c in counts], [(1, buckets)])
    held = np.zeros((buckets, len(counts)), int)
    for c in cuts:
        for t in range(c.lo + 1, c.hi + 1):
            held[(c.prefix + t - c.lo) % c.b, c.v] += 1
    for v, o in enumerate(counts):
        assert set(held[:, v]) <= {o // buckets, -(-o // buckets)}
    assert held.sum(1).max() - held.sum(1).min() <= 1


def test_uniform_caps_give_the_uniform_sizes():
    o = np.array([10] * 10)
    c = search.Counts(o, np.ones(10, np.int64), np.full(10, 5), np.ones(10, np.int64))
    assert search.driver_search(c, 12).loss == 20 * 16


def test_no_layout_in_range():
    c = search.Counts(np.array([5, 5]), np.array([1, 1]), np.array([60, 60]), np.ones(2, np.int64))
    got = search.driver_search(c, 50)
    assert got.loss is None and got.reason


def test_invalid_split_raises():
    with pytest.raises(ValueError, match="not valid"):
        assign.split_counts([5, 5], [1, 1], [1, 1], [(2, 1), (4, 2)])


@settings(max_examples=100, deadline=None)
@given(counts_, caps_, st.integers(1, 8), st.integers(1, 8), st.integers(0, 40))
def test_two_size_conditions_are_a_split_and_a_flow(counts, rule, a, b, i):
    c = instance(counts, rule)
    lat = lattice(c.n, min(a, b), max(a, b) + 1)
    if lat is None or i > lat.last:
        return
    b1, b2 = lat.at(i)
    layout = [(lat.s1, b1), (lat.s2, b2)]
    ok = bool(search.valid_positions(c, lat, np.array([i]))[0])
    q = np.stack([c.quota(lat.s1), c.quota(lat.s2)], 1)
    assert ok == (exact.flow_split(c.cnt, q, layout) is not None)
    if ok:
        for order in ("key", "rare_first", "common_first", "spread"):
            take = np.array(assign.split_counts(c.cnt, q[:, 0], q[:, 1], layout, order))
            assert (take <= q * [b1, b2]).all() and take.sum(0).tolist() == [lat.s1 * b1, lat.s2 * b2] and (take.sum(1) == c.cnt).all()
