"""Bounds, bucket plans, size trees, hierarchies and curves: worked examples, brute force and invariants."""

import itertools
import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from gainbound.functions.bounds import EPS, cap, check_monotone
from gainbound.functions.curves import bits_for, hilbert_keys
from gainbound.plans import sizetree
from gainbound.plans.buckets import can_share, ordered, plan_buckets, proportional_groups
from gainbound.plans.hierarchy import Hierarchy
from gainbound.plans.spec import CATEGORICAL, Attribute, ReleaseSpec
from gainbound.sources import views

NINETEEN = [("a", 2), ("b", 3), ("c", 3), ("d", 3), ("e", 4), ("f", 4)]
counts_of = st.lists(st.integers(1, 60), min_size=1, max_size=9)


def test_nineteen_rows():
    plan = plan_buckets(NINETEEN, 2.0)
    assert [round(c, 4) for c in plan.caps] == [0.3158, 0.4493, 0.5386]
    assert plan.sizes == (5, 6, 8)
    assert plan.segments == ((0, 2), (2, 4), (4, 6))
    leaves = sizetree.grow(plan.sizes, sizetree.gain_rule(plan.caps)).leaf_vectors()
    assert leaves.tolist() == [[1, 1, 2], [1, 2, 2], [3, 3, 4]]


@settings(max_examples=60, deadline=None)
@given(st.floats(0.001, 0.999), st.floats(0.001, 0.999), st.floats(0.5, 6))
def test_cap_rises_and_stays_below_one(p, q, beta):
    p, q = min(p, q), max(p, q)
    assert cap(p, beta) <= cap(q, beta) + EPS
    assert p <= cap(p, beta) < 1
    assert cap(1.0, beta) == 1.0


def test_cap_is_continuous_at_the_threshold():
    for beta in (1.0, 2.0, 4.0):
        p = math.exp(-beta)
        assert cap(p * (1 - 1e-9), beta) == pytest.approx(cap(p * (1 + 1e-9), beta), rel=1e-6)


def test_decreasing_caps_are_refused():
    with pytest.raises(ValueError):
        check_monotone([0.1, 0.3, 0.2])


@settings(max_examples=80, deadline=None)
@given(counts_of, st.sampled_from([0.5, 1.0, 2.0, 4.0]))
def test_plan_has_the_fewest_buckets(counts, beta):
    pairs = list(enumerate(counts))
    plan = plan_buckets(pairs, beta)
    n = [c for _, c in ordered(pairs)]
    total, m = sum(n), len(n)

    def ok(cuts):
        return all(e == b + 1 or can_share(sum(n[b:e]), n[b], total, beta) for b, e in zip([0, *cuts], [*cuts, m], strict=True))

    best = next(k + 1 for k in range(m) if any(ok(c) for c in itertools.combinations(range(1, m), k)))
    assert len(plan.segments) == best == len(plan_buckets(pairs, beta, tie="greedy").segments)
    assert plan.segments[0][0] == 0 and plan.segments[-1][1] == m and all(a[1] == b[0] for a, b in zip(plan.segments, plan.segments[1:], strict=False))
    assert len(plan_buckets(pairs, beta, tie="singletons").segments) == m


@settings(max_examples=60, deadline=None)
@given(counts_of, st.sampled_from([1.0, 2.0, 4.0]))
def test_tree_leaves_are_admissible_and_whole(counts, beta):
    plan = plan_buckets(list(enumerate(counts)), beta)
    rule = sizetree.gain_rule(plan.caps)
    tree = sizetree.grow(plan.sizes, rule)
    leaves = tree.leaf_vectors()
    assert leaves.sum(0).tolist() == list(plan.sizes) and len(leaves) == tree.n_leaves
    for v in leaves:
        half = [x // 2 for x in v]
        rest = [x - h for x, h in zip(v, half, strict=True)]
        assert len(leaves) == 1 or rule(tuple(v))
        assert not (rule(tuple(half)) and rule(tuple(rest)))
    bucket = np.concatenate([np.full(s, j) for j, s in enumerate(plan.sizes)])
    rank = np.concatenate([np.arange(s) for s in plan.sizes])
    ec, _, _ = tree.walk(bucket, rank)
    got = np.zeros_like(leaves)
    np.add.at(got, (ec, bucket), 1)
    assert (got == leaves).all()


def test_tree_of_a_very_large_table_is_small():
    plan = plan_buckets([(i, 10**11 + i * 10**9) for i in range(40)], 1.0)
    tree = sizetree.grow(plan.sizes, sizetree.gain_rule(plan.caps))
    assert len(tree.counts) < 5000 and tree.n_leaves > 10**6


def test_strict_slack_and_boundary():
    # 3 of 10 rows with a rarest value of 1 and beta 2: exactly at the bound
    assert can_share(3, 1, 10, 2.0) and not can_share(3, 1, 10, 2.0, strict=True) and not can_share(3, 1, 10, 2.0, slack=0.05)


def test_edges_of_planning():
    with pytest.raises(ValueError):
        plan_buckets([], 1.0)
    one = plan_buckets([("x", 5)], 1.0)
    assert one.segments == ((0, 1),) and one.caps == (1.0,)
    assert proportional_groups((7, 12)) == 1 and proportional_groups((6, 9)) == 3
    ties = plan_buckets([("b", 3), ("a", 3), (None, 3)], 0.1)
    assert ties.values == ("a", "b", None)
    assert not sizetree.gain_rule((1.0, 1.0))((0, 0))


def test_unique_value_needs_half_the_table():
    plan = plan_buckets([("rare", 1), ("a", 499), ("b", 500)], 1.0)
    tree = sizetree.grow(plan.sizes, sizetree.gain_rule(plan.caps))
    holder = [v for v in tree.leaf_vectors() if v[0]]
    assert all(v.sum() >= 500 for v in holder)


def test_hierarchy():
    assert views.NATION.height == 3 and len(views.NATION.leaves) == 25
    h = Hierarchy("x", ("any", ("p", "a", "b"), "c"))
    assert h.leaves == ["a", "b", "c"] and [(n.node, n.lo, n.hi) for n in h.nodes] == [("any", 0, 2), ("p", 0, 1), ("a", 0, 0), ("b", 1, 1), ("c", 2, 2)]


def test_spec_is_checked():
    with pytest.raises(ValueError):
        Attribute("a", CATEGORICAL)
    with pytest.raises(ValueError):
        ReleaseSpec((Attribute("a"),), "s", "k", (0.5,))


@pytest.mark.parametrize(("d", "bits"), [(2, 3), (3, 2), (4, 2)])
def test_hilbert_is_a_walk_through_all_cells(d, bits):
    points = np.array(list(itertools.product(range(1 << bits), repeat=d)))
    keys = hilbert_keys(points, bits)
    assert sorted(keys) == list(range(len(points)))
    steps = np.abs(np.diff(points[np.argsort(keys)], axis=0)).sum(1)
    assert (steps == 1).all()
    assert bits_for([83, 2, 11]) == 7


def test_golden_leaf_counts(spark):
    """Buckets and groups of the plans on the given tables, by beta. At beta 1 two pairs of p_size values have equal counts, which is just within the bound."""
    from gainbound.operators import model

    census = views.census_view(spark, "/root/testdata/sf0.01")
    price, size = model.domain(census, "price_class"), model.domain(census, "p_size")

    def groups(counts, beta):
        plan = plan_buckets(counts, beta)
        return len(plan.sizes), sizetree.grow(plan.sizes, sizetree.gain_rule(plan.caps)).n_leaves

    assert [groups(price, float(b)) for b in range(1, 6)] == [(50, 275), (25, 148), (17, 11), (13, 290), (13, 100)]
    assert [groups(size, float(b)) for b in range(1, 6)] == [(48, 1), (25, 2028), (17, 1181), (13, 1608), (13, 596)]
