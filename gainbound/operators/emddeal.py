"""emd-deal: the bucket-and-deal machinery under a closeness budget instead of a gain bound.

The sensitive order is split into buckets until, by their masses, moving values within buckets costs at most a share of the budget
t. A vector of sizes is admissible if that cost plus the distance of its bucket-shaped distribution
from the overall one is within t; by the triangle inequality so is every group filled to it.
"""

from __future__ import annotations

import numpy as np

from gainbound.functions.bounds import EPS
from gainbound.operators.deal import Dealing, encode, survey
from gainbound.operators.settle import settle
from gainbound.plans import sizetree
from gainbound.plans.buckets import Plan
from gainbound.plans.spec import ReleaseSpec


def plan_by_order(counts: list[tuple], t: float, share: float = 0.5) -> Plan:
    """Buckets of consecutive values of the sensitive order, split where mass times diameter is largest."""
    pairs = sorted(((v, n) for v, n in counts if n), key=lambda x: (x[0] is None, x[0]))
    n, m = [c for _, c in pairs], len(pairs)
    total, step = sum(n), 1 / max(1, m - 1)
    segments = [(0, m)]

    def cost(s):
        return sum(n[s[0] : s[1]]) / total * (s[1] - s[0] - 1) * step

    while sum(map(cost, segments)) > share * t + EPS:
        worst = max(segments, key=lambda s: (cost(s), -s[0]))
        mid = (worst[0] + worst[1]) // 2
        segments.remove(worst)
        segments += [(worst[0], mid), (mid, worst[1])]
    segments.sort()
    return Plan(tuple(v for v, _ in pairs), tuple(n), tuple(segments), tuple(1.0 for _ in segments))


def closeness_rule(plan: Plan, t: float) -> sizetree.Admit:
    p = np.array(plan.counts) / sum(plan.counts)
    m = len(p)
    diameter = np.array([(e - b - 1) / max(1, m - 1) for b, e in plan.segments])
    shape = np.zeros((len(plan.segments), m))
    for j, (b, e) in enumerate(plan.segments):
        shape[j, b:e] = p[b:e] / p[b:e].sum()

    def admit(x: tuple[int, ...]) -> bool:
        if not sum(x):
            return False
        y = np.array(x) / sum(x)
        return float(y @ diameter + np.abs(np.cumsum(y @ shape - p)).sum() / max(1, m - 1)) <= t + EPS

    return admit


def prepare(df, spec: ReleaseSpec, t: float, share: float = 0.5) -> Dealing:
    """A planned release for closeness t; deal it as any other."""
    spec.validate(df)
    encoded = settle(encode(df, spec))
    return planned_on(encoded, spec, *survey(encoded, spec), t, share)


def planned_on(encoded, spec: ReleaseSpec, counts: list[tuple], domains: list[tuple[int, int]], t: float, share: float = 0.5) -> Dealing:
    """The same on a table that is encoded and surveyed already."""
    plan = plan_by_order(counts, t, share)
    return Dealing(spec, encoded, domains, counts, plan, sizetree.grow(plan.sizes, closeness_rule(plan, t)))
