"""Packing sensitive values into buckets, from their counts alone.

Values stand in ascending order of count (ties by value). Consecutive values b..e may
share a bucket if their joint frequency stays within the cap of the rarest one. The plan has the fewest
buckets; it is found by dynamic programming over the order, on the driver, as the domain is small.
"""

from __future__ import annotations

from bisect import bisect_left
from dataclasses import dataclass
from fractions import Fraction

from gainbound.functions.bounds import EPS, cap


@dataclass(frozen=True)
class Plan:
    """Buckets in ascending frequency: the values' order, each bucket's first and end place, its size and cap."""

    values: tuple
    counts: tuple[int, ...]
    segments: tuple[tuple[int, int], ...]
    caps: tuple[float, ...]

    @property
    def sizes(self) -> tuple[int, ...]:
        return tuple(sum(self.counts[b:e]) for b, e in self.segments)

    @property
    def bucket_of(self) -> dict:
        return {v: j for j, (b, e) in enumerate(self.segments) for v in self.values[b:e]}

    def rows(self) -> list[tuple]:
        """(value, bucket, bucket size, rarest frequency, cap)"""
        n = sum(self.counts)
        return [(self.values[i], j, self.sizes[j], self.counts[b] / n, self.caps[j]) for j, (b, e) in enumerate(self.segments) for i in range(b, e)]


def ordered(counts: list[tuple]) -> list[tuple]:
    """(value, count) pairs in the order of the plan; null comes last among equals."""
    return sorted(((v, n) for v, n in counts if n > 0), key=lambda x: (x[1], x[0] is None, x[0]))


def can_share(mass: int, rarest: int, total: int, beta: float, kind: str = "capped", strict: bool = False, slack: float = 0.0) -> bool:
    """Whether values of joint count mass, the rarest of count rarest, may share a bucket.

    On the linear branch the comparison is between exact numbers."""
    p = rarest / total
    limit = cap(p, beta, kind)
    if kind in ("basic", "capped") and abs(limit - p * (1 + beta)) <= EPS * p:
        exact = (1 + Fraction(str(beta))) * (1 - Fraction(str(slack))) * rarest
        return mass < exact if strict else mass <= exact
    room = limit * (1 - slack) * total
    return mass < room - EPS * total if strict else mass <= room + EPS * total


def plan_buckets(counts: list[tuple], beta: float, kind: str = "capped", tie: str = "short", strict: bool = False, slack: float = 0.0) -> Plan:
    """The plan for (value, count) pairs. tie: `short` takes, among the fewest buckets, the shortest last one at each step;
    `greedy` fills from the most frequent value down; `singletons` gives each value its own bucket."""
    pairs = ordered(counts)
    if not pairs:
        raise ValueError("the table is empty; there is nothing to plan")
    n = [c for _, c in pairs]
    total, m = sum(n), len(n)
    before = [0]
    for c in n:
        before.append(before[-1] + c)

    def may(b: int, e: int) -> bool:
        return b == e - 1 or can_share(before[e] - before[b], n[b], total, beta, kind, strict, slack)

    cuts: list[int] = []
    if tie == "singletons":
        cuts = list(range(m))
    elif tie == "greedy":
        e = m
        while e:
            b = e - 1
            while b and may(b - 1, e):
                b -= 1
            cuts.insert(0, b)
            e = b
    else:
        # feasibility is monotone in the first place, so the least feasible place of each end moves right
        fewest, cut = [0] * (m + 1), [0] * (m + 1)
        for e in range(1, m + 1):
            first = bisect_left(range(e), True, key=lambda b, e=e: may(b, e))
            best = min(fewest[first:e])
            # fewest never decreases along the order, so the last place of the minimum is the shortest bucket
            cut[e] = max(b for b in range(first, e) if fewest[b] == best)
            fewest[e] = best + 1
        e = m
        while e:
            cuts.insert(0, cut[e])
            e = cut[e]
    ends = [*cuts[1:], m]
    return Plan(tuple(v for v, _ in pairs), tuple(n), tuple(zip(cuts, ends, strict=True)), tuple(cap(n[b] / total, beta, kind) for b in cuts))


def proportional_groups(sizes: tuple[int, ...]) -> int:
    """Number of groups that draw from every bucket strictly in proportion: the sizes' greatest common divisor."""
    from math import gcd

    return gcd(*sizes)
