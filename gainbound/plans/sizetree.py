"""The tree of group sizes: vectors of rows to draw from each bucket, halved while both halves are admissible.

The left child takes n div 2 of every component. A depth has few distinct vectors, so the
tree is kept as its distinct vectors: a plan for 10**13 rows has some thousand nodes, and a row finds its
group from its bucket and its rank in the bucket alone.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np

from gainbound.functions.bounds import EPS

Admit = Callable[[tuple[int, ...]], bool]


def gain_rule(caps: tuple[float, ...]) -> Admit:
    """No bucket's share of the group exceeds its cap; empty groups are refused."""

    def admit(x: tuple[int, ...]) -> bool:
        total = sum(x)
        return total > 0 and all(a <= c * total + EPS * total for a, c in zip(x, caps, strict=True))

    return admit


@dataclass
class SizeTree:
    """Distinct vectors; left and right are node numbers, or -1 at leaves."""

    counts: np.ndarray
    left: np.ndarray
    right: np.ndarray
    leaves: np.ndarray

    @property
    def n_leaves(self) -> int:
        return int(self.leaves[0])

    def walk(self, bucket: np.ndarray, rank: np.ndarray, depth: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For rows by bucket and rank: the group's number, the node reached and the rank there. depth: stop after so many steps."""
        node, rank, group = np.zeros(len(rank), np.int64), rank.astype(np.int64).copy(), np.zeros(len(rank), np.int64)
        step = 0
        while depth is None or step < depth:
            inner = self.left[node] >= 0
            if not inner.any():
                break
            l, r = self.left[node], self.right[node]
            here = np.where(inner, self.counts[l, bucket], 0)
            right = inner & (rank >= here)
            rank = np.where(right, rank - here, rank)
            group = group + np.where(right, self.leaves[l], 0)
            node = np.where(inner, np.where(right, r, l), node)
            step += 1
        return group, node, rank

    def leaf_vectors(self, root: int = 0) -> np.ndarray:
        """Size vectors of the leaves under a node, in order. For plans of moderate size."""
        nodes = np.array([root])
        while (inner := self.left[nodes] >= 0).any():
            # both children take their parent's place
            at = np.cumsum(1 + inner) - 1 - inner
            below = np.repeat(nodes, 1 + inner)
            below[at[inner]], below[at[inner] + 1] = self.left[nodes[inner]], self.right[nodes[inner]]
            nodes = below
        return self.counts[nodes]


def grow(sizes: tuple[int, ...], admit: Admit) -> SizeTree:
    """Splits from the root while both halves are admissible. The root is a legal group whatever the rule says."""
    number: dict[tuple[int, ...], int] = {}
    order: list[tuple[int, ...]] = []
    child: dict[int, tuple[int, int]] = {}

    def at(x: tuple[int, ...]) -> int:
        if x not in number:
            number[x] = len(order)
            order.append(x)
        return number[x]

    at(tuple(sizes))
    i = 0
    while i < len(order):
        x = order[i]
        l = tuple(a // 2 for a in x)
        r = tuple(a - b for a, b in zip(x, l, strict=True))
        if admit(l) and admit(r):
            child[i] = (at(l), at(r))
        i += 1
    left, right = np.full(len(order), -1), np.full(len(order), -1)
    leaves = np.ones(len(order), np.int64)
    for i, (l, r) in child.items():
        left[i], right[i] = l, r
    for i in sorted(child, key=lambda i: sum(order[i])):  # children are smaller than their parents
        leaves[i] = leaves[left[i]] + leaves[right[i]]
    return SizeTree(np.array(order, np.int64), left, right, leaves)
