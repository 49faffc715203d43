"""Gradient-boosted trees for a binary label: histogram splits, monotone constraints, flat node arrays.

Trees are grown level by level on binned features. A constrained feature may only be split
so that the child values rise (or fall) with it, and the children inherit bounds on their
values, so the whole ensemble is monotone in it. A trained ensemble is five arrays over all nodes of
all trees, and scoring walks them for all rows at once.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class Ensemble:
    """Nodes of all trees. A leaf points to itself, so that every row takes depth steps."""

    root: np.ndarray
    feature: np.ndarray
    threshold: np.ndarray
    left: np.ndarray
    right: np.ndarray
    value: np.ndarray
    base: float
    depth: int

    def raw(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.base)
        rows = np.arange(len(x))
        for root in self.root:
            node = np.full(len(x), root)
            for _ in range(self.depth):
                node = np.where(x[rows, self.feature[node]] <= self.threshold[node], self.left[node], self.right[node])
            out += self.value[node]
        return out

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-self.raw(x)))


def fit(x: np.ndarray, y: np.ndarray, monotone: dict[int, int] | None = None, trees: int = 60, depth: int = 4, rate: float = 0.15, bins: int = 64, l2: float = 1.0, least: float = 5.0) -> Ensemble:
    """Logistic boosting. monotone: +1 or -1 for a feature whose rise may only raise or lower the score."""
    monotone = monotone or {}
    n, m = x.shape
    nodes: dict[str, list] = {k: [] for k in ("feature", "threshold", "left", "right", "value")}
    roots: list[int] = []
    p = float(np.clip(y.mean() if n else 0.5, 1e-3, 1 - 1e-3))
    base = float(np.log(p / (1 - p)))

    def node(value: float) -> int:
        i = len(nodes["value"])
        for k, v in (("feature", 0), ("threshold", np.inf), ("left", i), ("right", i), ("value", value)):
            nodes[k].append(v)
        return i

    if n and 0 < y.sum() < n:
        edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) for j in range(m)]
        code = np.stack([np.searchsorted(edges[j], x[:, j], "left") for j in range(m)], 1)
        score = np.full(n, base)
        for _ in range(trees):
            q = 1 / (1 + np.exp(-score))
            g, h = y - q, q * (1 - q)
            roots.append(node(0.0))
            at = np.full(n, roots[-1])
            bound = {roots[-1]: (-np.inf, np.inf)}
            open_nodes = [roots[-1]]
            for _level in range(depth):
                nxt = []
                for i in open_nodes:
                    rows = np.flatnonzero(at == i)
                    G, H = g[rows].sum(), h[rows].sum()
                    best = (1e-6, None)
                    for j in range(m):
                        k = len(edges[j]) + 1
                        if k < 2:
                            continue
                        gs = np.cumsum(np.bincount(code[rows, j], g[rows], k))[:-1]
                        hs = np.cumsum(np.bincount(code[rows, j], h[rows], k))[:-1]
                        vl, vr = gs / (hs + l2), (G - gs) / (H - hs + l2)
                        gain = gs * vl + (G - gs) * vr - G * G / (H + l2)
                        ok = (hs >= least / 4) & (H - hs >= least / 4)
                        if j in monotone:
                            ok &= (vr - vl) * monotone[j] >= 0
                        gain = np.where(ok, gain, -1)
                        b = int(np.argmax(gain))
                        if gain[b] > best[0]:
                            best = (gain[b], (j, b, vl[b], vr[b]))
                    if best[1] is None:
                        continue
                    j, b, vl, vr = best[1]
                    low, high = bound[i]
                    vl, vr = float(np.clip(vl, low, high)), float(np.clip(vr, low, high))
                    a, c = node(vl * rate), node(vr * rate)
                    nodes["feature"][i], nodes["threshold"][i], nodes["left"][i], nodes["right"][i] = j, float(edges[j][b]), a, c
                    bound[a] = bound[c] = (low, high)
                    if monotone.get(j):
                        mid = (vl + vr) / 2
                        bound[a], bound[c] = ((low, mid), (mid, high)) if monotone[j] > 0 else ((mid, high), (low, mid))
                    side = code[rows, j] <= b
                    at[rows[side]], at[rows[~side]] = a, c
                    nxt += [a, c]
                open_nodes = nxt
            score += np.array(nodes["value"])[at]
    arrays = {k: np.array(v, np.float64 if k in ("threshold", "value") else np.int64) for k, v in nodes.items()}
    return Ensemble(np.array(roots, np.int64), base=base, depth=depth, **arrays)
