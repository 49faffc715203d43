"""kd-cut: median partitioning from the k-anonymity literature, with a pluggable rule on both sides of a cut.

A node's attributes are tried in order of their normalised extent; each is cut at its weighted median, and the
first cut whose two sides both keep the rule is made. It runs on cells (equal rows counted once).
While nodes have more cells than fit a task, all of them progress together, level by level: histograms, medians and both sides'
counts are aggregations, a task judges a node's cuts, and the driver learns only how many nodes are large. Once a node fits, one
task finishes it. Both ways make the same cuts.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gainbound.functions.bounds import EPS, cap
from gainbound.operators.deal import bucket_expr
from gainbound.operators.loss import losses
from gainbound.operators.packed import TOTALS, measures_of, order_of, prior_of, totals
from gainbound.operators.settle import settle
from gainbound.plans.spec import CATEGORICAL, ReleaseSpec

LIMIT_CELLS = 1_000_000
#: Rows about large nodes (one for each axis) that are sent to all tasks; more are joined by a shuffle.
SENT_ROWS = 200_000
#: A rule takes counts by sensitive value (values x sides) and says which sides keep it.
Rule = Callable[[np.ndarray], np.ndarray]
#: Sends rows about nodes to all tasks if they are few.
Beside = Callable[[DataFrame], DataFrame]


def rule_k(k: int) -> Rule:
    return lambda c: c.sum(0) >= k


def rule_gain(p: np.ndarray, beta: float) -> Rule:
    caps = np.array([cap(x, beta) for x in p])[:, None]
    return lambda c: (c <= caps * c.sum(0) + EPS * c.sum(0)).all(0) & (c.sum(0) > 0)


def delta_for(p: np.ndarray, beta: float) -> float:
    """The two-sided bound on |ln(q / p)| that implies the capped bound for beta."""
    return float(np.log(1 + min(beta, -np.log(p.max()))))


def rule_logratio(p: np.ndarray, delta: float) -> Rule:
    low, high = (p * np.exp(-delta))[:, None], (p * np.exp(delta))[:, None]
    return lambda c: ((c > low * c.sum(0)) & (c < high * c.sum(0))).all(0)


def rule_emd(p: np.ndarray, t: float, ground: str = "ordered") -> Rule:
    def rule(c: np.ndarray) -> np.ndarray:
        d = c / np.maximum(c.sum(0), 1) - p[:, None]
        emd = np.abs(np.cumsum(d, 0)).sum(0) / max(1, len(p) - 1) if ground == "ordered" else np.abs(d).sum(0) / 2
        return (emd <= t + EPS) & (c.sum(0) > 0)

    return rule


def rule_ldiv(level: float) -> Rule:
    return lambda c: (c.max(0) * level <= c.sum(0) + EPS) & (c.sum(0) > 0)


class Cutter:
    """Extents, medians and verdicts; the part that both ways share."""

    def __init__(self, spec: ReleaseSpec, domains: list[tuple[int, int]], rule: Rule, m: int, choice: str = "any"):
        self.rule, self.m, self.choice = rule, m, choice
        self.span = [hi - lo for lo, hi in domains]
        self.nodes = [[(n.lo, n.hi) for n in a.hierarchy.nodes] if a.kind == CATEGORICAL else None for a in spec.qi]
        self.leaves = [len(a.hierarchy.leaves) if a.kind == CATEGORICAL else 0 for a in spec.qi]

    def extent(self, axis: int, lo: int, hi: int) -> float:
        if lo == hi:
            return 0.0
        if self.nodes[axis]:
            return min(b - a + 1 for a, b in self.nodes[axis] if a <= lo and b >= hi) / self.leaves[axis]
        return (hi - lo) / max(1, self.span[axis])

    def order(self, bounds: list[tuple[int, int]]) -> list[int]:
        """Axes that can be cut, widest first."""
        wide = sorted((-self.extent(i, lo, hi), i) for i, (lo, hi) in enumerate(bounds) if lo < hi)
        return [i for _, i in wide][: 1 if self.choice == "widest" else None]

    @staticmethod
    def cut_at(values: np.ndarray, weights: np.ndarray) -> int:
        """Weighted median of distinct ascending values, or the value before it if nothing is above it."""
        at = int(np.searchsorted(np.cumsum(weights) * 2, weights.sum(), "left"))
        return int(values[min(at, len(values) - 2)])

    @staticmethod
    def spread(x: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Distinct values in ascending order and their weights."""
        low, span = int(x.min()), int(x.max()) - int(x.min())
        if span > 4 * len(x):
            values, which = np.unique(x, return_inverse=True)
            return values, np.bincount(which.reshape(-1), w)
        weights = np.bincount(x - low, w)
        at = np.flatnonzero(weights)
        return at + low, weights[at]

    def finish(self, points: np.ndarray, sa: np.ndarray, n: np.ndarray) -> np.ndarray:
        """Group number of each cell, for a node that fits in memory."""
        out, stack, groups = np.empty(len(n), np.int64), [np.arange(len(n))], 0
        columns = [np.ascontiguousarray(x) for x in points.T]
        while stack:
            rows = stack.pop()
            p, w, code = [x[rows] for x in columns], n[rows], 2 * sa[rows]
            for axis in self.order([(int(x.min()), int(x.max())) for x in p]):
                left = p[axis] <= self.cut_at(*self.spread(p[axis], w))
                if self.rule(np.bincount(code + ~left, w, 2 * self.m).reshape(self.m, 2)).all():
                    stack += [rows[~left], rows[left]]
                    break
            else:
                out[rows] = groups
                groups += 1
        return out


def _medians(long: DataFrame, beside: Beside) -> DataFrame:
    """_node, axis, lo, hi, cut of every axis of a node that has two values or more.

    Two passes, by the upper and the lower half of a value's bits, so that neither orders more than the root of an axis's
    domain; both are aggregations, and only the rows of the upper half's median are told apart in the second."""
    w = Window.partitionBy("_node", "axis")
    coarse = long.groupBy("_node", "axis", "part").agg(F.sum("n").alias("n"), F.min("value").alias("lo"), F.max("value").alias("hi"))
    run = coarse.select("_node", "axis", "part", "n", F.sum("n").over(w.orderBy("part")).alias("run"), F.sum("n").over(w).alias("total"), F.min("lo").over(w).alias("lo"), F.max("hi").over(w).alias("hi"))
    at = run.where("lo < hi and 2 * run >= total and 2 * (run - n) < total").select("_node", "axis", F.col("part").alias("at"), (F.col("run") - F.col("n")).alias("before"), "total", "lo", "hi")
    told = F.when(F.col("part") == F.col("at"), F.col("value")).alias("told")
    fine = long.join(beside(at), ["_node", "axis"]).groupBy("_node", "axis", "before", "total", "lo", "hi", told).agg(F.sum("n").alias("n"), F.max(F.when(F.col("value") < F.col("hi"), F.col("value"))).alias("under"))
    here = F.col("before") + F.sum(F.when(F.col("told").isNotNull(), F.col("n")).otherwise(0)).over(w.orderBy("told"))
    median = F.min(F.when(F.col("told").isNotNull() & (2 * F.col("run") >= F.col("total")), F.col("told")))
    return fine.withColumn("run", here).groupBy("_node", "axis", "lo", "hi").agg(F.least(median, F.max("under")).alias("cut"))


def kd_cut(cells: DataFrame, spec: ReleaseSpec, domains: list[tuple[int, int]], values: list, rule: Rule, choice: str = "any", limit: int = LIMIT_CELLS) -> DataFrame:
    """cells (axes, sa, n) with `ec`, a text that names the cuts. values: the sensitive domain in order, a null in it too; rules see counts in that order."""
    axes, cutter = spec.axes, Cutter(spec, domains, rule, len(values), choice)
    state = cells.withColumn("_value", bucket_expr({v: i for i, v in enumerate(values)}, F.col("sa"))).withColumn("_node", F.lit("")).withColumn("_open", F.lit(True))
    place = [F.col(x).cast("long") for x in axes]
    halves = [(int(lo), (int(hi) - int(lo)).bit_length() // 2) for lo, hi in domains]
    along = F.array(*[F.struct(F.lit(i).alias("axis"), x.alias("value"), F.shiftright(x - lo, half).alias("part")) for i, (x, (lo, half)) in enumerate(zip(place, halves, strict=True))])

    def choose(pdf: pd.DataFrame) -> pd.DataFrame:
        """The cut of one node: axes x values rows."""
        bounds, tally, cuts = [(0, 0)] * len(axes), {}, {}
        for axis, rows in pdf.groupby("axis"):
            bounds[axis], cuts[axis] = (int(rows["lo"].iloc[0]), int(rows["hi"].iloc[0])), int(rows["cut"].iloc[0])
            tally[axis] = np.zeros((cutter.m, 2))
            tally[axis][rows["_value"].to_numpy()] = rows[["left", "right"]].to_numpy(float)
        axis = next((i for i in cutter.order(bounds) if cutter.rule(tally[i]).all()), -1)
        return pd.DataFrame({"_node": pdf["_node"].iloc[:1], "axis": [axis], "cut": [cuts.get(axis, 0)]})

    while True:
        big = state.where("_open").groupBy("_node").count().where(F.col("count") > limit).select("_node")
        n_big = big.count()
        if not n_big:
            break

        def beside(few: DataFrame, n: int = n_big * len(axes)) -> DataFrame:
            # beyond that many nodes, none has so large a share of the rows that a shuffle by node is skewed
            return F.broadcast(few) if n <= SENT_ROWS else few

        long = state.join(beside(big), "_node").select("_node", "_value", "n", F.inline(along))
        right = F.when(F.col("value") > F.col("cut"), F.col("n")).otherwise(0)
        sides = long.join(beside(_medians(long, beside)), ["_node", "axis"]).groupBy("_node", "axis", "lo", "hi", "cut", "_value").agg(F.sum(F.col("n") - right).alias("left"), F.sum(right).alias("right"))
        chosen = sides.groupBy("_node").applyInPandas(choose, "_node string, axis int, cut long")
        made = big.join(chosen, "_node", "left").select("_node", F.coalesce("axis", F.lit(-1)).alias("axis"), "cut")
        side = F.when(F.element_at(F.array(*place), F.col("axis") + 1) <= F.col("cut"), "0").otherwise("1")
        # a node that wasn't large has no row in made and stays as it is
        state = settle(state.join(beside(made), "_node", "left").withColumn("_open", F.col("_open") & F.coalesce(F.col("axis") >= 0, F.lit(True)))
                       .withColumn("_node", F.when(F.col("axis") >= 0, F.concat("_node", side)).otherwise(F.col("_node"))).drop("axis", "cut"))

    kinds = T.StructType([*cells.schema.fields, T.StructField("ec", T.StringType())])
    names = [f.name for f in kinds.fields]

    def finish(pdf: pd.DataFrame) -> pd.DataFrame:
        group = cutter.finish(pdf[axes].to_numpy(np.int64), pdf["_value"].to_numpy(np.int64), pdf["n"].to_numpy(float))
        return pdf.assign(ec=[f"{k}.{g}" for k, g in zip(pdf["_node"], group, strict=True)])[names]

    done = state.where("_open").groupBy("_node").applyInPandas(finish, kinds)
    return done.union(state.where("not _open").withColumn("ec", F.col("_node")).select(*names))


@dataclass
class Held:
    """All cells of a table on the driver, in every task of a job that asks for them: as many as one task finishes, at most."""

    points: list[np.ndarray]
    code: np.ndarray
    n: np.ndarray


def hold(cells: DataFrame, axes: list[str], values: list, limit: int = LIMIT_CELLS):
    """A broadcast of the cells (code: place among values), or None if they are more than limit."""
    rows = cells.select(*(F.col(x).cast("long") for x in axes), bucket_expr({v: i for i, v in enumerate(values)}, F.col("sa")).cast("int"), "n").limit(limit + 1).toArrow()
    if len(rows) > limit:
        return None
    *points, code, n = (c.to_numpy() for c in rows.columns)
    small = [x.astype(np.int32) if len(x) and -(1 << 31) <= x.min() and x.max() < 1 << 31 else x for x in (*points, n)]
    return cells.sparkSession.sparkContext.broadcast(Held(small[:-1], code, small[-1]))


def emd_totals(held: Held, cutter: Cutter, p: np.ndarray, ts: np.ndarray, place: np.ndarray, prior: np.ndarray, lost: Callable) -> list[tuple]:
    """Totals (`packed.TOTALS`) of the cuts at each closeness. A cut's worse side is the same at any closeness, so nodes that several
    reach are cut once: each goes on with those whose closeness lets its first good cut be made, and is a group for the others."""
    points, n, m = np.stack(held.points, 1).astype(np.int64), held.n.astype(float), cutter.m
    leaves, stack = [], [(np.arange(len(n)), np.arange(len(ts)))]
    while stack:
        rows, some = stack.pop()
        at, w, code = points[rows], n[rows], held.code[rows].astype(np.int64)
        low, high = at.min(0), at.max(0)
        for axis in cutter.order(list(zip(low.tolist(), high.tolist(), strict=True))):
            left = at[:, axis] <= cutter.cut_at(*cutter.spread(at[:, axis], w))
            c = np.bincount(2 * code + ~left, w, 2 * m).reshape(m, 2)
            worse = (np.abs(np.cumsum(c / np.maximum(c.sum(0), 1) - p[:, None], 0)).sum(0) / max(1, m - 1)).max()
            made = worse <= ts[some] + EPS
            if made.any():
                stack += [(rows[~left], some[made]), (rows[left], some[made])]
                some = some[~made]
            if not len(some):
                break
        else:
            c = np.bincount(place[code], w, m)
            leaves.append((some, c, low, high))
    size = np.array([c.sum() for _, c, _, _ in leaves])
    q = np.array([c for _, c, _, _ in leaves]) / size[:, None]
    gain, top, emd = np.where(q > 0, q / prior - 1, -np.inf).max(1), q.max(1), np.abs(np.cumsum(q - prior, 1)).sum(1) / max(1, m - 1)
    loss = lost([np.array([x[2 + k][i] for x in leaves]) for i in range(points.shape[1]) for k in (0, 1)])
    holds = [np.array([i for i, x in enumerate(leaves) if t in x[0]]) for t in range(len(ts))]
    return [totals(t, *(x[of] for x in (size, gain, top, emd, loss))) for t, of in enumerate(holds)]


def measure_emd(spark: SparkSession, held, spec: ReleaseSpec, domains: list[tuple[int, int]], values: list, counts: list[tuple], p: np.ndarray, ts: list[float], each: int = 4) -> list[dict]:
    """Measures of the cuts at each closeness of ts, in one job. held: of `hold`; each: how many neighbours share a task and the nodes that they have in common."""
    cutter = Cutter(spec, domains, lambda c: c, len(values))
    place, prior, lost = order_of(values), prior_of(values, counts), losses(spec, domains)
    order = np.argsort(ts, kind="stable")
    parts = [order[i : i + each] for i in range(0, len(order), each)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in batch.column(0).to_pylist():
                rows = emd_totals(held.value, cutter, p, np.array(ts)[parts[i]], place, prior, lost)
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*((int(parts[i][r[0]]), *r[1:]) for r in rows), strict=True)], names=[c.split()[0] for c in TOTALS.split(", ")])

    found = {r["plan"]: measures_of(r) for r in spark.range(0, len(parts), 1, len(parts)).mapInArrow(run, TOTALS).collect()}
    return [found[i] for i in range(len(ts))]
