"""Answers to COUNT queries from what was published: boxes, randomised rows, or separate tables."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainbound.operators import meet
from gainbound.operators.perturb import Randomiser, reconstruct

#: Combinations of a box and a sensitive range for each query, up to which all of them are multiplied out: that many are as quick as a query by itself.
DENSE = 16


def from_boxes(queries: DataFrame, published: DataFrame, axes: list[str]) -> DataFrame:
    """Rows of a group are taken to spread evenly over its box: each counts by the product of its overlaps.

    published: (ec, sa, n, x1_lo, x1_hi, ...). A group is one row with its counts, whose running sum gives the rows in any sensitive range."""
    sides = [f"{x}_{k}" for x in axes for k in ("lo", "hi")]
    # one entry for each value of the domain at most
    groups = published.groupBy("ec", *sides).agg(F.array_sort(F.collect_list(F.struct(F.col("sa").cast("long").alias("sa"), F.col("n").cast("double").alias("n")))).alias("counts"))
    return from_groups(queries, groups.select(*sides, F.col("counts.sa").alias("sas"), F.col("counts.n").alias("ns")), axes)


def from_groups(queries: DataFrame | meet.Asked, groups: DataFrame, axes: list[str], n_groups: int | None = None) -> DataFrame:
    """The same from groups with their counts as lists: (x1_lo, x1_hi, ..., sas, ns). n_groups: how many there are, if that is known."""

    def spread(share: np.ndarray, columns: list, q: meet.Asked, box: np.ndarray) -> np.ndarray:
        sas, ns = (c.flatten().to_numpy() for c in columns)
        values, code = np.unique(sas, return_inverse=True)
        group = np.repeat(np.arange(len(share)), np.diff(columns[0].offsets.to_numpy()))
        # counts up to each value of the block; queries of the same sensitive range take the same difference, those of the same box the same shares
        run = np.zeros((len(share), len(values) + 1))
        run[:, 1:] = np.cumsum(np.bincount(group * len(values) + code.reshape(-1), ns, len(share) * len(values)).reshape(len(share), -1), 1)
        ends = np.searchsorted(values, q.sa_high, "right") * (len(values) + 1) + np.searchsorted(values, q.sa_low, "left")
        pairs, which = np.unique(ends, return_inverse=True)
        high, low = np.divmod(pairs, len(values) + 1)
        if share.shape[1] * len(pairs) <= DENSE * len(q.qid):
            # few boxes and ranges: all of their combinations
            return (share.T @ np.where(high > low, run[:, high] - run[:, low], 0.0))[box, which.reshape(-1)]
        out = np.zeros(len(q.qid))
        order = np.argsort(ends, kind="stable")
        for some in np.split(order, np.flatnonzero(np.diff(ends[order])) + 1):
            high, low = divmod(int(ends[some[0]]), len(values) + 1)
            if high > low:
                ranged, own = run[:, high] - run[:, low], box[some]
                out[some] = ranged @ share[:, own] if len(own) < share.shape[1] else (ranged @ share)[own]
        return out

    found = meet.sums(groups, [(f"{x}_lo", f"{x}_hi") for x in axes], ["sas", "ns"], meet.asked(queries, axes), meet.overlap, spread, True, n_groups)
    return found.where("v > 0").withColumnRenamed("v", "est")


def observed(queries: DataFrame, cells: DataFrame, axes: list[str]) -> DataFrame:
    """qid, sa and e: randomised rows in the query's quasi-identifier ranges by published value."""
    spots = cells.groupBy("sa", *axes).agg(F.sum("n").alias("n"))
    q, out = meet.asked(queries, axes), None
    # one pass for each value of the domain: only the clipped answers need the values apart
    for r in cells.select("sa").distinct().collect():
        part = meet.sums(spots.where(F.col("sa") == F.lit(r[0])), [(x, x) for x in axes], ["n"], q, meet.inside, lambda met, columns, _: columns[0].to_numpy(zero_copy_only=False).astype(float) @ met)
        part = part.select("qid", F.lit(r[0]).alias("sa"), F.round("v").cast("long").alias("e"))
        out = part if out is None else out.union(part)
    return out


def from_randomised(queries: DataFrame, cells: DataFrame, axes: list[str], r: Randomiser, post: str = "raw") -> DataFrame:
    """Reconstructed counts summed over the sensitive range; post `clip` sets negative ones to 0.

    The reconstruction is linear, so a row of published value v adds 1 / alpha_v to the queries whose sensitive range holds v, and takes
    (1 / alpha_v - 1) times the range's share of all 1 / alpha from every query that holds the row: answers need no counts by value."""
    if post == "clip":
        estimated = reconstruct(observed(queries, cells, axes), r, ["qid"]).where("n_hat > 0")
        ranged = estimated.join(F.broadcast(queries.select("qid", "sa_lo", "sa_hi").limit(meet.MAX_QUERIES)), "qid").where(F.col("sa").between(F.col("sa_lo"), F.col("sa_hi")))
        return ranged.groupBy("qid").agg(F.sum("n_hat").alias("est"))
    values, inverse = np.array(r.values, np.int64), 1 / np.array(r.alpha)
    run = np.concatenate(([0.0], np.cumsum(inverse))) / inverse.sum()

    def parts(sa: np.ndarray, n: np.ndarray) -> list:
        weight = inverse[np.searchsorted(values, sa)]
        return [(n * weight, True), (n * (weight - 1), False)]

    def estimate(found: list[np.ndarray], q: meet.Asked) -> np.ndarray:
        share = run[np.searchsorted(values, q.sa_high, "right")] - run[np.searchsorted(values, q.sa_low, "left")]
        return found[0] - found[1] * share

    return meet.range_sums(cells, axes, meet.asked(queries, axes), parts, estimate).withColumnRenamed("v", "est")


def from_separate(queries: DataFrame, cells: DataFrame, axes: list[str], prior: DataFrame) -> DataFrame:
    """The baseline of two separate tables: rows in the ranges times the sensitive range's overall share."""
    p = sorted((int(x.sa), x.p) for x in prior.select("sa", "p").collect())  # one row for each value of the domain
    values, run = np.array([v for v, _ in p]), np.concatenate(([0.0], np.cumsum([x for _, x in p])))

    def estimate(found: list[np.ndarray], q: meet.Asked) -> np.ndarray:
        return found[0] * (run[np.searchsorted(values, q.sa_high, "right")] - run[np.searchsorted(values, q.sa_low, "left")])

    return meet.range_sums(cells, axes, meet.asked(queries, axes), lambda sa, n: [(n.astype(float), False)], estimate).withColumnRenamed("v", "est")
