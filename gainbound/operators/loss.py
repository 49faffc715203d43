"""Information loss of groups: numeric extent, width of the covering hierarchy node, weighted mean, table average."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gainbound.plans.spec import CATEGORICAL, ReleaseSpec


def axis_domains(encoded: DataFrame, spec: ReleaseSpec) -> list[tuple[int, int]]:
    """Least and greatest coordinate of each axis over the whole table; of a categorical one, its leaves."""
    got = encoded.agg(*(f(a).alias(f"{a}_{n}") for a in spec.axes for f, n in ((F.min, "lo"), (F.max, "hi")))).first()
    if got[0] is None:
        raise ValueError("the table is empty")
    out = []
    for i, a in enumerate(spec.qi):
        out.append((0, len(a.hierarchy.leaves) - 1) if a.kind == CATEGORICAL else (got[2 * i], got[2 * i + 1]))
    return out


def boxes(rows: DataFrame, spec: ReleaseSpec, ec: str = "ec") -> DataFrame:
    """ec, size, and each axis's interval (x1_lo, x1_hi, ...)."""
    return rows.groupBy(F.col(ec).alias("ec")).agg(F.count("*").alias("size"), *(f(a).alias(f"{a}_{n}") for a in spec.axes for f, n in ((F.min, "lo"), (F.max, "hi"))))


def axis_loss(spec: ReleaseSpec, domains: list[tuple[int, int]], i: int) -> Column:
    """Share of the axis's domain that the group's interval, or its covering node, takes; 0 for a single value."""
    a, name = spec.qi[i], spec.axes[i]
    lo, hi = F.col(f"{name}_lo"), F.col(f"{name}_hi")
    if a.kind == CATEGORICAL:
        width = a.hierarchy.width(lo, hi)
        return F.when(width == 1, 0.0).otherwise(width / F.lit(float(len(a.hierarchy.leaves))))
    low, high = domains[i]
    return (hi - lo) / F.lit(float(high - low)) if high > low else F.lit(0.0)


def group_loss(box: DataFrame, spec: ReleaseSpec, domains: list[tuple[int, int]]) -> DataFrame:
    """The boxes with the loss of each axis (loss1, ...) and their weighted sum (loss)."""
    out = box
    for i in range(len(spec.qi)):
        out = out.withColumn(f"loss{i + 1}", axis_loss(spec, domains, i))
    total = sum((F.col(f"loss{i + 1}") * F.lit(w) for i, w in enumerate(spec.weights)), F.lit(0.0))
    return out.withColumn("loss", total)


def losses(spec: ReleaseSpec, domains: list[tuple[int, int]]) -> Callable[[list[np.ndarray]], np.ndarray]:
    """The same weighted sum in numpy, from each axis's least and greatest coordinates (x1_lo, x1_hi, ...)."""
    tables = []
    for a in spec.qi:
        if a.kind == CATEGORICAL:
            # width of the covering node for each first and last leaf
            m = len(a.hierarchy.leaves)
            wide = np.array([[min((n.hi - n.lo + 1 for n in a.hierarchy.nodes if n.lo <= i and n.hi >= j), default=m) for j in range(m)] for i in range(m)])
            tables.append(np.where(wide == 1, 0.0, wide / m))
        else:
            tables.append(None)

    def lost(bounds: list[np.ndarray]) -> np.ndarray:
        total = np.zeros(len(bounds[0]))
        for i, (wide, (low, high), w) in enumerate(zip(tables, domains, spec.weights, strict=True)):
            lo, hi = bounds[2 * i], bounds[2 * i + 1]
            if wide is not None:
                total += wide[lo, hi] * w
            elif high > low:
                total += (hi - lo) / float(high - low) * w
        return total

    return lost


def average_loss(losses: DataFrame) -> DataFrame:
    return losses.agg((F.sum(F.col("size") * F.col("loss")) / F.sum("size")).alias("ail"), F.count("*").alias("groups"))


def discernibility(box: DataFrame) -> DataFrame:
    return box.agg(F.sum(F.col("size") * F.col("size")).alias("discernibility"), F.avg("size").alias("mean_size"), F.max("size").alias("max_size"))
