"""Measures of groups from their counts by sensitive value and the bounds of their coordinates."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainbound.operators.deal import bucket_expr

#: Counts (groups x values) that are in memory at once.
BLOCK_COUNTS = 1 << 20


def pairs(rows: DataFrame, axes: list[str]) -> DataFrame:
    """ec, sa, n, x1_lo, x1_hi, ... from rows (axes, sa, ec, n); rows that have bounds already are returned as they are."""
    if f"{axes[0]}_lo" in rows.columns:
        return rows
    return rows.groupBy("ec", "sa").agg(F.sum("n").alias("n"), *[f(x).alias(f"{x}_{k}") for x in axes for f, k in ((F.min, "lo"), (F.max, "hi"))])


def judged(some: DataFrame, axes: list[str], counts: list[tuple]) -> DataFrame:
    """Per group: bounds, size, largest gain, largest frequency (top) and distance from the overall distribution by steps of the sensitive order (emd).

    some: as `pairs` gives them, a pair in one row or several; counts: the overall counts, whose order puts a null first, as windows do."""
    known = sorted(counts, key=lambda x: (x[0] is not None, x[0]))
    total, m = sum(n for _, n in known), len(known)
    p = np.array([n / total for _, n in known])
    bounds = [f"{x}_{k}" for x in axes for k in ("lo", "hi")]
    code = bucket_expr({v: i for i, (v, _) in enumerate(known)}, F.col("sa")).cast("int")
    # one entry for each value of the domain and task at most
    per = some.groupBy("ec").agg(F.collect_list(code).alias("codes"), F.collect_list(F.col("n").cast("long")).alias("ns"), *((F.min if c.endswith("_lo") else F.max)(c).cast("long").alias(c) for c in bounds)).drop("ec")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = max(1, BLOCK_COUNTS // m)
        for batch in batches:
            for at in range(0, len(batch), step):
                part = batch.slice(at, step)
                codes, ns = part.column(0), part.column(1)
                group = np.repeat(np.arange(len(part)), np.diff(codes.offsets.to_numpy()))
                n = np.bincount(group * m + codes.flatten().to_numpy(), ns.flatten().to_numpy(), len(part) * m).reshape(-1, m)
                size = n.sum(1)
                q = n / size[:, None]
                gain = np.where(n > 0, q / p - 1, -np.inf).max(1)
                emd = np.abs(np.cumsum(q - p, 1)).sum(1) / max(1, m - 1)
                yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(2, batch.num_columns)), pa.array(size.astype(np.int64)), *map(pa.array, (gain, q.max(1), emd))], names=[*bounds, "size", "gain", "top", "emd"])

    return per.mapInArrow(run, ", ".join(f"{c} long" for c in bounds) + ", size long, gain double, top double, emd double")
