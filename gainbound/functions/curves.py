"""Space-filling keys of integer points: z-order and lexicographic as column expressions, Hilbert in numpy."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def bits_for(cardinalities: list[int]) -> int:
    """Bits of each axis: enough for the widest one, 62 in all at most."""
    need = max(1, math.ceil(math.log2(max(2, *cardinalities))))
    return max(1, min(need, 62 // len(cardinalities)))


def grid_expr(x: Column, low: int, high: int, bits: int) -> Column:
    """x of [low, high] on the full grid of an axis."""
    if high == low:
        return F.lit(0).cast("long")
    return F.floor((x.cast("long") - low) * ((1 << bits) - 1) / F.lit(high - low)).cast("long")


def zorder_expr(axes: list[Column], bits: int) -> Column:
    """Bits are joined by OR, as sums of longs are checked for overflow one by one. axes are used once a bit: columns, not expressions."""
    d, key = len(axes), F.lit(0).cast("long")
    for b in range(bits):
        for i, x in enumerate(axes):
            key = key.bitwiseOR(F.shiftleft(F.shiftright(x, b).bitwiseAND(F.lit(1).cast("long")), b * d + d - 1 - i))
    return key


def lex_expr(axes: list[Column], bits: int) -> Column:
    key = F.lit(0).cast("long")
    for x in axes:
        key = F.shiftleft(key, bits) + x
    return key


def hilbert_keys(points: np.ndarray, bits: int) -> np.ndarray:
    """Hilbert index of each row of points (n x d, below 2**bits), by the published transposition of axes."""
    x = points.astype(np.int64).T.copy()
    d = len(x)
    m = 1 << (bits - 1)
    q = m
    while q > 1:  # undo the excess rotations, from the highest bit down
        p = q - 1
        for i in range(d):
            high = (x[i] & q) > 0
            swap = np.where(high, 0, (x[0] ^ x[i]) & p)
            x[0] = np.where(high, x[0] ^ p, x[0] ^ swap)
            if i:
                x[i] ^= swap
        q >>= 1
    for i in range(1, d):  # Gray code
        x[i] ^= x[i - 1]
    t = np.zeros_like(x[0])
    q = m
    while q > 1:
        t = np.where(x[d - 1] & q, t ^ (q - 1), t)
        q >>= 1
    x ^= t
    key = np.zeros(len(points), np.int64)
    for b in range(bits - 1, -1, -1):
        for i in range(d):
            key = (key << 1) | (x[i] >> b & 1)
    return key


#: Points of a grid whose keys the driver makes: for few, a job in Python workers takes longer to start.
FEW_POINTS = 1 << 14


def points_of_grid(domains: list[tuple[int, int]], bits: int) -> tuple[list[np.ndarray], np.ndarray]:
    """The coordinates of every point of small domains, axis by axis, and its Hilbert key."""
    points = [x.reshape(-1) for x in np.meshgrid(*(np.arange(lo, hi + 1) for lo, hi in domains), indexing="ij")]
    spread = [np.floor((x - lo) * ((1 << bits) - 1) / max(1, hi - lo)).astype(np.int64) for x, (lo, hi) in zip(points, domains, strict=True)]
    return points, hilbert_keys(np.stack(spread, 1), bits)


def keys_of_grid(spark: SparkSession, axes: list[str], domains: list[tuple[int, int]], bits: int, name: str) -> DataFrame:
    """Every point of small domains with its Hilbert key `name`."""
    points, rest = [], F.col("id")
    for x, (lo, hi) in reversed(list(zip(axes, domains, strict=True))):
        width = hi - lo + 1
        points.append((F.pmod(rest, F.lit(width)) + lo).cast("int").alias(x))
        rest = F.floor(rest / width)
    n = 1
    for lo, hi in domains:
        n *= hi - lo + 1
    if n <= FEW_POINTS:
        points, keys = points_of_grid(domains, bits)
        return spark.createDataFrame(pa.table([*(x.astype(np.int32) for x in points), keys], [*axes, name]))
    grid = spark.range(n).select(*reversed(points))
    return grid.withColumn(name, hilbert_expr([grid_expr(F.col(x), lo, hi, bits) for x, (lo, hi) in zip(axes, domains, strict=True)], bits))


def hilbert_expr(axes: list[Column], bits: int) -> Column:
    """Hilbert key as an Arrow-batched function of the axes."""

    @F.pandas_udf("long")
    def key(*columns: pd.Series) -> pd.Series:
        return pd.Series(hilbert_keys(np.stack([c.to_numpy() for c in columns], 1), bits))

    return key(*axes)


def curve_expr(kind: str, axes: list[Column], bits: int) -> Column:
    return {"zorder": zorder_expr, "lex": lex_expr, "hilbert": hilbert_expr}[kind](axes, bits)
