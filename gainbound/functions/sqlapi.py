"""Functions and tables for SQL users: gain_cap, gain_of, EMD as an aggregate, and leaves of a size tree as a table function."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gainbound.functions.bounds import cap
from gainbound.plans import sizetree


@F.pandas_udf(T.DoubleType())
def gain_cap(p: pd.Series, beta: pd.Series) -> pd.Series:
    """Largest frequency allowed to a value of frequency p."""
    return p * (1 + np.minimum(beta, -np.log(p)))


@F.pandas_udf(T.DoubleType())
def emd_ordered(rank: pd.Series, d: pd.Series) -> float:
    """Ordered earth mover's distance of a group: rank of each value, and its q - p. A group has one row for each value."""
    run = d.to_numpy()[np.argsort(rank.to_numpy(), kind="stable")].cumsum()
    return float(np.abs(run).sum() / max(1, len(run) - 1))


@F.udtf(returnType=T.StructType([T.StructField("ec", T.LongType()), T.StructField("bucket", T.IntegerType()), T.StructField("cnt", T.LongType())]))
class SizeLeaves:
    """Rows to draw from each bucket for each group, from bucket sizes and caps."""

    def eval(self, sizes: list, caps: list):
        tree = sizetree.grow(tuple(sizes), sizetree.gain_rule(tuple(caps)))
        for i, v in enumerate(tree.leaf_vectors()):
            for j, x in enumerate(v):
                yield i, j, int(x)


def register(spark: SparkSession) -> None:
    spark.udf.register("gain_cap", gain_cap)
    spark.udf.register("emd_ordered", emd_ordered)
    spark.udtf.register("size_leaves", SizeLeaves)
    spark.udf.register("gain_cap_scalar", lambda p, beta: cap(p, beta), T.DoubleType())


__all__ = ["SizeLeaves", "emd_ordered", "gain_cap", "register"]
