"""Queries that once made their data up: their results change with a given table."""

import shutil

import pytest
from pyspark.sql import functions as F

from gainbound.queries import experiments, operators, release  # noqa: F401
from gainbound.queries.registry import QUERIES

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def other(spark, tmp_path_factory):
    """The tables with the line items of status F and orders of a lower half only, and two nations fewer."""
    to = str(tmp_path_factory.mktemp("other"))
    for t in ("part",):
        shutil.copy(f"{SF}/{t}.parquet", f"{to}/{t}.parquet")
    spark.read.parquet(f"{SF}/nation.parquet").where("n_nationkey > 1").write.parquet(f"{to}/nation.parquet")
    spark.read.parquet(f"{SF}/lineitem.parquet").where((F.col("l_orderkey") % 19 < 11) & (F.col("l_linenumber") < 5) & (F.col("l_quantity") < 20)).write.parquet(f"{to}/lineitem.parquet")
    return to


@pytest.mark.parametrize("name", ["cte_size_tree", "ex_nineteen", "ex_six", "leaf_positions", "math_caps"])
def test_results_come_from_the_tables(spark, other, name):
    own, changed = (sorted(map(tuple, QUERIES[name](spark, d).collect())) for d in (SF, other))
    assert own != changed
