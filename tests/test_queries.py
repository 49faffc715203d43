"""Registered queries against their SQL on the smallest tables."""

import pytest

import __spark_entry__ as entries
from gainbound.queries.registry import ORACLE, QUERIES
from tests.oracle import check, connect

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    return connect(SF)


@pytest.mark.parametrize("name", sorted(ORACLE))
def test_query_matches_its_sql(spark, duck, name):
    check(spark, duck, SF, QUERIES[name], ORACLE[name])


def test_entry(spark):
    assert entries.entry(spark).count() > 0


def test_streams_and_batches_agree(spark):
    r = QUERIES["stream_randomise"](spark, SF).first()
    assert r.n == r.same > 0
    assert QUERIES["stream_late"](spark, SF).count() == 1000


def test_draws_fill_the_same_sizes(spark):
    rows = QUERIES["w_draws"](spark, SF).collect()
    for sa in ("price_class", "corr_class"):
        own = [r for r in rows if r.sa == sa]
        assert len({r.groups for r in own}) == 1 and all(r.achieved_beta <= 4.0 + 1e-6 for r in own)


def test_approximate_aggregates_run(spark):
    assert QUERIES["agg_approx"](spark, SF).count() > 0
