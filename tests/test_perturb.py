"""The randomiser: fixed cases, guarantees for arbitrary columns, reconstruction, determinism."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from gainbound.operators import perturb


def test_fixed_cases():
    raw = perturb.randomiser([(0, 9), (1, 1)], 4.0, "raw")
    assert [round(a, 4) for a in raw.alpha] == [0.9105, -0.6030]
    safe = perturb.randomiser([(0, 9), (1, 1)], 4.0)
    assert safe.cap_applied and min(safe.alpha) > 0
    plain = perturb.randomiser([(0, 5), (1, 3), (2, 2)], 2.0)
    assert not plain.cap_applied and [round(a, 4) for a in plain.alpha] == [0.6009, 0.4086, 0.3712]
    with pytest.raises(ValueError):
        perturb.randomiser([(0, 5)], 1.0)


@settings(max_examples=150, deadline=None)
@given(st.lists(st.integers(1, 1000), min_size=2, max_size=12), st.floats(0.3, 6))
def test_no_posterior_exceeds_its_bound(counts, beta):
    r = perturb.randomiser(list(enumerate(counts)), beta)
    m = r.matrix()
    assert np.allclose(m.sum(0), 1) and (m >= 0).all()
    assert (perturb.posterior(r) <= np.array(r.f)[None, :] + 1e-9).all()
    ratio = (m / m.min(1, keepdims=True)).max(0)
    assert (ratio <= np.array(r.gamma) + 1e-6).all()
    n = np.array(counts, float)
    back = perturb.reconstruct_dense(r, m @ n)
    assert np.allclose(back, n, rtol=1e-6, atol=1e-6 * n.sum())
    assert perturb.expectation_maximisation(r, m @ n, 20).min() >= 0


def test_closed_form_is_the_inverse(spark):
    r = perturb.randomiser([(0, 50), (1, 30), (2, 20)], 2.0)
    observed = np.array([45.0, 33.0, 22.0])
    df = spark.createDataFrame([(0, 45), (1, 33), (2, 22)], "sa int, e long")
    got = {x.sa: x.n_hat for x in perturb.reconstruct(df, r).collect()}
    assert np.allclose([got[i] for i in range(3)], perturb.reconstruct_dense(r, observed))
    assert sum(got.values()) == pytest.approx(100)


def test_rows_draw_the_same_whatever_the_partitioning(spark):
    r = perturb.randomiser([(i, 10 + i) for i in range(5)], 2.0)
    df = spark.range(2000).select(F.col("id").cast("string").alias("k"), (F.col("id") % 5).cast("int").alias("sa"))
    a = perturb.randomise(df.repartition(7), "sa", "k", r, "s").collect()
    b = perturb.randomise(df.coalesce(1), "sa", "k", r, "s").collect()
    c = perturb.randomise(df, "sa", "k", r, "other").collect()
    assert sorted(a) == sorted(b) != sorted(c)


def test_null_is_a_value(spark):
    r = perturb.randomiser([(None, 10), (1, 20), (2, 30)], 2.0)
    df = spark.createDataFrame([(str(i), None if i % 3 == 0 else i % 3) for i in range(300)], "k string, sa int")
    got = {x.sa for x in perturb.randomise(df, "sa", "k", r, "s").select("sa").distinct().collect()}
    assert got == {None, 1, 2}


def test_estimates_are_unbiased(spark):
    r = perturb.randomiser([(0, 600), (1, 300), (2, 100)], 3.0)
    df = spark.createDataFrame([(str(i), 0 if i < 600 else 1 if i < 900 else 2) for i in range(1000)], "k string, sa int").cache()
    sums = []
    for seed in range(12):
        e = perturb.randomise(df, "sa", "k", r, f"s{seed}").groupBy("sa").count().withColumnRenamed("count", "e")
        sums.append({x.sa: x.n_hat for x in perturb.reconstruct(e, r).collect()}[2])
    assert abs(np.mean(sums) - 100) < 3 * np.std(sums) / np.sqrt(len(sums)) + 10
