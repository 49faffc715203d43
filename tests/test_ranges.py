"""Sums over ranges from slabs: the same as by comparing each cell with each query."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from gainbound.operators import estimate, meet, perturb, workload


def _values(df, c):
    return {r["qid"]: r[c] for r in df.collect() if r[c]}


@pytest.mark.parametrize(("lengths", "slab_cells"), [((40,), 1 << 22), ((9, 30), 1 << 22), ((9, 30, 4), 1 << 22), ((9, 30, 4, 5), 200)])
def test_slabs_are_the_blocks(spark, lengths, slab_cells, monkeypatch):
    monkeypatch.setattr(meet, "SLAB_CELLS", slab_cells)
    axes, random = [f"x{i + 1}" for i in range(len(lengths))], np.random.default_rng(5)
    rows = [(*(int(random.integers(3, 3 + k)) for k in lengths), int(random.integers(-2, 6))) for _ in range(4000)]
    cells = workload.cube(spark.createDataFrame(rows, ", ".join(f"{x} int" for x in axes) + ", sa int"), axes).cache()
    domains = [(3, 2 + k) for k in lengths]
    queries = workload.wide(workload.workload(spark, domains, (-2, 5), len(axes), 0.2, 300), axes, domains).cache()
    counts = [(r.sa, r.n) for r in cells.groupBy("sa").agg(F.sum("n").alias("n")).collect()]
    r = perturb.randomiser(counts, 3.0)
    prior = spark.createDataFrame([(v, n / 4000) for v, n in counts], "sa int, p double")
    runs = (lambda: (workload.exact(queries, cells, axes), "prec"), lambda: (estimate.from_randomised(queries, cells, axes, r), "est"), lambda: (estimate.from_separate(queries, cells, axes, prior), "est"))
    blocks = [_values(*run()) for run in runs]
    monkeypatch.setattr(meet, "FEW_PAIRS", 0)
    # no cell is compared with any query from here on
    monkeypatch.setattr(meet, "sums", lambda *a: pytest.fail("blocks"))
    slabs = [_values(*run()) for run in runs]
    assert blocks[0] == slabs[0] and len(slabs[0]) > 200
    for a, b in zip(blocks[1:], slabs[1:], strict=True):
        assert all(a.get(k, 0.0) == pytest.approx(b.get(k, 0.0), abs=1e-7) for k in a.keys() | b.keys())
