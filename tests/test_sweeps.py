"""What the settings of a sweep share: draws of queries, counts by cell and key, and shares of boxes."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from gainbound.functions import curves
from gainbound.operators import deal, estimate, meet, packed, workload
from gainbound.queries import experiments
from gainbound.queries.registry import QUERIES

SF = "/root/testdata/sf0.001"


def test_draws_make_the_stated_workloads(spark):
    """One job's draws, over more axes than asked for, give the queries of each setting."""
    domains = [(0, 82), (-3, -2), (5, 15), (7, 7)]
    drawn = workload.draws(spark, 4, 500, 7)
    for n, width, theta in ((4, 1, 0.1), (4, 3, 0.25), (3, 3, 0.05), (2, 1, 0.9), (1, 1, 0.3)):
        axes = [f"x{i + 1}" for i in range(n)]
        plain = meet.together([meet.asked(workload.wide(workload.workload(spark, domains[:n], (0, 49), width, theta, 500, 7), axes, domains[:n]), axes)])
        got = meet.together([workload.asked(drawn, domains[:n], (0, 49), width, theta)])
        for k in ("qid", "low", "high", "sa_low", "sa_high"):
            assert (getattr(got, k) == getattr(plain, k)).all()
    with pytest.raises(ValueError):
        workload.asked(drawn, domains, (0, 49), 5, 0.1)
    with pytest.raises(ValueError):
        workload.draws(spark, 1, meet.MAX_QUERIES + 1)


def _groups(spark, n: int):
    random = np.random.default_rng(3)
    rows = []
    for _ in range(n):
        low = [int(random.integers(0, k)) for k in (20, 4)]
        high = [int(random.integers(a, k)) for a, k in zip(low, (20, 4), strict=True)]
        sas = sorted(random.choice(8, int(random.integers(1, 9)), replace=False).tolist())
        rows.append((low[0], high[0], low[1], high[1], sas, [float(random.integers(1, 9)) for _ in sas]))
    return rows, spark.createDataFrame(rows, "x1_lo long, x1_hi long, x2_lo long, x2_hi long, sas array<long>, ns array<double>")


@pytest.mark.parametrize(("dense", "pairs"), [(1 << 20, 1 << 20), (0, 1 << 20), (1 << 20, 1), (0, 1)])
def test_queries_of_the_same_box_share_its_work(spark, monkeypatch, dense, pairs):
    monkeypatch.setattr(estimate, "DENSE", dense)
    monkeypatch.setattr(meet, "BLOCK_PAIRS", pairs)
    random = np.random.default_rng(4)
    rows, groups = _groups(spark, 60)
    low = np.array([random.integers(0, k, 300) for k in (20, 2)])
    high = low + np.array([random.integers(0, k, 300) for k in (3, 2)])
    sa_low = random.integers(0, 10, 300)
    q = meet.Asked(np.arange(300), low, high, sa_low, sa_low + random.integers(0, 3, 300))
    own, box = meet.boxes_of(q)
    assert len(own.qid) == len(set(map(tuple, np.concatenate([low, high]).T.tolist()))) < 300 and (own.low[:, box] == low).all() and (own.high[:, box] == high).all()
    plain = np.zeros(300)
    for a, b, c, d, sas, ns in rows:
        for i in range(300):
            share = 1.0
            for x, y, lo, hi in zip((a, c), (b, d), low[:, i], high[:, i], strict=True):
                share *= max(0, min(y, hi) - max(x, lo) + 1) / (y - x + 1)
            plain[i] += share * sum(n for s, n in zip(sas, ns, strict=True) if q.sa_low[i] <= s <= q.sa_high[i])
    few = estimate.from_groups(q, groups, ["x1", "x2"], 60)
    got = {r.qid: r.est for r in few.collect()}
    assert sorted(got) == sorted(r.qid for r in estimate.from_groups(q, groups, ["x1", "x2"]).collect())
    assert set(got) == set(np.flatnonzero(plain)) and all(got[i] == pytest.approx(plain[i], rel=1e-12) for i in got)


def test_few_points_get_the_keys_of_many(spark, monkeypatch):
    domains = [(2, 9), (0, 0), (-4, 6)]
    few = curves.keys_of_grid(spark, ["a", "b", "c"], domains, 4, "key")
    monkeypatch.setattr(curves, "FEW_POINTS", 0)
    many = curves.keys_of_grid(spark, ["a", "b", "c"], domains, 4, "key")
    assert few.schema.simpleString() == many.schema.simpleString() and sorted(map(tuple, few.collect())) == sorted(map(tuple, many.collect()))


def _rows_in_order(p) -> list:
    out = []
    for r in sorted(p.table.collect()):
        codes, key, n = (np.frombuffer(r[x], t) for x, t in (("sa", np.uint8), ("key", np.int64), ("n", np.int64)))
        out += zip(codes.tolist(), np.repeat(key, n).tolist(), strict=True)
    return out


def test_known_counts_by_key_replace_the_sample(spark, monkeypatch):
    """The same rows in the same order, in about even parts; a key with more than a part's rows is split as before; wrong counts are refused."""
    monkeypatch.setattr(packed, "CHUNK_ROWS", 100)
    rows = spark.range(4000).select(F.md5(F.col("id").cast("string")).alias("row_key"), (F.col("id") % 37 * 3).alias("key"), (F.col("id") % 37).alias("x1"), (F.col("id") % 11).alias("sa"))
    by_key = tuple(np.unique([i % 37 * 3 for i in range(4000)], return_counts=True))
    parts = packed.parts_of(by_key, 8)
    assert (np.diff(parts) >= 0).all() and set(parts) == set(range(8)) and np.bincount(parts, by_key[1]).max() <= 4000 / 8 + by_key[1].max()
    assert packed.parts_of((np.array([1, 5]), np.array([10, 90])), 8) is None
    monkeypatch.setattr(packed, "PART_ROWS", 250)
    more = packed.parts_of(by_key, 8)
    assert (np.diff(more) >= 0).all() and set(more) == set(range(16)) and np.bincount(more, by_key[1]).max() <= 250 + by_key[1].max()
    monkeypatch.setattr(packed, "PART_ROWS", 10)
    # no more parts than the most frequent key allows
    assert packed.parts_of(by_key, 8).max() + 1 <= 4000 // by_key[1].max()
    sampled = packed.pack_columns(rows, ["x1"], {"sa": list(range(11))})["sa"]
    known = packed.pack_columns(rows, ["x1"], {"sa": list(range(11))}, by_key)["sa"]
    assert _rows_in_order(known) == _rows_in_order(sampled) and (known.counts.sum(0) == sampled.counts.sum(0)).all()
    with pytest.raises(Exception, match="no count"):
        packed.pack_columns(rows, ["x1"], {"sa": list(range(11))}, (by_key[0][1:], by_key[1][1:]))
    with pytest.raises(ValueError):
        packed.pack_columns(rows, ["x1"], {"sa": list(range(11))}, (by_key[0], by_key[1] + 1))


def test_a_sweep_of_one_release_counts_cells_and_draws_queries_once(spark, monkeypatch):
    """No setting makes a workload or counts cells of its own, and no pass samples the rows."""
    monkeypatch.setattr(experiments, "N_QUERIES", 100)
    done, draws, pack = [], workload.draws, packed.pack_columns
    monkeypatch.setattr(workload, "workload", lambda *a: pytest.fail("a workload by itself"))
    monkeypatch.setattr(workload, "cube", lambda *a: pytest.fail("cells of rows"))
    monkeypatch.setattr(workload, "draws", lambda *a: done.append("draws") or draws(*a))
    monkeypatch.setattr(packed, "pack_columns", lambda *a: done.append(f"sort {len(a[3][0])}") or pack(*a))
    got = QUERIES["w_q_theta"](spark, SF).collect()
    assert sorted(done)[0] == "draws" and len(done) == 2 and int(done[1].split()[1] if done[0] == "draws" else done[0].split()[1]) > 100
    assert len(got) == 30
    # cells, counts and errors are those that each setting has by itself
    monkeypatch.undo()
    monkeypatch.setattr(experiments, "N_QUERIES", 100)
    shelf = experiments._Shelf(experiments._encoded(spark, SF, experiments.C3), experiments.C3, True)
    for sa in experiments.SENSITIVE:
        spec = experiments.C3.with_sa(sa)
        celled, own = experiments._Queried(spark, None, spec, shelf), experiments._Queried(spark, SF, spec)
        assert sorted(celled.c.counts) == sorted(own.c.counts) and celled.c.domains == own.c.domains
        assert celled.cells.columns == own.cells.columns and sorted(map(tuple, celled.cells.collect())) == sorted(map(tuple, own.cells.collect()))
    rows = [(sa, *r) for sa in experiments.SENSITIVE for r in (lambda q: q.rows_of(experiments._Queried.box_rows, {t: (3, t) for t in (0.05, 0.25)}, experiments.BETA))(experiments._Queried(spark, SF, experiments.C3.with_sa(sa)))]
    found = {(r.sa, r.theta, r.method): r.median_error for r in got}
    assert len(rows) == 12 and all(found[r[:3]] == (None if r[3] is None else pytest.approx(r[3], rel=1e-9)) for r in rows)
