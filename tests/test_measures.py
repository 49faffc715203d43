"""Releases measured inside tasks: the same measures as from all groups' rows."""

import threading

import numpy as np
import pytest
from pyspark.sql import functions as F

from gainbound.operators import deal, emddeal, grouped, kdcut, loss, packed
from gainbound.plans import sizetree
from gainbound.plans.spec import CATEGORICAL, Attribute, ReleaseSpec
from gainbound.queries import experiments
from gainbound.queries.attacks import Compared, _measures
from gainbound.queries.registry import QUERIES, local_frame
from gainbound.sources.views import NATION

SPEC = ReleaseSpec((Attribute("a"), Attribute("b", CATEGORICAL, NATION)), "s", "row_key")


@pytest.fixture(scope="module")
def people(spark):
    s = F.when(F.col("id") % 7 == 0, F.lit(None)).otherwise((F.col("id") * F.col("id") % 9).cast("int"))
    nation = F.element_at(F.array(*[F.lit(x) for x in NATION.leaves]), (F.col("id") * 11 % 25 + 1).cast("int"))
    return spark.range(3000).select(F.md5(F.col("id").cast("string")).alias("row_key"), (F.col("id") * 37 % 50).cast("int").alias("a"), nation.alias("b"), s.cast("int").alias("s"))


@pytest.mark.parametrize(("draw", "xs"), [("curve", (3.0, 1.0, 0.01)), ("rank", (1.0, 0.3, 0.05))])
@pytest.mark.parametrize("shard_rows", [150, 1 << 17])
def test_measures_come_in_one_row_a_shard(spark, people, draw, xs, shard_rows, monkeypatch):
    monkeypatch.setattr(packed, "CHUNK_ROWS", 200)
    ds = [deal.prepare(people, SPEC, x) if draw == "curve" else emddeal.prepare(people, SPEC, x) for x in xs]
    own = packed.pack(deal.keyed(ds[0], "zorder" if draw == "rank" else "hilbert"), SPEC.axes, [v for v, _ in sorted(ds[0].counts, key=lambda x: (x[0] is None, x[0]))])
    rows, whole = [], packed.summed
    monkeypatch.setattr(packed, "summed", lambda some: rows.append(some.count()) or whole(some))
    got = packed.measure(own, ds, draw, shard_rows=shard_rows)
    # a loose plan has more groups than shards
    assert rows[0] <= len(xs) * (64 if shard_rows < 3000 else 1) and max(m["groups"] for m in got) > 64
    for d, m in zip(ds, got, strict=True):
        judged = grouped.judged(grouped.pairs(deal.deal(d, draw, shard_rows=shard_rows).withColumn("n", F.lit(1)), SPEC.axes), SPEC.axes, d.counts)
        plain = loss.group_loss(judged, SPEC, d.domains).agg(*_measures()).first().asDict()
        assert m == pytest.approx(plain, abs=1e-9)


@pytest.mark.parametrize(("n", "groups"), [(400, 400), (400, 150), (400, 3)])
def test_few_rows_a_group_are_judged_alike(n, groups):
    random = np.random.default_rng(groups)
    leaf = np.sort(np.r_[np.arange(groups), random.integers(0, groups, n - groups)])
    code = random.integers(0, 11, n)
    prior = np.bincount(code, minlength=11) / n
    for a, b in zip(packed.verdicts(leaf, code, None, groups, prior), packed.verdicts_of_few(np.sort(leaf * 11 + code), prior), strict=True):
        assert a == pytest.approx(b, abs=1e-12)


def test_leaves_stand_in_the_order_of_a_walk():
    tree = sizetree.grow((37, 21, 90), sizetree.gain_rule((0.6, 0.5, 0.9)))

    def below(i: int) -> list:
        return [tree.counts[i].tolist()] if tree.left[i] < 0 else below(int(tree.left[i])) + below(int(tree.right[i]))

    for root in range(len(tree.left)):
        assert tree.leaf_vectors(root).tolist() == below(root)


def test_few_rows_are_held_by_the_plan(spark):
    got = local_frame(spark, [(1, "a", None), (2, "b", 0.5)], "n int, s string, x double")
    assert got.dtypes == [("n", "int"), ("s", "string"), ("x", "double")] and [tuple(r) for r in got.collect()] == [(1, "a", None), (2, "b", 0.5)]
    assert "LocalTableScan" in got._jdf.queryExecution().toString()


@pytest.mark.parametrize("limit", [kdcut.LIMIT_CELLS, 10])
def test_cuts_at_several_closenesses_are_measured_in_one_job(spark, people, limit, monkeypatch):
    """Each as cut and judged by itself, also where the cells are too many to be held."""
    ts = [0.5, 0.02, 0.2, 0.05, 0.1, 0.0]
    c = Compared(spark, "", SPEC, people)
    plain = [c.measures(c.kd(kdcut.rule_emd(c.p, t)), t=True) for t in ts]
    assert len({m["groups"] for m in plain}) > 2
    runs, whole, hold = [], c.kd, kdcut.hold
    monkeypatch.setattr(kdcut, "hold", lambda *a: hold(*a, limit))
    monkeypatch.setattr(c, "kd", lambda rule: runs.append(1) or whole(rule))
    got = c.measured_all("kd-cut[emd]", ts)
    assert len(runs) == (0 if limit > 10 else len(ts))
    for a, b in zip(got, plain, strict=True):
        assert a == pytest.approx(b, abs=2e-6)


def test_levels_are_measured_together(spark, monkeypatch):
    asked, whole = [], Compared._measure_all
    monkeypatch.setattr(Compared, "_measure_all", lambda c, method, some: asked.append((method, len(some))) or whole(c, method, some))
    monkeypatch.setattr(experiments, "best_beta", lambda c, target, level: (None, None))
    rows = QUERIES["w_same_t"](spark, "/root/testdata/sf0.001").collect()
    assert len(rows) == 15 and [n for method, n in asked if method == "kd-cut[emd]"] == [5]


def test_columns_sorted_together_are_packed_as_apart(spark, people, monkeypatch):
    monkeypatch.setattr(packed, "CHUNK_ROWS", 200)
    d = deal.prepare(people, SPEC, 2.0)
    keyed = deal.keyed(d, "hilbert")
    values = [v for v, _ in d.counts]
    both = packed.pack_columns(keyed.withColumn("other", F.col("x1") % 4), SPEC.axes, {"sa": values, "other": [0, 1, 2, 3]})
    alone = {"sa": packed.pack(keyed, SPEC.axes, values), "other": packed.pack(keyed.withColumn("sa", F.col("x1") % 4), SPEC.axes, [0, 1, 2, 3])}

    def rows(p) -> list:
        """Codes and keys of all rows in order; where chunks end depends on a sample."""
        out = []
        for r in sorted(p.table.collect()):
            codes, key, n = (np.frombuffer(r[x], t) for x, t in (("sa", np.uint8), ("key", np.int64), ("n", np.int64)))
            out += zip(codes.tolist(), np.repeat(key, n).tolist(), strict=True)
        return out

    for c, p in alone.items():
        assert (both[c].counts.sum(0) == p.counts.sum(0)).all() and p.counts.sum() == 3000 and rows(both[c]) == rows(p)


def test_a_sweep_surveys_and_sorts_once_for_both_columns(spark, monkeypatch):
    sf, done, survey, pack = "/root/testdata/sf0.001", [], deal.survey, packed.pack_columns
    monkeypatch.setattr(experiments, "N_QUERIES", 50)
    monkeypatch.setattr(deal, "survey", lambda *a: done.append("survey") or survey(*a))
    monkeypatch.setattr(packed, "pack_columns", lambda *a: done.append("sort") or pack(*a))
    rows = QUERIES["w_q_qi"](spark, sf).collect()
    assert sorted(done) == ["sort"] * 5 + ["survey"] * 2
    assert [(r.sa, r.n_qi, r.method) for r in rows] == [(sa, n, name) for sa in experiments.SENSITIVE for n in range(1, 6) for name in ("bucket-and-deal", "kd-cut[gain]", "kd-cut[logratio]")]
    # a release from the shelf is the comparison's own
    shelf = experiments._Shelf(experiments._encoded(spark, sf))
    spec = experiments.C5.with_qi(2).with_sa("corr_class")
    c = experiments._Queried(spark, None, spec, shelf).c
    own = Compared(spark, sf, spec)
    assert sorted(c.counts) == sorted(own.counts) and c.domains == own.domains and c.measured("ours", 3.0) == own.measured("ours", 3.0)


def test_releases_wait_for_no_workload(spark, monkeypatch):
    """Each waits until the other is under way."""
    monkeypatch.setattr(experiments, "N_QUERIES", 50)
    met, asked, releases = threading.Barrier(2, timeout=60), experiments._Queried.asked, experiments._Queried.releases
    monkeypatch.setattr(experiments._Queried, "asked", lambda *a: met.wait() is None or asked(*a))
    monkeypatch.setattr(experiments._Queried, "releases", lambda *a: met.wait() is None or releases(*a))
    q = experiments._Queried(spark, "/root/testdata/sf0.001", experiments.C3.with_qi(1))
    rows = q.rows_of(experiments._Queried.box_rows, {1: (1, 0.1)}, 3.0)
    assert [r[1] for r in rows] == ["bucket-and-deal", "kd-cut[gain]", "kd-cut[logratio]"]
