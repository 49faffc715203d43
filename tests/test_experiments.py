"""Experiment sweeps: whole workloads, whole searches."""

import numpy as np
import pytest

from gainbound.operators import estimate, meet, perturb, workload
from gainbound.queries import attacks, experiments
from gainbound.queries.attacks import best_beta, best_t
from gainbound.queries.registry import QUERIES
from gainbound.queries.release import C3, C5

SF = "/root/testdata/sf0.001"


def test_sweeps_ask_ten_thousand_queries(spark):
    queries, truth = experiments._Queried(spark, SF, C3.with_qi(1)).ask(1, 0.1)
    assert queries.count() == truth.count() == 10_000


def test_workloads_are_answered_together_as_apart(spark, monkeypatch):
    """Two settings in one pass, by boxes and by rows: the errors of each asked by itself, and one exact pass for both."""
    monkeypatch.setattr(experiments, "N_QUERIES", 300)
    passes, whole = [], meet.range_sums
    monkeypatch.setattr(meet, "range_sums", lambda *a: passes.append(1) or whole(*a))
    spec = C3.with_sa("corr_class")
    q = experiments._Queried(spark, SF, spec)
    asked = q.asked({"a": (2, 0.1), "b": (3, 0.3)})
    assert len(passes) == 1 and len(asked.queries.qid) == 600
    got = {(k, name): e for k, name, e in q.box_rows(asked, 2.0) + q.row_rows(asked, 2.0)}
    assert len(got) == 10
    r = perturb.randomiser(q.c.counts, 2.0)
    cells = workload.cube(perturb.randomise(q.c.encoded, "sa", "row_key", r, experiments.SECRET), spec.axes)
    for k, width, theta in (("a", 2, 0.1), ("b", 3, 0.3)):
        queries, truth = q.ask(width, theta)
        # the groups' own boxes and counts, met query by query
        group = q.c.published(q.c.ours(2.0)).toPandas()
        est = []
        for x in queries.orderBy("qid").collect():
            share = 1.0
            for a in spec.axes:
                share = share * np.maximum(np.minimum(group[f"{a}_hi"], x[f"{a}_b"]) - np.maximum(group[f"{a}_lo"], x[f"{a}_a"]) + 1, 0) / (group[f"{a}_hi"] - group[f"{a}_lo"] + 1)
            est.append((x.qid, float((share * group["n"] * group["sa"].between(x.sa_lo, x.sa_hi)).sum())))
        plain = {"bucket-and-deal": spark.createDataFrame(est, "qid long, est double"), "randomiser": estimate.from_randomised(queries, cells, spec.axes, r)}
        for name, answers in plain.items():
            assert got[k, name] == pytest.approx(workload.median_error(workload.relative_errors(answers, truth)).first()[0], abs=1e-9)


def test_a_sweep_settles_its_rows_once(spark, monkeypatch):
    """All settings read one encoded table; it is the one that each would encode."""
    view = experiments._encoded(spark, SF)
    own = {(sa, n): experiments.Compared(spark, SF, C5.with_qi(n).with_sa(sa)).encoded for sa, n in (("price_class", 5), ("corr_class", 2))}
    monkeypatch.setattr(attacks, "settle", lambda df: pytest.fail("settled again") if "row_key" in df.columns else df)
    for (sa, n), plain in own.items():
        got = experiments._Queried(spark, SF, C5.with_qi(n).with_sa(sa), view).c.encoded
        assert got.columns == plain.columns and sorted(map(tuple, got.collect())) == sorted(map(tuple, plain.collect()))


def test_exchange_attack_runs_until_its_stop_rule(spark):
    r = QUERIES["exchange_attack"](spark, SF).first()
    assert r.converged and r.changed <= 0.001 and r.success > r.chance


class _Losses:
    """Stands for a comparison whose loss falls with the parameter but for one narrow dip."""

    p = np.array([0.02, 0.98])

    def measured(self, method, x):
        return {"ail": 0.1 if 1.1 < x < 1.3 else 1 - x / 10, "t": x / 10}


def test_searches_resolve_and_look_again():
    assert best_beta(_Losses(), "t", 0.1234)[0] == pytest.approx(1.234, abs=1e-4)
    assert 1.1 < best_beta(_Losses(), "ail", 0.5)[0] < 1.3
    assert best_beta(_Losses(), "ail", 0.0) == (None, None)
    assert best_t("emd-deal", _Losses(), 0.95)[0] == pytest.approx(0.5, abs=1e-4)
    assert best_t("emd-deal", _Losses(), 0.2) == (None, None)
