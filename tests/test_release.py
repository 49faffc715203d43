"""Dealing, publication, audits and baselines on small tables."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from gainbound.operators import attack, deal, emddeal, kdcut, loss, model, publish, workload
from gainbound.operators.search import search
from gainbound.plans.hierarchy import Hierarchy
from gainbound.plans.spec import CATEGORICAL, Attribute, ReleaseSpec
from gainbound.queries.registry import frame

COLOUR = Hierarchy("colour", ("any", ("warm", "red", "pink"), "blue"))
SPEC = ReleaseSpec((Attribute("age"), Attribute("colour", CATEGORICAL, COLOUR)), "sa", "id")


@pytest.fixture(scope="module")
def people(spark):
    random = np.random.default_rng(3)
    rows = [(f"{i:05d}", int(random.integers(20, 80)), ["red", "pink", "blue"][random.integers(3)], int(random.choice(8, p=[0.3, 0.2, 0.15, 0.1, 0.1, 0.05, 0.05, 0.05]))) for i in range(3000)]
    return spark.createDataFrame(rows, "id string, age int, colour string, sa int").cache()


@pytest.mark.parametrize("draw", ["rank", "curve", "euclid", "cosplit"])
@pytest.mark.parametrize("kind", ["capped", "basic"])
def test_releases_keep_the_bound(spark, people, draw, kind):
    d = deal.prepare(people, SPEC, 2.0, kind)
    rows = deal.deal(d, draw, shard_rows=1000).cache()
    assert rows.count() == 3000 and rows.select("row_key").distinct().count() == 3000
    assert rows.select("x1", "x2", "sa").exceptAll(d.encoded.select("x1", "x2", "sa")).isEmpty()
    sizes = sorted(tuple(v) for v in d.tree.leaf_vectors().tolist())
    got = rows.groupBy("ec").pivot("bucket", list(range(len(d.plan.sizes)))).count().na.fill(0).drop("ec").collect()
    assert sorted(map(tuple, got)) == sizes and len(sizes) > 4
    prior = model.prior_frame(spark, d.counts, "int")
    assert model.audit(model.histogram(rows, "sa"), prior, 2.0, kind).where("not ok").isEmpty()


def test_one_group_is_not_searched(spark, people):
    """A plan whose root can't be halved needs no task that holds the table."""
    lonely = people.withColumn("sa", F.when(F.col("id") == "00007", 99).otherwise(F.col("sa")))
    d = deal.prepare(lonely, SPEC, 0.5)
    rows = deal.deal(d, "curve")
    assert d.tree.n_leaves == 1 and rows.select("ec").distinct().count() == 1 and rows.count() == 3000
    assert "FlatMapGroupsInPandas" not in rows._jdf.queryExecution().toString()


def test_pools_are_the_plain_greedy_search():
    """Runs taken by stretches against lists that are cut."""
    random = np.random.default_rng(8)
    keys = [np.sort(random.integers(0, 400, n)) for n in (700, 90, 40)]
    rows = [np.arange(len(k)) + 1000 * j for j, k in enumerate(keys)]
    leaves = np.array([[35, 4, 2]] * 15 + [[175, 30, 10]])
    got = {(leaf, j): r.tolist() for leaf, j, r in deal.fill_curve(rows, keys, leaves, 5, 1)}
    left = [list(zip(k.tolist(), r.tolist(), strict=True)) for k, r in zip(keys, rows, strict=True)]
    for leaf in deal._by_lot(1, 5, len(leaves)):
        own = left[deal._chosen(leaves[leaf], 1, 5 + leaf)]
        x = own[int(deal._share(1, "row", 5 + leaf) * len(own))][0]
        for j, need in enumerate(leaves[leaf].tolist()):
            taken = [r for _, r in left[j] if r in set(got[leaf, j])]
            assert len(taken) == need and taken == got[leaf, j]
            far = max(abs(k - x) for k, r in left[j] if r in set(taken))
            rest = [abs(k - x) for k, r in left[j] if r not in set(taken)]
            assert not rest or min(rest) >= far
            left[j] = [p for p in left[j] if p[1] not in set(taken)]
    assert not any(left)


def test_null_coordinates_are_refused(spark, people):
    with pytest.raises(ValueError, match="age has nulls"):
        deal.prepare(people.withColumn("age", F.when(F.col("id") > "00002", F.col("age"))), SPEC, 2.0)


def test_attacks_on_text_and_null_values(spark, people):
    named = people.withColumn("sa", F.when(F.col("sa") > 0, F.concat(F.lit("v"), F.col("sa").cast("string"))))
    d = deal.prepare(named, SPEC, 2.0)
    prior = model.prior_frame(spark, d.counts, "string")
    cells = workload.cube(d.encoded, SPEC.axes)
    guesses = attack.bayes_predict(cells, SPEC.axes, attack.conditionals(attack.marginals(d.encoded, SPEC.axes), prior), prior)
    hit = attack.success(cells, SPEC.axes, guesses).first()
    assert hit.n_rows == 3000 and 0.2 < hit.success < 0.6
    rate, chance, rounds, changed = attack.exchange_attack(deal.deal(d, "rank"), SPEC.axes, rounds=3)
    assert 0 < rate < 1 and 0 < chance < 1 and 1 <= rounds <= 3 and 0 <= changed <= 1


def test_boxes_are_summed_as_if_compared(spark):
    published = spark.createDataFrame([(0, 1, 5, 0, 3), (1, 1, 2, 2, 6), (2, 2, 7, 9, 9)], "ec long, sa int, n long, x1_lo int, x1_hi int")
    got = {(r.value, r.sa): r.n for r in attack.box_marginals(published, ["x1"], [(0, 9)]).collect()}
    want = {}
    for _, sa, n, lo, hi in published.collect():
        for v in range(lo, hi + 1):
            want[v, sa] = want.get((v, sa), 0) + n
    assert got == want


def test_partitioning_does_not_matter(people):
    a = deal.bucket_and_deal(people.repartition(9), SPEC, 2.0, draw="curve")
    b = deal.bucket_and_deal(people.coalesce(1), SPEC, 2.0, draw="curve")
    assert a.select("row_key", "ec").exceptAll(b.select("row_key", "ec")).isEmpty()


def test_ranks_of_frequent_keys(spark):
    rows = spark.createDataFrame([(f"{i * 7919 % 1000:03x}", i % 2, 5 if i % 4 else i) for i in range(1000)], "row_key string, bucket int, key long")
    got = sorted((r.bucket, r.key, r.row_key, r["rank"]) for r in deal.rank_in_bucket(rows, 1000, 16).collect())
    for b in (0, 1):
        assert [r[3] for r in got if r[0] == b] == list(range(500))


def test_publication(people):
    d = deal.prepare(people, SPEC, 2.0)
    rows = deal.deal(d, "rank")
    out = publish.generalised(rows, SPEC)
    assert out.columns == ["ec", "age", "colour", "sa"] and out.count() == 3000
    counts = publish.counts(rows, SPEC)
    assert counts.agg(F.sum("n")).first()[0] == 3000
    assert counts.where("x2_lo = 0 and x2_hi = 1 or x2_lo = x2_hi or x2_lo = 0 and x2_hi = 2").count() == counts.count()
    once = publish.ReleaseOnce()
    once.claim("people", "1")
    with pytest.raises(PermissionError):
        once.claim("people", "1")


def test_losses(spark):
    spec = SPEC
    box = spark.createDataFrame([(0, 10, 20, 20, 0, 0), (1, 10, 20, 50, 0, 1), (2, 20, 20, 80, 1, 2)], "ec long, size long, x1_lo int, x1_hi int, x2_lo int, x2_hi int")
    got = {r.ec: (r.loss1, r.loss2, r.loss) for r in loss.group_loss(box, spec, [(20, 80), (0, 2)]).collect()}
    assert got[0] == (0.0, 0.0, 0.0)
    assert got[1] == pytest.approx((0.5, 2 / 3, (0.5 + 2 / 3) / 2))
    assert got[2] == pytest.approx((1.0, 1.0, 1.0))
    constant = loss.group_loss(box, spec, [(20, 20), (0, 2)]).select("loss1").distinct().collect()
    assert [r[0] for r in constant] == [0.0]


def test_bad_tables(spark, people):
    with pytest.raises(ValueError):
        deal.prepare(people.where("false"), SPEC, 1.0)
    with pytest.raises(ValueError):
        deal.prepare(people.drop("age"), SPEC, 1.0)
    with pytest.raises(ValueError):
        deal.prepare(people.withColumn("age", F.col("age").cast("double")), SPEC, 1.0)
    strange = spark.createDataFrame([("1", 30, "green", 1), ("2", 31, "red", 2)], people.schema)
    with pytest.raises(Exception, match="no leaf"):
        deal.encode(strange, SPEC).collect()


def test_null_sensitive_value_is_a_value(spark, people):
    some = people.withColumn("sa", F.when(F.col("sa") > 0, F.col("sa")))
    d = deal.prepare(some, SPEC, 2.0)
    rows = deal.deal(d, "rank")
    assert rows.where("bucket is null").isEmpty() and rows.where("sa is null").count() == people.where("sa = 0").count()
    prior = model.prior_frame(spark, d.counts, "int")
    assert model.audit(model.histogram(rows, "sa"), prior, 2.0).where("not ok").isEmpty()


def test_six_rows(spark):
    hist = model.histogram(frame(spark, [(i % 2, i) for i in range(6)], "ec long, sa int"), "sa")
    prior = model.prior_of(hist)
    assert model.audit(hist, prior, 1.0).where("not ok").isEmpty()
    assert model.audit(hist, prior, 0.9).where("ok").isEmpty()
    one = model.merge_groups(hist, 2)
    assert model.achieved(one, prior).first()["achieved_basic"] == 0.0


def test_absent_values(spark):
    hist = model.histogram(frame(spark, [(0, 0), (0, 1), (1, 0), (1, 1), (1, 2)], "ec long, sa int"), "sa")
    prior = model.prior_of(hist)
    delta = {r.ec: r.delta for r in model.delta_level(hist, prior).collect()}
    assert delta[0] == float("inf") and delta[1] < 1
    assert model.audit(hist, prior, 1.0).where("not ok").isEmpty()


def test_repair_by_merging(spark):
    rows = [(e, v) for e in range(16) for v in ([0] * 4 if e % 2 else [1, 2, 3, 0])]
    hist = model.histogram(frame(spark, rows, "ec long, sa int"), "sa")
    prior = model.prior_of(hist)
    assert not model.audit(hist, prior, 0.5).where("not ok").isEmpty()
    mapping, merged = model.repair_by_merging(hist, prior, 0.5)
    assert model.audit(merged, prior, 0.5).where("not ok").isEmpty() and mapping.count() == 16


@pytest.mark.parametrize("choice", ["any", "widest"])
def test_median_cuts_are_the_same_in_tasks_and_across_them(spark, people, choice):
    d = deal.prepare(people, SPEC, 2.0)
    values = sorted(v for v, _ in d.counts)
    p = np.array([dict(d.counts)[v] for v in values]) / 3000
    cells = workload.cube(d.encoded, SPEC.axes).cache()

    def groups(rule, limit):
        out = kdcut.kd_cut(cells, SPEC, d.domains, values, rule, choice, limit)
        return sorted(tuple(sorted((r.x1, r.x2, r.sa, r.n) for r in rows)) for rows in _by(out.collect()).values())

    def _by(rows):
        out = {}
        for r in rows:
            out.setdefault(r.ec, []).append(r)
        return out

    for rule in (kdcut.rule_gain(p, 2.0), kdcut.rule_k(200), kdcut.rule_emd(p, 0.1), kdcut.rule_ldiv(2.5), kdcut.rule_logratio(p, kdcut.delta_for(p, 2.0))):
        whole = groups(rule, 10**6)
        assert whole == groups(rule, 300)
        for g in whole:
            c = np.zeros((len(values), 1))
            for _, _, v, n in g:
                c[values.index(v)] += n
            assert len(whole) == 1 or rule(c).all()


def test_median_cuts_of_a_wide_axis_with_null_values(spark, people):
    wide = people.select("id", (F.pow(F.col("age"), F.lit(6)) - 10**9 + F.col("id").cast("long") % 7).cast("long").alias("age"), "colour", F.when(F.col("sa") != 3, F.col("sa")).alias("sa"))
    d = deal.prepare(wide, SPEC, 2.0)
    values = [v for v, _ in sorted(d.counts, key=lambda x: (x[0] is None, x[0]))]
    assert values[-1] is None
    cells = workload.cube(d.encoded, SPEC.axes).cache()
    found = []
    for limit in (10**6, 400):
        out = {}
        for r in kdcut.kd_cut(cells, SPEC, d.domains, values, kdcut.rule_k(150), limit=limit).collect():
            out.setdefault(r.ec, []).append((r.x1, r.x2, -1 if r.sa is None else r.sa, r.n))
        found.append(sorted(sorted(g) for g in out.values()))
    assert found[0] == found[1] and len(found[0]) > 4 and sum(c[3] for g in found[0] for c in g) == 3000


def test_emd_deal_keeps_its_budget(spark, people):
    d = emddeal.prepare(people, SPEC, 0.15)
    hist = model.histogram(deal.deal_rank(d), "sa")
    t = model.t_summary(model.t_level(hist, model.prior_frame(spark, d.counts, "int"), "ordered")).first()
    assert t["t"] <= 0.15 + 1e-9 and d.tree.n_leaves > 1


def test_search_survives_bumps():
    got = search(lambda x: x if x < 3 else x + 5 * (int(x * 4) % 2), lambda v: v <= 4, 0, 6, steps=6, grid=24)
    assert got[0] >= 3.9
    assert search(lambda x: 9.0, lambda v: v <= 4, 0, 6) is None


def test_workload_is_a_function_of_its_parameters(spark):
    domains = [(0, 82), (0, 1), (0, 10)]
    a = workload.workload(spark, domains, (0, 49), 2, 0.1, 50).collect()
    assert a == workload.workload(spark, domains, (0, 49), 2, 0.1, 50).collect()
    share = 0.1 ** (1 / 3)
    for q in a:
        assert len({x.axis for x in q.attrs}) == 2
        for x in q.attrs:
            lo, hi = domains[x.axis - 1]
            assert lo <= x.lo <= x.hi <= hi and x.hi - x.lo + 1 == max(1, int(share * (hi - lo + 1) + 0.5))
    with pytest.raises(ValueError):
        workload.workload(spark, domains, (0, 49), 4, 0.1, 5)
