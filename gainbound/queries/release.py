"""Views, model, plans, dealing, publication and loss."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gainbound.functions.bounds import cap_expr, gain_expr, sign_expr
from gainbound.functions.curves import curve_expr, grid_expr
from gainbound.operators import deal, loss, model, publish
from gainbound.operators.settle import settle
from gainbound.plans import sizetree
from gainbound.plans.buckets import can_share, ordered, plan_buckets, proportional_groups
from gainbound.plans.spec import ReleaseSpec
from gainbound.queries import chain as sql
from gainbound.queries.chain import chain
from gainbound.queries.registry import frame, query, r6
from gainbound.sources import views
from gainbound.sources.tables import table

BETA = 4.0
C3, C5 = views.CENSUS3, views.CENSUS


def census(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.census_view(spark, sf_dir)


def planned(spark: SparkSession, sf_dir: str, spec: ReleaseSpec = C3, beta: float = BETA, **options) -> deal.Dealing:
    return deal.prepare(census(spark, sf_dir), spec, beta, **options)


def grouped(spark: SparkSession, sf_dir: str, spec: ReleaseSpec = C3, beta: float = BETA, **options) -> tuple[deal.Dealing, DataFrame]:
    """The reference release of these queries: rank dealing along the z-order."""
    d = planned(spark, sf_dir, spec, beta, **options)
    return d, deal.deal_rank(d)


def hist_and_prior(spark: SparkSession, sf_dir: str, spec: ReleaseSpec = C3, beta: float = BETA) -> tuple[DataFrame, DataFrame]:
    d, rows = grouped(spark, sf_dir, spec, beta)
    return model.histogram(rows, "sa"), model.prior_frame(spark, d.counts, rows.schema["sa"].dataType.simpleString())


# views

_VIEW_COLUMNS = {
    "census": "row_key, ship_month, l_linestatus, disc_pct, p_type, nation, price_class, p_size, corr_class",
    "orders_view": "row_key, order_day, price_cents, nation, o_orderpriority",
    "customer_view": "row_key, balance_cents, nation, c_mktsegment",
    "events_view": "row_key, hour, day, k, value_band, event_type",
    "docs_view": "row_key, n_chars, source, lang, quality, toxic",
    "talk_view": "row_key, turn, text_length, role",
}


def _view(name: str, build):
    columns = [c.strip() for c in _VIEW_COLUMNS[name].split(",")]
    query("view_" + name.removesuffix("_view"), f"with {sql.VIEWS[name]} select {', '.join(columns)} from {name}")(lambda spark, sf_dir: build(spark, sf_dir).select(*columns))


for _name, _build in (("census", views.census_view), ("orders_view", views.orders_view), ("customer_view", views.customer_view), ("events_view", views.events_view), ("docs_view", views.docs_view), ("talk_view", views.talk_view)):
    _view(_name, _build)


@query("view_vector", "select md5(cast(vec_id as varchar)) as row_key, cast(floor(cast(embedding[1] as double) * 1000) as integer) as v1, cast(floor(cast(embedding[2] as double) * 1000) as integer) as v2, cast(floor(cast(embedding[3] as double) * 1000) as integer) as v3, label from embeddings")
def view_vector(spark, sf_dir):
    return views.vector_view(spark, sf_dir, 3)


# model


@query("sa_distribution", chain(upto="dist") + "select sa, n, round(p, 6) as p, cast(r - 1 as integer) as rank from d")
def sa_distribution(spark, sf_dir):
    return model.sa_distribution(census(spark, sf_dir), "price_class").select("sa", "n", r6("p"), "rank")


@query("sa_rank", chain(views.EVENTS, upto="dist") + "select sa, n, cast(r - 1 as integer) as rank from d")
def sa_rank(spark, sf_dir):
    rows = ordered(model.domain(views.events_view(spark, sf_dir), "value_band"))
    return frame(spark, [(v, n, i) for i, (v, n) in enumerate(rows)], "sa int, n long, rank int")


@query("ec_gain", chain(upto="hist") + "select ec, sa, n, round(q, 6) as q, round((q - p) / p, 6) as relative, round(q - p, 6) as absolute, round(q / p, 6) as ratio, round(abs(ln(q / p)), 6) as logratio from hp")
def ec_gain(spark, sf_dir):
    return model.gains(*hist_and_prior(spark, sf_dir)).select("ec", "sa", "n", *(r6(c) for c in ("q", "relative", "absolute", "ratio", "logratio")))


@query("gain_sign", chain(upto="hist") + "select ec, count_if(q > p)::bigint as positive, count_if(q < p)::bigint as negative, count_if(q = p)::bigint as none from hp group by ec")
def gain_sign(spark, sf_dir):
    rows = model.joined(*hist_and_prior(spark, sf_dir)).withColumn("s", sign_expr(F.col("p"), F.col("q")))
    return rows.groupBy("ec").agg(*(F.count_if(F.col("s") == s).alias(s) for s in ("positive", "negative", "none")))


def _caps(name: str, kind: str):
    @query(name, chain(upto="dist") + f"select sa, beta, round({sql.cap('p', 0, kind).replace('least(0,', 'least(beta,').replace('cast(0 as double)', 'cast(beta as double)')}, 6) as cap from d, (select unnest([1.0, 2.0, 3.0, 4.0, 5.0])::double as beta)")
    def caps(spark, sf_dir):
        prior = model.sa_distribution(census(spark, sf_dir), "price_class")
        return prior.select("sa", F.explode(F.array(*[F.struct(F.lit(float(b)).alias("beta"), cap_expr(F.col("p"), b, kind).alias("cap")) for b in range(1, 6)])).alias("x")).select("sa", "x.beta", r6(F.col("x.cap"), "cap"))


for _name, _kind in (("cap_basic", "basic"), ("cap_capped", "capped"), ("cap_custom_log2", "log2"), ("cap_custom_sqrt", "sqrt")):
    _caps(_name, _kind)


@query("cap_regime", chain(views.DOCS, 1.0, upto="dist") + f"select sa, round(p, 6) as p, round({sql.cap('p', 1.0)}, 6) as cap, case when -ln(p) < 1.0 then 'logarithmic' else 'linear' end as regime, round(1 / 2.0::double, 6) as least_prevalence, round(exp(-1.0::double), 6) as threshold from d")
def cap_regime(spark, sf_dir):
    prior = model.sa_distribution(views.docs_view(spark, sf_dir), "lang")
    return model.cap_report(prior, 1.0).select("sa", r6("p"), r6("cap"), "regime", r6("least_prevalence"), r6("threshold"))


@query("min_ec_size", chain(views.EVENTS, 1.0, upto="dist") + f"select sa, n as prior_n, cast(ceil(1 / {sql.cap('p', 1.0)} - 1e-12) as bigint) as min_size from d")
def min_ec_size(spark, sf_dir):
    counts = model.domain(views.events_view(spark, sf_dir), "value_band")
    return model.min_group_sizes(model.prior_frame(spark, counts, "int"), 1.0)


@query("audit_ec", chain(upto="hist") + f"select ec, max(size) as size, count(*) as n_values, round(greatest(max((q - p) / p), 0.0), 6) as max_gain, not bool_or(q > {sql.cap('p', BETA)} + 1e-12) as ok from hp group by ec")
def audit_ec(spark, sf_dir):
    return model.audit(*hist_and_prior(spark, sf_dir), BETA).select("ec", "size", "n_values", r6("max_gain"), "ok")


@query("achieved_beta", chain(upto="hist") + "select round(greatest(max((q - p) / p), 0.0), 6) as achieved_basic, round(case when bool_or((q - p) / p > -ln(p) + 1e-12) then 'infinity'::double else greatest(max((q - p) / p), 0.0) end, 6) as achieved_capped from hp")
def achieved_beta(spark, sf_dir):
    return model.achieved(*hist_and_prior(spark, sf_dir)).select(r6("achieved_basic"), r6("achieved_capped"))


@query("merge_monotone", chain(upto="hist") + """, mg as (select ec // 2 as ec, sa, sum(n) as n from hg group by 1, 2), ms as (select ec, sa, n / sum(n) over (partition by ec) as q from mg)
select a.ec, round(a.g, 6) as merged_gain, round(b.g, 6) as parts_gain, a.g <= b.g + 1e-9 as ok
from (select ec, max((q - p) / p) as g from ms join d using (sa) group by ec) as a join (select ec // 2 as ec, max((q - p) / p) as g from hp group by 1) as b using (ec)""")
def merge_monotone(spark, sf_dir):
    hist, prior = hist_and_prior(spark, sf_dir)
    gain = F.max(gain_expr(F.col("p"), F.col("q")))
    merged = model.joined(model.merge_groups(hist), prior).groupBy("ec").agg(gain.alias("merged_gain"))
    parts = model.joined(hist, prior).groupBy(F.floor(F.col("ec") / 2).cast("long").alias("ec")).agg(gain.alias("parts_gain"))
    return merged.join(parts, "ec").select("ec", r6("merged_gain"), r6("parts_gain"), (F.col("merged_gain") <= F.col("parts_gain") + 1e-9).alias("ok"))


_MERGING = f""", mp(k, ec, target) as (
    select 0, ec, ec from (select distinct ec from hg)
    union all
    (with mh as (select k, target, sa, n / sum(n) over (partition by target) as q from (select k, target, sa, sum(n) as n from mp join hg using (ec) group by k, target, sa)),
    bd as (select distinct target // (cast(1 as bigint) << (k + 1)) as b from mh join d using (sa) where q > {sql.cap('p', 2.0)} + 1e-12)
    select k + 1, ec, case when bd.b is null then target else bd.b * (cast(1 as bigint) << (k + 1)) end from mp left join bd on target // (cast(1 as bigint) << (k + 1)) = bd.b where exists (select 1 from bd) and k < 62)),
mf as materialized (select ec, target from mp where k = (select max(k) from mp)),
mh as materialized (select target as ec, sa, n, sum(n) over (partition by target) as size from (select target, sa, sum(n) as n from mf join hg using (ec) group by target, sa))
select ec, cast(max(size) as bigint) as size, round(greatest(max((mh.n / size - p) / p), 0.0), 6) as max_gain, not bool_or(mh.n / size > {sql.cap('p', 2.0)} + 1e-12) as ok from mh join d using (sa) group by ec"""


@query("repair_merge", chain(upto="hist") + _MERGING)
def repair_merge(spark, sf_dir):
    """A release dealt for beta 4 is repaired for beta 2."""
    hist, prior = hist_and_prior(spark, sf_dir)
    _, merged = model.repair_by_merging(hist, prior, 2.0)
    return model.audit(merged, prior, 2.0).select("ec", "size", r6("max_gain"), "ok")


@query("audit_two_sided", chain(upto="dense") + f"select ec, size, cast(sum((q > {sql.cap('p', BETA)} + 1e-12)::int) as bigint) as above, cast(sum((q < 0.1 * p - 1e-12)::int) as bigint) as under, sum((q > {sql.cap('p', BETA)} + 1e-12)::int) = 0 and sum((q < 0.1 * p - 1e-12)::int) = 0 as ok from dn group by ec, size")
def audit_two_sided(spark, sf_dir):
    return model.audit_two_sided(*hist_and_prior(spark, sf_dir), BETA, 0.9)


@query("audit_semantic", chain(upto="hist") + f""", fg as (select ec, sa // 10 as sa, sum(n) as n from hg group by 1, 2), fq as (select ec, sa, n, sum(n) over (partition by ec) as size from fg),
fp as (select sa // 10 as sa, sum(p) as p from d group by 1)
select ec, cast(max(size) as bigint) as size, count(*) as n_values, round(greatest(max((n / size - p) / p), 0.0), 6) as max_gain, not bool_or(n / size > {sql.cap('p', 1.0)} + 1e-12) as ok from fq join fp using (sa) group by ec""")
def audit_semantic(spark, sf_dir):
    """Families of ten neighbouring price classes as the values to protect, at beta 1."""
    hist, prior = hist_and_prior(spark, sf_dir)
    families = prior.select("sa", F.floor(F.col("sa") / 10).cast("int").alias("family"))
    grouped_hist = model.regroup_values(hist, families)
    return model.audit(grouped_hist, model.prior_of(grouped_hist), 1.0).select("ec", "size", "n_values", r6("max_gain"), "ok")


@query("audit_proximity", chain(upto="dense") + f""", nw as (select ec, size, sum(p) over w as pn, sum(n) over w / size as qn from dn window w as (partition by ec order by sa range between current row and 2 following))
select ec, size, round(greatest(max((qn - pn) / pn), 0.0), 6) as max_gain, cast(sum((qn > {sql.cap('least(pn, 1.0)', BETA)} + 1e-12)::int) as bigint) as intervals_over, sum((qn > {sql.cap('least(pn, 1.0)', BETA)} + 1e-12)::int) = 0 as ok from nw group by ec, size""")
def audit_proximity(spark, sf_dir):
    return model.audit_proximity(*hist_and_prior(spark, sf_dir), BETA, 2).select("ec", "size", r6("max_gain"), "intervals_over", "ok")


@query("k_level", chain(upto="hist") + "select min(size) as k, count(*) as groups, round(avg(size), 6) as avg_size from (select distinct ec, size from hg)")
def k_level(spark, sf_dir):
    return model.k_level(hist_and_prior(spark, sf_dir)[0]).select("k", "groups", r6("avg_size"))


@query("l_level", chain(upto="hist") + """select round(min(f), 6) as frequency_min, round(avg(f), 6) as frequency_avg, round(cast(min(d) as double), 6) as distinct_min, round(avg(d), 6) as distinct_avg, round(min(e), 6) as entropy_min, round(avg(e), 6) as entropy_avg
from (select ec, 1 / max(q) as f, count(*) as d, exp(-sum(q * ln(q))) as e from hg group by ec)""")
def l_level(spark, sf_dir):
    got = model.l_level(hist_and_prior(spark, sf_dir)[0])
    return got.select(*(r6(F.col(c).cast("double"), c) for c in got.columns))


@query("t_level_equal", chain(upto="dense") + "select ec, round(sum(abs(q - p)) / 2, 6) as emd from dn group by ec")
def t_level_equal(spark, sf_dir):
    return model.t_level(*hist_and_prior(spark, sf_dir), "equal").select("ec", r6("emd"))


@query("t_level_ordered", chain(upto="dense") + "select ec, round(sum(abs(s)) / (count(*) - 1), 6) as emd from (select ec, sum(q - p) over (partition by ec order by sa rows unbounded preceding) as s from dn) group by ec")
def t_level_ordered(spark, sf_dir):
    return model.t_level(*hist_and_prior(spark, sf_dir), "ordered").select("ec", r6("emd"))


@query("t_level_hier", chain(upto="dense") + """select ec, round(0.5 * sum(least(up, down)) + sum(abs(up - down)) / 2, 6) as emd
from (select ec, sa // 10 as f, sum(greatest(q - p, 0.0)) as up, sum(greatest(p - q, 0.0)) as down from dn group by 1, 2) group by ec""")
def t_level_hier(spark, sf_dir):
    hist, prior = hist_and_prior(spark, sf_dir)
    return model.t_level(hist, prior, "hier", prior.select("sa", F.floor(F.col("sa") / 10).cast("int").alias("family"))).select("ec", r6("emd"))


@query("delta_level", chain(upto="dense") + "select ec, round(max(case when q > 0 then abs(ln(q / p)) else 'infinity'::double end), 6) as delta from dn group by ec")
def delta_level(spark, sf_dir):
    return model.delta_level(*hist_and_prior(spark, sf_dir)).select("ec", r6("delta"))


@query("skewness", chain(upto="hist") + "select cast(tile as integer) as tile, round(max(q / d.p), 6) as max_ratio, count(distinct sa) as n_values from hg join (select sa, p, ntile(10) over (order by n, sa) as tile from d) as d using (sa) group by tile")
def skewness(spark, sf_dir):
    return model.skewness(*hist_and_prior(spark, sf_dir)).select("tile", r6("max_ratio"), "n_values")


# plans


def _plan_rows(spark, plan, kind: str = "int"):
    return frame(spark, plan.rows(), f"sa {kind}, bucket int, bucket_n long, p_min double, cap double").select("sa", "bucket", "bucket_n", r6("p_min"), r6("cap"))


_PLAN = "select sa, bucket, bn as bucket_n, round(p_min, 6) as p_min, round(cap, 6) as cap from plan"


@query("shareable_pairs", chain(upto="dist") + f", s as (select r, n, p, sum(n) over (order by r) as run, sum(n) over () as total from d) select cast(a.r - 1 as integer) as first, cast(b.r - 1 as integer) as last from s a join s b on a.r < b.r and b.run - a.run + a.n <= {sql.cap('a.p', BETA)} * a.total + 1e-12 * a.total")
def shareable_pairs(spark, sf_dir):
    counts = ordered(model.domain(census(spark, sf_dir), "price_class"))
    n = [c for _, c in counts]
    total = sum(n)
    return frame(spark, [(b, e) for b in range(len(n)) for e in range(b + 1, len(n)) if can_share(sum(n[b : e + 1]), n[b], total, BETA)], "first int, last int")


@query("bucket_plan", chain(upto="plan") + _PLAN)
def bucket_plan(spark, sf_dir):
    return _plan_rows(spark, plan_buckets(model.domain(census(spark, sf_dir), "price_class"), BETA))


@query("bucket_plan_events", chain(views.EVENTS, 2.0, upto="plan") + _PLAN)
def bucket_plan_events(spark, sf_dir):
    return _plan_rows(spark, plan_buckets(model.domain(views.events_view(spark, sf_dir), "value_band"), 2.0))


@query("bucket_plan_basic", chain(views.ORDERS, 1.0, "basic", upto="plan") + _PLAN)
def bucket_plan_basic(spark, sf_dir):
    return _plan_rows(spark, plan_buckets(model.domain(views.orders_view(spark, sf_dir), "o_orderpriority"), 1.0, "basic"), "string")


@query("bucket_plan_slack", chain(beta=3.0, slack=0.05, upto="plan") + _PLAN)
def bucket_plan_slack(spark, sf_dir):
    return _plan_rows(spark, plan_buckets(model.domain(census(spark, sf_dir), "price_class"), 3.0, slack=0.05))


@query("bucket_plan_greedy", chain(upto="dist") + f""", s as (select r, n, p, sa, sum(n) over (order by r) as run, sum(n) over () as total from d),
f as (select b.r as e, min(a.r) as b from s a join s b on a.r <= b.r and (a.r = b.r or b.run - a.run + a.n <= {sql.cap('a.p', BETA)} * a.total + 1e-12 * a.total) group by b.r),
g(b, e) as (select b, e from f where e = (select max(r) from d) union all select f.b, f.e from g join f on f.e = g.b - 1),
k as (select b, e, cast(row_number() over (order by b) - 1 as integer) as bucket from g)
select sa, bucket, cast(sum(n) over (partition by bucket) as bigint) as bucket_n, round(min(p) over (partition by bucket), 6) as p_min, round({sql.cap('min(p) over (partition by bucket)', BETA)}, 6) as cap from d join k on r between b and e""")
def bucket_plan_greedy(spark, sf_dir):
    return _plan_rows(spark, plan_buckets(model.domain(census(spark, sf_dir), "price_class"), BETA, tie="greedy"))


@query("bucket_singletons", chain(upto="dist") + f"select sa, cast(r - 1 as integer) as bucket, n as bucket_n, round(p, 6) as p_min, round({sql.cap('p', BETA)}, 6) as cap from d")
def bucket_singletons(spark, sf_dir):
    return _plan_rows(spark, plan_buckets(model.domain(census(spark, sf_dir), "price_class"), BETA, tie="singletons"))


@query("bucket_cover", chain(upto="plan") + "select (select count(*) from enc) as n_rows, (select count(*) from enc anti join plan using (sa)) as uncovered, (select count(*) from (select sa from plan group by sa having count(distinct bucket) > 1)) as in_several, (select cast(sum(bn) as bigint) from bk) as planned")
def bucket_cover(spark, sf_dir):
    d = planned(spark, sf_dir)
    plan = frame(spark, d.plan.rows(), "sa int, bucket int, bucket_n long, p_min double, cap double")
    several = plan.groupBy("sa").agg(F.countDistinct("bucket").alias("k")).where("k > 1").agg(F.count("*").alias("in_several"))
    uncovered = d.encoded.join(F.broadcast(plan), "sa", "left_anti").agg(F.count("*").alias("uncovered"))
    return d.encoded.agg(F.count("*").alias("n_rows")).crossJoin(uncovered).crossJoin(several).crossJoin(plan.select("bucket", "bucket_n").distinct().agg(F.sum("bucket_n").alias("planned")))


@query("eligibility", chain(upto="tree") + "select ec, list_bool_and(list_transform(range(1, len(c) + 1), lambda i: c[i] <= caps[i] * list_sum(c) + 1e-12 * list_sum(c))) as ok, cast(list_sum(c) as bigint) as size from leaves, sz")
def eligibility(spark, sf_dir):
    d = planned(spark, sf_dir)
    leaves = frame(spark, [(i, [int(x) for x in v]) for i, v in enumerate(d.tree.leaf_vectors())], "ec long, c array<long>")
    total = F.aggregate("c", F.lit(0).cast("long"), lambda a, x: a + x)
    caps = F.array(*[F.lit(c) for c in d.plan.caps])
    return leaves.withColumn("size", total).select("ec", F.forall(F.arrays_zip("c", caps.alias("cap")), lambda z: z["c"] <= z["cap"] * F.col("size") + 1e-12 * F.col("size")).alias("ok"), "size")


@query("lemma2", chain(upto="plan") + "select bucket, round(bn / total, 6) as mass, round(cap, 6) as cap, bn <= cap * total + 1e-12 * total or e = b as ok from bk, dl")
def lemma2(spark, sf_dir):
    plan = plan_buckets(model.domain(census(spark, sf_dir), "price_class"), BETA)
    total = sum(plan.sizes)
    rows = frame(spark, [(j, s / total, c, e - b == 1) for j, (s, c, (b, e)) in enumerate(zip(plan.sizes, plan.caps, plan.segments, strict=True))], "bucket int, mass double, cap double, single boolean")
    return rows.select("bucket", r6("mass"), r6("cap"), ((F.col("mass") <= F.col("cap") + 1e-12) | F.col("single")).alias("ok"))


@query("size_leaves", chain(upto="tree") + "select ec, bucket, cnt from runs")
def size_leaves(spark, sf_dir):
    plan = plan_buckets(model.domain(census(spark, sf_dir), "price_class"), BETA)
    tree = sizetree.grow(plan.sizes, sizetree.gain_rule(plan.caps))
    return frame(spark, [(i, j, int(x)) for i, v in enumerate(tree.leaf_vectors()) for j, x in enumerate(v)], "ec long, bucket int, cnt long")


@query("proportionality", chain(upto="dealt") + """, g as (select ec, bucket, count(*) as n from dealt group by ec, bucket), s as (select ec, sum(n) as size from g group by ec)
select s.ec, round(max(abs(coalesce(n, 0) / size - bn / total)), 6) as deviation from s cross join bk cross join dl left join g on g.ec = s.ec and g.bucket = bk.bucket group by s.ec""")
def proportionality(spark, sf_dir):
    d, rows = grouped(spark, sf_dir)
    total = sum(d.plan.sizes)
    buckets = F.broadcast(frame(spark, [(j, s / total) for j, s in enumerate(d.plan.sizes)], "bucket int, share double"))
    counts = rows.groupBy("ec", "bucket").agg(F.count("*").alias("n"))
    sizes = counts.groupBy("ec").agg(F.sum("n").alias("size"))
    return sizes.crossJoin(buckets).join(counts, ["ec", "bucket"], "left").groupBy("ec").agg(r6(F.max(F.abs(F.coalesce("n", F.lit(0)) / F.col("size") - F.col("share"))), "deviation"))


@query("ec_proportional", chain(upto="plan") + "select cast(list_reduce(list(bn), lambda a, x: gcd(a, x)) as integer) as n_groups, cast(count(*) as integer) as n_buckets from bk")
def ec_proportional(spark, sf_dir):
    plan = plan_buckets(model.domain(census(spark, sf_dir), "price_class"), BETA)
    return frame(spark, [(proportional_groups(plan.sizes), len(plan.sizes))], "n_groups int, n_buckets int")


_LEAVES = ((views.LINE_STATUS, "lineitem", "l_linestatus"), (views.PART_TYPE, "part", "p_type"), (views.NATION, "nation", "n_name"))


@query("leaf_positions", " union all ".join(f"select distinct '{h.attr}' as attr, {c} as leaf, list_position([{', '.join(repr(x) for x in h.leaves)}], {c}) - 1 as pos from {t}" for h, t, c in _LEAVES))
def leaf_positions(spark, sf_dir):
    """Positions of the leaves that occur in the tables."""
    parts = [table(spark, sf_dir, t).select(F.lit(h.attr).alias("attr"), F.col(c).alias("leaf")).distinct().withColumn("pos", h.position(F.col("leaf"))) for h, t, c in _LEAVES]
    return parts[0].union(parts[1]).union(parts[2])


@query("zorder_keys", chain(C5, upto="key") + "select row_key, key from kd")
def zorder_keys(spark, sf_dir):
    return deal.keyed(planned(spark, sf_dir, C5), "zorder").select("row_key", "key")


@query("lex_keys", chain(C5, upto="key", curve="lex") + "select row_key, key from kd")
def lex_keys(spark, sf_dir):
    return deal.keyed(planned(spark, sf_dir, C5), "lex").select("row_key", "key")


@query("hilbert_keys", chain(upto="key", curve="hilbert") + "select distinct x1, x2, x3, key from kd")
def hilbert_keys(spark, sf_dir):
    """Keys of distinct cells only."""
    d = planned(spark, sf_dir)
    cells = d.encoded.select(*d.spec.axes).distinct()
    grid = [grid_expr(F.col(x), lo, hi, d.bits) for x, (lo, hi) in zip(d.spec.axes, d.domains, strict=True)]
    return cells.withColumn("key", curve_expr("hilbert", grid, d.bits))


@query("hilbert_keys_five", chain(C5, upto="key", curve="hilbert") + "select row_key, key from kd")
def hilbert_keys_five(spark, sf_dir):
    """Five axes, whose grid is too large for a table of its points."""
    return deal.keyed(planned(spark, sf_dir, C5), "hilbert").select("row_key", "key")


# dealing and publication

_DEALT = chain(upto="dealt") + "select row_key, x1, x2, x3, sa, bucket, rank, ec from dealt"


@query("deal_rank", _DEALT)
def deal_rank(spark, sf_dir):
    return grouped(spark, sf_dir)[1].select("row_key", "x1", "x2", "x3", "sa", "bucket", "rank", "ec")


@query("deal_rank_orders", chain(views.ORDERS, 1.0, upto="dealt") + "select row_key, sa, bucket, rank, ec from dealt")
def deal_rank_orders(spark, sf_dir):
    return deal.deal_rank(deal.prepare(views.orders_view(spark, sf_dir), views.ORDERS, 1.0)).select("row_key", "sa", "bucket", "rank", "ec")


@query("deal_curve", chain(upto="dealt", draw="curve") + "select row_key, sa, bucket, ec from dealt")
def deal_curve(spark, sf_dir):
    """The greedy search along the Hilbert curve: every row's group."""
    return deal.bucket_and_deal(census(spark, sf_dir), C3, BETA, draw="curve").select("row_key", "sa", "bucket", "ec")


_SIZED = ", rc as materialized (select bucket, cast(sum(cast('0x' || substr(row_key, 1, 8) as bigint)) as bigint) as checksum from enc join plan on enc.sa is not distinct from plan.sa group by bucket)\nselect ec, bucket, cnt as n, checksum from runs join rc using (bucket) where cnt > 0"


def _sized(name: str, draw: str, sa: str):
    @query(name, chain(C3.with_sa(sa), upto="tree") + _SIZED)
    def run(spark, sf_dir):
        rows = deal.bucket_and_deal(census(spark, sf_dir), C3.with_sa(sa), BETA, draw=draw)
        taken = rows.groupBy("ec", "bucket").agg(F.count("*").alias("n"), F.sum(F.conv(F.substring("row_key", 1, 8), 16, 10).cast("long")).alias("part"))
        return taken.select("ec", "bucket", "n", F.sum("part").over(Window.partitionBy("bucket")).alias("checksum"))

    run.__doc__ = "Rows of each group and bucket, which the plan fixes, beside a checksum of each bucket's rows, of which none is lost or doubled."


_sized("deal_euclid", "euclid", "corr_class")
_sized("deal_cosplit", "cosplit", "price_class")


_AUDITED = "select ec, cast(any_value(size) as bigint) as size, round(any_value(loss), 6) as loss, " + ", ".join(f"any_value({x}_{n}) as {x}_{n}" for x in ("x1", "x2", "x3") for n in ("lo", "hi")) + f", round(greatest(max((q - p) / p), 0.0), 6) as max_gain, not bool_or(q > {sql.cap('p', BETA)} + 1e-12) as ok from ls join hp using (ec, size) group by ec"


def _audited(d: deal.Dealing, rows: DataFrame) -> DataFrame:
    """Box, loss and largest gain of each group."""
    lost = loss.group_loss(loss.boxes(rows, d.spec), d.spec, d.domains)
    prior = model.prior_frame(rows.sparkSession, d.counts, "int")
    audited = model.audit(model.histogram(rows, "sa"), prior, BETA).select("ec", "max_gain", "ok")
    return lost.join(audited, "ec").select("ec", "size", r6("loss"), *(f"{x}_{n}" for x in d.spec.axes for n in ("lo", "hi")), r6("max_gain"), "ok")


@query("flagship_release", chain(upto="losses") + _AUDITED)
def flagship_release(spark, sf_dir):
    """The whole method with its audit, drawn by rank along the z-order."""
    return _audited(*grouped(spark, sf_dir))


@query("flagship_curve", chain(upto="losses", draw="curve") + _AUDITED)
def flagship_curve(spark, sf_dir):
    """The whole method with its audit, drawn by the greedy search along the Hilbert curve."""
    d = planned(spark, sf_dir)
    return _audited(d, settle(deal.deal(d, "curve")))


def _cover_sql(spec: ReleaseSpec) -> str:
    """Text of each axis's interval, from the boxes bx."""
    out = []
    for a, x in zip(spec.qi, spec.axes, strict=True):
        if a.hierarchy:
            nodes = ", ".join(f"('{n.node}', {n.lo}, {n.hi}, {n.depth})" for n in a.hierarchy.nodes)
            out.append(f"(select first(node order by b - a, -dep) from (values {nodes}) as t(node, a, b, dep) where a <= {x}_lo and b >= {x}_hi) as {a.name}")
        else:
            out.append(f"'[' || {x}_lo || ', ' || {x}_hi || ']' as {a.name}")
    return ", ".join(out)


@query("published_boxes", chain(C5, upto="boxes") + f"select ec, {_cover_sql(C5)}, sa as price_class from dealt join bx using (ec)")
def published_boxes(spark, sf_dir):
    d, rows = grouped(spark, sf_dir, C5)
    return publish.generalised(rows, d.spec)


@query("published_counts", chain(upto="boxes") + "select ec, sa, n, x1_lo, x1_hi, case when x2_lo = x2_hi then x2_lo else 0 end as x2_lo, case when x2_lo = x2_hi then x2_hi else 1 end as x2_hi, x3_lo, x3_hi from (select ec, sa, count(*) as n from dealt group by ec, sa) join bx using (ec)")
def published_counts(spark, sf_dir):
    d, rows = grouped(spark, sf_dir)
    return publish.counts(rows, d.spec).select("ec", "sa", "n", "x1_lo", "x1_hi", "x2_lo", "x2_hi", "x3_lo", "x3_hi")


# loss


def _lost(spark, sf_dir, spec=C5):
    d, rows = grouped(spark, sf_dir, spec)
    return loss.group_loss(loss.boxes(rows, d.spec), d.spec, d.domains)


@query("loss_numeric", chain(C5) + "select ec, round(loss1, 6) as loss1, round(loss3, 6) as loss3 from ls")
def loss_numeric(spark, sf_dir):
    return _lost(spark, sf_dir).select("ec", r6("loss1"), r6("loss3"))


@query("loss_categorical", chain(C5) + "select ec, round(loss2, 6) as loss2, round(loss4, 6) as loss4, round(loss5, 6) as loss5 from ls")
def loss_categorical(spark, sf_dir):
    return _lost(spark, sf_dir).select("ec", r6("loss2"), r6("loss4"), r6("loss5"))


@query("loss_ec", chain(C5) + "select ec, size, round(loss, 6) as loss from ls")
def loss_ec(spark, sf_dir):
    return _lost(spark, sf_dir).select("ec", "size", r6("loss"))


@query("ail", chain(C3) + "select round(sum(size * loss) / sum(size), 6) as ail, count(*) as groups from ls")
def ail(spark, sf_dir):
    return loss.average_loss(_lost(spark, sf_dir, C3)).select(r6("ail"), "groups")


@query("discernibility", chain(upto="boxes") + "select cast(sum(size * size) as bigint) as discernibility, round(avg(size), 6) as mean_size, max(size) as max_size from bx")
def discernibility(spark, sf_dir):
    d, rows = grouped(spark, sf_dir)
    return loss.discernibility(loss.boxes(rows, d.spec)).select("discernibility", r6("mean_size"), "max_size")


@query("ec_single", chain(upto="dist") + "select count(*) as size, min(x1) as x1_lo, max(x1) as x1_hi, 0.0::double as max_gain, 1.0::double as ail from enc")
def ec_single(spark, sf_dir):
    """The whole table as one group: nothing is learned, and nothing is kept."""
    d = planned(spark, sf_dir)
    rows = d.encoded.withColumn("ec", F.lit(0).cast("long"))
    lost = loss.group_loss(loss.boxes(rows, d.spec), d.spec, d.domains)
    gain = model.audit(model.histogram(rows, "sa"), model.prior_frame(spark, d.counts, "int"), BETA).select("ec", "max_gain")
    return lost.join(gain, "ec").select("size", "x1_lo", "x1_hi", r6("max_gain"), r6("loss", "ail"))

