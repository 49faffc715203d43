"""The randomiser, its measures, query workloads and estimates."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from gainbound.operators import estimate, model, perturb, publish, workload
from gainbound.operators.deal import encode
from gainbound.operators.loss import axis_domains
from gainbound.queries import chain as sql
from gainbound.queries.chain import chain
from gainbound.queries.registry import frame, query, r6
from gainbound.queries.release import BETA, C3, census, grouped
from gainbound.sources import views

SECRET = "not the published key"
N_QUERIES, WIDTH, THETA, SEED = 200, 3, 0.1, 7
KINDS = "sa int, p double, f double, gamma double, alpha double, keep double, off double, cap_applied boolean"


def _r(spark, sf_dir, beta=BETA, kind="each", sa="price_class"):
    return perturb.randomiser(model.domain(census(spark, sf_dir), sa), beta, kind)


def _lang(spark, sf_dir, beta, kind="each"):
    return perturb.randomiser(model.domain(views.docs_view(spark, sf_dir), "lang"), beta, kind)


def gamma_sql(beta: float) -> str:
    """ga: sa, p, f, gamma; al: alpha by the floor of all gammas, with the safe limit where needed."""
    return f""", ga as materialized (select sa, p, f, (f / p) * (1 - p) / (1 - f) as gamma from (select sa, p, {sql.cap('p', beta)} as f from d)),
gm as materialized (select max(gamma) as top, min(gamma) as low, count(*) as m from ga),
raw as materialized (select sa, p, f, gamma, (m * gamma / (top + m - 1) - 1) / (m - 1) as alpha from ga, gm),
lim as materialized (select (select min(alpha) from raw) <= 0 as applied, 1 + 0.5::double * m * (low - 1) as bound from gm),
g2 as materialized (select sa, p, f, case when applied then least(gamma, bound) else gamma end as gamma, applied from ga, lim),
m2 as materialized (select max(gamma) as top, count(*) as m from g2),
al as materialized (select sa, p, f, gamma, applied, (m * gamma / (top + m - 1) - 1) / (m - 1) as alpha, m from g2, m2),
tm as materialized (select sa, p, f, gamma, alpha, alpha + (1 - alpha) / m as keep, (1 - alpha) / m as off, m, applied from al)
"""


_P = chain(upto="dist")
_L1 = chain(views.DOCS, 1.0, upto="dist")


@query("gammas", _P + gamma_sql(BETA) + "select sa, round(p, 6) as p, round(f, 6) as f, round(gamma, 6) as gamma from ga")
def gammas(spark, sf_dir):
    return frame(spark, _r(spark, sf_dir, kind="raw").rows(), KINDS).select("sa", r6("p"), r6("f"), r6("gamma"))


@query("alphas", _P + gamma_sql(BETA) + "select sa, round(alpha, 6) as alpha, round(keep, 6) as keep, round(off, 6) as off, applied as cap_applied from tm")
def alphas(spark, sf_dir):
    return frame(spark, _r(spark, sf_dir).rows(), KINDS).select("sa", r6("alpha"), r6("keep"), r6("off"), "cap_applied")


@query("alphas_capped", _L1 + gamma_sql(1.0) + "select sa, round(gamma, 6) as gamma, round(alpha, 6) as alpha, applied as cap_applied from tm")
def alphas_capped(spark, sf_dir):
    """A skewed column, whose alphas would be negative as they stand."""
    return frame(spark, _lang(spark, sf_dir, 1.0).rows(), KINDS.replace("sa int", "sa string")).select("sa", r6("gamma"), r6("alpha"), "cap_applied")


@query("alphas_uniform", _P + gamma_sql(BETA) + "select sa, round((low - 1) / (low + m - 1), 6) as alpha from ga, gm")
def alphas_uniform(spark, sf_dir):
    return frame(spark, _r(spark, sf_dir, kind="uniform").rows(), KINDS).select("sa", r6("alpha"))


def _cells_of(r: perturb.Randomiser, matrix: np.ndarray) -> list[tuple]:
    return [(r.values[i], r.values[j], float(matrix[i, j])) for i in range(r.m) for j in range(r.m)]


@query("transition", _P + gamma_sql(BETA) + "select b.sa as published, a.sa as original, round(case when a.sa = b.sa then a.keep else a.off end, 6) as prob from tm a cross join tm b")
def transition(spark, sf_dir):
    r = _r(spark, sf_dir)
    return frame(spark, _cells_of(r, r.matrix()), "published int, original int, prob double").select("published", "original", r6("prob"))


@query("published_pm", _P + gamma_sql(BETA) + "select sa, round(keep, 6) as keep, round(off, 6) as off, round(p, 6) as p from tm")
def published_pm(spark, sf_dir):
    """The matrix as its m rows: all of it follows from them."""
    return frame(spark, _r(spark, sf_dir).rows(), KINDS).select("sa", r6("keep"), r6("off"), r6("p"))


@query("posterior", _P + gamma_sql(BETA) + """, j as (select b.sa as published, a.sa as original, a.p * case when a.sa = b.sa then a.keep else a.off end as w, a.f from tm a cross join tm b)
select published, original, round(w / sum(w) over (partition by published), 6) as posterior, w / sum(w) over (partition by published) <= f + 1e-9 as ok from j""")
def posterior(spark, sf_dir):
    r = _r(spark, sf_dir)
    limit = dict(zip(r.values, r.f, strict=True))
    rows = [(i, j, q, q <= limit[j] + 1e-9) for i, j, q in _cells_of(r, perturb.posterior(r))]
    return frame(spark, rows, "published int, original int, posterior double, ok boolean").select("published", "original", r6("posterior"), "ok")


@query("ratio_check", _P + gamma_sql(BETA) + """, j as (select b.sa as published, a.sa as original, a.gamma, case when a.sa = b.sa then a.keep else a.off end as w from tm a cross join tm b)
select original, round(max(w / least_w), 6) as largest_ratio, max(w / least_w) <= any_value(gamma) + 1e-9 as ok from j join (select published, min(w) as least_w from j group by published) using (published) group by original""")
def ratio_check(spark, sf_dir):
    r = _r(spark, sf_dir)
    m = r.matrix()
    largest = (m / m.min(1, keepdims=True)).max(0)
    return frame(spark, [(v, float(x), bool(x <= g + 1e-9)) for v, x, g in zip(r.values, largest, r.gamma, strict=True)], "original int, largest_ratio double, ok boolean").select("original", r6("largest_ratio"), "ok")


def coins_sql(view: str = "enc") -> str:
    u = "cast('0x' || substr(md5('{0}|' || row_key || '|{1}'), 1, 13) as bigint) / 4503599627370496"
    return f""", vs as materialized (select list(sa order by sa) as vals from tm),
rz as materialized (select {view}.*, case when {u.format(SECRET, 'a')} < alpha then {view}.sa else vals[cast(floor({u.format(SECRET, 'b')} * m) as bigint) + 1] end as pub from {view} join tm using (sa), vs)
"""


def _randomised(spark, sf_dir, spec=C3, beta=BETA):
    encoded = encode(census(spark, sf_dir), spec)
    r = perturb.randomiser(model.domain(census(spark, sf_dir), spec.sa), beta)
    return encoded, r, perturb.randomise(encoded.withColumn("original", F.col("sa")), "sa", "row_key", r, SECRET)


@query("randomised_counts", _P + gamma_sql(BETA) + coins_sql() + "select pub as sa, count(*) as n, count_if(pub = sa)::bigint as same from rz group by pub")
def randomised_counts(spark, sf_dir):
    return _randomised(spark, sf_dir)[2].groupBy("sa").agg(F.count("*").alias("n"), F.count_if(F.col("sa") == F.col("original")).alias("same"))


@query("published_randomised", _P + gamma_sql(BETA) + coins_sql() + "select x1, x2, x3, pub as sa from rz")
def published_randomised(spark, sf_dir):
    """Exact quasi-identifiers and perturbed values, without the key."""
    return _randomised(spark, sf_dir)[2].select("x1", "x2", "x3", "sa")


@query("empirical_posterior", _P + gamma_sql(BETA) + coins_sql() + "select pub as published, sa as original, round(count(*) / sum(count(*)) over (partition by pub), 6) as posterior from rz group by pub, sa")
def empirical_posterior(spark, sf_dir):
    counts = _randomised(spark, sf_dir)[2].groupBy(F.col("sa").alias("published"), "original").agg(F.count("*").alias("n"))
    total = counts.groupBy("published").agg(F.sum("n").alias("t"))
    return counts.join(F.broadcast(total), "published").select("published", "original", r6(F.col("n") / F.col("t"), "posterior"))


_RECONSTRUCT = """, ob as (select tm.sa, alpha, coalesce(e, 0) as e from tm left join (select pub as sa, count(*) as e from rz group by pub) as o using (sa)),
kk as (select (sum(e / alpha) - sum(e)) / sum(1 / alpha) as k from ob)
"""


@query("reconstruct_global", _P + gamma_sql(BETA) + coins_sql() + _RECONSTRUCT + "select sa, e, round((e - k) / alpha, 4) as n_hat from ob, kk")
def reconstruct_global(spark, sf_dir):
    _, r, published = _randomised(spark, sf_dir)
    return perturb.reconstruct(published.groupBy("sa").agg(F.count("*").alias("e")), r).select("sa", "e", F.round("n_hat", 4).alias("n_hat"))


@query("reconstruct_clip", _P + gamma_sql(BETA) + coins_sql() + _RECONSTRUCT + "select sa, round(greatest((e - k) / alpha, 0.0), 4) as n_hat from ob, kk")
def reconstruct_clip(spark, sf_dir):
    _, r, published = _randomised(spark, sf_dir)
    return perturb.reconstruct(published.groupBy("sa").agg(F.count("*").alias("e")), r).select("sa", F.round(F.greatest("n_hat", F.lit(0.0)), 4).alias("n_hat"))


@query("reconstruct_em", _P + gamma_sql(BETA) + coins_sql() + """, ob as (select tm.sa, alpha, off, coalesce(e, 0) as e from tm left join (select pub as sa, count(*) as e from rz group by pub) as o using (sa)),
ls as materialized (select list(sa order by sa) as vs, list(alpha order by sa) as al, list(off order by sa) as of, list(e order by sa) as es from ob),
em(round, x) as (
    select 0, list_transform(es, lambda e: list_sum(es) / len(es)) from ls
    union all
    select round + 1, list_transform(range(1, len(x) + 1), lambda i: x[i] * (al[i] * ra[i] + of[i] * list_sum(ra)))
    from (select *, list_transform(range(1, len(x) + 1), lambda i: es[i] / (al[i] * x[i] + pull)) as ra from (select *, list_sum(list_transform(range(1, len(x) + 1), lambda i: of[i] * x[i])) as pull from em, ls where round < 200)))
select unnest(vs) as sa, round(unnest(x), 6) as n_hat from em, ls where round = 200""")
def reconstruct_em(spark, sf_dir):
    """Non-negative counts by iterating Bayes' rule on the observed ones."""
    _, r, published = _randomised(spark, sf_dir)
    seen = {x.sa: x.n for x in published.groupBy("sa").agg(F.count("*").alias("n")).collect()}
    got = perturb.expectation_maximisation(r, np.array([seen.get(v, 0) for v in r.values], float))
    return frame(spark, list(zip(r.values, map(float, got), strict=True)), "sa int, n_hat double").select("sa", r6("n_hat"))


# workloads and estimates


def workload_sql(spec=C3, width: int = WIDTH, theta: float = THETA, n: int = N_QUERIES) -> str:
    """wl: qid and an interval for each axis and the sensitive column; dm: their domains."""
    share, d = repr(theta ** (1 / (width + 1))), len(spec.qi)
    bounds = ", ".join(f"{0 if a.hierarchy else f'min({x})'} as l{i + 1}, {len(a.hierarchy.leaves) - 1 if a.hierarchy else f'max({x})'} as h{i + 1}" for i, (a, x) in enumerate(zip(spec.qi, spec.axes, strict=True)))
    length = "cast(greatest(1, floor({s}::double * (h{i} - l{i} + 1) + 0.5::double)) as bigint)"
    u = "(cast('0x' || substr(md5('{seed}|' || qid || '|{name}'), 1, 13) as bigint) / 4503599627370496)"
    lens = ", ".join(length.format(s=share, i=i) + f" as n{i}" for i in [*range(1, d + 1), "s"])
    starts = ", ".join(f"cast(floor({u.format(seed=SEED, name=('sa' if i == 's' else i))} * (h{i} - l{i} + 2 - n{i})) + l{i} as bigint) as s{i}" for i in [*range(1, d + 1), "s"])
    orders = ", ".join(f"md5('{SEED}|' || qid || '|order{i}') as o{i}" for i in range(1, d + 1))
    chosen = [f"({' + '.join(f'(o{j} < o{i})::int' for j in range(1, d + 1))}) < {width}" for i in range(1, d + 1)]
    cols = ", ".join(f"case when {chosen[i]} then s{i + 1} else l{i + 1} end as x{i + 1}_a, case when {chosen[i]} then s{i + 1} + n{i + 1} - 1 else h{i + 1} end as x{i + 1}_b, {chosen[i]} as c{i + 1}" for i in range(d))
    return f""", dm as materialized (select *, {lens} from (select {bounds}, min(sa) as ls, max(sa) as hs from enc)),
wl as materialized (select qid, {cols}, ss as sa_lo, ss + ns - 1 as sa_hi from (select qid, {starts}, {orders}, dm.* from range({n}) as q(qid), dm)),
cu as materialized (select {', '.join(spec.axes)}, sa, count(*) as n from enc group by all)
"""


def _queries(spark, encoded, spec, width=WIDTH, theta=THETA, n=N_QUERIES):
    domains = axis_domains(encoded, spec)
    low, high = encoded.agg(F.min("sa"), F.max("sa")).first()
    made = workload.workload(spark, domains, (low, high), width, theta, n, SEED)
    return made, workload.wide(made, spec.axes, domains)


_W = _P + workload_sql()
_INSIDE = " and ".join(f"x{i} between x{i}_a and x{i}_b" for i in (1, 2, 3))
_PREC = f", pr as materialized (select wl.qid, coalesce(prec, 0)::bigint as prec from wl left join (select qid, sum(n) as prec from wl join cu on {_INSIDE} and sa between sa_lo and sa_hi group by qid) using (qid))\n"


@query("workload_gen", _W + "select qid, axis, lo, hi, sa_lo, sa_hi from (" + " union all ".join(f"select qid, {i} as axis, x{i}_a as lo, x{i}_b as hi, sa_lo, sa_hi from wl where c{i}" for i in (1, 2, 3)) + ")")
def workload_gen(spark, sf_dir):
    made, _ = _queries(spark, encode(census(spark, sf_dir), C3), C3)
    return made.select("qid", F.explode("attrs").alias("a"), "sa_lo", "sa_hi").select("qid", "a.axis", "a.lo", "a.hi", "sa_lo", "sa_hi")


@query("prec", _W + _PREC + "select qid, prec from pr")
def prec(spark, sf_dir):
    encoded = encode(census(spark, sf_dir), C3)
    _, wide = _queries(spark, encoded, C3)
    return workload.exact(wide, workload.cube(encoded, C3.axes), C3.axes)


_BOXES_SQL = chain(upto="boxes") + workload_sql() + _PREC + f""", pc as materialized (select ec, sa, n, x1_lo, x1_hi, case when x2_lo = x2_hi then x2_lo else 0 end as x2_lo, case when x2_lo = x2_hi then x2_hi else 1 end as x2_hi, x3_lo, x3_hi from (select ec, sa, count(*) as n from dealt group by ec, sa) join bx using (ec)),
es as materialized (select qid, sum({'n * ' + ' * '.join(f'((least(x{i}_hi, x{i}_b) - greatest(x{i}_lo, x{i}_a) + 1) / (x{i}_hi - x{i}_lo + 1))' for i in (1, 2, 3))}) as est from pc join wl on sa between sa_lo and sa_hi and {' and '.join(f'x{i}_lo <= x{i}_b and x{i}_hi >= x{i}_a' for i in (1, 2, 3))} group by qid),
er as materialized (select pr.qid, prec, coalesce(est, 0) as est, abs(coalesce(est, 0) - prec) / prec as rel_error from pr left join es using (qid) where prec > 0)
"""


def _boxes(spark, sf_dir):
    d, rows = grouped(spark, sf_dir)
    _, wide = _queries(spark, d.encoded, C3)
    truth = workload.exact(wide, workload.cube(d.encoded, C3.axes), C3.axes)
    return estimate.from_boxes(wide, publish.counts(rows, C3), C3.axes), truth


@query("est_boxes", _BOXES_SQL + "select qid, round(est, 4) as est from es")
def est_boxes(spark, sf_dir):
    return _boxes(spark, sf_dir)[0].select("qid", F.round("est", 4).alias("est"))


@query("rel_error", _BOXES_SQL + "select qid, prec, round(rel_error, 6) as rel_error from er")
def rel_error(spark, sf_dir):
    return workload.relative_errors(*_boxes(spark, sf_dir)).select("qid", "prec", r6("rel_error"))


@query("median_error", _BOXES_SQL + "select round(median(rel_error), 6) as median_error, count(*) as n_queries from er")
def median_error(spark, sf_dir):
    return workload.median_error(workload.relative_errors(*_boxes(spark, sf_dir))).select(r6("median_error"), "n_queries")


@query("est_randomised", _P + gamma_sql(BETA) + coins_sql() + workload_sql() + f""", oc as materialized (select qid, pub as sa, count(*) as e from rz join wl on {_INSIDE} group by 1, 2),
fl as materialized (select q.qid, q.sa_lo, q.sa_hi, tm.sa, alpha, coalesce(e, 0) as e from (select wl.* from wl where qid in (select qid from oc)) as q cross join tm left join oc on oc.qid = q.qid and oc.sa = tm.sa),
kq as materialized (select qid, (sum(e / alpha) - sum(e)) / sum(1 / alpha) as k from fl group by qid)
select qid, round(sum((e - k) / alpha), 4) as est from fl join kq using (qid) where sa between sa_lo and sa_hi group by qid""")
def est_randomised(spark, sf_dir):
    encoded, r, published = _randomised(spark, sf_dir)
    _, wide = _queries(spark, encoded, C3)
    return estimate.from_randomised(wide, workload.cube(published, C3.axes), C3.axes, r).select("qid", F.round("est", 4).alias("est"))


@query("est_separate", _W + f"select qid, round(rows * share, 6) as est from (select qid, sum(n) as rows from wl join cu on {_INSIDE} group by qid) join (select qid, sum(p) as share from wl join d on sa between sa_lo and sa_hi group by qid) using (qid)")
def est_separate(spark, sf_dir):
    encoded = encode(census(spark, sf_dir), C3)
    _, wide = _queries(spark, encoded, C3)
    prior = model.prior_frame(spark, model.domain(census(spark, sf_dir), "price_class"), "int")
    return estimate.from_separate(wide, workload.cube(encoded, C3.axes), C3.axes, prior).select("qid", r6("est"))
