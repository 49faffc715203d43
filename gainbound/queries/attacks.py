"""Attacks, baselines and searches."""

from __future__ import annotations

import math
import threading
from concurrent.futures import Future

import numpy as np
from pyspark.sql import functions as F

from gainbound.operators import attack, deal, emddeal, grouped as groups_of, kdcut, loss, model, packed, perturb, publish, workload
from gainbound.operators.search import beside, search
from gainbound.operators.settle import settle, settle_columns
from gainbound.queries import chain as sql
from gainbound.queries import cuts
from gainbound.queries.chain import chain
from gainbound.queries.perturbation import SECRET, coins_sql, gamma_sql
from gainbound.queries.registry import frame, local_frame, query, r6
from gainbound.queries.release import BETA, C3, C5, census, grouped, hist_and_prior, planned
from gainbound.sources.tables import table

_AXES = ["x1", "x2", "x3"]
_MARGIN = ", ml as materialized (" + " union all ".join(f"select {i} as axis, x{i}::bigint as value, sa, count(*) as n from enc group by 2, 3" for i in (1, 2, 3)) + ")\n"
_COVER = """, pc as materialized (select ec, sa, n, x1_lo, x1_hi, case when x2_lo = x2_hi then x2_lo else 0 end as x2_lo, case when x2_lo = x2_hi then x2_hi else 1 end as x2_hi, x3_lo, x3_hi from (select ec, sa, count(*) as n from dealt group by ec, sa) join bx using (ec))
"""
_BOX_MARGIN = _COVER + ", ml as materialized (" + " union all ".join(f"select {i} as axis, value::bigint as value, sa, sum(n) as n from pc join (select unnest(range(x{i}_l, x{i}_h + 1)) as value from dom) on value between x{i}_lo and x{i}_hi group by 2, 3" for i in (1, 2, 3)) + ")\n"


def _predict(cond_n: str = "n", more: str = "") -> str:
    """Success of the arg-max guess, from marginals ml."""
    joins = " ".join(f"left join cd c{i} on c{i}.axis = {i} and c{i}.value = s.x{i} and c{i}.sa = d.sa" for i in (1, 2, 3))
    score = "ln(d.p) + " + " + ".join(f"ln(greatest(coalesce(c{i}.cond, 0), 1e-12::double))" for i in (1, 2, 3))
    return f""", cd as materialized (select axis, value, ml.sa, ml.{cond_n} / d.n as cond from ml join d using (sa)),
cl as materialized (select x1, x2, x3, sa, count(*) as n from enc group by all),
gs as materialized (select x1, x2, x3, arg_max(sa, (round(score, 9), -sa)) as guess from (select s.*, d.sa, {score} as score from (select distinct x1, x2, x3 from cl) as s cross join d {joins}) group by 1, 2, 3)
select round(sum(case when sa = guess then n else 0 end) / sum(n), 6) as success, cast(sum(n) as bigint) as n_rows{more} from cl join gs using (x1, x2, x3)"""


def _prior(spark, d):
    return model.prior_frame(spark, d.counts, "int")


def _attack(cells, marginal, prior):
    return attack.success(cells, _AXES, attack.bayes_predict(cells, _AXES, attack.conditionals(marginal, prior), prior)).select(r6("success"), "n_rows")


@query("nb_attack_raw", chain(upto="dist") + _MARGIN + _predict())
def nb_attack_raw(spark, sf_dir):
    d = planned(spark, sf_dir)
    return _attack(workload.cube(d.encoded, _AXES), attack.marginals(d.encoded, _AXES), _prior(spark, d))


@query("nb_attack_boxes", chain(upto="boxes") + _BOX_MARGIN + _predict())
def nb_attack_boxes(spark, sf_dir):
    d, rows = grouped(spark, sf_dir)
    return _attack(workload.cube(d.encoded, _AXES), attack.box_marginals(publish.counts(rows, C3), _AXES, d.domains), _prior(spark, d))


_NOISY = ", nz as materialized (select axis, value, sa, greatest(n - sign(c) * 3 * ln(greatest(1 - 2 * abs(c), 1e-300::double)), 0.1::double) as n from (select *, cast('0x' || substr(md5('3|' || axis || '|' || value || '|' || sa), 1, 13) as bigint) / 4503599627370496 - 0.5::double as c from ml))\n"


@query("nb_attack_noisy", chain(upto="dist") + _MARGIN + _NOISY + _predict().replace("ml", "nz"))
def nb_attack_noisy(spark, sf_dir):
    d = planned(spark, sf_dir)
    return _attack(workload.cube(d.encoded, _AXES), attack.noisy(attack.marginals(d.encoded, _AXES), 1.0, 3), _prior(spark, d))


_PERTURBED = chain(upto="dist") + gamma_sql(BETA) + coins_sql() + ", mo as materialized (" + " union all ".join(f"select {i} as axis, x{i}::bigint as value, pub as sa, count(*) as e from rz group by 2, 3" for i in (1, 2, 3)) + """),
mg as materialized (select g.axis, g.value, tm.sa, alpha, coalesce(e, 0) as e from (select distinct axis, value from mo) as g cross join tm left join mo on mo.axis = g.axis and mo.value = g.value and mo.sa = tm.sa),
mk as (select axis, value, (sum(e / alpha) - sum(e)) / sum(1 / alpha) as k from mg group by axis, value),
ml as materialized (select axis, value, sa, greatest((e - k) / alpha, 0.0::double) as n from mg join mk using (axis, value))
"""


@query("nb_attack_randomised", _PERTURBED + _predict())
def nb_attack_randomised(spark, sf_dir):
    """The attack on perturbed rows: each axis's counts are reconstructed first."""
    d = planned(spark, sf_dir)
    r = perturb.randomiser(d.counts, BETA)
    published = perturb.randomise(d.encoded, "sa", "row_key", r, SECRET)
    return _attack(workload.cube(d.encoded, _AXES), attack.reconstructed_marginals(published, _AXES, r), _prior(spark, d))


@query("noisy_counts", chain(upto="dist") + _MARGIN + """select axis, value, sa, round(greatest(n - sign(c) * 3 * ln(greatest(1 - 2 * abs(c), 1e-300::double)), 0.1::double), 6) as n
from (select *, cast('0x' || substr(md5('3|' || axis || '|' || value || '|' || sa), 1, 13) as bigint) / 4503599627370496 - 0.5::double as c from ml)""")
def noisy_counts(spark, sf_dir):
    return attack.noisy(attack.marginals(planned(spark, sf_dir).encoded, _AXES), 1.0, 3).select("axis", "value", "sa", r6("n"))


@query("nb_conditional", chain(upto="boxes") + _BOX_MARGIN + "select axis, value, ml.sa, round(ml.n / d.n, 6) as cond from ml join d using (sa)")
def nb_conditional(spark, sf_dir):
    d, rows = grouped(spark, sf_dir)
    return attack.conditionals(attack.box_marginals(publish.counts(rows, C3), _AXES, d.domains), _prior(spark, d)).select("axis", "value", "sa", r6("cond"))


@query("nb_bound", chain(upto="boxes") + _BOX_MARGIN + f""", cv as (select axis, value, sum(n) / (select sum(n) from d) as coverage from ml group by 1, 2)
select axis, round(max(ml.n / d.n / ({sql.cap('d.p', BETA)} / d.p * coverage)), 6) as largest_share, bool_and(ml.n / d.n <= {sql.cap('d.p', BETA)} / d.p * coverage + 1e-9) as ok from ml join d using (sa) join cv using (axis, value) group by axis""")
def nb_bound(spark, sf_dir):
    """A value's conditional given a sensitive value exceeds its coverage by the bound's factor at most."""
    from gainbound.functions.bounds import cap_expr

    d, rows = grouped(spark, sf_dir)
    marginal = attack.box_marginals(publish.counts(rows, C3), _AXES, d.domains)
    coverage = marginal.groupBy("axis", "value").agg((F.sum("n") / F.lit(sum(n for _, n in d.counts))).alias("coverage"))
    limit = cap_expr(F.col("p"), BETA) / F.col("p") * F.col("coverage")
    both = marginal.join(F.broadcast(_prior(spark, d)), "sa").join(coverage, ["axis", "value"]).withColumn("cond", F.col("n") / F.col("prior_n"))
    return both.groupBy("axis").agg(r6(F.max(F.col("cond") / limit), "largest_share"), F.bool_and(F.col("cond") <= limit + 1e-9).alias("ok"))


@query("majority", chain(upto="dist") + "select round(max(p), 6) as top_share from d")
def majority(spark, sf_dir):
    return model.sa_distribution(census(spark, sf_dir), "price_class").agg(r6(F.max("p"), "top_share"))


@query("exchange_attack")
def exchange_attack(spark, sf_dir):
    hit, chance, rounds, changed = attack.exchange_attack_on(census(spark, sf_dir), C3, BETA)
    return frame(spark, [(round(hit, 6), round(chance, 6), rounds, round(changed, 6), changed <= attack.STOP)], "success double, chance double, rounds int, changed double, converged boolean")


@query("minimality_invariant", "select 0::bigint as moved")
def minimality_invariant(spark, sf_dir):
    """Rows whose group changes when every sensitive value is replaced by its bucket: the dealing sees buckets only."""
    d, rows = grouped(spark, sf_dir)
    blind = deal.rank_in_bucket(deal.keyed(d, "zorder").withColumn("sa", F.lit(None).cast("int")), sum(d.plan.sizes))
    again = blind.withColumn("ec2", deal.walk_expr(d, F.col("bucket"), F.col("rank"))["ec"]).select("row_key", "ec2")
    return rows.join(again, "row_key").where("ec <> ec2").agg(F.count("*").alias("moved"))


@query("corruption_boxes", chain(upto="hist") + "select ec, any_value(size) as size, round(max(n) / any_value(size), 6) as before, round(max(n) / greatest(any_value(size) - 20, max(n)), 6) as after from hg group by ec")
def corruption_boxes(spark, sf_dir):
    return attack.corruption(hist_and_prior(spark, sf_dir)[0], 20).select("ec", "size", r6("before"), r6("after"))


@query("corruption_randomised", chain(upto="dist") + gamma_sql(BETA) + """, tot as (select sum(n) as total, sum(n * off) as pull from tm join d using (sa))
select tm.sa, round(d.n * keep / (d.n * keep + pull - d.n * off), 6) as before, round(d.n * keep / (d.n * keep + (pull - d.n * off) * greatest(total - d.n - 20, 0) / (total - d.n)), 6) as after, d.n * keep / (d.n * keep + pull - d.n * off) <= f + 1e-9 as ok from tm join d using (sa), tot""")
def corruption_randomised(spark, sf_dir):
    """The randomiser under corruption: 20 others with other values are known, which tells next to nothing, as rows are perturbed apart."""
    counts = model.domain(census(spark, sf_dir), "price_class")
    rows = attack.corruption_randomised(perturb.randomiser(counts, BETA), dict(counts), 20)
    return frame(spark, rows, "sa int, before double, after double, ok boolean").select("sa", r6("before"), r6("after"), "ok")


_TWICE = ", ".join(f"r{i} as materialized (select row_key, ec, sa from ({chain(beta=b, upto='dealt')} select row_key, ec, sa from dealt)), s{i} as (select ec, list(distinct sa) as s from r{i} group by ec)" for i, b in ((1, 4.0), (2, 2.0)))


@query("composition", f"with {_TWICE}, bo as (select r1.ec as e1, r2.ec as e2, count(*) as n from r1 join r2 using (row_key) group by 1, 2) select cast(len(list_intersect(s1.s, s2.s)) as integer) as possible, cast(sum(n) as bigint) as n_rows from bo join s1 on s1.ec = e1 join s2 on s2.ec = e2 group by 1")
def composition(spark, sf_dir):
    """What two releases of the same rows leave open."""
    return attack.composition(grouped(spark, sf_dir, beta=4.0)[1], grouped(spark, sf_dir, beta=2.0)[1])


@query("linkage", chain(C5.with_qi(5), upto="boxes") + f""", people as (select s_suppkey as person, list_position({sql.quoted(C5.qi[4].hierarchy.leaves)}, n_name) - 1 as value from supplier join nation on s_nationkey = n_nationkey)
select person, coalesce(sum(size), 0)::bigint as candidates, count(ec) as groups from people left join bx on value between x5_lo and x5_hi group by person""")
def linkage(spark, sf_dir):
    """Suppliers as a public table: which groups could each be in, by nation."""
    d, rows = grouped(spark, sf_dir, C5)
    named = table(spark, sf_dir, "supplier").join(table(spark, sf_dir, "nation"), F.col("s_nationkey") == F.col("n_nationkey"))
    people = named.select(F.col("s_suppkey").alias("person"), C5.qi[4].hierarchy.position(F.col("n_name")).alias("value"))
    return attack.linkage(people, loss.boxes(rows, C5), "x5")


# median cuts and emd-deal


DRAW = "curve"


def _measures() -> list:
    """Measures of a release, from its groups with their losses."""
    return [F.count("*").alias("groups"), (F.sum(F.col("size") * F.col("loss")) / F.sum("size")).alias("ail"), F.max("gain").alias("beta"), F.min(1 / F.col("top")).alias("l"), F.avg(1 / F.col("top")).alias("avg_l"),
            F.max("emd").alias("t"), F.avg("emd").alias("avg_t")]


def _rounded(got: dict) -> dict:
    return {k: round(v, 6) if isinstance(v, float) else v for k, v in got.items()}


class Compared:
    """Releases of one view by all methods, with the measures that the comparisons use.

    The view is encoded and settled once, and sorted and packed once for each curve; a release of it costs its plan and its dealing."""

    def __init__(self, spark, sf_dir, spec=C3, df=None, encoded=None, surveyed=None, packer=None, cells=None):
        """encoded: a settled table that is encoded already, in place of df; surveyed: its counts and domains, if they are known;
        packer: packs it along a curve, from (dealing, curve), where several comparisons share that; cells: makes its cells, if not from all of its rows."""
        self.spark, self.spec, self._seen, self._keyed, self._cells = spark, spec, {}, {}, None
        self._packed, self._plans, self._held, self._lock = {}, {}, None, threading.Lock()
        self._packing, self._packer = {}, packer or (lambda d, curve: packed.pack(deal.keyed(d, curve), spec.axes, self.values))
        self._count_cells = cells or (lambda: workload.cube(self.encoded, spec.axes))
        if encoded is None:
            df = census(spark, sf_dir) if df is None else df
            spec.validate(df)
            encoded = settle_columns(deal.encode(df, spec))
        self.encoded = encoded
        self.counts, self.domains = deal.survey(self.encoded, spec) if surveyed is None else surveyed
        self.values = [v for v, _ in sorted(self.counts, key=lambda x: (x[0] is None, x[0]))]
        total = sum(n for _, n in self.counts)
        self.p = np.array([dict(self.counts)[v] / total for v in self.values])
        self.prior = model.prior_frame(spark, self.counts, self.encoded.schema["sa"].dataType.simpleString())

    @property
    def cells(self):
        with self._lock:
            return self._cells_made()

    def _cells_made(self):
        if self._cells is None:
            self._cells = settle(self._count_cells())
        return self._cells

    def _pack(self, draw: str, d) -> packed.Packed:
        """The table packed along the draw's curve, once."""
        curve = "zorder" if draw == "rank" else "hilbert"
        with self._lock:
            lock = self._packing.setdefault(curve, threading.Lock())
        with lock:
            if curve not in self._packed:
                self._packed[curve] = self._packer(d, curve)
            return self._packed[curve]

    def _dealt(self, draw: str, plan):
        """A release as counts by group and value with their boxes (rank, curve), or as rows with n = 1. plan: from an encoded table to a dealing."""
        curve = "zorder" if draw == "rank" else "hilbert"
        if draw in ("rank", "curve"):
            d = plan(self.encoded)
            return packed.release(self._pack(draw, d), d, draw)
        if curve not in self._keyed:
            self._keyed[curve] = deal.with_keys(plan(self.encoded), curve).encoded
        return deal.deal(plan(self._keyed[curve]), draw, curve).withColumn("n", F.lit(1).cast("long"))

    def ours(self, beta: float, draw: str = DRAW, **options):
        return self._dealt(draw, lambda encoded: deal.planned_on(encoded, self.spec, self.counts, self.domains, beta, **options))

    def kd(self, rule, choice: str = "any"):
        return kdcut.kd_cut(self.cells, self.spec, self.domains, self.values, rule, choice)

    def emd_deal(self, t: float):
        return self._dealt("rank", lambda encoded: emddeal.planned_on(encoded, self.spec, self.counts, self.domains, t))

    def measured(self, method: str, x: float) -> dict:
        """Measures of a method's release at a parameter, once for each plan: near parameters often have the same one."""
        return self.measured_all(method, [x])[0]

    def measured_all(self, method: str, xs: list[float]) -> list[dict]:
        """The same for several parameters, whose releases go through one job."""
        plans = {x: self._planned(method, x) for x in dict.fromkeys(xs)}
        mine = {}
        with self._lock:
            for key, d in plans.values():
                if key not in self._seen:
                    self._seen[key], mine[key] = Future(), d
            found = [self._seen[plans[x][0]] for x in xs]
        if mine:
            try:
                made = self._measure_all(method, list(mine.values()))
                for key, m in zip(mine, made, strict=True):
                    self._seen[key].set_result(m)
            except BaseException as e:
                for key in mine:
                    self._seen[key].set_exception(e)
        return [f.result() for f in found]

    def _planned(self, method: str, x: float) -> tuple:
        """What tells a release from others, and its plan, or its closeness."""
        if method == "kd-cut[emd]":
            return (method, x), x
        key = (method, x)
        with self._lock:
            known = self._plans.get(key)
        if known is None:
            d = emddeal.planned_on(self.encoded, self.spec, self.counts, self.domains, x) if method == "emd-deal" else deal.planned_on(self.encoded, self.spec, self.counts, self.domains, x)
            tree = d.tree
            known = (method, tuple(d.plan.bucket_of.items()), tree.counts.tobytes(), tree.left.tobytes(), tree.right.tobytes()), d
            with self._lock:
                self._plans[key] = known
        return known

    def _measure_all(self, method: str, some: list) -> list[dict]:
        if method == "kd-cut[emd]":
            with self._lock:
                if self._held is None:
                    self._held = (kdcut.hold(self._cells_made(), self.spec.axes, self.values),)
            if self._held[0] is None:
                return beside(lambda t: self.measures(self.kd(kdcut.rule_emd(self.p, t)), t=True), some)
            return [_rounded(m) for m in kdcut.measure_emd(self.spark, self._held[0], self.spec, self.domains, self.values, self.counts, self.p, some)]
        draw = "rank" if method == "emd-deal" else DRAW
        return [_rounded(m) for m in packed.measure(self._pack(draw, some[0]), some, draw)]

    def published(self, rows):
        """A release in long form: ec, covering box, sa and n."""
        return publish.covered(groups_of.pairs(rows, self.spec.axes), self.spec)

    def measures(self, rows, t: bool = False) -> dict:
        """Groups, AIL, achieved gain and diversity and, if asked for, closeness. rows: (axes or their bounds, sa, ec, n)."""
        lost = loss.group_loss(groups_of.judged(groups_of.pairs(rows, self.spec.axes), self.spec.axes, self.counts), self.spec, self.domains)
        return {k: v for k, v in _rounded(lost.agg(*_measures()).first().asDict()).items() if t or k not in ("t", "avg_t")}


_FOUR = "groups, ail, beta as achieved_beta, l"


def _kd(name: str, rule, rule_sql: str, choice: str = "any"):
    @query(name, f"select {_FOUR} from ({cuts.measured(cuts.cut(C3, rule_sql, choice))})")
    def run(spark, sf_dir):
        c = Compared(spark, sf_dir)
        m = c.measures(c.kd(rule(c), choice))
        return frame(spark, [(m["groups"], m["ail"], m["beta"], m["l"])], "groups long, ail double, achieved_beta double, l double")


_kd("kd_k", lambda c: kdcut.rule_k(100), cuts.rule_k(100))
_kd("kd_gain", lambda c: kdcut.rule_gain(c.p, BETA), cuts.rule_gain(BETA))
_kd("kd_gain_widest", lambda c: kdcut.rule_gain(c.p, BETA), cuts.rule_gain(BETA), "widest")
_kd("kd_logratio", lambda c: kdcut.rule_logratio(c.p, kdcut.delta_for(c.p, BETA)), cuts.rule_logratio(BETA))
_kd("kd_emd", lambda c: kdcut.rule_emd(c.p, 0.1), cuts.rule_emd(0.1))
_kd("kd_emd_equal", lambda c: kdcut.rule_emd(c.p, 0.3, "equal"), cuts.rule_emd_equal(0.3))
_kd("kd_ldiv", lambda c: kdcut.rule_ldiv(7.0), cuts.rule_ldiv(7.0))


@query("kd_first_cut", chain(upto="dist") + ", tot as (select sum(n) as total from d)\n" + " union all ".join(
    f"""select {i} as axis, cut, round(greatest(max(case when l / lt > {sql.cap('p', BETA)} + 1e-12 then 1 else 0 end), max(case when r / rt > {sql.cap('p', BETA)} + 1e-12 then 1 else 0 end)), 0)::int = 0 as ok
from (select cut, d.sa, d.p, count_if(x{i} <= cut) as l, count_if(x{i} > cut) as r from enc join d using (sa), (select least(min(case when run * 2 >= total then v end), max(case when v < top then v end))::bigint as cut from (select v, sum(c) over (order by v) as run, max(v) over () as top from (select x{i} as v, count(*) as c from enc group by 1)), tot) group by cut, d.sa, d.p),
(select count_if(x{i} <= cut) as lt, count_if(x{i} > cut) as rt from enc, (select least(min(case when run * 2 >= total then v end), max(case when v < top then v end))::bigint as cut from (select v, sum(c) over (order by v) as run, max(v) over () as top from (select x{i} as v, count(*) as c from enc group by 1)), tot)) group by cut, lt, rt""" for i in (1, 2, 3)))
def kd_first_cut(spark, sf_dir):
    """Median and verdict of the gain rule for each attribute at the root."""
    c = Compared(spark, sf_dir)
    rule, out = kdcut.rule_gain(c.p, BETA), []
    for i, x in enumerate(_AXES):
        hist = c.encoded.groupBy(x, "sa").count().collect()  # an axis's domain x the sensitive one
        values = np.array(sorted({r[0] for r in hist}))
        weights = np.array([sum(r["count"] for r in hist if r[0] == v) for v in values])
        cut = kdcut.Cutter.cut_at(values, weights)
        sides = np.zeros((len(c.values), 2))
        for r in hist:
            sides[c.values.index(r["sa"]), int(r[0] > cut)] += r["count"]
        out.append((i + 1, cut, bool(rule(sides).all())))
    return frame(spark, out, "axis int, cut long, ok boolean")


@query("delta_for_beta", chain(upto="dist") + "select beta, round(ln(1 + least(beta, -ln((select max(p) from d)))), 6) as delta from (select unnest([1.0, 2.0, 3.0, 4.0, 5.0])::double as beta)")
def delta_for_beta(spark, sf_dir):
    counts = model.domain(census(spark, sf_dir), "price_class")
    p = np.array([n for _, n in counts]) / sum(n for _, n in counts)
    return frame(spark, [(float(b), kdcut.delta_for(p, b)) for b in range(1, 6)], "beta double, delta double").select("beta", r6("delta"))


@query("emd_deal", f"select groups, ail, beta as achieved_beta, t, avg_t from ({cuts.measured(cuts.emd_deal(C3, 0.1), True)})")
def emd_deal(spark, sf_dir):
    c = Compared(spark, sf_dir)
    m = c.measures(c.emd_deal(0.1), t=True)
    return frame(spark, [(m["groups"], m["ail"], m["beta"], m["t"], m["avg_t"])], "groups long, ail double, achieved_beta double, t double, avg_t double")


# searches


@query("closeness_of", chain(upto="dense") + "select round(max(emd), 6) as t, round(avg(emd), 6) as avg_t from (select ec, sum(abs(s)) / (count(*) - 1) as emd from (select ec, sum(q - p) over (partition by ec order by sa rows unbounded preceding) as s from dn) group by ec)")
def closeness_of(spark, sf_dir):
    return model.t_summary(model.t_level(*hist_and_prior(spark, sf_dir), "ordered")).select(r6("t"), r6("avg_t"))


#: Bisection steps, points of the grid re-check and range of t of a search, and how far a loss may be from the one asked for.
STEPS, GRID, T_RANGE, NEAR = 20, 16, (0.001, 1.0), 0.02
NOTHING = (None, None)


def _ahead(c, method: str):
    """Measures several parameters in one job, where a comparison can."""
    return (lambda xs: c.measured_all(method, xs)) if hasattr(c, "measured_all") else None


def best_beta(c: Compared, target: str, limit: float, steps: int = STEPS, grid: int = GRID) -> tuple:
    """The beta whose release has closeness (t) or loss (ail) within the limit: the largest for t, the smallest for ail. Nulls if there is none."""
    high = max(6.0, -math.log(float(c.p.min())))
    return search(lambda b: c.measured("ours", b)[target], lambda v: v <= limit, 0.05, high, larger=target == "t", steps=steps, grid=grid, ahead=_ahead(c, "ours")) or NOTHING


def best_t(method: str, c: Compared, loss_at_least: float, steps: int = STEPS, grid: int = GRID, near: float | None = None) -> tuple:
    """The t at which a method's loss is nearest to `near` and not below the given one, so that a comparison never favours ours.

    near is the given loss by default. Nulls if no loss is within NEAR of it."""
    aim = loss_at_least if near is None else near
    found = search(lambda t: c.measured(method, t)["ail"], lambda v: v >= loss_at_least, *T_RANGE, larger=True, steps=steps, grid=grid, prefer=lambda t, v: (abs(v - aim), -t), ahead=_ahead(c, method))
    return found if found and abs(found[1] - aim) <= NEAR else NOTHING


@query("search_beta_t")
def search_beta_t(spark, sf_dir):
    beta, t = best_beta(Compared(spark, sf_dir), "t", 0.1)
    return local_frame(spark, [(beta, t)], "beta double, t double")


@query("search_beta_ail")
def search_beta_ail(spark, sf_dir):
    beta, ail = best_beta(Compared(spark, sf_dir), "ail", 0.3)
    return local_frame(spark, [(beta, ail)], "beta double, ail double")


@query("search_t_ail")
def search_t_ail(spark, sf_dir):
    c = Compared(spark, sf_dir)
    t, ail = best_t("emd-deal", c, 0.2)
    return local_frame(spark, [(t, ail)], "t double, ail double")
