"""The experiment workloads on the census view: sweeps of each parameter, with all methods beside each other.

Each query returns one row per setting and method; releases are drawn by the greedy search along the Hilbert curve. Sweeps that answer queries
do so for `corr_class`, which depends on the first attribute as sensitive data do, and for `price_class`, which doesn't. A workload has
10,000 queries; those with SQL keep the 200 that their SQL states. Seconds are measured by bench.py.
"""

from __future__ import annotations

import threading
from dataclasses import dataclass

import numpy as np
from pyspark.sql import functions as F

from gainbound.operators import attack, deal, estimate, grouped as groups_of, kdcut, meet, model, packed, perturb, publish, workload
from gainbound.operators.search import beside
from gainbound.operators.settle import settle, settle_columns
from gainbound.queries import cuts
from gainbound.queries.attacks import _BOX_MARGIN, Compared, _predict, best_beta, best_t
from gainbound.queries.chain import DIST, chain
from gainbound.queries.chain import plan as plan_sql
from gainbound.queries.chain import tree as tree_sql
from gainbound.queries.perturbation import SECRET, SEED, gamma_sql
from gainbound.queries.registry import frame, local_frame, query
from gainbound.queries.release import BETA, C3, C5, census
from gainbound.sources import views
from gainbound.sources.tables import table

BETAS = (1.0, 2.0, 3.0, 4.0, 5.0)
N_QUERIES = 10_000
NAN = float("nan")


def _ours_sql(beta: float, spec=C3, t: bool = False, **options) -> str:
    return cuts.measured(chain(spec, beta, draw="curve", **options), t)


def _reached(beta: float) -> str:
    """CTE ot: the closeness that ours reaches."""
    return f"ot as materialized (select t from ({_ours_sql(beta, t=True)}))"


def _same_t_sql(b: float) -> list[tuple[str, str, str]]:
    lead, t = f"{b}::double as beta", "(select t from ot)"
    kd = cuts.measured(cuts.cut(C3, cuts.rule_emd(t), before=_reached(b))) + f", {t} as t"
    emd = cuts.measured(cuts.emd_deal(C3, t, _reached(b))) + f", {t} as t"
    return [(lead, body, f"t, '{name}' as method, beta as achieved_beta, ail") for name, body in (("bucket-and-deal", _ours_sql(b, t=True)), ("kd-cut[emd]", kd), ("emd-deal", emd))]


@query("w_same_t_from_beta", cuts.rows_of([x for b in BETAS for x in _same_t_sql(b)]))
def w_same_t_from_beta(spark, sf_dir):
    """Ours at each beta; the closeness methods at the closeness that ours happens to reach."""
    c, out = Compared(spark, sf_dir), []
    for b in BETAS:
        ours = c.measures(c.ours(b), t=True)
        kd, emd = c.measures(c.kd(kdcut.rule_emd(c.p, ours["t"]))), c.measures(c.emd_deal(ours["t"]))
        out += [(b, ours["t"], name, m["beta"], m["ail"]) for name, m in (("bucket-and-deal", ours), ("kd-cut[emd]", kd), ("emd-deal", emd))]
    return frame(spark, out, "beta double, t double, method string, achieved_beta double, ail double")


@query("w_same_t")
def w_same_t(spark, sf_dir):
    c = Compared(spark, sf_dir)

    def at(t: float) -> list[tuple]:
        beta, reached = best_beta(c, "t", t)
        ours = None if beta is None else c.measured("ours", beta)["beta"]
        return [(t, "bucket-and-deal", beta, reached, ours), *((t, name, NAN, t, c.measured(name, t)["beta"]) for name in ("kd-cut[emd]", "emd-deal"))]

    levels = [0.05, 0.1, 0.15, 0.2, 0.25]
    # each method's releases at all levels are measured together, beside the searches
    rows = beside(lambda run: run(), [*(lambda name=name: c.measured_all(name, levels) for name in ("kd-cut[emd]", "emd-deal")), lambda: beside(at, levels)])[-1]
    out = [r for own in rows for r in own]
    return local_frame(spark, out, "t double, method string, parameter double, reached double, achieved_beta double")


@query("w_same_loss")
def w_same_loss(spark, sf_dir):
    c = Compared(spark, sf_dir)

    def at(level: float) -> list[tuple]:
        beta, ail = best_beta(c, "ail", level)

        def other(name: str) -> tuple:
            t, reached = (None, None) if beta is None else best_t(name, c, ail, near=level)
            return level, name, t, reached, None if t is None else c.measured(name, t)["beta"]

        return [(level, "bucket-and-deal", beta, ail, None if beta is None else c.measured("ours", beta)["beta"]), *beside(other, ("kd-cut[emd]", "emd-deal"))]

    out = [r for rows in beside(at, (0.2, 0.3, 0.4, 0.5)) for r in rows]
    return local_frame(spark, out, "ail_target double, method string, parameter double, ail double, achieved_beta double")


def _three(c: Compared, beta: float) -> list[tuple]:
    """Groups, loss and achieved gain of ours and both adapted median cuts."""
    out = []
    for name, run in (("bucket-and-deal", lambda: c.ours(beta)), ("kd-cut[gain]", lambda: c.kd(kdcut.rule_gain(c.p, beta))), ("kd-cut[logratio]", lambda: c.kd(kdcut.rule_logratio(c.p, kdcut.delta_for(c.p, beta))))):
        m = c.measures(run())
        out.append((name, m["groups"], m["ail"], m["beta"]))
    return out


def _three_sql(lead: str, beta: float, spec=C3, where: str = "") -> list[tuple[str, str, str]]:
    bodies = (("bucket-and-deal", _ours_sql(beta, spec, where=where)), ("kd-cut[gain]", cuts.measured(cuts.cut(spec, cuts.rule_gain(beta), where=where))), ("kd-cut[logratio]", cuts.measured(cuts.cut(spec, cuts.rule_logratio(beta), where=where))))
    return [(lead, body, f"'{name}' as method, groups, ail, beta as achieved_beta") for name, body in bodies]


_THREE = "method string, groups long, ail double, achieved_beta double"


@query("w_vary_beta", cuts.rows_of([x for b in BETAS for x in _three_sql(f"{b}::double as beta", b)]))
def w_vary_beta(spark, sf_dir):
    c = Compared(spark, sf_dir)
    return frame(spark, [(b, *r) for b in BETAS for r in _three(c, b)], "beta double, " + _THREE)


@query("w_vary_qi", cuts.rows_of([x for n in range(1, 6) for x in _three_sql(f"{n} as n_qi", BETA, C5.with_qi(n))]))
def w_vary_qi(spark, sf_dir):
    return frame(spark, [(n, *r) for n in range(1, 6) for c in [Compared(spark, sf_dir, C5.with_qi(n))] for r in _three(c, BETA)], "n_qi int, " + _THREE)


def first_by_hash(df, share: float):
    """A share of the rows, chosen by a hash of the key: nested for growing shares."""
    return df.where(F.conv(F.substring(F.md5(F.concat(F.lit("sample|"), "row_key")), 1, 8), 16, 10).cast("long") < int(share * (1 << 32)))


def _first_sql(share: float) -> str:
    return f"where cast('0x' || substr(md5('sample|' || row_key), 1, 8) as bigint) < {int(share * (1 << 32))}"


@query("w_vary_rows", cuts.rows_of([x for k in range(1, 6) for x in _three_sql(f"{k} as sixths", BETA, where=_first_sql(k / 6))]))
def w_vary_rows(spark, sf_dir):
    whole, out = settle(census(spark, sf_dir).select("row_key", "ship_month", "l_linestatus", "disc_pct", "price_class")), []
    for k in range(1, 6):
        part = first_by_hash(whole, k / 6)
        out += [(k, *r) for r in _three(Compared(spark, sf_dir, C3, part), BETA)]
    return frame(spark, out, "sixths int, " + _THREE)


def _answers(q: meet.Asked, found) -> np.ndarray:
    """Answers in the order of the queries, 0 where nothing was met. found: (qid, v or est), a row for each query at most."""
    rows = found.toArrow()
    out = np.zeros(len(q.qid))
    out[rows.column(0).to_numpy()] = rows.column(1).to_numpy()
    return out


@dataclass
class _Asked:
    """Workloads of several settings as one, with their exact answers."""

    settings: list
    queries: meet.Asked
    truth: np.ndarray

    def errors(self, answers: dict) -> list[tuple]:
        """(setting, method, median relative error of the queries whose answer isn't zero) from each method's answers."""
        out = []
        for k, truth, *own in zip(self.settings, *(np.split(x, len(self.settings)) for x in (self.truth, *answers.values())), strict=True):
            some = truth > 0
            out += [(k, name, float(np.median(np.abs(est[some] - truth[some]) / truth[some])) if some.any() else None) for name, est in zip(answers, own, strict=True)]
        return out


class _Queried:
    """Errors of boxes, randomised rows and separate tables on one workload."""

    def __init__(self, spark, sf_dir, spec, view=None):
        """view: of `_encoded`, which holds the coordinates of all specs and both sensitive columns, or a `_Shelf` of it."""
        if isinstance(view, _Shelf):
            self.c = Compared(spark, sf_dir, spec, encoded=view.encoded(spec), surveyed=view.surveyed(spec), packer=view.pack, cells=view.cells(spec))
        else:
            self.c = Compared(spark, sf_dir, spec, encoded=None if view is None else view.select("row_key", *spec.axes, F.col(spec.sa).alias("sa")))
        self.spark, self.spec, self._shelf = spark, spec, view if isinstance(view, _Shelf) else None
        self.cells = self.c.cells

    def ask(self, width: int, theta: float):
        made = workload.workload(self.spark, self.c.domains, (self.c.values[0], self.c.values[-1]), width, theta, N_QUERIES, SEED)
        queries = settle(workload.wide(made, self.spec.axes, self.c.domains))
        return queries, settle(workload.exact(queries, self.cells, self.spec.axes))

    def asked(self, settings: dict) -> _Asked:
        """The workloads of several settings, to (width, theta), which are answered together."""
        drawn = workload.draws(self.spark, len(self.c.domains), N_QUERIES, SEED) if self._shelf is None else self._shelf.drawn()
        q = meet.together([workload.asked(drawn, self.c.domains, (self.c.values[0], self.c.values[-1]), *s) for s in settings.values()])
        return _Asked(list(settings), q, np.rint(_answers(q, meet.range_sums(self.cells, self.spec.axes, q, lambda sa, n: [(n.astype(float), True)], lambda found, _: found[0]))))

    def releases(self, beta: float) -> dict:
        """The releases at a beta by method, as groups. The last cuts are one task each, so they start first."""
        runs = {"bucket-and-deal": lambda: self.c.ours(beta), "kd-cut[gain]": lambda: self.c.kd(kdcut.rule_gain(self.c.p, beta)), "kd-cut[logratio]": lambda: self.c.kd(kdcut.rule_logratio(self.c.p, kdcut.delta_for(self.c.p, beta)))}
        found = dict(zip(reversed(runs), beside(lambda run: settle(publish.listed(groups_of.pairs(run(), self.spec.axes), self.spec)), reversed(runs.values())), strict=True))
        return {name: found[name] for name in runs}

    def box_rows(self, asked: _Asked, beta: float, released: dict | None = None) -> list[tuple]:
        """Errors of the releases at a beta: (setting, method, error)."""
        released = self.releases(beta) if released is None else released
        found = beside(lambda groups: _answers(asked.queries, estimate.from_groups(asked.queries, groups, self.spec.axes, groups.count())), released.values())
        return asked.errors(dict(zip(released, found, strict=True)))

    def rows_of(self, answers, settings: dict, beta: float) -> list[tuple]:
        """Errors at one beta, for the workloads of several settings. Releases wait for no workload, so they are made beside it."""
        if answers is not _Queried.box_rows:
            return answers(self, self.asked(settings), beta)
        released, asked = beside(lambda run: run(), [lambda: self.releases(beta), lambda: self.asked(settings)])
        return self.box_rows(asked, beta, released)

    def row_rows(self, asked: _Asked, beta: float) -> list[tuple]:
        """The same for the randomised rows and the separate tables."""
        r = perturb.randomiser(self.c.counts, beta)

        def randomised() -> np.ndarray:
            cells = settle(workload.cube(perturb.randomise(self.c.encoded, "sa", "row_key", r, SECRET), self.spec.axes))
            return _answers(asked.queries, estimate.from_randomised(asked.queries, cells, self.spec.axes, r))

        runs = {"randomiser": randomised, "separate-release": lambda: _answers(asked.queries, estimate.from_separate(asked.queries, self.cells, self.spec.axes, self.c.prior))}
        return asked.errors(dict(zip(runs, beside(lambda run: run(), runs.values()), strict=True)))


SENSITIVE = ("price_class", "corr_class")
THETAS = (0.05, 0.1, 0.15, 0.2, 0.25)
_ERRORS = "method string, median_error double"


def _encoded(spark, sf_dir, spec=C5):
    """The census view as releases need it, joined, encoded and settled once for all settings of a sweep: row_key, the axes of spec, and the sensitive columns."""
    rows = census(spark, sf_dir)
    first = SENSITIVE[0]
    spread = rows.select("row_key", *(a.name for a in spec.qi), F.struct(*SENSITIVE).alias(first))
    return settle_columns(deal.encode(spread, spec.with_sa(first)).select("row_key", *spec.axes, "sa.*"))


class _Shelf:
    """What the settings of a sweep share: the view, one survey of it for each sensitive column, its rows sorted once for both columns, and what queries are drawn from."""

    def __init__(self, view, spec=C5, celled: bool = False, drawn: workload.Draws | None = None):
        """celled: the view has few cells by the axes of spec, so they are counted once for both columns, and surveys and cells come from them."""
        self.view, self.spec, self._drawn, self._packed, self._lock, self._locks = view, spec, drawn, {}, threading.Lock(), {}
        self._cells = settle(view.groupBy(*spec.axes, *SENSITIVE).agg(F.count("*").alias("n"))) if celled else None

        def survey(sa: str) -> tuple:
            own = spec.with_sa(sa)
            return deal.survey(self._cells.select(*own.axes, F.col(sa).alias("sa"), "n") if celled else self.encoded(own), own)

        self._surveys = dict(zip(SENSITIVE, beside(survey, SENSITIVE), strict=True))

    def encoded(self, spec):
        return self.view.select("row_key", *spec.axes, F.col(spec.sa).alias("sa"))

    def surveyed(self, spec) -> tuple:
        counts, domains = self._surveys[spec.sa]
        return counts, domains[: len(spec.axes)]

    def cells(self, spec):
        """Makes the cells of a specification; None where they are counted from rows."""
        return None if self._cells is None else lambda: self._cells.groupBy(*spec.axes, F.col(spec.sa).alias("sa")).agg(F.sum("n").alias("n"))

    def drawn(self) -> workload.Draws:
        with self._lock:
            if self._drawn is None:
                self._drawn = workload.draws(self.view.sparkSession, len(self.spec.axes), N_QUERIES, SEED)
            return self._drawn

    def sort(self) -> None:
        """Packs the view along the curve, which needs no plan."""
        spec = self.spec.with_sa(SENSITIVE[0])
        counts, domains = self.surveyed(spec)
        self.pack(deal.Dealing(spec, self.view, domains, counts, None, None), "hilbert")

    def pack(self, d: deal.Dealing, curve: str) -> packed.Packed:
        axes = tuple(d.spec.axes)
        with self._lock:
            lock = self._locks.setdefault((axes, curve), threading.Lock())
        with lock:
            if (axes, curve) not in self._packed:
                keyed = deal.key_of(d, self.view.select("row_key", *axes, *SENSITIVE), curve, "key")
                values = {sa: [v for v, _ in sorted(counts, key=lambda x: (x[0] is None, x[0]))] for sa, (counts, _) in self._surveys.items()}
                known = (deal.counts_by_key(d, self._cells),) if self._cells is not None and curve == "hilbert" else ()
                self._packed[axes, curve] = packed.pack_columns(keyed, list(axes), values, *known)
        return self._packed[axes, curve][d.spec.sa]


def _sweep(name: str, answers, what: str, rows, spec=C5) -> None:
    """A sweep for both sensitive columns. rows: from a shelf and a sensitive column to (setting, method, error); spec has all axes that its settings use. The view is
    joined once for all of them, and what doesn't wait for each other runs beside each other: workers start and queries are drawn while the view is joined,
    and where all settings have the axes of one release, its rows are sorted while everything else is under way."""
    celled = spec is C3

    @query(name)
    def run(spark, sf_dir):
        view, drawn, _ = beside(lambda part: part(), [lambda: _encoded(spark, sf_dir, spec), lambda: workload.draws(spark, len(spec.axes), N_QUERIES, SEED), lambda: packed.awake(spark)])
        shelf = _Shelf(view, spec, celled, drawn)
        sort = [shelf.sort] if celled and answers is _Queried.box_rows else []
        found = beside(lambda part: part(), [*sort, *(lambda sa=sa: rows(spark, shelf, sa, answers) for sa in SENSITIVE)])[len(sort) :]
        return local_frame(spark, [(sa, *r) for sa, own in zip(SENSITIVE, found, strict=True) for r in own], f"sa string, {what}, {_ERRORS}")

    run.__doc__ = f"Median relative errors by {what.split()[0]}."


def _by_width(spark, shelf, sa, answers):
    q = _Queried(spark, None, C5.with_sa(sa), shelf)
    return q.rows_of(answers, {width: (width, 0.1) for width in range(1, 6)}, BETA)


def _by_beta(spark, shelf, sa, answers):
    q = _Queried(spark, None, C3.with_sa(sa), shelf)
    asked = q.asked({None: (3, 0.1)})
    return [(b, *r[1:]) for b, rows in zip(BETAS, beside(lambda b: answers(q, asked, b), BETAS), strict=True) for r in rows]


def _by_qi(spark, shelf, sa, answers):
    def at(n: int) -> list[tuple]:
        q = _Queried(spark, None, C5.with_qi(n).with_sa(sa), shelf)
        return q.rows_of(answers, {n: (min(3, n), 0.1)}, BETA)

    # most attributes first, as they take longest
    return [r for rows in beside(at, range(5, 0, -1))[::-1] for r in rows]


def _by_theta(spark, shelf, sa, answers):
    q = _Queried(spark, None, C3.with_sa(sa), shelf)
    return q.rows_of(answers, {theta: (3, theta) for theta in THETAS}, BETA)


for _kind, _how in (("q", _Queried.box_rows), ("p", _Queried.row_rows)):
    _sweep(f"w_{_kind}_lambda", _how, "width int", _by_width)
    _sweep(f"w_{_kind}_beta", _how, "beta double", _by_beta, C3)
    _sweep(f"w_{_kind}_qi", _how, "n_qi int", _by_qi)
    _sweep(f"w_{_kind}_theta", _how, "theta double", _by_theta, C3)


@query("w_t_l_table", cuts.rows_of([(f"{b}::double as beta", _ours_sql(b, t=True), "t, avg_t, l, avg_l") for b in BETAS]))
def w_t_l_table(spark, sf_dir):
    """Closeness and diversity that come with each beta."""
    c = Compared(spark, sf_dir)
    out = [(b, m["t"], m["avg_t"], m["l"], m["avg_l"]) for b in BETAS for m in [c.measures(c.ours(b), t=True)]]
    return frame(spark, out, "beta double, t double, avg_t double, l double, avg_l double")


_TOP = ", (select round(max(p), 6) from d) as top_share"


@query("w_nb", cuts.rows_of([(f"{b}::double as beta", chain(beta=b, draw="curve", upto="boxes") + _BOX_MARGIN + _predict(more=_TOP), "success, top_share") for b in BETAS]))
def w_nb(spark, sf_dir):
    """Success of the naive Bayes attack on releases, beside the share of the most frequent value."""
    c, axes = Compared(spark, sf_dir), C3.axes
    cells, top = settle(workload.cube(c.encoded, axes)), float(np.max(c.p))
    out = []
    for b in BETAS:
        marginal = attack.box_marginals(c.published(settle(c.ours(b))), axes, c.domains)
        got = attack.success(cells, axes, attack.bayes_predict(cells, axes, attack.conditionals(marginal, c.prior), c.prior)).first()[0]
        out.append((b, round(got, 6), round(top, 6)))
    return frame(spark, out, "beta double, success double, top_share double")


_SIX = """with r as (select l_orderkey % 2 as ec, l_linenumber % 6 as sa from lineitem), g as (select ec, sa, count(*) as n, sum(count(*)) over (partition by ec) as size from r group by ec, sa),
p as (select sa, count(*) / (select count(*) from r) as p from r group by sa), q as (select ec, size, p, n / size as q from g join p using (sa))
select ec::bigint as ec, any_value(size)::bigint as size, round(greatest(max(q / p - 1), 0), 6) as max_gain, bool_and(q <= p * (1 + least(1.0, -ln(p))) + 1e-12) as ok, bool_and(q <= p * (1 + least(0.9, -ln(p))) + 1e-12) as ok_below from q group by ec"""


@query("ex_six", _SIX)
def ex_six(spark, sf_dir):
    """Line items by six values of the line's number, in two groups by order: audited at beta 1 and below."""
    rows = table(spark, sf_dir, "lineitem").select((F.col("l_orderkey") % 2).alias("ec"), (F.col("l_linenumber") % 6).alias("sa"))
    hist = settle(model.histogram(rows, "sa"))
    prior = model.prior_of(hist)
    return model.audit(hist, prior, 1.0).select("ec", "size", F.round("max_gain", 6).alias("max_gain"), "ok").join(model.audit(hist, prior, 0.9).select("ec", F.col("ok").alias("ok_below")), "ec")


_NINETEEN_VIEW = "enc as materialized (select q % 19 % 6 as sa from (select distinct l_quantity::bigint as q from lineitem))"


@query("ex_nineteen", f"with recursive {_NINETEEN_VIEW},\n{DIST},\n{plan_sql(2.0)},\n{tree_sql()}\nselect ec, array_to_string(c, ',') as sizes from leaves")
def ex_nineteen(spark, sf_dir):
    """The quantities that occur, as individuals of six unequal values, at beta 2: the sizes of all groups."""
    from gainbound.plans import sizetree
    from gainbound.plans.buckets import plan_buckets

    quantities = table(spark, sf_dir, "lineitem").select(F.col("l_quantity").cast("long").alias("q")).distinct()
    counts = model.domain(quantities.select((F.col("q") % 19 % 6).alias("sa")), "sa")
    plan = plan_buckets(counts, 2.0)
    leaves = sizetree.grow(plan.sizes, sizetree.gain_rule(plan.caps)).leaf_vectors()
    return frame(spark, [(i, ",".join(map(str, v))) for i, v in enumerate(leaves)], "ec long, sizes string")


_ALPHAS = ", (select round(min(alpha), 6) from tm) as alpha_min, (select round(max(alpha), 6) from tm) as alpha_max, (select any_value(applied) from tm) as cap_applied"


@query("w_outlier", cuts.rows_of([(f"{b}::double as beta", chain(views.EVENTS, b, draw="curve") + gamma_sql(b) + "select " + cuts.MEASURES + _ALPHAS, "groups, ail, alpha_min, alpha_max, cap_applied") for b in BETAS]))
def w_outlier(spark, sf_dir):
    """Values of a single row: groups collapse, the randomiser doesn't."""
    c, out = Compared(spark, sf_dir, views.EVENTS, views.events_view(spark, sf_dir)), []
    for b in BETAS:
        m = c.measures(c.ours(b))
        r = perturb.randomiser(c.counts, b)
        out.append((b, m["groups"], m["ail"], round(min(r.alpha), 6), round(max(r.alpha), 6), r.cap_applied))
    return frame(spark, out, "beta double, groups long, ail double, alpha_min double, alpha_max double, cap_applied boolean")


SLACKS = (0.0, 0.05, 0.1, 0.2)


@query("w_slack", cuts.rows_of([(f"{x}::double as slack", _ours_sql(3.0, slack=x), "groups, ail") for x in SLACKS]))
def w_slack(spark, sf_dir):
    """Looser packing leaves room for more halvings."""
    c = Compared(spark, sf_dir)
    return frame(spark, [(s, m["groups"], m["ail"]) for s in SLACKS for m in [c.measures(c.ours(3.0, slack=s))]], "slack double, groups long, ail double")


@query("w_draws")
def w_draws(spark, sf_dir):
    """The ways of filling the same sizes, for both kinds of sensitive column."""
    out = []
    for sa in ("price_class", "corr_class"):
        c = Compared(spark, sf_dir, C3.with_sa(sa))
        out += [(sa, draw, m["groups"], m["ail"], m["beta"]) for draw in ("rank", "curve", "cosplit") for m in [c.measures(c.ours(BETA, draw))]]
    return frame(spark, out, "sa string, draw string, groups long, ail double, achieved_beta double")


_VIEWS = (("orders", views.ORDERS, views.orders_view), ("customers", views.CUSTOMERS, views.customer_view), ("talk", views.TALK, views.talk_view), ("docs", views.DOCS, views.docs_view), ("vectors", views.vector_spec(4), lambda spark, sf_dir: views.vector_view(spark, sf_dir, 4)))


@query("view_releases", cuts.rows_of([(f"'{name}' as view", cuts.measured(chain(spec, 2.0)), "groups, ail, beta as achieved_beta") for name, spec, _ in _VIEWS]))
def view_releases(spark, sf_dir):
    """The method on the other views."""
    out = []
    for name, spec, view in _VIEWS:
        c = Compared(spark, sf_dir, spec, view(spark, sf_dir))
        m = c.measures(c.ours(2.0, "rank"))
        out.append((name, m["groups"], m["ail"], m["beta"]))
    return frame(spark, out, "view string, groups long, ail double, achieved_beta double")
