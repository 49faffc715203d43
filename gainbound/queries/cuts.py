"""DuckDB SQL for the median cuts, emd-deal and the measures by which releases are compared.

A cut is a recursive table of cells: each round brings all open nodes one level down, with every axis's weighted median, both
sides' counts, the rule's verdict, and the widest axis whose cut keeps the rule.
"""

from __future__ import annotations

from gainbound.plans.spec import CATEGORICAL, ReleaseSpec
from gainbound.queries import chain as sql

#: Per node and axis, from the sides' counts c of values of frequency p, and the sides' totals t. Present values only, but for emd.
_EPS = "1e-12"


def rule_k(k: int) -> str:
    return f"min(t) >= {k}"


def rule_gain(beta: float) -> str:
    return f"bool_and(c <= {sql.cap('p', beta)} * t + {_EPS} * t)"


def delta_for(beta: float) -> str:
    return f"ln(1 + least({beta}, -ln((select max(p) from d))))"


def rule_logratio(beta: float) -> str:
    return f"count(*) = 2 * (select count(*) from d) and bool_and(c > p * exp(-{delta_for(beta)}) * t and c < p * exp({delta_for(beta)}) * t)"


def rule_ldiv(level: float) -> str:
    return f"bool_and(c * {level} <= t + {_EPS})"


def rule_emd_equal(t: float) -> str:
    # what absent values add is what present ones lack
    return f"bool_and((away + 1) / 2 <= {t} + {_EPS})"


def rule_emd(t: str | float) -> str:
    return f"bool_and(away <= {t} + {_EPS})"


def _extent(spec: ReleaseSpec) -> str:
    """Share of an axis's domain that an interval takes: of the smallest covering node for a categorical one."""
    whens = []
    for i, a in enumerate(spec.qi):
        if a.kind == CATEGORICAL:
            nodes = ", ".join(f"({n.lo}, {n.hi})" for n in a.hierarchy.nodes)
            whens.append(f"when {i + 1} then (select min(b - a + 1) from (values {nodes}) as t(a, b) where a <= lo and b >= hi) / {float(len(a.hierarchy.leaves))}::double")
        else:
            whens.append(f"when {i + 1} then (hi - lo) / cast(greatest(1, x{i + 1}_h - x{i + 1}_l) as double)")
    return f"case axis {' '.join(whens)} end"


def cut(spec: ReleaseSpec, rule: str, choice: str = "any", where: str = "", before: str = "") -> str:
    """WITH clause of a cut release: hg, hp, dn, bx and ls as of a dealt one."""
    d = len(spec.qi)
    long = " union all ".join(f"select node, {i} as axis, x{i}::bigint as v, si, n from s" for i in range(1, d + 1))
    at = "case axis " + " ".join(f"when {i} then x{i}" for i in range(1, d + 1)) + " end"
    if "away" in rule and "/ 2" in rule:
        verdict = f"select node, axis, {rule} as ok from (select node, axis, side, sum(abs(c / t - p) - p) as away from sd group by node, axis, side) group by node, axis"
    elif "away" in rule:
        verdict = f"""select node, axis, {rule} as ok from (
            select node, axis, side, sum(abs(run)) / greatest(1, count(*) - 1) as away from (
                select g.node, g.axis, g.side, sum(coalesce(c, 0) / g.t - v.p) over (partition by g.node, g.axis, g.side order by v.si rows unbounded preceding) as run
                from (select distinct node, axis, side, t from sd) as g cross join vl as v left join sd on sd.node = g.node and sd.axis = g.axis and sd.side = g.side and sd.si = v.si)
            group by node, axis, side) group by node, axis"""
    else:
        verdict = f"select node, axis, {rule} as ok from sd group by node, axis"
    pick = "ok" if choice == "any" else "true"
    steps = f"""vl as materialized (select sa, n, p, row_number() over (order by sa) - 1 as si from d),
cl as materialized (select row_number() over () as cid, {', '.join(spec.axes)}, si, enc.sa, count(*) as n from enc join vl on enc.sa is not distinct from vl.sa group by {', '.join(spec.axes)}, si, enc.sa),
kt(node, done, cid) as (
    select '', false, cid from cl
    union all
    (with s as (select node, cl.* from kt join cl using (cid) where not done),
    lg as ({long}),
    rn as (select node, axis, v, sum(n) over (partition by node, axis order by v) as run, sum(n) over (partition by node, axis) as tot, max(v) over (partition by node, axis) as top from (select node, axis, v, sum(n) as n from lg group by node, axis, v)),
    ct as (select node, axis, least(min(case when 2 * run >= tot then v end), max(case when v < top then v end)) as cut, min(v) as lo, max(v) as hi from rn group by node, axis having min(v) < max(v)),
    sc as (select lg.node, lg.axis, v > cut as side, si, sum(n) as c from lg join ct on lg.node = ct.node and lg.axis = ct.axis group by lg.node, lg.axis, v > cut, si),
    sd as (select node, axis, side, sc.si, c, p, sum(c) over (partition by node, axis, side) as t from sc join vl using (si)),
    vd as ({verdict}),
    wd as (select node, axis, cut, ok, {_extent(spec)} as wide from (select * from ct join vd using (node, axis)) cross join dom),
    pk as (select node, axis, cut, ok from (select *, row_number() over (partition by node order by wide desc, axis) as place from wd where {pick}) where place = 1 and ok)
    select case when pk.node is null then s.node else s.node || case when {at} <= cut then '0' else '1' end end, pk.node is null, cid from s left join pk on s.node = pk.node)),
fin as materialized (select node as ec, cl.* from kt join cl using (cid) where done),
hg as materialized (select ec, sa, n, size, n / size as q from (select ec, sa, n, cast(sum(n) over (partition by ec) as bigint) as size from (select ec, sa, sum(n) as n from fin group by ec, sa))),
hp as materialized (select hg.*, d.p from hg join d on hg.sa is not distinct from d.sa),
bx as materialized (select ec, sum(n) as size, {', '.join(f'min({x}) as {x}_lo, max({x}) as {x}_hi' for x in spec.axes)} from fin group by ec)"""
    parts = [*([before] if before else []), sql.VIEWS[sql.view_of(spec)], sql.encoded(spec, where), sql.DIST, sql.domains(spec), steps, sql.DENSE, sql.losses(spec)]
    return "with recursive " + ",\n".join(parts) + "\n"


#: One row of measures from hp, ls (and dn).
MEASURES = """(select count(*) from ls) as groups, (select round(sum(size * loss) / sum(size), 6) from ls) as ail, (select round(max(q / p - 1), 6) from hp) as beta,
(select round(min(1 / top), 6) from (select max(q) as top from hp group by ec)) as l, (select round(avg(1 / top), 6) from (select max(q) as top from hp group by ec)) as avg_l"""
CLOSENESS = ", (select round(max(emd), 6) from em) as t, (select round(avg(emd), 6) from em) as avg_t"
EMD = ", em as materialized (select ec, sum(abs(s)) / (count(*) - 1) as emd from (select ec, sum(q - p) over (partition by ec order by sa rows unbounded preceding) as s from dn) group by ec)\n"


def measured(with_clause: str, t: bool = False) -> str:
    """A query of one row: groups, ail, beta (achieved), l, avg_l and, if asked for, t and avg_t."""
    return with_clause + (EMD if t else "") + "select " + MEASURES + (CLOSENESS if t else "")


def by_order(t: str | float, share: float = 0.5) -> str:
    """bk and plan of emd-deal: the costliest segment of the sensitive order is halved until the segments' cost is within its share."""
    costs = "list_transform(range(1, len(bs) + 1), lambda i: (cum[es[i] + 1] - cum[bs[i] + 1]) / total * (es[i] - bs[i] - 1) * step)"
    mid = "((bs[w] + es[w]) // 2)"
    return f"""so as materialized (select list_concat([0], list(run order by si)) as cum, cast(sum(n) as bigint) as total, cast(count(*) as integer) as m, 1 / greatest(1, count(*) - 1) as step
    from (select n, row_number() over (order by sa) as si, cast(sum(n) over (order by sa) as bigint) as run from d)),
sg(bs, es, more) as (
    select [0], [m], true from so
    union all
    select case when w is null then bs else list_concat(list_concat(bs[1:w], [{mid}]), bs[w + 1:]) end, case when w is null then es else list_concat(list_concat(es[1:w - 1], [{mid}]), es[w:]) end, w is not null
    from (select bs, es, case when list_sum(costs) > {share} * {t} + {_EPS} then list_position(costs, list_max(costs)) end as w from (select bs, es, {costs} as costs from sg, so where more))),
se as materialized (select unnest(range(len(bs))) as bucket, unnest(bs) as b, unnest(es) as e from sg where not more),
bk as materialized (select cast(bucket as integer) as bucket, b, e, cast(cum[e + 1] - cum[b + 1] as bigint) as bn, 1.0::double as cap from se, so),
plan as materialized (select sa, n, p, r, bucket, bn, cap from (select *, row_number() over (order by sa) - 1 as si from d) join bk on si >= b and si < e)"""


def by_closeness(t: str | float) -> str:
    """The tree under a closeness budget: the cost within buckets plus the distance of the bucket-shaped distribution from the overall one."""
    away = "abs(coalesce(list_sum({0}[1:jb[i] - 1]), 0) / list_sum({0}) + {0}[jb[i]] / list_sum({0}) * wc[i] - pc[i])"
    admit = "list_sum({0}) > 0 and list_sum(list_transform(range(1, len({0}) + 1), lambda j: {0}[j] * dm[j])) / list_sum({0}) + list_sum(list_transform(range(1, len(jb) + 1), lambda i: " + away + ")) / greatest(1, len(jb) - 1) <= " + f"{t} + {_EPS}"
    shape = """(select list(bucket + 1 order by sa) from plan) as jb, (select list(wc order by sa) from (select sa, sum(p) over (partition by bucket order by sa) / sum(p) over (partition by bucket) as wc from plan)) as wc,
    (select list(pc order by sa) from (select sa, sum(p) over (order by sa) as pc from plan)) as pc, list((e - b - 1) / greatest(1, (select count(*) from d) - 1) order by bucket) as dm"""
    return sql.tree(admit, "jb, wc, pc, dm", shape)


def emd_deal(spec: ReleaseSpec, t: str | float, before: str = "") -> str:
    return sql.chain(spec, buckets=by_order(t), halving=by_closeness(t), before=before)


def rows_of(parts: list[tuple[str, str]]) -> str:
    """Several one-row queries under one another. parts: (leading columns, query of one row, columns taken)."""
    return " union all ".join(f"select {lead}, {columns} from ({body}) as q" for lead, body, columns in parts)

