"""DuckDB SQL for views, plans and releases, written apart from the Spark code so that agreement means something.

A chain is a WITH clause: the view, its encoded rows (enc), the distribution (d), the bucket plan by a
recursive table over lists (bk, plan), the tree of sizes (leaves, runs) and the dealt rows. Rows are dealt by
rank, or by the greedy search along the Hilbert curve, which is a recursive table of the buckets' lists.
"""

from __future__ import annotations

from gainbound.plans.spec import CATEGORICAL, ReleaseSpec
from gainbound.sources import views

_HUNDREDTHS = "cast(round({0} * 100) as bigint)"

VIEWS = {
    "census": """census as materialized (
select md5(concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, cast(round(l_quantity * 100) as bigint), cast(round(l_extendedprice * 100) as bigint),
       cast(round(l_discount * 100) as bigint), cast(round(l_tax * 100) as bigint), date_diff('day', date '1970-01-01', cast(l_shipdate as date)))) as row_key,
       ship_month, l_linestatus, cast(round(l_discount * 100) as integer) as disc_pct, p_type, n_name as nation, price_class, p_size,
       cast(floor((price_class + floor(ship_month * 50 / 83)) / 2) as integer) as corr_class
from (select *, cast((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 as integer) as ship_month,
             least(49, cast(floor(50 * ((-0.1 + sqrt(0.01 + 3.6 * ((l_extendedprice - 900) / 104100))) / 1.8)) as integer)) as price_class from lineitem)
join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join part on l_partkey = p_partkey)""",
    "orders_view": """orders_view as materialized (
select md5(cast(o_orderkey as varchar)) as row_key, cast(date_diff('day', date '1970-01-01', cast(o_orderdate as date)) as integer) as order_day, cast(round(o_totalprice * 100) as bigint) as price_cents, n_name as nation, o_orderpriority
from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey)""",
    "customer_view": """customer_view as materialized (
select md5(cast(c_custkey as varchar)) as row_key, cast(round(c_acctbal * 100) as bigint) as balance_cents, n_name as nation, c_mktsegment from customer join nation on c_nationkey = n_nationkey)""",
    "events_view": """events_view as materialized (
select md5(cast(event_id as varchar)) as row_key, event_id, ts, user_id, cast(hour(ts) as integer) as hour, cast(day(ts) as integer) as day, cast(json_extract_string(props, '$.k') as integer) as k,
       cast(floor(value / 10) as integer) as value_band, event_type, value from events)""",
    "docs_view": """docs_view as materialized (
select md5(cast(doc_id as varchar)) as row_key, n_chars, source, lang, quality, toxic
from documents left join (select doc_id, max(quality) as quality, max(toxic) as toxic from labels group by doc_id) using (doc_id))""",
    "vector_view": """vector_view as materialized (
select md5(cast(vec_id as varchar)) as row_key, cast(floor(cast(embedding[1] as double) * 1000) as integer) as v1, cast(floor(cast(embedding[2] as double) * 1000) as integer) as v2,
       cast(floor(cast(embedding[3] as double) * 1000) as integer) as v3, cast(floor(cast(embedding[4] as double) * 1000) as integer) as v4, label from embeddings)""",
    "talk_view": """talk_view as materialized (
select md5(concat_ws('|', conv_id, turn)) as row_key, turn, cast(length(text) as integer) as text_length, role from conversations)""",
}
_OF_SPEC = {"row_key": "census"}


def quoted(values) -> str:
    return "[" + ", ".join("'" + str(v).replace("'", "''") + "'" for v in values) + "]"


def view_of(spec: ReleaseSpec) -> str:
    names = {a.name for a in spec.qi}
    for name, known in (("census", views.CENSUS), ("orders_view", views.ORDERS), ("customer_view", views.CUSTOMERS), ("events_view", views.EVENTS), ("docs_view", views.DOCS), ("talk_view", views.TALK), ("vector_view", views.vector_spec(4))):
        if names <= {a.name for a in known.qi}:
            return name
    raise KeyError(spec)


def encoded(spec: ReleaseSpec, where: str = "") -> str:
    axes = ", ".join((f"cast(list_position({quoted(a.hierarchy.leaves)}, {a.name}) - 1 as integer)" if a.kind == CATEGORICAL else a.name) + f" as {x}" for a, x in zip(spec.qi, spec.axes, strict=True))
    return f"enc as materialized (select row_key, {axes}, {spec.sa} as sa from {view_of(spec)} {where})"


def cap(p: str, beta: float, kind: str = "capped") -> str:
    gain = {"basic": f"{beta}", "capped": f"least({beta}, -ln({p}))", "log2": f"least({beta}, -log2({p}))", "sqrt": f"least({beta}, 1 / sqrt({p}) - 1)"}[kind]
    return f"({p} * (1 + cast({gain} as double)))"


DIST = "d as materialized (select sa, n, n / sum(n) over () as p, row_number() over (order by n, sa) as r from (select sa, count(*) as n from enc group by sa))"


def plan(beta: float, kind: str = "capped", slack: float = 0.0) -> str:
    may = f"b = e + 1 or list_sum(ns[b:e + 1]) <= {cap('ps[b]', beta, kind)} * total * (1 - {slack}) + 1e-12 * total"
    return f"""dl as materialized (select list(n order by r) as ns, list(p order by r) as ps, cast(sum(n) as bigint) as total, cast(count(*) as integer) as m from d),
dp(e, fewest, cut) as (
    select 0, [0], cast([] as integer[])
    union all
    select e + 1, list_append(fewest, best + 1), list_append(cut, cast(e + 2 - list_position(list_reverse(fewest[first:e + 1]), best) as integer))
    from (select *, list_min(fewest[first:e + 1]) as best
          from (select e, fewest, cut, list_min(list_filter(range(1, e + 2), lambda b: {may})) as first from dp, dl where e < m))),
cuts as materialized (select cut from dp where e = (select m from dl)),
seg(b, e) as (select cut[m], m from cuts, dl union all select cut[b - 1], b - 1 from seg, cuts where b > 1),
bk as materialized (select cast(row_number() over (order by b) - 1 as integer) as bucket, b, e, cast(list_sum(ns[b:e]) as bigint) as bn, ps[b] as p_min, {cap('ps[b]', beta, kind)} as cap from seg, dl),
plan as materialized (select sa, n, p, r, bucket, bn, p_min, cap from d join bk on r between b and e)"""


GAIN_ADMIT = "list_sum({0}) > 0 and list_bool_and(list_transform(range(1, len({0}) + 1), lambda i: {0}[i] <= caps[i] * list_sum({0}) + 1e-12 * list_sum({0})))"


def tree(admit: str = GAIN_ADMIT, carried: str = "caps", sizes: str = "list(cap order by bucket) as caps") -> str:
    """Halving from the vector of all bucket sizes; the rule sees the carried lists."""
    split = f"({admit.format('l')}) and ({admit.format('h')})"
    halves = "list_transform(c, lambda x: x // 2) as l, list_transform(c, lambda x: x - x // 2) as h"
    return f"""sz as materialized (select list(bn order by bucket) as sizes, {sizes} from bk),
tree(path, c, split) as (
    select path, c, {split} from (select '' as path, sizes as c, {carried}, list_transform(sizes, lambda x: x // 2) as l, list_transform(sizes, lambda x: x - x // 2) as h from sz)
    union all
    select path, c, {split} from (select path, c, {carried}, {halves} from (
        select path || side as path, case when side = '0' then list_transform(c, lambda x: x // 2) else list_transform(c, lambda x: x - x // 2) end as c, {carried}
        from tree, sz, (values ('0'), ('1')) as s(side) where split))),
leaves as materialized (select cast(row_number() over (order by path) - 1 as bigint) as ec, path, c from tree where not split),
runs as materialized (select ec, cast(j - 1 as integer) as bucket, cnt, cast(sum(cnt) over (partition by j order by ec) - cnt as bigint) as off
         from (select ec, unnest(range(1, len(c) + 1)) as j, unnest(c) as cnt from leaves))"""


def domains(spec: ReleaseSpec) -> str:
    cols = []
    for a, x in zip(spec.qi, spec.axes, strict=True):
        lo, hi = ("0", str(len(a.hierarchy.leaves) - 1)) if a.kind == CATEGORICAL else (f"min({x})", f"max({x})")
        cols += [f"{lo} as {x}_l", f"{hi} as {x}_h"]
    return f"dom as materialized (select {', '.join(cols)} from enc)"


def keyed(spec: ReleaseSpec, curve: str = "zorder") -> str:
    d = len(spec.qi)
    card = ", ".join(f"{x}_h - {x}_l + 1" for x in spec.axes)
    grid = ", ".join(f"cast(case when {x}_h = {x}_l then 0 else floor(cast({x} - {x}_l as bigint) * ((1 << bits) - 1) / ({x}_h - {x}_l)) end as bigint) as g{i}" for i, x in enumerate(spec.axes))
    bits = f"bw as materialized (select *, cast(greatest(1, least(62 // {d}, greatest(1, ceil(log2(greatest(2, {card})))))) as integer) as bits from dom)"
    if curve == "hilbert":
        return f"{bits},\n{hilbert(spec, grid)}"
    if curve == "zorder":
        key = "cast(list_sum(list_transform(range(bits), lambda b: " + " + ".join(f"(((g{i} >> b) & 1) << (b * {d} + {d - 1 - i}))" for i in range(d)) + ")) as bigint)"
    else:
        key = " + ".join(f"(g{i} << cast(bits * {d - 1 - i} as bigint))" for i in range(d))
    return f"""{bits},
kd as materialized (select row_key, {', '.join(spec.axes)}, sa, {key} as key from (select enc.*, bits, {grid} from enc, bw))"""


def hilbert(spec: ReleaseSpec, grid: str) -> str:
    """kd: rows with their Hilbert keys, by folding over the bits of each occupied grid point."""
    d, one = len(spec.qi), "cast(1 as bigint)"
    cells = ", ".join(f"g{i}" for i in range(d))
    steps = f"flatten(list_transform(range(bits - 1, 0, -1), lambda b: [{', '.join(f'[{one} << b, {i}]' for i in range(d))}]))"
    high, low, swap = "(s[e[2] + 1] & e[1]) <> 0", "(e[1] - 1)", "(xor(s[1], s[e[2] + 1]) & (e[1] - 1))"
    new = [f"case when {high} then xor(s[1], {low}) else xor(s[1], {swap}) end"]
    new += [f"case when e[2] = {j} and not ({high}) then xor(s[{j + 1}], {swap}) else s[{j + 1}] end" for j in range(1, d)]
    gray = ["hx[1]"]
    for i in range(1, d):
        gray.append(f"xor({gray[-1]}, hx[{i + 1}])")
    turned = " + ".join(f"(((xor(hy[{i + 1}], ht) >> b) & 1) << cast(b * {d} + {d - 1 - i} as bigint))" for i in range(d))
    return f"""gr as materialized (select enc.*, bits, {grid} from enc, bw),
hc as materialized (select *, list_reduce({steps}, lambda s, e: [{', '.join(new)}], [{cells}]) as hx from (select distinct bits, {cells} from gr)),
hd as materialized (select *, [{', '.join(gray)}] as hy from hc),
he as materialized (select *, list_reduce(list_transform(range(bits - 1, 0, -1), lambda b: case when (hy[{d}] >> b) & 1 = 1 then ({one} << b) - 1 else cast(0 as bigint) end), lambda a, v: xor(a, v), cast(0 as bigint)) as ht from hd),
kd as materialized (select row_key, {', '.join(spec.axes)}, sa, key from gr join (select {cells}, cast(list_sum(list_transform(range(bits), lambda b: {turned})) as bigint) as key from he) using ({cells}))"""


def dealt(spec: ReleaseSpec, draw: str = "rank") -> str:
    axes = ", ".join(spec.axes)
    ranks = f"rk as materialized (select row_key, {axes}, kd.sa, bucket, key, row_number() over (partition by bucket order by key, row_key) - 1 as rank from kd join plan on kd.sa is not distinct from plan.sa)"
    if draw == "curve":
        return f"{ranks},\n{greedy(axes)}"
    return f"""{ranks},
dealt as materialized (select row_key, {axes}, sa, rk.bucket, rank, ec from rk asof join (select * from runs where cnt > 0) as u on rk.bucket = u.bucket and rank >= off)"""


def share(what: str) -> str:
    """The uniform that belongs to the group `now`."""
    return f"(cast('0x' || substr(md5('1|{what}|' || now), 1, 13) as bigint) / 4503599627370496)"


def greedy(axes: str) -> str:
    """dealt: one group after the other, in the order of their hashes, takes from every bucket the run nearest to a row drawn by hash."""
    each = "list_transform(range(1, len(ks) + 1), lambda j: {0})"
    start = """least(greatest(0, ps[j] - need[j]), len(ks[j]) - need[j]) + coalesce(nullif(list_position(list_transform(range(least(greatest(0, ps[j] - need[j]), len(ks[j]) - need[j]), least(ps[j], len(ks[j]) - need[j])), lambda i: abs(ks[j][i + need[j] + 1] - x) >= abs(ks[j][i + 1] - x)), true), 0) - 1,
        greatest(0, least(ps[j], len(ks[j]) - need[j]) - least(greatest(0, ps[j] - need[j]), len(ks[j]) - need[j])))"""
    cut = "list_concat({0}[j][1:st[j]], {0}[j][st[j] + need[j] + 1:])"
    return f"""rn as materialized (select *, row_number() over (order by bucket, rank) as rid from rk),
lots as materialized (select list(ec order by md5('1|group|' || ec)) as ecs, list(c order by md5('1|group|' || ec)) as cs from leaves),
gd(step, now, ks, rs, took) as (
    select 0::bigint, cast(null as bigint), ks, rs, cast([] as bigint[]) from (select list(keys order by bucket) as ks, list(ids order by bucket) as rs from (select bucket, list(key order by rank) as keys, list(rid order by rank) as ids from rn group by bucket))
    union all
    select step + 1, now, {each.format(cut.format('ks'))}, {each.format(cut.format('rs'))}, flatten({each.format('rs[j][st[j] + 1:st[j] + need[j]]')})
    from (select *, {each.format(start)} as st
        from (select *, {each.format('len(list_filter(ks[j], lambda v: v < x))')} as ps
            from (select *, ks[own][1 + cast(floor({share('row')} * len(ks[own])) as bigint)] as x
                from (select *, drawn[1 + cast(floor({share('bucket')} * len(drawn)) as bigint)] as own
                    from (select step, ks, rs, ecs[step + 1] as now, cs[step + 1] as need, list_filter(range(1, len(ks) + 1), lambda j: cs[step + 1][j] > 0) as drawn from gd, lots where step < len(ecs))))))),
dealt as materialized (select row_key, {axes}, sa, bucket, rank, ec from rn join (select now as ec, unnest(took) as rid from gd where step > 0) using (rid))"""


def boxes(spec: ReleaseSpec) -> str:
    return f"bx as materialized (select ec, count(*) as size, {', '.join(f'min({x}) as {x}_lo, max({x}) as {x}_hi' for x in spec.axes)} from dealt group by ec)"


def losses(spec: ReleaseSpec) -> str:
    parts = []
    for i, (a, x) in enumerate(zip(spec.qi, spec.axes, strict=True)):
        if a.kind == CATEGORICAL:
            nodes = ", ".join(f"({n.lo}, {n.hi})" for n in a.hierarchy.nodes)
            parts.append(f"(select case when min(b - a + 1) = 1 then 0.0::double else min(b - a + 1) / {float(len(a.hierarchy.leaves))}::double end from (values {nodes}) as t(a, b) where a <= {x}_lo and b >= {x}_hi) as loss{i + 1}")
        else:
            parts.append(f"case when {x}_h = {x}_l then 0.0::double else ({x}_hi - {x}_lo) / cast({x}_h - {x}_l as double) end as loss{i + 1}")
    total = " + ".join(f"loss{i + 1} * {w!r}::double" for i, w in enumerate(spec.weights))
    return f"ls as materialized (select *, {total} as loss from (select bx.*, {', '.join(parts)} from bx, dom))"


HIST = "hg as materialized (select ec, sa, n, size, n / size as q from (select ec, sa, n, cast(sum(n) over (partition by ec) as bigint) as size from (select ec, sa, count(*) as n from dealt group by ec, sa))), hp as materialized (select hg.*, d.p from hg join d on hg.sa is not distinct from d.sa)"
DENSE = "dn as materialized (select g.ec, d.sa, d.p, coalesce(hg.n, 0) as n, g.size, coalesce(hg.n, 0) / g.size as q from (select distinct ec, size from hg) as g cross join d left join hg on hg.ec = g.ec and hg.sa is not distinct from d.sa)"


def chain(spec: ReleaseSpec = views.CENSUS3, beta: float = 4.0, kind: str = "capped", slack: float = 0.0, upto: str = "losses", curve: str | None = None, draw: str = "rank", where: str = "", buckets: str | None = None, halving: str | None = None, before: str = "") -> str:
    """WITH clause up to a stage: view, enc, dist, plan, tree, dealt, hist, dense or losses. buckets and halving replace the plan's and the tree's part; before comes first."""
    curve = curve or {"rank": "zorder", "curve": "hilbert"}[draw]
    parts = [*([before] if before else []), VIEWS[view_of(spec)], encoded(spec, where)]
    steps = [("enc", []), ("dist", [DIST]), ("plan", [buckets or plan(beta, kind, slack)]), ("tree", [halving or tree()]), ("key", [domains(spec), keyed(spec, curve)]), ("dealt", [dealt(spec, draw)]), ("hist", [HIST]), ("dense", [DENSE]), ("boxes", [boxes(spec)]), ("losses", [losses(spec)])]
    for name, some in steps:
        parts += some
        if name == upto:
            break
    return "with recursive " + ",\n".join(parts) + "\n"
