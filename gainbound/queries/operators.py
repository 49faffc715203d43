"""The relational operators around the methods, each on a step of a release, and the streams."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from gainbound.functions import sqlapi
from gainbound.functions.bounds import cap_expr
from gainbound.operators import loss, model, perturb
from gainbound.operators.settle import remove, shared
from gainbound.plans import sizetree
from gainbound.plans.buckets import plan_buckets
from gainbound.queries import chain as sql
from gainbound.queries.chain import chain
from gainbound.queries.experiments import first_by_hash
from gainbound.queries.registry import frame, query, r6
from gainbound.queries.release import BETA, C3, C5, census, grouped, hist_and_prior, planned
from gainbound.sources import tables, views
from gainbound.sources.tables import table
from gainbound.streaming import stream

_V = f"with {sql.VIEWS['census']} "
_E = f"with {sql.VIEWS['events_view']} "


def _events(spark, sf_dir):
    return views.events_view(spark, sf_dir)


@query("scan_all", " union all ".join(f"select '{t}' as name, count(*) as n from {t}" for t in tables.SCHEMAS))
def scan_all(spark, sf_dir):
    out = None
    for t in tables.SCHEMAS:
        one = table(spark, sf_dir, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.union(one)
    return out


def _round_trip(kind: str):
    @query(f"sink_{kind}", _V + "select nation, count(*) as n, sum(ship_month)::bigint as months from census group by nation")
    def run(spark, sf_dir):
        """The view written in another format and read back."""
        path = f"{shared(spark)}/sink-{uuid.uuid4().hex}"
        rows = census(spark, sf_dir).select("ship_month", "nation")
        tables.write(rows, path, kind, ["nation"] if kind == "parquet" else None)
        back = tables.read(spark, path, kind, "ship_month int, nation string" if kind != "parquet" else None)
        result = back.groupBy("nation").agg(F.count("*").alias("n"), F.sum("ship_month").alias("months"))
        kept = frame(spark, [tuple(r) for r in result.collect()], "nation string, n long, months long")  # one row a nation
        remove(spark, path)
        return kept


for _kind in ("parquet", "csv", "json", "orc"):
    _round_trip(_kind)


@query("sink_bucketed", "select c_mktsegment, count(*) as n from customer join orders on o_custkey = c_custkey group by c_mktsegment")
def sink_bucketed(spark, sf_dir):
    """Two tables written in equal buckets of the key, whose join then needs no exchange."""
    names = [f"{t}_{uuid.uuid4().hex}" for t in ("customer", "orders")]
    try:
        for t, key, name in (("customer", "c_custkey", names[0]), ("orders", "o_custkey", names[1])):
            table(spark, sf_dir, t).repartition(8, key).write.bucketBy(8, key).sortBy(key).saveAsTable(name)
        c, o = (spark.table(n) for n in names)
        result = c.join(o.hint("merge"), F.col("c_custkey") == F.col("o_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))
        return frame(spark, [tuple(r) for r in result.collect()], "c_mktsegment string, n long")  # one row a segment
    finally:
        for n in names:
            spark.sql(f"drop table if exists {n}")


@query("deidentify", "select c_mktsegment, round(c_acctbal, 2) as c_acctbal, c_nationkey from customer")
def deidentify(spark, sf_dir):
    return table(spark, sf_dir, "customer").drop("c_custkey", "c_name").select("c_mktsegment", F.round("c_acctbal", 2).alias("c_acctbal"), "c_nationkey")


@query("count_query", _V + "select count(*) as n from census where ship_month between 10 and 40 and disc_pct between 2 and 6 and nation in ('NATION_1', 'NATION_3') and price_class between 5 and 20")
def count_query(spark, sf_dir):
    c = F.col
    return census(spark, sf_dir).where(c("ship_month").between(10, 40) & c("disc_pct").between(2, 6) & c("nation").isin("NATION_1", "NATION_3") & c("price_class").between(5, 20)).agg(F.count("*").alias("n"))


@query("predicate_mix", "select count(*) as n from customer where (c_mktsegment like 'B%' or c_acctbal < 0) and not c_nationkey in (1, 2) and c_nationkey is not distinct from c_nationkey")
def predicate_mix(spark, sf_dir):
    c = F.col
    return table(spark, sf_dir, "customer").where((c("c_mktsegment").like("B%") | (c("c_acctbal") < 0)) & ~c("c_nationkey").isin(1, 2) & c("c_nationkey").eqNullSafe(c("c_nationkey"))).agg(F.count("*").alias("n"))


@query("join_broadcast", chain(upto="dist") + "select sa, count(*) as n, round(any_value(p), 6) as p from enc join d using (sa) group by sa")
def join_broadcast(spark, sf_dir):
    d = planned(spark, sf_dir)
    return d.encoded.join(F.broadcast(model.prior_frame(spark, d.counts, "int")), "sa").groupBy("sa").agg(F.count("*").alias("n"), r6(F.first("p"), "p"))


def _strategy(hint: str):
    @query(f"join_{hint}", "select o_orderstatus, count(*) as n, sum(l_linenumber)::bigint as lines from lineitem join orders on o_orderkey = l_orderkey group by o_orderstatus")
    def run(spark, sf_dir):
        """An equi-join of two large tables by the physical way that the hint names."""
        o = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus")
        rows = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber").join(o.hint(hint), F.col("o_orderkey") == F.col("l_orderkey"))
        return rows.groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum("l_linenumber").alias("lines"))


for _hint in ("merge", "shuffle_hash"):
    _strategy(_hint)


@query("join_boxes", chain(upto="boxes") + "select row_key, dealt.ec, x1_lo, x1_hi, x1 between x1_lo and x1_hi as inside from dealt join bx on bx.ec = dealt.ec")
def join_boxes(spark, sf_dir):
    d, rows = grouped(spark, sf_dir)
    return rows.join(loss.boxes(rows, d.spec), "ec").select("row_key", "ec", "x1_lo", "x1_hi", F.col("x1").between(F.col("x1_lo"), F.col("x1_hi")).alias("inside"))


@query("join_lca", chain(C5, upto="boxes") + ", nd(node, a, b, dep) as (values " + ", ".join(f"('{n.node}', {n.lo}, {n.hi}, {n.depth})" for n in views.NATION.nodes) + ") select ec, first(node order by b - a, -dep) as node from bx join nd on a <= x5_lo and b >= x5_hi group by ec")
def join_lca(spark, sf_dir):
    """The covering node by a range join with the hierarchy's table."""
    d, rows = grouped(spark, sf_dir, C5)
    nodes = F.broadcast(views.NATION.table(spark))
    met = loss.boxes(rows, d.spec).join(nodes, (F.col("lo") <= F.col("x5_lo")) & (F.col("hi") >= F.col("x5_hi")))
    return met.groupBy("ec").agg(F.min_by("node", F.struct(F.col("hi") - F.col("lo"), -F.col("depth"))).alias("node"))


@query("join_rank_run", chain(upto="dealt") + "select ec, bucket, count(*) as n, min(rank) as first, max(rank) as last from dealt group by ec, bucket")
def join_rank_run(spark, sf_dir):
    """Each group is one run of ranks in every bucket."""
    return grouped(spark, sf_dir)[1].groupBy("ec", "bucket").agg(F.count("*").alias("n"), F.min("rank").alias("first"), F.max("rank").alias("last"))


@query("join_overlap", chain(upto="boxes") + "select a.ec as a, b.ec as b from bx a join bx b on a.ec < b.ec and a.x1_lo <= b.x1_hi and b.x1_lo <= a.x1_hi and a.x2_lo <= b.x2_hi and b.x2_lo <= a.x2_hi and a.x3_lo <= b.x3_hi and b.x3_lo <= a.x3_hi and abs(a.ec - b.ec) <= 1")
def join_overlap(spark, sf_dir):
    """Neighbouring groups whose boxes overlap: an equi-join on neighbouring numbers with a range condition on each axis."""
    d, rows = grouped(spark, sf_dir)
    box = loss.boxes(rows, d.spec)
    a = box.select(F.col("ec").alias("a"), (F.col("ec") + 1).alias("b"), *(F.col(f"{x}_{k}").alias(f"a_{x}_{k}") for x in d.spec.axes for k in ("lo", "hi")))
    met = a.join(box.withColumnRenamed("ec", "b"), "b")
    for x in d.spec.axes:
        met = met.where((F.col(f"a_{x}_lo") <= F.col(f"{x}_hi")) & (F.col(f"{x}_lo") <= F.col(f"a_{x}_hi")))
    return met.select("a", "b")


@query("join_dense", chain(upto="dense") + "select count(*) as n, count_if(n = 0)::bigint as absent from dn")
def join_dense(spark, sf_dir):
    return model.dense(*hist_and_prior(spark, sf_dir)).agg(F.count("*").alias("n"), F.count_if(F.col("n") == 0).alias("absent"))


@query("join_absent", chain(upto="dense") + "select ec, sa from dn where n = 0")
def join_absent(spark, sf_dir):
    return model.dense(*hist_and_prior(spark, sf_dir)).where("n = 0").select("ec", "sa")


@query("join_semi", "select c_custkey from customer semi join orders on o_custkey = c_custkey")
def join_semi(spark, sf_dir):
    o = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, sf_dir, "customer").select("c_custkey").join(o, "c_custkey", "left_semi")


@query("join_anti", "select c_custkey from customer anti join (select o_custkey from orders where o_totalprice > 400000) on o_custkey = c_custkey")
def join_anti(spark, sf_dir):
    o = table(spark, sf_dir, "orders").where("o_totalprice > 400000").select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, sf_dir, "customer").select("c_custkey").join(o, "c_custkey", "left_anti")


@query("join_full", "select coalesce(a.user_id, b.user_id) as user_id, coalesce(a.n, 0) as clicks, coalesce(b.n, 0) as errors from (select user_id, count(*) as n from events where event_type = 'click' group by 1) a full join (select user_id, count(*) as n from events where event_type = 'error' group by 1) b on a.user_id = b.user_id")
def join_full(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("user_id", "event_type")
    a, b = (e.where(F.col("event_type") == k).groupBy("user_id").agg(F.count("*").alias(name)) for k, name in (("click", "clicks"), ("error", "errors")))
    return a.join(b, "user_id", "full").select("user_id", F.coalesce("clicks", F.lit(0)).alias("clicks"), F.coalesce("errors", F.lit(0)).alias("errors"))


@query("join_asof", "select e.event_id, p.event_id as prior_id from (select * from events where event_type <> 'signup') e asof left join (select * from events where event_type = 'signup') p on e.user_id = p.user_id and e.ts >= p.ts")
def join_asof(spark, sf_dir):
    """The latest signup before each event of its user: a running last value, without a join."""
    w = Window.partitionBy("user_id").orderBy("ts", F.col("event_type") != "signup").rowsBetween(Window.unboundedPreceding, 0)
    prior = F.last(F.when(F.col("event_type") == "signup", F.col("event_id")), ignorenulls=True).over(w)
    return table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type").withColumn("prior_id", prior).where("event_type <> 'signup'").select("event_id", "prior_id")


@query("join_interval", "select count(*) as n from events a join events b on a.user_id = b.user_id and a.event_type = 'view' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 3600 seconds")
def join_interval(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("user_id", "ts", "event_type")
    return stream.within(e.where("event_type = 'view'"), e.where("event_type = 'purchase'"), "user_id", 3600).agg(F.count("*").alias("n"))


@query("agg_hist", chain(upto="hist") + "select ec, string_agg(sa || ':' || n, ',' order by sa) as hist from hg group by ec")
def agg_hist(spark, sf_dir):
    hist = hist_and_prior(spark, sf_dir)[0]
    return hist.groupBy("ec").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("sa", "n"))), lambda x: F.concat(x["sa"].cast("string"), F.lit(":"), x["n"].cast("string"))), ",").alias("hist"))


@query("agg_distinct", _V + "select nation, count(distinct price_class) as classes, count(distinct ship_month) as months from census group by nation")
def agg_distinct(spark, sf_dir):
    return census(spark, sf_dir).groupBy("nation").agg(F.countDistinct("price_class").alias("classes"), F.countDistinct("ship_month").alias("months"))


@query("agg_conditional", _V + "select nation, count_if(price_class < 10)::bigint as low, sum(case when l_linestatus = 'F' then disc_pct else 0 end)::bigint as disc from census group by nation")
def agg_conditional(spark, sf_dir):
    return census(spark, sf_dir).groupBy("nation").agg(F.count_if(F.col("price_class") < 10).alias("low"), F.sum(F.when(F.col("l_linestatus") == "F", F.col("disc_pct")).otherwise(0)).alias("disc"))


@query("agg_approx")
def agg_approx(spark, sf_dir):
    """Sketches that choose between the cube and the row path."""
    return census(spark, sf_dir).agg(F.approx_count_distinct(F.struct("ship_month", "l_linestatus", "disc_pct")).alias("cells"), F.percentile_approx("ship_month", 0.5, 1000).alias("middle_month"))


@query("agg_grouping_sets", _V + "select nation, l_linestatus, price_class, count(*) as n from census group by grouping sets ((nation, price_class), (l_linestatus, price_class), (price_class))")
def agg_grouping_sets(spark, sf_dir):
    c = F.col
    return census(spark, sf_dir).groupingSets([[c("nation"), c("price_class")], [c("l_linestatus"), c("price_class")], [c("price_class")]], c("nation"), c("l_linestatus"), c("price_class")).agg(F.count("*").alias("n"))


@query("agg_cube", _V + "select l_linestatus, p_type, count(*) as n from census group by cube (l_linestatus, p_type)")
def agg_cube(spark, sf_dir):
    return census(spark, sf_dir).cube("l_linestatus", "p_type").agg(F.count("*").alias("n"))


@query("agg_rollup", _V + "select r_name, nation, count(*) as n from census join nation on n_name = nation join region on r_regionkey = n_regionkey group by rollup (r_name, nation)")
def agg_rollup(spark, sf_dir):
    region = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_name").alias("nation"), "r_name")
    return census(spark, sf_dir).join(region, "nation").rollup("r_name", "nation").agg(F.count("*").alias("n"))


@query("pivot_ec_bucket", chain(upto="dealt") + "select ec, " + ", ".join(f"count_if(bucket = {j})::bigint as b{j}" for j in range(5)) + " from dealt group by ec")
def pivot_ec_bucket(spark, sf_dir):
    rows = grouped(spark, sf_dir)[1]
    return rows.groupBy("ec").pivot("bucket", [0, 1, 2, 3, 4]).count().select("ec", *(F.coalesce(F.col(str(j)), F.lit(0)).alias(f"b{j}") for j in range(5)))


@query("unpivot_qi", chain(upto="enc") + "select axis, value, count(*) as n from (unpivot (select x1, x2, x3 from enc) on x1, x2, x3 into name axis value value) group by 1, 2")
def unpivot_qi(spark, sf_dir):
    rows = planned(spark, sf_dir).encoded.select("x1", "x2", "x3")
    return rows.unpivot([], ["x1", "x2", "x3"], "axis", "value").groupBy("axis", "value").agg(F.count("*").alias("n"))


@query("win_rank", _E + "select value_band, n, cast(rank() over (order by n desc) as integer) as r, cast(dense_rank() over (order by n desc) as integer) as dr, round(percent_rank() over (order by n desc), 6) as pr, round(cume_dist() over (order by n desc), 6) as cd from (select value_band, count(*) as n from events_view group by 1)")
def win_rank(spark, sf_dir):
    w = Window.orderBy(F.desc("n"))  # over one row for each value
    counts = _events(spark, sf_dir).groupBy("value_band").agg(F.count("*").alias("n"))
    return counts.select("value_band", "n", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), r6(F.percent_rank().over(w), "pr"), r6(F.cume_dist().over(w), "cd"))


@query("win_ntile", chain(upto="dist") + "select sa, cast(ntile(5) over (order by n, sa) as integer) as tile from d")
def win_ntile(spark, sf_dir):
    return model.sa_distribution(census(spark, sf_dir), "price_class").select("sa", F.ntile(5).over(Window.orderBy("n", "sa")).alias("tile"))


@query("win_prefix", chain(upto="dist") + "select sa, cast(sum(n) over (order by r) as bigint) as mass from d")
def win_prefix(spark, sf_dir):
    return model.sa_distribution(census(spark, sf_dir), "price_class").select("sa", F.sum("n").over(Window.orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)).alias("mass"))


@query("win_lag", "select event_id, epoch_us(ts) - epoch_us(lag(ts) over (partition by user_id order by ts, event_id)) as gap_us, lead(event_type) over (partition by user_id order by ts, event_id) as next_type from events")
def win_lag(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf_dir, "events").select("event_id", (F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lag("ts").over(w).cast("timestamp"))).alias("gap_us"), F.lead("event_type").over(w).alias("next_type"))


@query("win_range", _V + "select price_class, n, cast(sum(n) over (order by price_class range between 2 preceding and 2 following) as bigint) as near from (select price_class, count(*) as n from census group by 1)")
def win_range(spark, sf_dir):
    counts = census(spark, sf_dir).groupBy("price_class").agg(F.count("*").alias("n"))
    return counts.select("price_class", "n", F.sum("n").over(Window.orderBy("price_class").rangeBetween(-2, 2)).alias("near"))


@query("topk_rare", chain(upto="dist") + "select sa, n from d order by n, sa limit 5")
def topk_rare(spark, sf_dir):
    """A top-k report of the rarest values."""
    return model.sa_distribution(census(spark, sf_dir), "price_class").orderBy("n", "sa").select("sa", "n").limit(5)


@query("argmax_sa", chain(upto="hist") + "select ec, arg_max(sa, (n, -sa)) as sa from hg group by ec")
def argmax_sa(spark, sf_dir):
    return hist_and_prior(spark, sf_dir)[0].groupBy("ec").agg(F.max_by("sa", F.struct("n", -F.col("sa"))).alias("sa"))


@query("set_union", _V + "select 'F' as part, count(*) as n from census where l_linestatus = 'F' union all select 'O', count(*) from census where l_linestatus = 'O'")
def set_union(spark, sf_dir):
    v = census(spark, sf_dir)
    parts = [v.where(F.col("l_linestatus") == s).agg(F.count("*").alias("n")).select(F.lit(s).alias("part"), "n") for s in "FO"]
    return parts[0].unionByName(parts[1])


@query("set_except", "select 0::bigint as lost")
def set_except(spark, sf_dir):
    """The release keeps the multiset of quasi-identifiers and sensitive values."""
    d, rows = grouped(spark, sf_dir)
    return d.encoded.select("x1", "x2", "x3", "sa").exceptAll(rows.select("x1", "x2", "x3", "sa")).agg(F.count("*").alias("lost"))


@query("set_intersect", "select c_nationkey as k from customer intersect select s_nationkey from supplier")
def set_intersect(spark, sf_dir):
    return table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")).intersect(table(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k")))


@query("sample_prefix", _V + "select row_key from census where cast('0x' || substr(md5('sample|' || row_key), 1, 8) as bigint) < 429496729")
def sample_prefix(spark, sf_dir):
    """A sampling operator: a tenth of the rows by hash; larger shares contain smaller ones."""
    return first_by_hash(census(spark, sf_dir), 0.1).select("row_key")


#: Share of each stratum's rows, as the part of 2^32 that a row's hash falls below.
_STRATA = {"F": 429496729, "O": 858993459}


@query("sample_strata", _V + "select row_key, l_linestatus from census where cast('0x' || substr(md5('strata|' || row_key), 1, 8) as bigint) < case l_linestatus " + " ".join(f"when '{k}' then {v}" for k, v in _STRATA.items()) + " end")
def sample_strata(spark, sf_dir):
    """A stratified sample: a share of its own for each line status, drawn by the row's hash, so a retry draws the same rows."""
    lot = F.conv(F.substring(F.md5(F.concat(F.lit("strata|"), F.col("row_key"))), 1, 8), 16, 10).cast("long")
    share = F.create_map(*[F.lit(x) for kv in _STRATA.items() for x in kv])
    return census(spark, sf_dir).where(lot < share[F.col("l_linestatus")]).select("row_key", "l_linestatus")


@query("str_mask", "select c_custkey, left(c_name, 4) || regexp_replace(substr(c_name, 5), '[0-9]', '*', 'g') as masked, upper(left(c_mktsegment, 3)) as seg, lpad(cast(c_nationkey as varchar), 3, '0') as nation, md5('k|' || c_name) as pseudonym from customer")
def str_mask(spark, sf_dir):
    name = F.col("c_name")
    return table(spark, sf_dir, "customer").select("c_custkey", F.concat(F.substring(name, 1, 4), F.regexp_replace(F.expr("substring(c_name, 5)"), "[0-9]", "*")).alias("masked"), F.upper(F.substring("c_mktsegment", 1, 3)).alias("seg"), F.lpad(F.col("c_nationkey").cast("string"), 3, "0").alias("nation"), F.md5(F.concat(F.lit("k|"), name)).alias("pseudonym"))


@query("str_box", chain(upto="boxes") + "select ec, '[' || x1_lo || ', ' || x1_hi || ']' as months from bx")
def str_box(spark, sf_dir):
    from gainbound.operators.publish import render

    d, rows = grouped(spark, sf_dir)
    return loss.boxes(rows, d.spec).select("ec", render(d.spec, 0).alias("months"))


@query("date_parts", "select event_id, year(ts)::integer as y, month(ts)::integer as m, hour(ts)::integer as h, (dayofweek(ts) + 1)::integer as dow, date_diff('day', date '2024-01-01', cast(ts as date))::integer as since, strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') as hour_start from events")
def date_parts(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.year("ts").alias("y"), F.month("ts").alias("m"), F.hour("ts").alias("h"), F.dayofweek("ts").alias("dow"), F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).alias("since"), F.date_format(F.date_trunc("hour", "ts"), "yyyy-MM-dd HH:mm:ss").alias("hour_start"))


@query("math_caps", "select p, round(p * (1 + least(2.0, -ln(p))), 6) as cap, round(exp(-2.0::double), 6) as threshold, round(sqrt(p), 6) as root, round(pow(p, 2), 6) as square, cast(floor(p * 10) as bigint) as tile from (select count(*) / (sum(count(*)) over ())::double as p from lineitem group by l_quantity)")
def math_caps(spark, sf_dir):
    """Caps of the frequencies of the quantities."""
    p = F.col("p")
    found = model.sa_distribution(table(spark, sf_dir, "lineitem"), "l_quantity")
    return found.select("p", r6(cap_expr(p, 2.0), "cap"), r6(F.exp(F.lit(-2.0)), "threshold"), r6(F.sqrt(p), "root"), r6(F.pow(p, F.lit(2)), "square"), F.floor(p * 10).alias("tile"))


@query("arr_gain", chain(upto="dense") + "select ec, round(max(abs(q - p)), 6) as widest, count_if(q > p)::bigint as over from dn group by ec")
def arr_gain(spark, sf_dir):
    """A group's distribution and the overall one as arrays."""
    rows = model.dense(*hist_and_prior(spark, sf_dir)).groupBy("ec").agg(F.array_sort(F.collect_list(F.struct("sa", "q", "p"))).alias("d"))
    diff = F.zip_with(F.transform("d", lambda x: x["q"]), F.transform("d", lambda x: x["p"]), lambda q, p: q - p)
    return rows.select("ec", r6(F.array_max(F.transform(diff, lambda x: F.abs(x))), "widest"), F.aggregate(diff, F.lit(0).cast("long"), lambda a, x: a + F.when(x > 0, 1).otherwise(0)).alias("over"))


@query("map_hist", chain(upto="hist") + "select ec, count(*) as n_keys, coalesce(max(case when sa = 20 then n end), 0) as n_20 from hg group by ec")
def map_hist(spark, sf_dir):
    maps = hist_and_prior(spark, sf_dir)[0].groupBy("ec").agg(F.map_from_entries(F.collect_list(F.struct("sa", "n"))).alias("m"))
    return maps.select("ec", F.size(F.map_keys("m")).cast("long").alias("n_keys"), F.coalesce(F.element_at("m", 20), F.lit(0)).alias("n_20"))


@query("arr_explode", chain(upto="tree") + "select ec, bucket, cnt from runs where cnt > 0")
def arr_explode(spark, sf_dir):
    d = planned(spark, sf_dir)
    leaves = frame(spark, [(i, [int(x) for x in v]) for i, v in enumerate(d.tree.leaf_vectors())], "ec long, c array<long>")
    return leaves.select("ec", F.posexplode("c").alias("bucket", "cnt")).where("cnt > 0")


@query("json_qi", "select event_id, cast(json_extract_string(props, '$.k') as integer) as k from events")
def json_qi(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("null_safe", "select o_orderkey, coalesce(nullif(o_orderstatus, 'P'), '?') as status, case when o_totalprice > 200000 then 'high' else 'low' end as band from orders")
def null_safe(spark, sf_dir):
    return table(spark, sf_dir, "orders").select("o_orderkey", F.coalesce(F.nullif("o_orderstatus", F.lit("P")), F.lit("?")).alias("status"), F.when(F.col("o_totalprice") > 200000, "high").otherwise("low").alias("band"))


_TREE_CTE = """with recursive s as (
select cast(count_if(l_linenumber = 1) as bigint) as a, cast(count_if(l_linenumber in (2, 3)) as bigint) as b, cast(count_if(l_linenumber > 3) as bigint) as c from {0}),
t(path, a, b, c) as (
select '' as path, a, b, c from s
union all
select concat(path, s) as path, cast(case when s = '0' then floor(a / 2) else a - floor(a / 2) end as bigint) as a,
       cast(case when s = '0' then floor(b / 2) else b - floor(b / 2) end as bigint) as b, cast(case when s = '0' then floor(c / 2) else c - floor(c / 2) end as bigint) as c
from t cross join (select '0' as s union all select '1') as sides where length(path) < 2)
select path, a, b, c from t"""


@query("cte_size_tree", _TREE_CTE.format("lineitem"))
def cte_size_tree(spark, sf_dir):
    """Halving of a vector of line counts as a recursive table, in Spark's SQL too."""
    table(spark, sf_dir, "lineitem").createOrReplaceTempView("lineitem_tmp")
    return spark.sql(_TREE_CTE.format("lineitem_tmp"))


@query("sub_exists", "select n_name from nation where exists (select 1 from customer where c_nationkey = n_nationkey and c_acctbal > (select avg(c_acctbal) from customer))")
def sub_exists(spark, sf_dir):
    for t in ("nation", "customer"):
        table(spark, sf_dir, t).createOrReplaceTempView(f"{t}_tmp")
    return spark.sql("select n_name from nation_tmp where exists (select 1 from customer_tmp where c_nationkey = n_nationkey and c_acctbal > (select avg(c_acctbal) from customer_tmp))")


@query("udaf_emd", chain(upto="dense") + "select ec, round(sum(abs(s)) / (count(*) - 1), 6) as emd from (select ec, sum(q - p) over (partition by ec order by sa rows unbounded preceding) as s from dn) group by ec")
def udaf_emd(spark, sf_dir):
    """The ordered distance as an Arrow-backed aggregate, as SQL users call it."""
    return model.dense(*hist_and_prior(spark, sf_dir)).withColumn("d", F.col("q") - F.col("p")).groupBy("ec").agg(r6(sqlapi.emd_ordered("sa", "d"), "emd"))


@query("udf_cap", chain(upto="dist") + f"select sa, round({sql.cap('p', BETA)}, 6) as cap from d")
def udf_cap(spark, sf_dir):
    sqlapi.register(spark)
    model.sa_distribution(census(spark, sf_dir), "price_class").createOrReplaceTempView("sa_tmp")
    return spark.sql(f"select sa, round(gain_cap(p, {BETA}D), 6) as cap from sa_tmp")


@query("map_batches", "select c_custkey, least(4, greatest(0, floor((c_acctbal + 1000) / 2200)))::integer as band from customer")
def map_batches(spark, sf_dir):
    """A user's function over batches of rows: balances to five bands."""

    def bands(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({"c_custkey": b["c_custkey"], "band": ((b["c_acctbal"] + 1000) // 2200).clip(0, 4).astype("int32")})

    return table(spark, sf_dir, "customer").select("c_custkey", "c_acctbal").mapInPandas(bands, "c_custkey long, band int")


@query("udtf_leaves", chain(upto="tree") + "select ec, bucket, cnt from runs")
def udtf_leaves(spark, sf_dir):
    plan = plan_buckets(model.domain(census(spark, sf_dir), "price_class"), BETA)
    return sqlapi.SizeLeaves(F.array(*[F.lit(int(s)) for s in plan.sizes]), F.array(*[F.lit(float(c)) for c in plan.caps]))


@query("str_pages", "select page_id, regexp_extract(url, '^https?://([^/]+)', 1) as host, length(html)::integer as n_html from pages")
def str_pages(spark, sf_dir):
    return table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"), F.length("html").alias("n_html"))


# streams


def _stream(spark, sf_dir):
    return stream.events_stream(spark, f"{sf_dir}/events.parquet")


@query("stream_scan", "select event_type, count(*) as n from events group by event_type")
def stream_scan(spark, sf_dir):
    return stream.drain(_stream(spark, sf_dir).groupBy("event_type").agg(F.count("*").alias("n")), "scan", "complete")


def _windows(name: str, slide: str | None, sql_text: str):
    @query(name, sql_text)
    def run(spark, sf_dir):
        got = stream.drain(stream.window_counts(_stream(spark, sf_dir), "event_type", "1 day", slide), "w", "complete")
        return got.select(F.date_format("begin", "yyyy-MM-dd HH:mm:ss").alias("begin"), "sa", "n")


_windows("stream_tumbling", None, "select strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') as begin, event_type as sa, count(*) as n from events group by 1, 2")
_windows("stream_sliding", "6 hours", "select strftime(b, '%Y-%m-%d %H:%M:%S') as begin, event_type as sa, count(*) as n from (select event_type, unnest([time_bucket(interval '6 hours', ts) - i * interval '6 hours' for i in range(4)]) as b from events) group by 1, 2")


@query("stream_gain_tumbling", """with p as (select event_type as sa, count(*) / sum(count(*)) over () as p from events group by 1), w as (select date_trunc('day', ts) as b, event_type as sa, count(*) as n from events group by 1, 2)
select strftime(b, '%Y-%m-%d %H:%M:%S') as begin, cast(any_value(size) as bigint) as size, round(max((n / size - p) / p), 6) as max_gain from (select *, sum(n) over (partition by b) as size from w) join p using (sa) group by b""")
def stream_gain_tumbling(spark, sf_dir):
    """The privacy monitor: gains of each day's groups over the frozen prior."""
    prior = model.prior_frame(spark, model.domain(table(spark, sf_dir, "events"), "event_type"), "string")
    counts = stream.drain(stream.window_counts(_stream(spark, sf_dir), "event_type"), "g", "complete")
    return stream.window_gains(counts, prior).select(F.date_format("begin", "yyyy-MM-dd HH:mm:ss").alias("begin"), "size", r6("max_gain"))


@query("stream_sessions", """with g as (select user_id, ts, event_id, case when lag(ts) over w is null or ts - lag(ts) over w >= interval '30 minutes' then 1 else 0 end as new from events window w as (partition by user_id order by ts, event_id)),
s as (select *, sum(new) over (partition by user_id order by ts, event_id rows unbounded preceding) as k from g)
select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S.%f') as begin, strftime(max(ts) + interval '30 minutes', '%Y-%m-%d %H:%M:%S.%f') as finish, count(*) as n from s group by user_id, k""")
def stream_sessions(spark, sf_dir):
    got = stream.sessions(table(spark, sf_dir, "events"))
    return got.select("user_id", *(F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS").alias(name) for c, name in (("begin", "begin"), ("end", "finish"))), "n")


@query("stream_late", "select event_id, event_type from events")
def stream_late(spark, sf_dir):
    """Each event once, although it is sent twice."""
    e = _stream(spark, sf_dir)
    twice = e.union(_stream(spark, sf_dir))
    return stream.drain(stream.deduplicated(twice, "40 days").select("event_id", "event_type"), "late")


@query("stream_dropped", """with a as (select date_trunc('milliseconds', max(ts)) - interval '1 day' as mark from events where hour(ts) >= 12)
select count_if(hour(ts) >= 12 or ts > mark)::bigint as kept, count_if(hour(ts) < 12 and ts <= mark)::bigint as dropped from events, a""")
def stream_dropped(spark, sf_dir):
    """Mornings arrive when the stream has seen all afternoons: a second run goes on from the first one's checkpoint and drops what is later than its watermark."""
    folder = f"{shared(spark)}/arrivals-{uuid.uuid4().hex}"
    e, dropped = table(spark, sf_dir, "events"), 0
    for part in (F.hour("ts") >= 12, F.hour("ts") < 12):
        e.where(part).write.mode("append").parquet(f"{folder}/in")
        arriving = stream.deduplicated(stream.events_stream(spark, f"{folder}/in", 1_000), "1 day")
        dropped += stream.to_parquet(arriving.select("event_id"), f"{folder}/out", f"{folder}/log")
    kept = spark.read.schema("event_id long").parquet(f"{folder}/out").count()
    remove(spark, folder)
    return frame(spark, [(kept, dropped)], "kept long, dropped long")


@query("stream_update", "select event_type, count(*) as n from events group by event_type")
def stream_update(spark, sf_dir):
    """Update mode: batches write only the counts that changed, and the newest of each type is read."""
    return stream.drain(_stream(spark, sf_dir).groupBy("event_type").agg(F.count("*").alias("n")), "update", "update", ["event_type"])


@query("stream_randomise", "select count(*) as n, count(*) as same from events")
def stream_randomise(spark, sf_dir):
    """The stream's rows are those of the batch: coins belong to rows."""
    r = perturb.randomiser(model.domain(table(spark, sf_dir, "events"), "event_type"), 2.0)
    rows = views.events_of(_stream(spark, sf_dir)).select("row_key", "event_type")
    got = stream.drain(stream.randomise_stream(rows, "event_type", "row_key", r, "secret"), "r")
    batch = perturb.randomise(views.events_view(spark, sf_dir).select("row_key", "event_type"), "event_type", "row_key", r, "secret")
    return got.join(batch.withColumnRenamed("event_type", "again"), "row_key").agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == F.col("again")).alias("same"))


@query("stream_join", "select event_type, count(*) as n from events group by event_type")
def stream_join(spark, sf_dir):
    prior = model.prior_frame(spark, model.domain(table(spark, sf_dir, "events"), "event_type"), "string")
    got = stream.drain(stream.with_prior(_stream(spark, sf_dir), prior, "event_type").select("event_id", "event_type", "p"), "j")
    return got.groupBy("event_type").agg(F.count("*").alias("n"))


@query("stream_interval_join", "select count(*) as n from events a join events b on a.user_id = b.user_id and a.event_type = 'view' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 3600 seconds")
def stream_interval_join(spark, sf_dir):
    """Two streams joined within an hour of each other."""
    a = _stream(spark, sf_dir).where("event_type = 'view'").select("event_id", "user_id", "ts")
    b = _stream(spark, sf_dir).where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    got = stream.within(a, b, "user_id", 3600, "2 hours").select(F.col("a.event_id").alias("a"), F.col("b.event_id").alias("b"))
    return stream.drain(got, "ij").agg(F.count("*").alias("n"))


@query("stream_deal")
def stream_deal(spark, sf_dir):
    """Groups dealt from a stream by all vectors of a plan, what is left over merged if that keeps the bound, and the number of rows left unpublished."""
    counts = model.domain(_events(spark, sf_dir), "value_band")
    plan = plan_buckets(counts, 5.0)
    tree = sizetree.grow(plan.sizes, sizetree.gain_rule(plan.caps))
    from gainbound.operators.deal import bucket_expr

    rows = views.events_of(_stream(spark, sf_dir)).select(F.lit(0).alias("shard"), bucket_expr(plan.bucket_of, F.col("value_band")).alias("bucket"), "row_key", F.col("value_band").alias("sa"))
    with stream.rocksdb(spark):
        dealt = stream.drain(stream.deal_stream(rows, tree.leaf_vectors()), "deal")
    every = _events(spark, sf_dir).select("row_key", F.col("value_band").alias("sa"))
    merged, left = stream.merge_left(every, dealt, model.prior_frame(spark, counts, "int"), 5.0)
    groups = dealt.select("ec").withColumn("kind", F.lit("dealt")).union(merged.select("ec").withColumn("kind", F.lit("merged")))
    return groups.groupBy("ec", "kind").agg(F.count("*").alias("size")).union(left.agg(F.lit(None).cast("string"), F.lit("left over"), F.count("*"))).select("ec", "size", "kind")


@query("release_composed", _V + "select count(*) as n_rows from census")
def release_composed(spark, sf_dir):
    """Published boxes keep every row."""
    from gainbound.operators.publish import generalised

    d, rows = grouped(spark, sf_dir, C3)
    return generalised(rows, d.spec).agg(F.count("*").alias("n_rows"))
