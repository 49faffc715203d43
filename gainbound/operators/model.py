"""The sensitive column's distribution, groups' histograms, and audits of a grouped table.

A grouped table has a row per individual with its group's number (`ec`) and sensitive value; most
functions take its long histogram (ec, sa, n) instead, which is far smaller and is built once.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gainbound.functions.bounds import EPS, cap_expr, gain_expr, sign_expr
from gainbound.operators.settle import settle

#: Largest domain of a sensitive column that is planned on the driver.
MAX_DOMAIN = 100_000


def sa_distribution(df: DataFrame, sa: str) -> DataFrame:
    """sa, n, p and rank (ascending by count, then value)."""
    counts = df.groupBy(F.col(sa).alias("sa")).agg(F.count("*").alias("n"))
    # the window runs over one row for each value, not over the table
    return counts.select("sa", "n", (F.col("n") / F.sum("n").over(Window.partitionBy())).alias("p"), (F.row_number().over(Window.orderBy(F.col("n"), F.col("sa").asc_nulls_last())) - 1).alias("rank"))


def domain(df: DataFrame, sa: str) -> list[tuple]:
    """(value, count) of each value, on the driver; a column with too many values isn't categorical."""
    rows = df.groupBy(F.col(sa).alias("sa")).count().limit(MAX_DOMAIN + 1).collect()
    if len(rows) > MAX_DOMAIN:
        raise ValueError(f"{sa} has more than {MAX_DOMAIN} values; discretise it")
    if not rows:
        raise ValueError("the table is empty")
    return [(r[0], r[1]) for r in rows]


def prior_frame(spark, counts: list[tuple], kind: str) -> DataFrame:
    """(sa, prior_n, p) of a domain, small enough to broadcast."""
    total = sum(n for _, n in counts)
    return spark.createDataFrame([(v, n, n / total) for v, n in counts], f"sa {kind}, prior_n long, p double")


def histogram(rows: DataFrame, sa: str, ec: str = "ec") -> DataFrame:
    """ec, sa, n, size (of the group) and q."""
    counts = rows.groupBy(F.col(ec).alias("ec"), F.col(sa).alias("sa")).agg(F.count("*").alias("n"))
    return with_sizes(counts)


def with_sizes(counts: DataFrame) -> DataFrame:
    size = F.sum("n").over(Window.partitionBy("ec"))
    return counts.withColumn("size", size).withColumn("q", F.col("n") / F.col("size"))


def prior_of(hist: DataFrame) -> DataFrame:
    """The overall distribution that a histogram adds up to: sa, prior_n, p."""
    counts = hist.groupBy("sa").agg(F.sum("n").alias("prior_n"))
    return counts.withColumn("p", F.col("prior_n") / F.sum("prior_n").over(Window.partitionBy()))


def dense(hist: DataFrame, prior: DataFrame) -> DataFrame:
    """One row for each group and value of the domain, absent ones with n = 0. prior: one row for each value, so the cross product is groups x domain."""
    groups = hist.select("ec", "size").distinct()
    values = F.broadcast(prior.select(F.col("sa").alias("_v"), "p"))
    have = hist.select(F.col("ec").alias("_e"), F.col("sa").alias("_s"), "n")
    full = groups.crossJoin(values).join(have, (F.col("ec") == F.col("_e")) & F.col("_v").eqNullSafe(F.col("_s")), "left")
    n = F.coalesce("n", F.lit(0))
    return full.select("ec", F.col("_v").alias("sa"), n.alias("n"), "size", (n / F.col("size")).alias("q"), "p")


def joined(hist: DataFrame, prior: DataFrame) -> DataFrame:
    """The histogram with each value's overall frequency p."""
    right = prior.select(F.col("sa").alias("_sa"), "p")
    return hist.join(F.broadcast(right), hist["sa"].eqNullSafe(F.col("_sa"))).drop("_sa")


def gains(hist: DataFrame, prior: DataFrame) -> DataFrame:
    """Each group and value with the gains of all kinds and the sign."""
    p, q = F.col("p"), F.col("q")
    return joined(hist, prior).select("ec", "sa", "n", "q", "p", *(gain_expr(p, q, k).alias(k) for k in ("relative", "absolute", "ratio", "logratio")), sign_expr(p, q).alias("sign"))


def audit(hist: DataFrame, prior: DataFrame, beta: float, kind: str = "capped") -> DataFrame:
    """Per group: size, number of values, largest frequency relative to its cap, largest gain, and whether it keeps the bound."""
    p, q = F.col("p"), F.col("q")
    rows = joined(hist, prior)
    return rows.groupBy("ec").agg(
        F.max("size").alias("size"), F.count("*").alias("n_values"), F.max(gain_expr(p, q)).alias("max_gain"),
        F.max((q > cap_expr(p, beta, kind) + EPS).cast("int")).alias("violations"),
    ).select("ec", "size", "n_values", F.greatest("max_gain", F.lit(0.0)).alias("max_gain"), (F.col("violations") == 0).alias("ok"))


def achieved(hist: DataFrame, prior: DataFrame) -> DataFrame:
    """One row: the least beta that a release keeps, basic and capped (infinite if some gain exceeds -ln p)."""
    gain = (F.col("q") - F.col("p")) / F.col("p")
    over = F.max(F.when(gain > -F.ln("p") + EPS, 1).otherwise(0))
    return joined(hist, prior).agg(F.greatest(F.max(gain), F.lit(0.0)).alias("achieved_basic"), F.when(over == 1, F.lit(float("inf"))).otherwise(F.greatest(F.max(gain), F.lit(0.0))).alias("achieved_capped"))


def audit_two_sided(hist: DataFrame, prior: DataFrame, beta: float, below: float) -> DataFrame:
    """Per group: whether it also keeps q >= (1 - below) p for every value, absent ones included."""
    rows = dense(hist, prior)
    high = (F.col("q") > cap_expr(F.col("p"), beta) + EPS).cast("int")
    low = (F.col("q") < (1 - below) * F.col("p") - EPS).cast("int")
    return rows.groupBy("ec").agg(F.max("size").alias("size"), F.sum(high).alias("above"), F.sum(low).alias("under")).withColumn("ok", (F.col("above") == 0) & (F.col("under") == 0))


def regroup_values(hist: DataFrame, groups: DataFrame) -> DataFrame:
    """The histogram over groups of values. groups: (sa, family), one row for each value."""
    right = groups.select(F.col("sa").alias("_sa"), "family")
    counts = hist.join(F.broadcast(right), hist["sa"].eqNullSafe(F.col("_sa"))).groupBy("ec", F.col("family").alias("sa")).agg(F.sum("n").alias("n"))
    return with_sizes(counts)


def audit_proximity(hist: DataFrame, prior: DataFrame, beta: float, width: int) -> DataFrame:
    """Per group: the bound for every interval [v, v + width] of an integer sensitive column, taken as one value."""
    near = Window.partitionBy("ec").orderBy("sa").rangeBetween(0, width)
    rows = dense(hist, prior).withColumn("p_near", F.sum("p").over(near)).withColumn("q_near", F.sum("n").over(near) / F.col("size"))
    gain = (F.col("q_near") - F.col("p_near")) / F.col("p_near")
    bad = (F.col("q_near") > cap_expr(F.least("p_near", F.lit(1.0)), beta) + EPS).cast("int")
    return rows.groupBy("ec").agg(F.max("size").alias("size"), F.greatest(F.max(gain), F.lit(0.0)).alias("max_gain"), F.sum(bad).alias("intervals_over")).withColumn("ok", F.col("intervals_over") == 0)


def k_level(hist: DataFrame) -> DataFrame:
    sizes = hist.select("ec", "size").distinct()
    return sizes.agg(F.min("size").alias("k"), F.count("*").alias("groups"), F.avg("size").alias("avg_size"))


def l_level(hist: DataFrame) -> DataFrame:
    """Least and average diversity by frequency (1 / largest q), by distinct values, and by entropy (its exponential)."""
    per = hist.groupBy("ec").agg((1 / F.max("q")).alias("f"), F.count("*").alias("d"), F.exp(-F.sum(F.col("q") * F.ln("q"))).alias("e"))
    return per.agg(*(g(c).alias(f"{long}_{name}") for c, long in (("f", "frequency"), ("d", "distinct"), ("e", "entropy")) for g, name in ((F.min, "min"), (F.avg, "avg"))))


def t_level(hist: DataFrame, prior: DataFrame, ground: str = "ordered", families: DataFrame | None = None) -> DataFrame:
    """Per group: earth mover's distance of its distribution from the overall one.

    ground: `equal` (all values equally apart), `ordered` (steps of the sensitive order), or `hier` (values under
    the same family at half distance; families: (sa, family))."""
    rows = dense(hist, prior).withColumn("d", F.col("q") - F.col("p"))
    if ground == "equal":
        return rows.groupBy("ec").agg((F.sum(F.abs("d")) / 2).alias("emd"))
    if ground == "ordered":
        run = F.sum("d").over(Window.partitionBy("ec").orderBy("sa").rowsBetween(Window.unboundedPreceding, 0))
        return rows.withColumn("run", run).groupBy("ec").agg((F.sum(F.abs("run")) / F.greatest(F.count("*") - 1, F.lit(1))).alias("emd"))
    rows = rows.join(F.broadcast(families), "sa")
    inner = rows.groupBy("ec", "family").agg(F.sum(F.greatest("d", F.lit(0.0))).alias("up"), F.sum(F.greatest(-F.col("d"), F.lit(0.0))).alias("down"))
    within = 0.5 * F.sum(F.least("up", "down"))
    return inner.groupBy("ec").agg((within + F.sum(F.abs(F.col("up") - F.col("down"))) / 2).alias("emd"))


def t_summary(per_group: DataFrame) -> DataFrame:
    return per_group.agg(F.max("emd").alias("t"), F.avg("emd").alias("avg_t"))


def delta_level(hist: DataFrame, prior: DataFrame) -> DataFrame:
    """Per group: largest |ln(q / p)|, infinite where a value is absent."""
    return dense(hist, prior).groupBy("ec").agg(F.max(gain_expr(F.col("p"), F.col("q"), "logratio")).alias("delta"))


def skewness(hist: DataFrame, prior: DataFrame, tiles: int = 10) -> DataFrame:
    """Largest q / p by tile of rarity (1: the rarest values)."""
    tiled = prior.select(F.col("sa").alias("_sa"), "p", F.ntile(tiles).over(Window.orderBy("prior_n", "sa")).alias("tile"))
    rows = hist.join(F.broadcast(tiled), hist["sa"].eqNullSafe(F.col("_sa")))
    return rows.groupBy("tile").agg(F.max(F.col("q") / F.col("p")).alias("max_ratio"), F.countDistinct("sa").alias("n_values"))


def cap_report(prior: DataFrame, beta: float, kind: str = "capped") -> DataFrame:
    """Per value: its cap, which branch of the bound holds, and the least prevalence that means anything at this beta."""
    p = F.col("p")
    return prior.select("sa", "p", cap_expr(p, beta, kind).alias("cap"), F.when(-F.ln(p) < beta, "logarithmic").otherwise("linear").alias("regime"), F.lit(1 / (1 + beta)).alias("least_prevalence"), F.exp(F.lit(-float(beta))).alias("threshold"))


def min_group_sizes(prior: DataFrame, beta: float, kind: str = "capped") -> DataFrame:
    """Per value: rows that any group must have to hold it once."""
    return prior.select("sa", "prior_n", F.ceil(1 / cap_expr(F.col("p"), beta, kind) - EPS).cast("long").alias("min_size"))


def merge_groups(hist: DataFrame, parts: int = 2) -> DataFrame:
    """The histogram after merging each `parts` groups of neighbouring numbers; no gain can rise above the parts' largest."""
    return with_sizes(hist.groupBy(F.floor(F.col("ec") / parts).cast("long").alias("ec"), "sa").agg(F.sum("n").alias("n")))


def repair_by_merging(hist: DataFrame, prior: DataFrame, beta: float, kind: str = "capped", rounds: int = 64) -> tuple[DataFrame, DataFrame]:
    """Merges failing groups with their neighbours along the numbering, doubling blocks, until every group keeps the bound.

    Returns the map (ec, to) of groups and the merged histogram. A block of 2**k neighbours is merged only if a failing group is in it."""
    hist = settle(hist)
    mapping = settle(hist.select("ec").distinct().withColumn("to", F.col("ec")))
    merged = hist
    for k in range(1, rounds):
        bad = settle(audit(merged, prior, beta, kind).where(~F.col("ok")).select("ec"))
        if bad.isEmpty():
            break
        block = F.floor(F.col("to") / (1 << k)).cast("long")
        hit = bad.select(F.floor(F.col("ec") / (1 << k)).cast("long").alias("b")).distinct()
        mapping = settle(mapping.withColumn("b", block).join(hit.withColumn("hit", F.lit(True)), "b", "left").select("ec", F.when(F.col("hit"), F.col("b") * (1 << k)).otherwise(F.col("to")).alias("to")))
        merged = with_sizes(hist.join(mapping, "ec").groupBy(F.col("to").alias("ec"), "sa").agg(F.sum("n").alias("n")))
    return mapping, merged
