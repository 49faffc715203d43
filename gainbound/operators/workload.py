"""Workloads of COUNT queries with range predicates, and their exact answers.

A query has `width` ranges over distinct quasi-identifiers and one over the sensitive column; with
selectivity theta each range takes theta ** (1 / (width + 1)) of its domain. Everything is drawn by hashes
of the seed and the query's number, so a workload is a function of its parameters.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gainbound.operators import meet


def _uniform(*parts) -> Column:
    digest = F.md5(F.concat_ws("|", *[p if isinstance(p, Column) else F.lit(str(p)) for p in parts]))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") / float(1 << 52)


def workload(spark: SparkSession, domains: list[tuple[int, int]], sa_domain: tuple[int, int], width: int, theta: float, n: int, seed: int = 7) -> DataFrame:
    """qid, attrs (array of (axis, lo, hi), axes counted from 1), sa_lo, sa_hi."""
    if not 1 <= width <= len(domains):
        raise ValueError("a query has between one and as many ranges as there are attributes")
    share = theta ** (1 / (width + 1))

    def ranged(name, lo: int, hi: int) -> tuple[Column, Column]:
        length = max(1, int(share * (hi - lo + 1) + 0.5))
        start = (F.floor(_uniform(seed, F.col("qid"), name) * (hi - lo + 2 - length)) + lo).cast("long")
        return start, start + (length - 1)

    axes = F.array(*[F.struct(F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("qid"), F.lit(f"order{i + 1}"))).alias("o"), F.lit(i + 1).alias("axis"), ranged(i + 1, lo, hi)[0].alias("lo"), ranged(i + 1, lo, hi)[1].alias("hi")) for i, (lo, hi) in enumerate(domains)])
    chosen = F.slice(F.array_sort(axes), 1, width)
    sa = ranged("sa", *sa_domain)
    return spark.range(n).withColumnRenamed("id", "qid").select("qid", F.transform(chosen, lambda a: F.struct(a["axis"].alias("axis"), a["lo"].alias("lo"), a["hi"].alias("hi"))).alias("attrs"), sa[0].alias("sa_lo"), sa[1].alias("sa_hi"))


@dataclass
class Draws:
    """What the hashes say about each query, whatever its settings: its number, a share of [0, 1) for each axis and, last, the sensitive column, and each axis's hash, by which axes are chosen."""

    qid: np.ndarray
    shares: np.ndarray
    order: np.ndarray


def draws(spark: SparkSession, n_axes: int, n: int, seed: int = 7) -> Draws:
    """The draws of n queries over n_axes axes, in one job, of which `asked` makes the workloads of any number of settings."""
    if n > meet.MAX_QUERIES:
        raise ValueError(f"a workload has more than {meet.MAX_QUERIES} queries; ask it in parts")
    names = [*range(1, n_axes + 1), "sa"]
    hashes = [F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("id"), F.lit(f"order{i}"))) for i in range(1, n_axes + 1)]
    rows = spark.range(n).select("id", *(_uniform(seed, F.col("id"), x).alias(f"u{x}") for x in names), *(h.alias(f"o{i}") for i, h in enumerate(hashes))).toArrow()
    c = [rows.column(i).to_numpy() for i in range(rows.num_columns)]
    return Draws(c[0], np.array(c[1 : 2 + n_axes]), np.array(c[2 + n_axes :]).astype(str))


def asked(drawn: Draws, domains: list[tuple[int, int]], sa_domain: tuple[int, int], width: int, theta: float) -> meet.Asked:
    """The queries of `workload`, as `wide` puts them, over the first of the drawn axes."""
    if not 1 <= width <= len(domains):
        raise ValueError("a query has between one and as many ranges as there are attributes")
    share = theta ** (1 / (width + 1))
    # equal hashes go by the axis's number
    place = np.argsort(np.argsort(drawn.order[: len(domains)], axis=0, kind="stable"), axis=0)
    ends = []
    for u, (lo, hi) in zip((*drawn.shares[: len(domains)], drawn.shares[-1]), (*domains, sa_domain), strict=True):
        length = max(1, int(share * (hi - lo + 1) + 0.5))
        start = np.floor(u * (hi - lo + 2 - length)).astype(np.int64) + lo
        ends.append((start, start + (length - 1)))
    low, high = (np.array([np.where(at < width, end[k], span[k]) for at, end, span in zip(place, ends[:-1], domains, strict=True)]) for k in (0, 1))
    return meet.Asked(drawn.qid, low, high, *ends[-1])


def wide(queries: DataFrame, axes: list[str], domains: list[tuple[int, int]]) -> DataFrame:
    """One row per query with an interval for every axis; an axis without a range has its whole domain."""
    def ranges_of(axis: int) -> Column:
        return F.filter("attrs", lambda a: a["axis"] == axis)

    cols = []
    for i, (x, (lo, hi)) in enumerate(zip(axes, domains, strict=True)):
        own = ranges_of(i + 1)
        cols += [F.coalesce(F.get(own, F.lit(0))["lo"], F.lit(lo).cast("long")).alias(f"{x}_a"), F.coalesce(F.get(own, F.lit(0))["hi"], F.lit(hi).cast("long")).alias(f"{x}_b")]
    return queries.select("qid", *cols, "sa_lo", "sa_hi")


def cube(encoded: DataFrame, axes: list[str]) -> DataFrame:
    """Rows of equal coordinates and sensitive value as one cell with its count."""
    return encoded.groupBy(*axes, "sa").agg(F.count("*").alias("n"))


def exact(queries: DataFrame, cells: DataFrame, axes: list[str]) -> DataFrame:
    """qid and prec, the number of rows in the ranges. The workload is a stated query set of checked size and goes to all cells."""
    hits = meet.range_sums(cells, axes, meet.asked(queries, axes), lambda sa, n: [(n.astype(float), True)], lambda found, q: found[0])
    return queries.select("qid").join(hits, "qid", "left").select("qid", F.coalesce(F.round("v").cast("long"), F.lit(0)).alias("prec"))


def relative_errors(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """qid, prec, est and rel_error (a share) of the queries whose answer isn't zero."""
    return truth.join(answers, "qid", "left").where("prec > 0").select("qid", "prec", F.coalesce("est", F.lit(0.0)).alias("est")).withColumn("rel_error", F.abs(F.col("est") - F.col("prec")) / F.col("prec"))


def median_error(errors: DataFrame, at_scale: bool = False) -> DataFrame:
    """Median of the relative errors and the number of queries; an approximate median for very many."""
    mid = F.percentile_approx("rel_error", 0.5, 10_000) if at_scale else F.median("rel_error")
    return errors.agg(mid.alias("median_error"), F.count("*").alias("n_queries"))

