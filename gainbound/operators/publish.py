"""What leaves the house: boxes in place of quasi-identifiers, exact sensitive values, no key, in an order that tells nothing."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gainbound.operators.loss import boxes
from gainbound.plans.spec import CATEGORICAL, ReleaseSpec


def covering(box: DataFrame, spec: ReleaseSpec) -> DataFrame:
    """Boxes in which a categorical axis's interval is that of the smallest hierarchy node that covers it."""
    for a, x in zip(spec.qi, spec.axes, strict=True):
        if a.kind == CATEGORICAL:
            nodes = a.hierarchy.nodes
            lo, hi = F.col(f"{x}_lo"), F.col(f"{x}_hi")
            best = F.array_min(F.array(*[F.when((lo >= n.lo) & (hi <= n.hi), F.struct(F.lit(n.hi - n.lo), F.lit(n.lo).alias("lo"), F.lit(n.hi).alias("hi"))) for n in nodes]))
            box = box.withColumn("_node", best).withColumn(f"{x}_lo", F.col("_node.lo")).withColumn(f"{x}_hi", F.col("_node.hi")).drop("_node")
    return box


def render(spec: ReleaseSpec, i: int) -> Column:
    """Text of an axis's interval: the node's name, or [lo, hi]."""
    a, x = spec.qi[i], spec.axes[i]
    lo, hi = F.col(f"{x}_lo"), F.col(f"{x}_hi")
    return a.hierarchy.label(lo, hi) if a.kind == CATEGORICAL else F.concat(F.lit("["), lo.cast("string"), F.lit(", "), hi.cast("string"), F.lit("]"))


def generalised(rows: DataFrame, spec: ReleaseSpec, secret: str = "") -> DataFrame:
    """One row per individual: ec, the box as text, and sa, ordered within the group by a keyed hash."""
    box = boxes(rows, spec)
    shown = box.select("ec", *(render(spec, i).alias(a.name) for i, a in enumerate(spec.qi)))
    order = F.md5(F.concat(F.lit(secret), F.col("row_key")))
    return rows.select("ec", "sa", order.alias("_o")).join(shown, "ec").sortWithinPartitions("ec", "_o").select("ec", *(a.name for a in spec.qi), F.col("sa").alias(spec.sa))


def counts(rows: DataFrame, spec: ReleaseSpec) -> DataFrame:
    """The release in long form: ec, covering box, sa and n."""
    box = covering(boxes(rows, spec), spec).drop("size")
    return rows.groupBy("ec", "sa").agg(F.count("*").alias("n")).join(box, "ec")


def covered(pairs: DataFrame, spec: ReleaseSpec) -> DataFrame:
    """The same from counts by group and value with their bounds (ec, sa, n, x1_lo, x1_hi, ...)."""
    box = pairs.groupBy("ec").agg(*(f(f"{x}_{k}").alias(f"{x}_{k}") for x in spec.axes for f, k in ((F.min, "lo"), (F.max, "hi"))))
    return pairs.groupBy("ec", "sa").agg(F.sum("n").alias("n")).join(covering(box, spec), "ec")


def listed(pairs: DataFrame, spec: ReleaseSpec) -> DataFrame:
    """The same with a row for each group: its covering box, and its counts as lists (sas, ns) with an entry for each row that it has in pairs."""
    bounds = [f(f"{x}_{k}").cast("long").alias(f"{x}_{k}") for x in spec.axes for f, k in ((F.min, "lo"), (F.max, "hi"))]
    return covering(pairs.groupBy("ec").agg(F.collect_list(F.col("sa").cast("long")).alias("sas"), F.collect_list(F.col("n").cast("double")).alias("ns"), *bounds), spec)


class ReleaseOnce:
    """Refuses a second release of the same source and version: two releases of the same rows can be intersected."""

    def __init__(self):
        self._seen: set[tuple[str, str]] = set()

    def claim(self, source: str, version: str, force: bool = False) -> None:
        if (source, version) in self._seen and not force:
            raise PermissionError(f"{source} {version} was released before")
        self._seen.add((source, version))
