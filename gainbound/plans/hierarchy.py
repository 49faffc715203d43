"""Generalisation hierarchies: leaves in pre-order, inner nodes as intervals of leaf positions."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Leaf that stands for null.
MISSING = "⊥"


@dataclass(frozen=True)
class Node:
    node: str
    parent: str | None
    lo: int
    hi: int
    depth: int


@dataclass(frozen=True)
class Hierarchy:
    """tree: a nested tuple (name, children...) whose leaves are strings."""

    attr: str
    tree: tuple

    @cached_property
    def nodes(self) -> list[Node]:
        out: list[Node] = []

        def walk(t, parent, depth, at):
            name, children = (t, ()) if isinstance(t, str) else (t[0], t[1:])
            here = len(out)
            out.append(None)  # type: ignore[arg-type]
            end = at
            for c in children:
                end = walk(c, name, depth + 1, end)
            if not children:
                end = at + 1
            out[here] = Node(name, parent, at, end - 1, depth)
            return end

        walk(self.tree, None, 0, 0)
        return out

    @cached_property
    def leaves(self) -> list[str]:
        return [n.node for n in self.nodes if n.lo == n.hi and not any(m.parent == n.node for m in self.nodes)]

    @property
    def height(self) -> int:
        return max(n.depth for n in self.nodes)

    def position(self, value: Column) -> Column:
        """Pre-order leaf position; a value that is no leaf is an error, null is the leaf for null if there is one."""
        known = F.create_map(*[F.lit(x) for i, leaf in enumerate(self.leaves) for x in (leaf, i)])
        value = F.coalesce(value, F.lit(MISSING))
        return F.coalesce(known[value], F.raise_error(F.concat(F.lit(f"{self.attr} has no leaf "), value)).cast("int"))

    def width(self, lo: Column, hi: Column) -> Column:
        """Number of leaves under the smallest node that covers [lo, hi]."""
        return F.array_min(F.array(*[F.when((lo >= n.lo) & (hi <= n.hi), n.hi - n.lo + 1) for n in self.nodes])).cast("int")

    def label(self, lo: Column, hi: Column) -> Column:
        """Name of that node."""
        best = F.array_min(F.array(*[F.when((lo >= n.lo) & (hi <= n.hi), F.struct(F.lit(n.hi - n.lo + 1), F.lit(-n.depth), F.lit(n.node).alias("node"))) for n in self.nodes]))
        return best["node"]

    def table(self, spark: SparkSession) -> DataFrame:
        rows = [(self.attr, n.node, n.parent, n.lo, n.hi, n.depth) for n in self.nodes]
        return spark.createDataFrame(rows, "attr string, node string, parent string, lo int, hi int, depth int")
