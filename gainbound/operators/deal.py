"""Bucket-and-deal: from a table to groups that keep the bound.

The plan (buckets and tree of sizes) needs the sensitive column's counts only. Filling it
needs an order of each bucket's rows along a space-filling curve:

* `rank` gives the i-th group the i-th run of every bucket. Ranks are distributed: quantiles of the
  key cut each bucket into blocks, block counts give offsets, and a window ranks within a block, never within a bucket.
  A row then finds its group by walking the tree, so nothing is joined.
* `curve`, `euclid` and `cosplit` cut the rows into shards by the top of the same tree, and fill each shard's
  groups by a greedy or recursive search in one task. A shard that is a leaf already needs no search and gathers nowhere,
  however large it is. Sizes, and so the guarantee, are the same.

What is drawn at random (the order of the groups, and the row that each grows around) comes from hashes of the seed and the
group's number: a retried task draws the same, and so does anyone who repeats the release elsewhere.
"""

from __future__ import annotations

import hashlib
import math
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gainbound.functions.curves import FEW_POINTS, bits_for, curve_expr, grid_expr, keys_of_grid, points_of_grid
from gainbound.operators.model import MAX_DOMAIN
from gainbound.operators.settle import settle
from gainbound.plans import sizetree
from gainbound.plans.buckets import Plan, plan_buckets
from gainbound.plans.spec import CATEGORICAL, ReleaseSpec

#: Rows of a block of the key range in distributed ranking, and the bounds of the number of blocks.
BLOCK_ROWS, MIN_BLOCKS, MAX_BLOCKS = 1 << 17, 16, 4096
#: Most rows that one task searches, along a curve and (quadratically) by true distances.
SHARD_ROWS, EUCLID_ROWS = 1 << 17, 1 << 16
#: Distinct keys of a shard up to which the search along the curve runs on counts by key, and how many of the nearest keys it looks at first.
KEYS, NEAREST = 2048, (8, 64)
#: Grids of at most so many cells get their Hilbert keys cell by cell, and rows look them up.
GRID_CELLS = 1 << 19


def encode(df: DataFrame, spec: ReleaseSpec) -> DataFrame:
    """row_key, the coordinates x1.. and sa; nothing else of the table goes on."""
    axes = [(a.hierarchy.position(F.col(a.name)) if a.kind == CATEGORICAL else F.col(a.name)).alias(x) for a, x in zip(spec.qi, spec.axes, strict=True)]
    return df.select(F.col(spec.key).alias("row_key"), *axes, F.col(spec.sa).alias("sa"))


@dataclass
class Dealing:
    """A planned release: the encoded table, its domains, the plan and the tree."""

    spec: ReleaseSpec
    encoded: DataFrame
    domains: list[tuple[int, int]]
    counts: list[tuple]
    plan: Plan
    tree: sizetree.SizeTree

    @property
    def bits(self) -> int:
        return bits_for([hi - lo + 1 for lo, hi in self.domains])


def bucket_expr(values: dict, sa: Column) -> Column:
    """Bucket of a sensitive value, from a map that is as small as the domain."""
    known = [(v, j) for v, j in values.items() if v is not None]
    out = F.create_map(*[F.lit(x) for v, j in known for x in (v, j)])[sa] if known else F.lit(None).cast("int")
    return F.coalesce(out, F.lit(values[None])) if None in values else out


def survey(encoded: DataFrame, spec: ReleaseSpec) -> tuple[list[tuple], list[tuple[int, int]]]:
    """Counts of the sensitive values and the axes' domains, in one pass. encoded: rows, or cells with their counts n."""
    count = F.sum("n") if "n" in encoded.columns else F.count("*")
    missing = [F.sum(F.col(x).isNull().cast("int")) for x in spec.axes]
    rows = encoded.groupBy("sa").agg(count.alias("n"), *(f(x) for x in spec.axes for f in (F.min, F.max)), *missing).limit(MAX_DOMAIN + 1).collect()
    if len(rows) > MAX_DOMAIN:
        raise ValueError(f"{spec.sa} has more than {MAX_DOMAIN} values; discretise it")
    if not rows:
        raise ValueError("the table is empty")
    for i, a in enumerate(spec.qi):
        if any(r[2 + 2 * len(spec.qi) + i] for r in rows):
            raise ValueError(f"{a.name} has nulls, which no box covers; give them a value or a leaf first")
    spans = []
    for i, a in enumerate(spec.qi):
        seen = [(r[2 + 2 * i], r[3 + 2 * i]) for r in rows if r[2 + 2 * i] is not None]
        spans.append((0, len(a.hierarchy.leaves) - 1) if a.kind == CATEGORICAL else (min(x for x, _ in seen), max(x for _, x in seen)))
    return [(r[0], r[1]) for r in rows], spans


def prepare(df: DataFrame, spec: ReleaseSpec, beta: float, kind: str = "capped", tie: str = "short", slack: float = 0.0, strict: bool = False) -> Dealing:
    """Plans a release of df.

    The encoded table is settled: planning, ranking and dealing pass over it several times, and what df joins should run once."""
    spec.validate(df)
    encoded = settle(encode(df, spec))
    counts, domains = survey(encoded, spec)
    return planned_on(encoded, spec, counts, domains, beta, kind, tie, slack, strict)


def planned_on(encoded: DataFrame, spec: ReleaseSpec, counts: list[tuple], domains: list[tuple[int, int]], beta: float, kind: str = "capped", tie: str = "short", slack: float = 0.0, strict: bool = False) -> Dealing:
    """A release planned on a table that is encoded and surveyed already: plans for other parameters cost no pass over it."""
    plan = plan_buckets(counts, beta, kind, tie, strict, slack)
    return Dealing(spec, encoded, domains, counts, plan, sizetree.grow(plan.sizes, sizetree.gain_rule(plan.caps)))


def with_keys(d: Dealing, *curves: str) -> Dealing:
    """The dealing on a settled table that holds its rows' keys, for several releases of it."""
    table = d.encoded
    for curve in curves:
        table = key_of(d, table, curve, f"key_{curve}")
    return replace(d, encoded=settle(table))


def key_of(d: Dealing, rows: DataFrame, curve: str, name: str) -> DataFrame:
    """rows with their keys along a curve."""
    axes, n_cells = d.spec.axes, 1
    for lo, hi in d.domains:
        n_cells *= hi - lo + 1
    if curve == "hilbert" and n_cells <= GRID_CELLS:
        grid = keys_of_grid(rows.sparkSession, axes, d.domains, d.bits, name)  # at most GRID_CELLS rows
        return rows.join(F.broadcast(grid), axes, "left").select(*rows.columns, name)
    # the grid as columns of its own, or a key's expression would hold an axis's arithmetic once for each bit
    grid = {f"_{x}": grid_expr(F.col(x), lo, hi, d.bits) for x, (lo, hi) in zip(axes, d.domains, strict=True)}
    return rows.withColumns(grid).select(*rows.columns, curve_expr(curve, [F.col(x) for x in grid], d.bits).alias(name))


def counts_by_key(d: Dealing, cells: DataFrame) -> tuple[np.ndarray, np.ndarray] | None:
    """The Hilbert keys that occur, in ascending order, and how many rows have each, from cells (axes, n); None if the grid has too many points."""
    lengths = [hi - lo + 1 for lo, hi in d.domains]
    if math.prod(lengths) > FEW_POINTS:
        return None
    found = cells.groupBy(*d.spec.axes).agg(F.sum("n")).toArrow()  # a row for each point at most
    *points, n = (c.to_numpy() for c in found.columns)
    place = np.ravel_multi_index([x.astype(np.int64) - lo for x, (lo, _) in zip(points, d.domains, strict=True)], lengths)
    keys, which = np.unique(points_of_grid(d.domains, d.bits)[1][place], return_inverse=True)
    return keys, np.bincount(which, n).astype(np.int64)


def keyed(d: Dealing, curve: str = "hilbert") -> DataFrame:
    """The encoded table with its bucket and curve key."""
    columns = [c for c in d.encoded.columns if not c.startswith("key_")]
    rows = d.encoded.withColumnRenamed(f"key_{curve}", "key") if f"key_{curve}" in d.encoded.columns else key_of(d, d.encoded, curve, "key")
    return rows.select(*columns, bucket_expr(d.plan.bucket_of, F.col("sa")).alias("bucket"), "key")


def rank_in_bucket(rows: DataFrame, n_rows: int, blocks: int | None = None) -> DataFrame:
    """rows with `rank`: place in its bucket by (key, row_key), from 0. n_rows: about how many there are.

    Blocks come from quantiles of the key over the whole table; a key so frequent that it is a
    quantile twice has its rows split by their row_key's first digits, which keep the order."""
    blocks = blocks or max(MIN_BLOCKS, min(MAX_BLOCKS, n_rows // BLOCK_ROWS))
    steps = rows.agg(F.percentile_approx("key", [i / blocks for i in range(1, blocks)], 10_000)).first()[0] or []
    distinct = sorted(set(steps))
    hot = sorted({a for a, b in zip(steps, steps[1:], strict=False) if a == b})
    # a hot key is a block of its own: the steps just below and at it are both cuts
    cuts = sorted(set(distinct) | {h - 1 for h in hot})
    at = _count_below(cuts, F.col("key"))
    part = F.when(F.col("key").isin(hot), F.conv(F.substring("row_key", 1, 1), 16, 10).cast("int")).otherwise(0) if hot else F.lit(0)
    rows = rows.withColumn("_block", at).withColumn("_part", F.coalesce(part, F.lit(0)))
    # buckets x blocks x parts rows at most
    counts = rows.groupBy("bucket", "_block", "_part").count().collect()
    before, offsets = {}, []
    for b, k, p, n in sorted(counts):
        offsets.append((b, k, p, before.get(b, 0)))
        before[b] = before.get(b, 0) + n
    spark = rows.sparkSession
    offset = F.broadcast(spark.createDataFrame(offsets or [(0, 0, 0, 0)], "bucket int, _block int, _part int, _before long"))
    within = F.row_number().over(Window.partitionBy("bucket", "_block", "_part").orderBy("key", "row_key")) - 1
    ranked = rows.withColumn("_within", within).join(offset, ["bucket", "_block", "_part"])
    return ranked.withColumn("rank", (F.col("_within") + F.col("_before")).cast("long")).drop("_within", "_before", "_block", "_part")


def _count_below(cuts: list[int], x: Column) -> Column:
    """How many of the sorted cuts are below x, by a binary search: as nested conditions while cuts are few, else over Arrow batches."""
    if len(cuts) <= 64:

        def between(a: int, b: int) -> Column:
            m = (a + b) // 2
            return F.lit(a) if a == b else F.when(x > cuts[m], between(m + 1, b)).otherwise(between(a, m))

        return between(0, len(cuts))
    edges = np.array(cuts, np.int64)

    @F.pandas_udf("int")
    def below(key: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(edges, key.to_numpy(), "left").astype(np.int32))

    return below(x)


def walk_expr(d: Dealing, bucket: Column, rank: Column, depth: int | None = None) -> Column:
    """Struct of group number, node and rank there, by an Arrow-batched walk of the tree."""
    tree = d.encoded.sparkSession.sparkContext.broadcast(d.tree)

    @F.pandas_udf("ec long, node long, rank long")
    def walk(b: pd.Series, r: pd.Series) -> pd.DataFrame:
        ec, node, rest = tree.value.walk(b.to_numpy(), r.to_numpy(), depth)
        return pd.DataFrame({"ec": ec, "node": node, "rank": rest})

    return walk(bucket, rank)


def deal_rank(d: Dealing, curve: str = "zorder") -> DataFrame:
    """row_key, coordinates, sa, bucket, rank and ec."""
    ranked = rank_in_bucket(keyed(d, curve), sum(d.plan.sizes))
    return ranked.withColumn("ec", walk_expr(d, F.col("bucket"), F.col("rank"))["ec"]).drop("key")


@dataclass
class Filling:
    """Which group of a shard each of its rows is in, for rank dealing of rows that are known by their cell's number (axes and sa).

    slot: of each cell, numbered by bucket and key; bucket: of each slot; nodes, firsts: root and first group of each shard."""

    tree: sizetree.SizeTree
    slot: np.ndarray
    bucket: np.ndarray
    nodes: np.ndarray
    firsts: np.ndarray

    def groups(self, shard: int, cell: np.ndarray) -> np.ndarray:
        """Group of each row. cell: of all rows of the shard, in the order of row_key."""
        node, slot = int(self.nodes[shard]), self.slot[cell]
        n = self.tree.counts.shape[1]
        if (np.bincount(self.bucket[slot], minlength=n) != self.tree.counts[node]).any():
            raise ValueError("the counts by cell are not those of the rows")
        leaves, out = self.tree.leaf_vectors(node), np.empty(len(cell), np.int64)
        out[np.argsort(slot, kind="stable")] = np.repeat(np.tile(np.arange(len(leaves)), n), leaves.T.reshape(-1))
        return self.firsts[shard] + out


@dataclass
class Dealt:
    """A release by rank whose rows lie by shards: (shard, cell), a partition for each shard and in the order of row_key there; and what the cells are."""

    table: DataFrame
    filling: Filling
    points: list[np.ndarray]
    sa: list


def cells_of(encoded: DataFrame, axes: list[str], most: int) -> pa.Table | None:
    """axes, sa and n of each combination that occurs; None if there are more than `most`."""
    found = encoded.groupBy(*axes, "sa").agg(F.count("*").alias("n")).limit(most + 1).toArrow()
    return found if len(found) <= most else None


def deal_cells(d: Dealing, cells: pa.Table, shard_rows: int) -> Dealt:
    """The groups of `deal_rank`, for a table of few cells (axes, sa and n, by `cells_of`), without ranks of its rows.

    The counts give each bucket's ranks before each key, so a row's cell tells its shard unless its key's rows are cut by a shard's end; only those are
    ranked. All rows are dealt to their shards once, and sorted by row_key there. shard_rows: most rows of a shard, unless a group has more."""
    spark, axes, tree = d.encoded.sparkSession, d.spec.axes, d.tree
    found = keyed(replace(d, encoded=spark.createDataFrame(cells)), "zorder").select(*axes, "sa", "n", "bucket", "key").toArrow()
    n, bucket, key = (found.column(c).to_numpy().astype(np.int64) for c in ("n", "bucket", "key"))
    order = np.lexsort((key, bucket))
    new = np.r_[True, (np.diff(bucket[order]) != 0) | (np.diff(key[order]) != 0)]
    slot = np.empty(len(n), np.int64)
    slot[order] = np.cumsum(new) - 1
    of, count = bucket[order][new], np.bincount(slot, n).astype(np.int64)
    depth, nodes = 0, [0]
    while (sum(d.plan.sizes) >> depth) > shard_rows:
        depth += 1
        nodes = [int(c) for i in nodes for c in ((tree.left[i], tree.right[i]) if tree.left[i] >= 0 else (i,))]
    held = tree.leaves[nodes]
    filling = Filling(tree, slot, of, np.array(nodes), np.cumsum(held) - held)
    # places run over the ranks of one bucket after the other; a shard ends once in each
    sizes = np.array(d.plan.sizes, np.int64)
    ends = (np.cumsum(tree.counts[nodes], 0)[:-1] + np.cumsum(sizes) - sizes).T.reshape(-1)
    first = np.cumsum(count) - count

    def shard_of(place: np.ndarray, bucket: np.ndarray) -> np.ndarray:
        return np.searchsorted(ends, place, "right") - bucket * (len(nodes) - 1)

    shard = shard_of(first, of)
    cut = shard != shard_of(first + count - 1, of)
    names = [f"_{x}" for x in (*axes, "sa")]
    known = pa.table([*(found.column(x) for x in (*axes, "sa")), pa.array(np.arange(len(n), dtype=np.int32)), pa.array(np.where(cut, -1, shard)[slot].astype(np.int32)), found.column("bucket"), found.column("key")], [*names, "cell", "shard", "bucket", "key"])
    met = [F.col(x).eqNullSafe(F.col(f"_{x}")) for x in (*axes, "sa")]
    rows = d.encoded.join(F.broadcast(spark.createDataFrame(known)), met).select("row_key", "cell", "shard", "bucket", "key")
    table = rows.where("shard >= 0").select("shard", "row_key", "cell")
    if cut.any():
        # ranks among the cut keys' rows alone, moved to where the key's ranks begin
        some = np.where(cut, count, 0)
        to = first - (np.cumsum(some) - some - (np.cumsum(np.bincount(of, some, len(sizes))) - np.bincount(of, some, len(sizes))).astype(np.int64)[of])

        @F.pandas_udf("int")
        def at(cell: pd.Series, rank: pd.Series) -> pd.Series:
            own = slot[cell.to_numpy()]
            return pd.Series(shard_of(rank.to_numpy() + to[own], of[own]).astype(np.int32))

        ranked = rank_in_bucket(settle(rows.where("shard < 0").drop("shard")), int(some.sum()))
        table = table.union(ranked.select(at("cell", "rank").alias("shard"), "row_key", "cell"))
    table = table.repartitionById(len(nodes), F.col("shard")).sortWithinPartitions("row_key").select("shard", "cell")
    return Dealt(table, filling, [found.column(x).to_numpy().astype(np.int64) for x in axes], found.column("sa").to_pylist())


def _nearest_run(keys: np.ndarray, x: int, n: int) -> int:
    """Start of the n sorted keys that are nearest to x: a run, as distances grow to both sides."""
    place = int(np.searchsorted(keys, x))
    at, end = min(max(0, place - n), len(keys) - n), min(place, len(keys) - n)
    # the run slides right while the key that it would gain is nearer than the one it would lose
    starts = np.arange(at, end)
    stop = np.flatnonzero(np.abs(keys[starts + n] - x) >= np.abs(keys[starts] - x))
    return int(starts[stop[0]]) if len(stop) else max(at, end)


class Pool:
    """A bucket's rows in the order of their keys, of which runs are taken away; counts by stretch find the k-th row that is left."""

    STRETCH = 256

    def __init__(self, keys: np.ndarray, rows: np.ndarray):
        self.keys, self.rows, self.here = keys, rows, np.ones(len(keys), bool)
        self.counts = np.bincount(np.arange(len(keys)) // self.STRETCH, minlength=1)

    @property
    def left(self) -> int:
        return int(self.counts.sum())

    def places(self, first: int, end: int) -> np.ndarray:
        """Places of the rows that are first, first + 1, ... end - 1 among those left."""
        till = np.cumsum(self.counts)
        a, b = int(np.searchsorted(till, first, "right")), int(np.searchsorted(till, end - 1, "right"))
        at = np.flatnonzero(self.here[a * self.STRETCH : (b + 1) * self.STRETCH]) + a * self.STRETCH
        skip = first - (int(till[a - 1]) if a else 0)
        return at[skip : skip + end - first]

    def key(self, k: int) -> int:
        return int(self.keys[self.places(k, k + 1)[0]])

    def take_nearest(self, x: int, n: int) -> np.ndarray:
        """Takes the n rows whose keys are nearest to x. Only the n rows left on either side of x are looked at."""
        place = int(np.searchsorted(self.keys, x))
        whole = place // self.STRETCH
        before = int(self.counts[:whole].sum()) + int(self.here[whole * self.STRETCH : place].sum())
        some = self.places(max(0, before - n), min(self.left, before + n))
        at = _nearest_run(self.keys[some], x, n)
        gone = some[at : at + n]
        self.here[gone] = False
        np.subtract.at(self.counts, gone // self.STRETCH, 1)
        return self.rows[gone]


def _share(seed: int, what: str, group: int) -> float:
    """A uniform in [0, 1) that belongs to a group."""
    return int(hashlib.md5(f"{seed}|{what}|{group}".encode()).hexdigest()[:13], 16) / (1 << 52)


def _by_lot(seed: int, first: int, n: int) -> list[int]:
    """Groups first .. first + n - 1 in the order of their hashes."""
    return sorted(range(n), key=lambda i: hashlib.md5(f"{seed}|group|{first + i}".encode()).hexdigest())


def _chosen(need: np.ndarray, seed: int, group: int) -> int:
    """The bucket that a group's first row comes from."""
    some = np.flatnonzero(need)
    return int(some[int(_share(seed, "bucket", group) * len(some))])


def fill_curve(buckets: list[np.ndarray], keys: list[np.ndarray], leaves: np.ndarray, first: int = 0, seed: int = 1) -> list[tuple[int, int, np.ndarray]]:
    """Greedy filling: for each leaf, in an order by lot, a row drawn by lot draws its nearest along the curve from every bucket. Returns (leaf, bucket, rows).

    buckets and keys: rows and sorted keys of each bucket; first: number of the first leaf's group."""
    pools = [Pool(k, r) for k, r in zip(keys, buckets, strict=True)]
    out = []
    for leaf in _by_lot(seed, first, len(leaves)):
        need = leaves[leaf]
        own = pools[_chosen(need, seed, first + leaf)]
        x = own.key(int(_share(seed, "row", first + leaf) * own.left))
        out += [(leaf, j, pools[j].take_nearest(x, int(need[j]))) for j in np.flatnonzero(need).tolist()]
    return out


def fill_counts(bucket: np.ndarray, key: np.ndarray, leaves: np.ndarray, first: int = 0, seed: int = 1) -> np.ndarray:
    """Leaf of each row: the same groups as by `fill_curve`, for rows of few distinct keys; rows must be in the order of their keys.

    Rows of a bucket and key leave their run at its ends only: at its last row if the run is before the key that draws, at its first row
    otherwise. So a run is two numbers, and a leaf takes from all buckets in a few passes over buckets x nearest keys."""
    starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
    keys, n = key[starts], leaves.shape[1]
    slot = bucket * len(keys) + np.repeat(np.arange(len(keys)), np.diff(np.r_[starts, len(key)]))
    rows = np.argsort(slot, kind="stable")
    left = np.bincount(slot, minlength=n * len(keys)).reshape(n, -1)
    low = (np.cumsum(left.reshape(-1)) - left.reshape(-1)).reshape(n, -1)
    near: dict[int, np.ndarray] = {}
    taken = []
    for leaf in _by_lot(seed, first, len(leaves)):
        need = leaves[leaf]
        run = np.cumsum(left[_chosen(need, seed, first + leaf)])
        c = int(np.searchsorted(run, int(_share(seed, "row", first + leaf) * int(run[-1])), "right"))
        if c not in near:
            near[c] = np.lexsort((keys, np.abs(keys - keys[c])))
        for width in (*NEAREST, len(keys)):
            some = near[c][:width]
            have = left[:, some]
            before = np.cumsum(have, 1)
            if width >= len(keys) or (before[:, -1] >= need).all():
                break
        take = np.minimum(have, np.maximum(need[:, None] - before + have, 0))
        j, k = np.nonzero(take)
        k, count = some[k], take[j, k]
        left[j, k] -= count
        at = low[j, k]
        tail = k < c
        low[j, k] += np.where(tail, 0, count)
        taken.append((at + np.where(tail, left[j, k], 0), count, np.full(len(j), leaf)))
    at, count, leaf = (np.concatenate(x) for x in zip(*taken, strict=True))
    out = np.empty(len(key), np.int64)
    out[rows[np.repeat(at - np.cumsum(count) + count, count) + np.arange(len(key))]] = np.repeat(leaf, count)
    return out


def leaf_of_rows(bucket: np.ndarray, key: np.ndarray, leaves: np.ndarray, first: int = 0, seed: int = 1) -> np.ndarray:
    """Leaf of each row of a shard by the greedy search along the curve; rows in the order of (key, row_key)."""
    if np.count_nonzero(key[1:] != key[:-1]) < KEYS:
        return fill_counts(bucket, key, leaves, first, seed)
    out = np.empty(len(key), np.int64)
    parts = [np.flatnonzero(bucket == j) for j in range(leaves.shape[1])]
    for leaf, _, some in fill_curve(parts, [key[r] for r in parts], leaves, first, seed):
        out[some] = leaf
    return out


def fill_euclid(buckets: list[np.ndarray], points: list[np.ndarray], leaves: np.ndarray, first: int = 0, seed: int = 1) -> list[tuple[int, int, np.ndarray]]:
    """The same with true distances between normalised points: quadratic, for small shards."""
    left = [(p.copy(), r.copy()) for p, r in zip(points, buckets, strict=True)]
    out = []
    for leaf in _by_lot(seed, first, len(leaves)):
        need = leaves[leaf]
        p = left[_chosen(need, seed, first + leaf)][0]
        x = p[int(_share(seed, "row", first + leaf) * len(p))]
        for j in np.flatnonzero(need):
            p, r = left[j]
            near = np.argsort(((p - x) ** 2).sum(1), kind="stable")[: need[j]]
            out.append((leaf, j, r[near]))
            left[j] = (np.delete(p, near, 0), np.delete(r, near))
    return out


def fill_cosplit(tree: sizetree.SizeTree, root: int, buckets: list[np.ndarray], points: list[np.ndarray]) -> list[tuple[int, int, np.ndarray]]:
    """Follows the tree down; at each node every bucket is ordered by the axis that leaves the least extent, and its first rows go left."""
    out, stack, leaf = [], [(root, list(zip(buckets, points, strict=True)))], 0
    while stack:
        node, parts = stack.pop()
        if tree.left[node] < 0:
            out += [(leaf, j, r) for j, (r, _) in enumerate(parts) if len(r)]
            leaf += 1
            continue
        take = tree.counts[tree.left[node]]
        best = None
        for axis in range(parts[0][1].shape[1]):
            orders = [np.argsort(p[:, axis], kind="stable") for _, p in parts]
            sides = ([p[o[:t]] for (_, p), o, t in zip(parts, orders, take, strict=True)], [p[o[t:]] for (_, p), o, t in zip(parts, orders, take, strict=True)])
            extent = 0.0
            for side in sides:
                x = np.concatenate(side)
                extent += len(x) * float((x.max(0) - x.min(0)).sum()) if len(x) else 0.0
            if best is None or extent < best[0]:
                best = (extent, orders)
        lefts = [(r[o[:t]], p[o[:t]]) for (r, p), o, t in zip(parts, best[1], take, strict=True)]
        rights = [(r[o[t:]], p[o[t:]]) for (r, p), o, t in zip(parts, best[1], take, strict=True)]
        stack += [(int(tree.right[node]), rights), (int(tree.left[node]), lefts)]
    return out


def deal_sharded(d: Dealing, draw: str = "curve", curve: str = "hilbert", seed: int = 1, shard_rows: int | None = None) -> DataFrame:
    """row_key, coordinates, sa, bucket and ec, by a search within shards of at most about shard_rows rows.

    A shard is a subtree, cut off at the depth at which vectors have that size; its rows are the runs of each bucket's
    ranks that the walk to the subtree's root selects. A shard's outcome depends on its rows and the seed alone. A subtree
    of one leaf is a group as it stands, and its rows go past the search."""
    if draw not in ("curve", "euclid", "cosplit"):
        raise ValueError(draw)
    shard_rows = shard_rows or (EUCLID_ROWS if draw == "euclid" else SHARD_ROWS)
    total, depth = sum(d.plan.sizes), 0
    while (total >> depth) > shard_rows:
        depth += 1
    names = [*("row_key", *d.spec.axes), "sa", "bucket"]
    rows = keyed(d, curve)
    if d.tree.left[0] < 0:
        return rows.select(*names, F.lit(0).cast("long").alias("ec"))
    if depth:
        rows = rank_in_bucket(rows, total).withColumn("_at", walk_expr(d, F.col("bucket"), F.col("rank"), depth))
        rows = rows.select(*names, "key", F.col("_at.ec").alias("_first"), F.col("_at.node").alias("_node"))
    else:
        rows = rows.select(*names, "key", F.lit(0).cast("long").alias("_first"), F.lit(0).cast("long").alias("_node"))
    # a depth has few distinct nodes, whatever the table's size
    reached = {0}
    for _ in range(depth):
        reached = {int(c) for i in reached for c in ((d.tree.left[i], d.tree.right[i]) if d.tree.left[i] >= 0 else (i,))}
    done = sorted(i for i in reached if d.tree.left[i] < 0)
    closed = F.col("_node").isin(done)
    tree, axes = rows.sparkSession.sparkContext.broadcast(d.tree), d.spec.axes
    low, extent = np.array([lo for lo, _ in d.domains], float), np.array([max(1, hi - lo) for lo, hi in d.domains], float)
    kinds = T.StructType([*(rows.schema[c] for c in names), T.StructField("ec", T.LongType())])

    def fill(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["key", "row_key"], kind="stable").reset_index(drop=True)
        node, first = int(pdf["_node"].iloc[0]), int(pdf["_first"].iloc[0])
        n = tree.value.counts.shape[1]
        bucket = pdf["bucket"].to_numpy()
        leaves = tree.value.leaf_vectors(node)
        if draw == "curve":
            return pdf.assign(ec=first + leaf_of_rows(bucket, pdf["key"].to_numpy(), leaves, first, seed))[[*names, "ec"]]
        parts = [np.flatnonzero(bucket == j) for j in range(n)]
        points = (pdf[axes].to_numpy(float) - low) / extent
        some = [points[p] for p in parts]
        filled = fill_euclid(parts, some, leaves, first, seed) if draw == "euclid" else fill_cosplit(tree.value, node, parts, some)
        ec = np.empty(len(pdf), np.int64)
        for leaf, _, some in filled:
            ec[some] = first + leaf
        return pdf.assign(ec=ec)[[*names, "ec"]]

    if not done:
        return rows.groupBy("_first", "_node").applyInPandas(fill, kinds)
    whole = rows.where(closed).select(*names, F.col("_first").alias("ec"))
    if len(done) == len(reached):
        return whole
    return rows.where(~closed).groupBy("_first", "_node").applyInPandas(fill, kinds).union(whole)


def deal(d: Dealing, draw: str = "curve", curve: str | None = None, seed: int = 1, shard_rows: int | None = None) -> DataFrame:
    """Groups by any of the four ways of drawing."""
    if draw == "rank":
        return deal_rank(d, curve or "zorder").drop("rank")
    return deal_sharded(d, draw, curve or "hilbert", seed, shard_rows)


def bucket_and_deal(df: DataFrame, spec: ReleaseSpec, beta: float, kind: str = "capped", draw: str = "curve", curve: str | None = None, tie: str = "short", slack: float = 0.0, seed: int = 1) -> DataFrame:
    """The whole method: row_key, coordinates, sa, bucket and ec of every row."""
    return deal(prepare(df, spec, beta, kind, tie, slack), draw, curve, seed)
