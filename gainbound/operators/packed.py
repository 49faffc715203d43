"""A table sorted once along a curve and packed into chunks, for releases of it under many plans.

A release by `deal` sorts and ranks all rows again. Here the rows are sorted by (key, row_key) once and kept as chunks: a code of the
sensitive value for each row, and coordinates once for each run of equal ones. A chunk's counts by sensitive value are all that the driver
holds. They give, for any plan, the ranks at which the chunk's rows begin in each bucket, so a release is one pass that cuts chunks at the
shards' bounds, and one task a shard. What comes out is each group's histogram with its box, or only the group's measures: the same groups as
`deal` makes by the same draw. Several plans go through one job.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gainbound.operators.deal import SHARD_ROWS, Dealing, bucket_expr, leaf_of_rows
from gainbound.operators.grouped import BLOCK_COUNTS
from gainbound.operators.loss import losses
from gainbound.operators.settle import settle
from gainbound.plans import sizetree

#: Rows of a chunk, and about as many as a task sorts where that is known beforehand.
CHUNK_ROWS, PART_ROWS = 1 << 16, 1 << 19


@dataclass
class Packed:
    """Chunks (chunk, sa for each row, and for each run of equal rows key, n, x1, ... as bytes), their numbers in order, and their counts by sensitive value (chunks x values)."""

    table: DataFrame
    chunks: np.ndarray
    counts: np.ndarray
    values: list


def _width(n_values: int) -> np.dtype:
    return np.min_scalar_type(max(0, n_values - 1))


def _runs(columns: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """First row and length of each run of rows that are equal in all columns."""
    new = np.zeros(len(columns[0]), bool)
    new[:1] = True
    for c in columns:
        new[1:] |= c[1:] != c[:-1]
    at = np.flatnonzero(new)
    return at, np.diff(np.r_[at, len(new)])


def pack(keyed: DataFrame, axes: list[str], values: list) -> Packed:
    """keyed: row_key, axes, sa and key. values: the sensitive domain."""
    return pack_columns(keyed, axes, {"sa": values})["sa"]


def parts_of(by_key: tuple[np.ndarray, np.ndarray], n: int) -> np.ndarray | None:
    """Which of n runs of about as many rows each of the keys goes to, or of more runs so that they have PART_ROWS or fewer, from the keys in ascending
    order and their counts; None if a key alone has more rows than one of n runs."""
    counts = by_key[1]
    total, most = int(counts.sum()), int(counts.max())
    if most * n > total:
        return None
    return (np.cumsum(counts) - counts) * max(n, min(-(-total // PART_ROWS), total // most)) // total


def pack_columns(keyed: DataFrame, axes: list[str], values: dict[str, list], by_key: tuple[np.ndarray, np.ndarray] | None = None) -> dict[str, Packed]:
    """The same for several sensitive columns (to their domains), which are sorted together: one table each, of the same chunks.

    by_key: the keys that occur in ascending order and their counts, if they are known; the rows are then dealt without a pass that samples them."""
    k, widths = len(values), [_width(len(v)) for v in values.values()]
    codes = [bucket_expr({v: i for i, v in enumerate(own)}, F.col(c)).cast("int").alias(c) for c, own in values.items()]
    rows = keyed.select("key", "row_key", *codes, *(F.col(x).cast("long") for x in axes))
    n = max(keyed.sparkSession.sparkContext.defaultParallelism, int(keyed.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    sizes, tallies = [len(v) for v in values.values()], [f"_n_{c}" for c in values]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, seq, held, size = TaskContext.get().partitionId(), 0, [], 0

        def out() -> pa.RecordBatch:
            key, *rest = (np.concatenate([b[i] for b in held]) for i in range(len(axes) + k + 1))
            own, points = rest[:k], rest[k:]
            at, length = _runs([key, *points])
            columns = [*(np.bincount(x, minlength=m).astype(np.int64) for x, m in zip(own, sizes, strict=True)), *(x.astype(w) for x, w in zip(own, widths, strict=True)), key[at], length, *(x[at] for x in points)]
            return pa.RecordBatch.from_arrays([pa.array([(part << 32) | seq], pa.int64()), *(pa.array([c.tobytes()]) for c in columns)], names=["chunk", *tallies, *values, "key", "n", *axes])

        for batch in batches:
            held.append([batch.column(i).to_numpy(zero_copy_only=False) for i in range(batch.num_columns)])
            size += len(batch)
            if size >= CHUNK_ROWS:
                yield out()
                seq, held, size = seq + 1, [], 0
        if size:
            yield out()

    parts = None if by_key is None else parts_of(by_key, n)
    if parts is None:
        dealt = rows.repartitionByRange(n, "key", "row_key")
    else:
        known = keyed.sparkSession.createDataFrame(pa.table([by_key[0], parts.astype(np.int32)], ["key", "_part"]))
        part = F.coalesce("_part", F.raise_error(F.lit("a key has no count")).cast("int"))
        dealt = rows.join(F.broadcast(known), "key", "left").repartitionById(int(parts[-1]) + 1, part).select(*rows.columns)
    ordered = dealt.sortWithinPartitions("key", "row_key").drop("row_key")
    table = settle(ordered.mapInArrow(run, "chunk long, " + ", ".join(f"{x} binary" for x in (*tallies, *values, "key", "n", *axes))))
    found = sorted((r[0], *map(bytes, r[1:])) for r in table.select("chunk", *tallies).collect())  # a row for each CHUNK_ROWS rows
    chunks, out = np.array([r[0] for r in found], np.int64), {}
    if by_key is not None and sum(np.frombuffer(r[1], np.int64).sum() for r in found) != by_key[1].sum():
        raise ValueError("the counts by key are not those of the rows")
    for i, (c, own) in enumerate(values.items()):
        counts = np.array([np.frombuffer(r[1 + i], np.int64) for r in found]).reshape(len(found), len(own))
        out[c] = Packed(table.select("chunk", F.col(c).alias("sa"), "key", "n", *axes), chunks, counts, list(own))
    return out


def awake(spark: SparkSession) -> None:
    """Starts a Python worker for each core, with what releases import: that takes seconds in which the driver can plan and the JVM read."""
    n = spark.sparkContext.defaultParallelism

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(pd.Series(leaf_of_rows.__code__.co_argcount, range(len(batch))))], names=["id"])

    spark.range(0, n, 1, n).mapInArrow(run, "id long").write.format("noop").mode("overwrite").save()


def tally(ec: np.ndarray, sa: np.ndarray, points: list[np.ndarray], m: int) -> tuple:
    """Each group and value once: ec, sa, n and the least and greatest coordinate of each axis."""
    pair = ec * m + sa
    order = np.argsort(pair, kind="stable")
    pair = pair[order]
    at = np.flatnonzero(np.r_[True, pair[1:] != pair[:-1]]) if len(pair) else np.zeros(0, np.int64)
    bounds = [f.reduceat(x[order], at) for x in points for f in (np.minimum, np.maximum)]
    return pair[at] // m, pair[at] % m, np.diff(np.r_[at, len(pair)]), *bounds


@dataclass
class _Cut:
    """A plan as tasks need it: tree, bucket of each code, ranks before each chunk, and the shards in order (first group, node, and where each bucket's ranks end)."""

    tree: sizetree.SizeTree
    bucket: np.ndarray
    before: dict
    firsts: np.ndarray
    nodes: np.ndarray
    ends: np.ndarray


def _cut_of(p: Packed, d: Dealing, shard_rows: int) -> _Cut:
    tree = d.tree
    bucket = np.array([d.plan.bucket_of[v] for v in p.values], np.int64)
    by_bucket = np.zeros((len(p.chunks), len(d.plan.sizes)), np.int64)
    np.add.at(by_bucket.T, bucket, p.counts.T)
    before = dict(zip(p.chunks.tolist(), np.cumsum(by_bucket, 0) - by_bucket, strict=True))
    depth, nodes = 0, [0]
    while (sum(d.plan.sizes) >> depth) > shard_rows:
        depth += 1
        nodes = [int(c) for i in nodes for c in ((tree.left[i], tree.right[i]) if tree.left[i] >= 0 else (i,))]
    held = tree.leaves[nodes]
    return _Cut(tree, bucket, before, np.cumsum(held) - held, np.array(nodes), np.cumsum(tree.counts[nodes], 0))


def _shards(p: Packed, ds: list[Dealing], draw: str, seed: int, shard_rows: int, answer: Callable, kind: str) -> DataFrame:
    """What `answer` makes of each shard of each plan. answer: from (plan, first group, leaf of each row, number of leaves, codes, points), or of a shard that is
    one group (plan, its group, None, 1, codes, (n, bounds of each axis) by code), to a frame."""
    axes, m = ds[0].spec.axes, len(p.values)
    spark = p.table.sparkSession
    known = spark.sparkContext.broadcast([_cut_of(p, d, shard_rows) for d in ds])
    names = ["plan", "first", "node", "chunk", "sa", "key", "n", *axes]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(len(batch)):
                chunk = batch.column(0)[i].as_py()
                sa, key, length, *points = (np.frombuffer(batch.column(j)[i].as_buffer(), _width(m) if j == 1 else np.int64) for j in range(1, batch.num_columns))
                run = np.repeat(np.arange(len(length)), length)
                for number, c in enumerate(known.value):
                    own = c.bucket.astype(_width(c.ends.shape[1]))[sa]
                    sizes = np.bincount(own, minlength=c.ends.shape[1])
                    # each bucket's rows of the chunk are a run of its ranks, which the shards' ends cut
                    here = np.clip(np.vstack([0 * c.ends[:1], c.ends]) - c.before[chunk], 0, sizes)
                    counts = np.diff(here, axis=0)
                    some = np.flatnonzero(counts.any(1))
                    shard = np.empty(len(own), _width(len(some)))
                    shard[np.argsort(own, kind="stable")] = np.repeat(np.tile(np.arange(len(some)), counts.shape[1]), counts[some].T.reshape(-1))
                    order = np.argsort(shard, kind="stable")
                    at = 0
                    for s, held in zip(some.tolist(), counts[some].sum(1).tolist(), strict=True):
                        rows = order[at : at + held]
                        at += held
                        if c.tree.left[c.nodes[s]] < 0:
                            # a group as it stands gathers by value
                            _, code, n, *bounds = tally(np.zeros(held, np.int64), sa[rows].astype(np.int64), [x[run[rows]] for x in points], m)
                            columns = [code.astype(_width(m)), np.zeros(0, np.int64), n, *(np.concatenate(bounds[2 * k : 2 * k + 2]) for k in range(len(axes)))]
                        else:
                            n = np.bincount(run[rows], minlength=len(length))
                            used = np.flatnonzero(n)
                            columns = [sa[rows], key[used], n[used], *(x[used] for x in points)]
                        arrays = [pa.array([x], pa.int64()) for x in (number, int(c.firsts[s]), int(c.nodes[s]), chunk)] + [pa.array([x.tobytes()]) for x in columns]
                        yield pa.RecordBatch.from_arrays(arrays, names=names)

    def fill(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("chunk")
        number, first, node = (int(pdf[k].iloc[0]) for k in ("plan", "first", "node"))
        c = known.value[number]
        sa, key, n, *points = (np.frombuffer(b"".join(pdf[k]), _width(m) if k == "sa" else np.int64) for k in names[4:])
        sa = sa.astype(np.int64)
        if c.tree.left[node] < 0:
            parts = [[np.frombuffer(b, np.int64).reshape(2, -1) for b in pdf[x]] for x in axes]
            order = np.argsort(sa, kind="stable")
            at = np.flatnonzero(np.r_[True, np.diff(sa[order]) != 0])
            bounds = [f.reduceat(np.concatenate([b[k] for b in part])[order], at) for part in parts for k, f in enumerate((np.minimum, np.maximum))]
            return answer(number, first, None, 1, sa[order][at], [np.add.reduceat(n[order], at), *bounds])
        key, *points = (np.repeat(x, n) for x in (key, *points))
        own, leaves = c.bucket[sa], c.tree.leaf_vectors(node)
        if draw == "curve":
            leaf = leaf_of_rows(own, key, leaves, first, seed)
        else:
            leaf = np.empty(len(sa), np.int64)
            leaf[np.argsort(own, kind="stable")] = np.repeat(np.tile(np.arange(len(leaves)), leaves.shape[1]), leaves.T.reshape(-1))
        return answer(number, first, leaf, len(leaves), sa, points)

    pieces = p.table.mapInArrow(cut, "plan long, first long, node long, chunk long, " + ", ".join(f"{x} binary" for x in names[4:]))
    n = 2 * max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    # pieces are few bytes and long work, so they are spread by number and not by size
    return pieces.repartition(n, "plan", "first").groupBy("plan", "first").applyInPandas(fill, kind)


def _checked(draw: str) -> None:
    if draw not in ("curve", "rank"):
        raise ValueError(draw)


def release(p: Packed, d: Dealing, draw: str = "curve", seed: int = 1, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """ec, sa, n and x1_lo, x1_hi, ... of each group and value.

    p must be packed along the curve that the draw sorts by, from the table that d plans."""
    _checked(draw)
    names, m = ["ec", "code", "n", *(f"{x}_{k}" for x in d.spec.axes for k in ("lo", "hi"))], len(p.values)

    def answer(_, first, leaf, n_leaves, sa, points) -> pd.DataFrame:
        columns = tally(first + leaf, sa, points, m) if leaf is not None else (np.full(len(sa), first), sa, *points)
        return pd.DataFrame(dict(zip(names, columns, strict=True)))

    found = _shards(p, [d], draw, seed, shard_rows, answer, ", ".join(f"{c} long" for c in names))
    values = F.array(*[F.lit(v) for v in p.values])
    return found.select("ec", F.get(values, F.col("code").cast("int")).cast(d.encoded.schema["sa"].dataType).alias("sa"), *names[2:])


def order_of(values: list) -> np.ndarray:
    """Place of each code in the order of the values that puts a null first, as windows do."""
    return np.array([i for i, _ in sorted(enumerate(sorted(range(len(values)), key=lambda i: values[i] is not None)), key=lambda x: x[1])])


def prior_of(values: list, counts: list[tuple]) -> np.ndarray:
    """Overall shares in that order."""
    n_of = dict(counts)
    out = np.empty(len(values))
    out[order_of(values)] = [n_of[v] / sum(n_of.values()) for v in values]
    return out


def verdicts(leaf: np.ndarray, code: np.ndarray, weight: np.ndarray | None, n_leaves: int, prior: np.ndarray) -> list[np.ndarray]:
    """Size, largest gain, largest frequency and distance from the overall distribution of each group. code: places in the order of prior; leaf in ascending order."""
    m, out = len(prior), []
    step = max(1, BLOCK_COUNTS // m)
    for a in range(0, n_leaves, step):
        b = min(n_leaves, a + step)
        some = slice(*np.searchsorted(leaf, (a, b)))
        n = np.bincount((leaf[some] - a) * m + code[some], None if weight is None else weight[some], (b - a) * m).reshape(-1, m)
        size = n.sum(1)
        q = n / size[:, None]
        out.append((size.astype(np.int64), np.where(n > 0, q / prior - 1, -np.inf).max(1), q.max(1), np.abs(np.cumsum(q - prior, 1)).sum(1) / max(1, m - 1)))
    return [np.concatenate(x) for x in zip(*out, strict=True)]


def verdicts_of_few(pair: np.ndarray, prior: np.ndarray) -> list[np.ndarray]:
    """The same for groups of few rows, from each row's group x values + place in ascending order: the work is that of the rows and not of groups x values."""
    m = len(prior)
    at = np.flatnonzero(np.r_[True, pair[1:] != pair[:-1]])
    n, code, group = np.diff(np.r_[at, len(pair)]), pair[at] % m, pair[at] // m
    first = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
    size = np.add.reduceat(n, first)
    each = np.repeat(np.arange(len(first)), np.diff(np.r_[first, len(group)]))
    q = n / size[each]
    # between two values that occur, the running share stands still while the overall one rises
    run = np.cumsum(n)
    share = (run - (run - n)[first][each]) / size[each]
    overall = np.cumsum(prior)
    area = np.r_[0.0, np.cumsum(overall)]
    end = np.r_[code[1:], m]
    end[np.r_[first[1:] - 1, len(code) - 1]] = m
    mid = np.clip(np.searchsorted(overall, share), code, end)
    moved = share * (2 * mid - code - end) - 2 * area[mid] + area[code] + area[end]
    emd = (np.add.reduceat(moved, first) + area[code[first]]) / max(1, m - 1)
    return [size, np.maximum.reduceat(q / prior[code] - 1, first), np.maximum.reduceat(q, first), emd]


def judge(p: Packed, ds: list[Dealing], draw: str = "curve", seed: int = 1, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """Of each group of each plan (its place in ds): what `grouped.judged` makes of the release, without its histogram leaving the shard's task."""
    _checked(draw)
    axes = ds[0].spec.axes
    place, prior = order_of(p.values), prior_of(p.values, ds[0].counts)
    bounds = [f"{x}_{k}" for x in axes for k in ("lo", "hi")]

    def answer(number, first, leaf, n_leaves, sa, points) -> pd.DataFrame:
        if leaf is None:
            weight, *span = points
            span = [f(x).reshape(1) for x, f in zip(span, [np.min, np.max] * len(axes), strict=True)]
            leaf = np.zeros(len(sa), np.int64)
        else:
            weight = None
            order = np.argsort(leaf, kind="stable")
            size = np.bincount(leaf, minlength=n_leaves)
            at = np.cumsum(size) - size
            span = [f.reduceat(x[order], at) for x in points for f in (np.minimum, np.maximum)]
            leaf, sa = leaf[order], sa[order]
        return pd.DataFrame({"plan": number} | dict(zip(bounds, span, strict=True)) | dict(zip(("size", "gain", "top", "emd"), verdicts(leaf, place[sa], weight, n_leaves, prior), strict=True)))

    return _shards(p, ds, draw, seed, shard_rows, answer, "plan long, " + ", ".join(f"{c} long" for c in bounds) + ", size long, gain double, top double, emd double")


#: Sums and extremes of groups, which sum up further: by plan and shard, by plan.
TOTALS = "plan long, groups long, n long, lost double, gain double, top double, each_l double, emd double, each_emd double"


def totals(number: int, size: np.ndarray, gain: np.ndarray, top: np.ndarray, emd: np.ndarray, lost: np.ndarray) -> tuple:
    """A row of TOTALS."""
    return number, len(size), int(size.sum()), float((size * lost).sum()), float(gain.max()), float(top.max()), float((1 / top).sum()), float(emd.max()), float(emd.sum())


def measures_of(r) -> dict:
    """A plan's measures from its totals."""
    return {"groups": r["groups"], "ail": r["lost"] / r["n"], "beta": r["gain"], "l": 1 / r["top"], "avg_l": r["each_l"] / r["groups"], "t": r["emd"], "avg_t": r["each_emd"] / r["groups"]}


def summed(some: DataFrame) -> dict[int, dict]:
    """Measures of each plan from the totals of its shards."""
    parts = [(F.max if c in ("gain", "top", "emd") else F.sum)(c).alias(c) for c in some.columns if c != "plan"]
    return {r["plan"]: measures_of(r) for r in some.groupBy("plan").agg(*parts).collect()}


def measure(p: Packed, ds: list[Dealing], draw: str = "curve", seed: int = 1, shard_rows: int = SHARD_ROWS) -> list[dict]:
    """Measures of each plan's release. A task sums its shard's groups up, so no group leaves it: a loose plan has as many as rows."""
    _checked(draw)
    place, prior, m = order_of(p.values), prior_of(p.values, ds[0].counts), len(p.values)
    lost, names = losses(ds[0].spec, ds[0].domains), [c.split()[0] for c in TOTALS.split(", ")]

    def answer(number, first, leaf, n_leaves, sa, points) -> pd.DataFrame:
        code = place[sa]
        if leaf is None:
            weight, *span = points
            span = [f(x).reshape(1) for x, f in zip(span, [np.min, np.max] * (len(points) // 2), strict=True)]
            found = verdicts(np.zeros(len(sa), np.int64), code, weight, 1, prior)
        else:
            few = n_leaves * m > 2 * len(sa)
            by = leaf * m + code if few else leaf.astype(_width(n_leaves))
            order = np.argsort(by, kind=None if few else "stable")
            size = np.bincount(leaf, minlength=n_leaves)
            at = np.cumsum(size) - size
            span = [f.reduceat(y, at) for y in (x[order] for x in points) for f in (np.minimum, np.maximum)]
            found = verdicts_of_few(by[order], prior) if few else verdicts(leaf[order], code[order], None, n_leaves, prior)
        return pd.DataFrame([totals(number, *found, lost(span))], columns=names)

    found = summed(_shards(p, ds, draw, seed, shard_rows, answer, TOTALS))
    return [found[i] for i in range(len(ds))]
