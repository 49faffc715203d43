"""A stated workload of COUNT queries against all published rows or groups, in blocks.

The workload is held by every task as arrays (its size is checked first); rows pass by in
Arrow batches, and a block of rows meets all queries in a few numpy passes. A task hands on one
partial sum for each query that it touched, so what is shuffled doesn't depend on the number of rows.

Where rows are cells of a grid and many queries meet many of them, `range_sums` cuts the grid into slabs and sums each along its axes, so that
a query reads a slab's corners instead of its cells. It is exact as well, and takes the blocks where the grid is too sparse for slabs to pay.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Most queries of a workload; each task holds two numbers a query and axis.
MAX_QUERIES = 100_000
#: Pairs of a row and a query that are in memory at once, and that a task of its own is worth.
BLOCK_PAIRS, TASK_PAIRS = 1 << 20, 1 << 25


#: Cells of a slab, and pairs of a row and a query below which blocks are as good.
SLAB_CELLS, FEW_PAIRS = 1 << 22, 1 << 28


@dataclass
class Asked:
    """The queries' numbers and intervals; low and high have a row for each axis."""

    qid: np.ndarray
    low: np.ndarray
    high: np.ndarray
    sa_low: np.ndarray
    sa_high: np.ndarray


def asked(queries: DataFrame | Asked, axes: list[str]) -> Asked:
    """The workload (qid, x1_a, x1_b, ..., sa_lo, sa_hi) on the driver."""
    if isinstance(queries, Asked):
        return queries
    rows = queries.select("qid", *(F.col(f"{x}_{k}").cast("long") for x in axes for k in ("a", "b")), F.col("sa_lo").cast("long"), F.col("sa_hi").cast("long")).limit(MAX_QUERIES + 1).toArrow()
    if len(rows) > MAX_QUERIES:
        raise ValueError(f"a workload has more than {MAX_QUERIES} queries; ask it in parts")
    c = [rows.column(i).to_numpy() for i in range(rows.num_columns)]
    return Asked(c[0], np.array(c[1:-2:2]).reshape(len(axes), -1), np.array(c[2:-2:2]).reshape(len(axes), -1), c[-2], c[-1])


def boxes_of(q: Asked) -> tuple[Asked, np.ndarray]:
    """The distinct ranges of a workload's axes as queries of their own, and which of them each query has."""
    own, box = np.unique(np.concatenate([q.low, q.high]), axis=1, return_inverse=True)
    none = np.zeros(own.shape[1], np.int64)
    return Asked(np.arange(own.shape[1]), own[: len(q.low)], own[len(q.low) :], none, none), box.reshape(-1)


def together(some: list[Asked]) -> Asked:
    """Several workloads as one, for a single pass: queries are numbered from 0, workload by workload, each in the order of its own numbers."""
    if sum(len(q.qid) for q in some) > MAX_QUERIES:
        raise ValueError(f"the workloads have more than {MAX_QUERIES} queries; ask them in parts")
    order = [np.argsort(q.qid, kind="stable") for q in some]
    low, high, sa_low, sa_high = (np.concatenate([getattr(q, k)[..., o] for q, o in zip(some, order, strict=True)], -1) for k in ("low", "high", "sa_low", "sa_high"))
    return Asked(np.arange(len(sa_low)), low, high, sa_low, sa_high)


#: Shares (rows x queries) of a block whose axes' bounds are given, and whether a row meets a query at all.
Shares = Callable[[np.ndarray, np.ndarray, Asked], np.ndarray]


def inside(low: np.ndarray, high: np.ndarray, q: Asked) -> np.ndarray:
    """Points: whether they lie in the queries' intervals."""
    out = np.ones((low.shape[1], len(q.qid)), bool)
    for x, a, b in zip(low, q.low, q.high, strict=True):
        # rows of few distinct coordinates are compared once a coordinate
        own, which = np.unique(x, return_inverse=True)
        met = (own[:, None] >= a) & (own[:, None] <= b)
        out &= met[which.reshape(-1)] if len(own) < len(x) else met
    return out


def overlap(low: np.ndarray, high: np.ndarray, q: Asked) -> np.ndarray:
    """Boxes: the share of them that lies in the queries' intervals, rows being spread evenly."""
    out = np.ones((low.shape[1], len(q.qid)))
    for x, y, a, b in zip(low, high, q.low, q.high, strict=True):
        # rows of few distinct intervals are compared once an interval
        own, which = np.unique(np.stack([x, y]), axis=1, return_inverse=True)
        lo, hi = own[:, :, None]
        share = np.maximum(np.minimum(hi, b) - np.maximum(lo, a) + 1, 0) / (hi - lo + 1)
        out *= share[which.reshape(-1)]
    return out


def sums(rows: DataFrame, bounds: list[tuple[str, str]], weights: list[str], q: Asked, shares: Shares, value: Callable[..., np.ndarray], boxed: bool = False, n_rows: int | None = None) -> DataFrame:
    """qid, v (sum over rows of what value makes of a block's shares) for the queries that some row meets.

    bounds: names of each axis's low and high column; weights: further columns, which value gets as arrays (lists of a block's rows).
    boxed: shares are made once for queries of the same ranges, and value gets which of these columns each query has as well.
    n_rows: how many rows there are, if that is known: a few meet the queries in fewer tasks, as each hands on a sum for each query."""
    context = rows.sparkSession.sparkContext
    known = context.broadcast((q, *(boxes_of(q) if boxed else (q, None))))
    columns = list(dict.fromkeys([*(c for pair in bounds for c in pair), *weights]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        asked, own, box = known.value
        total, met = np.zeros(len(asked.qid)), np.zeros(len(own.qid), bool)
        # a block meets its distinct sensitive ranges as well
        step = max(1, BLOCK_PAIRS // max(1, len(own.qid), 0 if box is None else np.unique(np.stack([asked.sa_low, asked.sa_high]), axis=1).shape[1]))
        for batch in batches:
            for at in range(0, len(batch), step):
                part = batch.slice(at, step)
                low, high = (np.array([part.column(columns.index(pair[k])).to_numpy(zero_copy_only=False).astype(np.int64) for pair in bounds]).reshape(len(bounds), len(part)) for k in (0, 1))
                some = shares(low, high, own)
                met |= some.any(0)
                total += value(some, [part.column(columns.index(w)) for w in weights], asked, *(() if box is None else (box,)))
        met = met if box is None else met[box]
        yield pa.RecordBatch.from_arrays([pa.array(asked.qid[met]), pa.array(total[met])], names=["qid", "v"])

    # a row is few bytes and as many comparisons as there are queries, so rows are spread by number and not by size
    n = max(context.defaultParallelism, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    if n_rows is not None:
        n = min(n, 1 + n_rows * max(1, len(q.qid)) // TASK_PAIRS)
    spread = rows.select(*columns).repartition(n)
    return spread.mapInArrow(run, "qid long, v double").groupBy("qid").agg(F.sum("v").alias("v"))


#: What a sum adds up: from sensitive values and counts to (weights, whether only rows in the sensitive range count) of each part.
Parts = Callable[[np.ndarray, np.ndarray], list[tuple[np.ndarray, bool]]]


def range_sums(cells: DataFrame, axes: list[str], q: Asked, parts: Parts, join: Callable[[list[np.ndarray], Asked], np.ndarray], few_pairs: int | None = None) -> DataFrame:
    """qid, v (what join makes of the parts' sums over the query's ranges). cells: axes, sa, n, each combination of axes and sa once."""
    few_pairs = FEW_PAIRS if few_pairs is None else few_pairs
    seen = cells.agg(F.count("*"), F.count("sa"), *(f(F.col(x).cast("long")) for x in (*axes, "sa") for f in (F.min, F.max))).first()
    n_cells, whole = seen[0], seen[0] == seen[1]
    low = [seen[2 + 2 * i] for i in range(len(axes) + 1)]
    lengths = [seen[3 + 2 * i] - low[i] + 1 for i in range(len(axes) + 1)] if n_cells and whole else []
    if lengths:
        # the longest axes are cut into their values, one at least, until a slab has few cells
        order, sliced, size = sorted(range(len(axes)), key=lambda i: -lengths[i]), [], np.prod([n + 1.0 for n in lengths])
        for i in order:
            if sliced and size <= SLAB_CELLS:
                break
            sliced.append(i)
            size /= lengths[i] + 1
        slabs = np.prod([float(lengths[i]) for i in sliced])
        corners = slabs * (size * (len(axes) + 1) + len(q.qid) * 2.0 ** (len(axes) - len(sliced) + 1))
        lengths = lengths if size <= SLAB_CELLS and few_pairs <= n_cells * len(q.qid) >= corners / 4 else []
    if not lengths:

        def value(met: np.ndarray, columns: list, q: Asked) -> np.ndarray:
            sa, n = (c.to_numpy(zero_copy_only=False) for c in columns)
            ranged = None
            out = []
            for weight, own in parts(sa, n):
                if own and ranged is None:
                    ranged = met & (sa[:, None] >= q.sa_low) & (sa[:, None] <= q.sa_high)
                out.append(weight @ (ranged if own else met))
            return join(out, q)

        return sums(cells, [(x, x) for x in axes], ["sa", "n"], q, inside, value)

    inner = [i for i in range(len(axes)) if i not in sliced]
    shape = [lengths[i] for i in (*inner, len(axes))]
    context = cells.sparkSession.sparkContext
    known = context.broadcast(q)
    number = F.lit(0).cast("long")
    for i in sliced:
        number = number * lengths[i] + (F.col(axes[i]).cast("long") - low[i])
    flat = F.lit(0).cast("long")
    for i, c in zip((*inner, len(axes)), (*(axes[i] for i in inner), "sa"), strict=True):
        flat = flat * (lengths[i] + 1) + (F.col(c).cast("long") - low[i] + 1)

    def answer(slab: int, at: np.ndarray, sa: np.ndarray, n: np.ndarray, asked: Asked) -> tuple[np.ndarray, np.ndarray]:
        hit = np.ones(len(asked.qid), bool)
        for i in reversed(sliced):
            slab, x = divmod(slab, lengths[i])
            hit &= (asked.low[i] <= x + low[i]) & (asked.high[i] >= x + low[i])
        some = np.flatnonzero(hit)
        strides = np.cumprod([1, *[k + 1 for k in shape[::-1]]])[-2::-1]
        # a range's ends among the running sums; an empty one adds nothing
        ends = [(np.clip(asked.low[i][some] - low[i], 0, lengths[i]), np.clip(asked.high[i][some] - low[i] + 1, 0, lengths[i])) for i in inner]
        span = (np.clip(asked.sa_low[some] - low[-1], 0, lengths[-1]), np.clip(asked.sa_high[some] - low[-1] + 1, 0, lengths[-1]))
        out = []
        for weight, own in parts(sa, n):
            cube = np.bincount(at, weight, int(np.prod([k + 1 for k in shape]))).reshape([k + 1 for k in shape])
            for axis in range(len(shape)):
                np.cumsum(cube, axis, out=cube)
            cube = cube.reshape(-1)
            last = span if own else (np.zeros(len(some), np.int64), np.full(len(some), lengths[-1]))
            total = np.zeros(len(some))
            for corner in range(1 << len(shape)):
                place, sign = np.zeros(len(some), np.int64), 1
                for j, (pair, stride) in enumerate(zip((*ends, last), strides, strict=True)):
                    high = corner >> j & 1
                    sign = sign if high else -sign
                    place += pair[high] * stride
                total += sign * cube[place]
            out.append(total)
        return some, join(out, Asked(asked.qid[some], asked.low[:, some], asked.high[:, some], asked.sa_low[some], asked.sa_high[some]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        asked = known.value
        total, met = np.zeros(len(asked.qid)), np.zeros(len(asked.qid), bool)
        now, held = None, []

        def settle_slab() -> None:
            some, v = answer(now, *(np.concatenate(c) for c in zip(*held, strict=True)), asked)
            total[some] += v
            met[some] = True

        for batch in batches:
            slab, *rest = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
            for piece in np.split(np.arange(len(slab)), np.flatnonzero(np.diff(slab)) + 1) if len(slab) else ():
                if now is not None and slab[piece[0]] != now:
                    settle_slab()
                    held = []
                now = int(slab[piece[0]])
                held.append([c[piece] for c in rest])
        if held:
            settle_slab()
        yield pa.RecordBatch.from_arrays([pa.array(asked.qid[met]), pa.array(total[met])], names=["qid", "v"])

    spread = cells.select(number.alias("slab"), flat.alias("at"), F.col("sa").cast("long").alias("sa"), "n")
    spread = spread.repartition(max(context.defaultParallelism, int(cells.sparkSession.conf.get("spark.sql.shuffle.partitions"))), "slab").sortWithinPartitions("slab")
    return spread.mapInArrow(run, "qid long, v double").groupBy("qid").agg(F.sum("v").alias("v"))
