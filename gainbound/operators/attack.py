"""Attacks on releases: naive Bayes, exchangeable assignment, corruption, composition and linkage."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gainbound.operators.deal import Dealt, cells_of, deal_cells, deal_rank, encode, planned_on, survey
from gainbound.operators.perturb import Randomiser, reconstruct
from gainbound.operators.settle import forget, settle, settle_columns
from gainbound.plans.spec import ReleaseSpec

FLOOR = 1e-12
#: Share of rows that a round of the exchangeable assignment may still change when it is called done, and most rounds.
STOP, ROUNDS = 0.001, 60
#: Most rows of the small tables that go to every task.
MAX_SMALL = 1 << 20


def small(df: DataFrame) -> DataFrame:
    """df for a broadcast, if it has at most MAX_SMALL rows; a larger one is joined by a shuffle."""
    return F.broadcast(df) if df.limit(MAX_SMALL + 1).count() <= MAX_SMALL else df


def marginals(encoded: DataFrame, axes: list[str], weight: Column | None = None) -> DataFrame:
    """axis, value, sa and n for every axis, by one pass with grouping sets' effect: rows are unpivoted after counting cells."""
    cells = encoded.groupBy(*axes, "sa").agg((F.count("*") if weight is None else F.sum(weight)).alias("n"))
    long = cells.select("sa", "n", F.explode(F.array(*[F.struct(F.lit(i + 1).alias("axis"), F.col(x).cast("long").alias("value")) for i, x in enumerate(axes)])).alias("a"))
    return long.groupBy(F.col("a.axis").alias("axis"), F.col("a.value").alias("value"), "sa").agg(F.sum("n").alias("n"))


def conditionals(marginal: DataFrame, prior: DataFrame) -> DataFrame:
    """axis, value, sa and cond = n / prior_n."""
    overall = prior.select(F.col("sa").alias("_sa"), "prior_n")
    return marginal.join(F.broadcast(overall), F.col("sa").eqNullSafe(F.col("_sa"))).select("axis", "value", "sa", (F.col("n") / F.col("prior_n")).alias("cond"))


def reconstructed_marginals(published: DataFrame, axes: list[str], r: Randomiser) -> DataFrame:
    """The marginals behind randomised rows: each value's counts reconstructed, negative ones set to 0."""
    kind = published.schema["sa"].dataType.simpleString()
    seen = marginals(published, axes).withColumnRenamed("n", "e")
    return reconstruct(seen, r, ["axis", "value"], kind).select("axis", "value", "sa", F.greatest("n_hat", F.lit(0.0)).alias("n"))


def box_marginals(published: DataFrame, axes: list[str], domains: list[tuple[int, int]]) -> DataFrame:
    """Rows of each sensitive value in groups whose box covers a value of an axis. published: (ec, sa, n, boxes).

    An interval adds its rows where it begins and takes them away after its end; a running sum over an axis's values, of which
    only those where something begins or ends are held, gives the counts between. No interval is compared with any value."""
    steps = []
    for i, x in enumerate(axes):
        lo, hi = domains[i]
        steps += [F.struct(F.lit(i + 1).alias("axis"), F.col(f"{x}_lo").cast("long").alias("at"), F.col("n").alias("d")), F.struct(F.lit(i + 1).alias("axis"), (F.col(f"{x}_hi").cast("long") + 1).alias("at"), (-F.col("n")).alias("d"))]
    edges = published.select("sa", F.explode(F.array(*steps)).alias("s")).groupBy("sa", F.col("s.axis").alias("axis"), F.col("s.at").alias("at")).agg(F.sum("s.d").alias("d"))
    # one axis and sensitive value: at most as many rows as the axis has values
    w = Window.partitionBy("axis", "sa").orderBy("at")
    runs = edges.select("axis", "sa", "at", F.sum("d").over(w).alias("n"), F.lead("at").over(w).alias("next")).where("n > 0 and next is not null")
    return runs.select("axis", F.explode(F.sequence(F.col("at"), F.col("next") - 1)).alias("value"), "sa", "n")


def bayes_predict(cells: DataFrame, axes: list[str], cond: DataFrame, prior: DataFrame) -> DataFrame:
    """The most probable sensitive value of each distinct combination of coordinates: axes and guess; ties go to the smallest value."""
    spots = cells.select(*axes).distinct()
    # spots x values of the domain: each spot is scored for each value
    scored = spots.crossJoin(F.broadcast(prior.select("sa", F.ln("p").alias("score"))))
    cond = settle(cond)
    for i, x in enumerate(axes):
        c = cond.where(F.col("axis") == i + 1).select(F.col("value").alias(f"_v{i}"), F.col("sa").alias(f"_s{i}"), "cond")
        scored = scored.join(small(c), (F.col(x) == F.col(f"_v{i}")) & F.col("sa").eqNullSafe(F.col(f"_s{i}")), "left").withColumn("score", F.col("score") + F.ln(F.greatest(F.coalesce("cond", F.lit(0.0)), F.lit(FLOOR)))).drop("cond", f"_v{i}", f"_s{i}")
    # rounded, so that scores equal but for the order of additions tie
    best = F.min(F.struct((-F.round("score", 9)).alias("behind"), F.col("sa").alias("guess")))
    return scored.groupBy(*axes).agg(best.alias("b")).select(*axes, F.col("b.guess").alias("guess"))


def success(cells: DataFrame, axes: list[str], guesses: DataFrame) -> DataFrame:
    """Share of rows whose sensitive value is guessed. cells: (axes, sa, n)."""
    return cells.join(guesses, axes).agg((F.sum(F.when(F.col("sa").eqNullSafe(F.col("guess")), F.col("n")).otherwise(0)) / F.sum("n")).alias("success"), F.sum("n").alias("n_rows"))


def laplace(u: Column, scale: float) -> Column:
    """Laplace noise from a uniform, by the inverse of its distribution."""
    c = u - 0.5
    return -F.signum(c) * scale * F.ln(F.greatest(1 - 2 * F.abs(c), F.lit(1e-300)))


def noisy(marginal: DataFrame, epsilon: float, n_axes: int, seed: int = 3) -> DataFrame:
    """The counts with Laplace noise of scale (axes / epsilon), not below a tenth; drawn by hashes, so that a retry adds the same."""
    digest = F.md5(F.concat_ws("|", F.lit(str(seed)), "axis", "value", "sa"))
    u = F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") / float(1 << 52)
    return marginal.select("axis", "value", "sa", F.greatest(F.col("n") + laplace(u, n_axes / epsilon), F.lit(0.1)).alias("n"))


#: Rows of a chunk of whole groups, about as many as a task has at least and at most, and pairs of cells and values that are ordered at once.
CHUNK_ROWS, FEW_ROWS, PART_ROWS, PAIRS = 1 << 18, 1 << 15, 1 << 20, 1 << 20
#: Fewest groups that are served step by step together, and pairs that each then meets before used-up ones are dropped.
TOGETHER, STEPS = 64, 32


def _bytes(x: np.ndarray) -> bytes:
    """Numbers from 0 on in as few bytes each as the largest needs; the first byte tells how many."""
    width = np.min_scalar_type(int(x.max(initial=0)))
    return bytes([width.itemsize]) + x.astype(width).tobytes()


def _numbers(x: bytes) -> np.ndarray:
    return np.frombuffer(x, f"u{x[0]}", offset=1)


def _order(*columns: np.ndarray) -> np.ndarray:
    """Stable order by columns, the first one first. Narrow columns are joined into one number with the place, which sorts fastest."""
    n = len(columns[0])
    key, bits = np.zeros(n, np.int64), 0
    for c in columns:
        low, high = (int(c.min()), int(c.max())) if n else (0, 0)
        wide = (high - low).bit_length()
        bits += wide
        if bits + n.bit_length() > 63:
            return np.lexsort(columns[::-1])
        key = (key << wide) | (c - low)
    wide = n.bit_length()
    return np.sort((key << wide) | np.arange(n)) & ((1 << wide) - 1)


def _rank(x: np.ndarray) -> np.ndarray:
    """Rank of each number, equal ones sharing theirs."""
    order = np.argsort(x)
    sorted_ = x[order]
    out = np.empty(len(x), np.int64)
    out[order] = np.cumsum(np.r_[False, sorted_[1:] != sorted_[:-1]][: len(x)])
    return out


def _spread(counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Number of the entry that each of sum(counts) items belongs to, and the item's place in it."""
    entry = np.repeat(np.arange(len(counts)), counts)
    return entry, np.arange(len(entry)) - (np.cumsum(counts) - counts)[entry]


def _serve_one(cell: list, own: list, rank: list, free: list, room: list, rows: Callable[[int], np.ndarray]) -> list[int]:
    """How many rows each pair of a group takes, pairs in order. Where cells tie for a value, their rows take turns in the group's order of rows.

    rows: places of a cell's rows in the group, in ascending order; those that are free are the last ones. free and room are used up."""
    take, left, i = [0] * len(cell), sum(free[c] for c in set(cell)), 0
    while left:
        j = i + 1
        while j < len(cell) and rank[j] == rank[i]:
            j += 1
        if j - i == 1 or len(set(own[i:j])) == j - i:
            for k in range(i, j):
                n = min(free[cell[k]], room[own[k]])
                if n:
                    take[k] = n
                    free[cell[k]] -= n
                    room[own[k]] -= n
                    left -= n
        else:
            tied = {}
            for k in range(i, j):
                tied.setdefault(cell[k], []).append(k)
            for _, c in sorted((p, c) for c in tied if free[c] for p in rows(c)[-free[c] :].tolist()):
                for k in tied[c]:
                    if room[own[k]]:
                        take[k] += 1
                        free[c] -= 1
                        room[own[k]] -= 1
                        left -= 1
                        break
        i = j
    return take


def _serve(score: Callable, n_cells: np.ndarray, n_own: np.ndarray, length: np.ndarray, own: np.ndarray, room: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Each group's values given to its rows, best score first, each as often as the group has it: (cell, value, number of rows), a cell's rows in order.

    Rows of a group with the same coordinates are a cell and score the same, so cells and values are paired, not rows and values. A pair serves as many rows
    as its cell and its value have left; equal scores go by the rows' order, then by value. score: from cells and values; n_cells, n_own: cells and
    values of each group; length: rows of a cell; room: rows of a group's value; place: of each row in its group, cell by cell."""
    free, room = length.copy(), room.copy()
    ends = np.cumsum(length)
    first_cell, first_own = np.cumsum(n_cells) - n_cells, np.cumsum(n_own) - n_own
    group, at = _spread(n_cells * n_own)
    cell, value = first_cell[group] + at // n_own[group], first_own[group] + at % n_own[group]
    rank = _rank(-score(cell, own[value]))
    order = _order(group, rank)
    group, cell, value, rank = group[order], cell[order], value[order], rank[order]
    take = np.zeros(len(cell), np.int64)

    # groups in which cells tie for a value go one by one
    same = (group[1:] == group[:-1]) & (rank[1:] == rank[:-1])
    block = np.cumsum(np.r_[True, ~same])
    tied = np.flatnonzero(np.r_[False, same] | np.r_[same, False])
    single = np.zeros(len(n_cells), bool)
    if len(tied):
        tied = tied[_order(block[tied], value[tied])]
        clash = (block[tied][1:] == block[tied][:-1]) & (value[tied][1:] == value[tied][:-1])
        single[group[tied[1:][clash]]] = True

    left = np.add.reduceat(length, first_cell)
    open_ = np.flatnonzero(~single[group])
    while len(open_):
        # pairs of a cell or a value that is used up are dropped together
        open_ = open_[(free[cell[open_]] > 0) & (room[value[open_]] > 0)]
        starts = np.flatnonzero(np.r_[True, group[open_][1:] != group[open_][:-1]][: len(open_)])
        if len(starts) < TOGETHER:
            single[group[open_[starts]]] = True
            break
        met = np.zeros(len(open_), bool)
        ends_at = np.r_[starts[1:], len(open_)]
        for step in range(STEPS):
            here = starts + step
            on = (here < ends_at) & (left[group[open_[starts]]] > 0)
            starts, ends_at, here = starts[on], ends_at[on], here[on]
            if not len(here):
                break
            k = open_[here]
            n = np.minimum(free[cell[k]], room[value[k]])
            take[k] = n
            free[cell[k]] -= n
            room[value[k]] -= n
            left[group[k]] -= n
            met[here] = True
        open_ = open_[~met]

    bounds = np.searchsorted(group, np.flatnonzero(single))
    for a, g in zip(bounds.tolist(), np.flatnonzero(single).tolist(), strict=True):
        some = a + np.flatnonzero((free[cell[a : a + n_cells[g] * n_own[g]]] > 0) & (room[value[a : a + n_cells[g] * n_own[g]]] > 0))
        c0, v0 = int(first_cell[g]), int(first_own[g])
        cells, values = slice(c0, c0 + int(n_cells[g])), slice(v0, v0 + int(n_own[g]))
        take[some] = _serve_one((cell[some] - c0).tolist(), (value[some] - v0).tolist(), rank[some].tolist(), free[cells].tolist(), room[values].tolist(), lambda c, c0=c0: place[ends[c0 + c] - length[c0 + c] : ends[c0 + c]])

    used = np.flatnonzero(take)
    used = used[_order(cell[used])]
    return cell[used], own[value[used]], take[used]


def exchange_attack(rows: DataFrame | Dealt, axes: list[str], rounds: int = ROUNDS, seed: int = 5, stop: float = STOP, counts: list[tuple] | None = None) -> tuple[float, float, int, float]:
    """Assigns each group's sensitive values to its rows by an evolving naive Bayes model.

    rows: row_key, axes, sa, ec, where sa is used as each group's multiset and, at the end, as the truth, or such rows by shards; counts: (value, rows) of
    sa, if they are known, as they must be for shards. Returns the success rate, that of random assignment, the rounds taken and the share of rows that the last one changed, which is
    above `stop` if the attack was cut. Whole groups are packed into chunks once, by cell and in the order of row_key; a round is one pass over
    the chunks without a shuffle of rows, whose tasks sum their counts up. A group is a task's unit; the model, axes' values by sensitive values, is a small table."""
    from gainbound.operators.model import domain

    counts = domain(rows, "sa") if counts is None else counts
    values = [v for v, _ in sorted(counts, key=lambda x: (x[0] is None, x[0]))]
    spark, m = (rows.table if isinstance(rows, Dealt) else rows).sparkSession, len(values)
    names = ["n_cells", "n_own", "length", "own", "room", "code", "place", "given", *axes, "tally", "chance"]
    schema = ", ".join(f"{c} binary" for c in names[:-2]) + ", tally array<struct<axis int, value long, sa long, n long>>, chance double"
    struct = pa.struct([("axis", pa.int32()), ("value", pa.int64()), ("sa", pa.int64()), ("n", pa.int64())])

    class Sums:
        """A task's counts of axes' values by given values, and its rows, moved rows and hits, as counts of an axis 0."""

        def __init__(self):
            self.of, self.rows = [{} for _ in axes], np.zeros(3, np.int64)

        def add(self, points: list[np.ndarray], given: np.ndarray, n: np.ndarray, size: int, moved: int, hit: int) -> None:
            self.rows += (size, moved, hit)
            for own, x in zip(self.of, points, strict=True):
                held, at = np.unique(x, return_inverse=True)
                per = np.bincount(at * m + given, n, len(held) * m).astype(np.int64)
                for v, counted in zip(held.tolist(), per.reshape(-1, m), strict=True):
                    if v in own:
                        own[v] += counted
                    else:
                        own[v] = counted.copy()

        def batch(self, chance: float = 0.0) -> pa.RecordBatch:
            parts = [(np.zeros(3, np.int64), np.arange(3), np.zeros(3, np.int64), self.rows)]
            for i, own in enumerate(self.of):
                per = np.array(list(own.values()), np.int64).reshape(-1, m)
                at, sa = np.nonzero(per)
                parts.append((np.full(len(at), i + 1), np.array(list(own), np.int64)[at], sa, per[at, sa]))
            axis, *rest = (np.concatenate(c) for c in zip(*parts, strict=True))
            entries = pa.StructArray.from_arrays([pa.array(axis.astype(np.int32)), *map(pa.array, rest)], fields=list(struct))
            tally = pa.ListArray.from_arrays(pa.array([0, len(entries)], pa.int32()), entries)
            return pa.RecordBatch.from_arrays([*(pa.array([None], pa.binary()) for _ in names[:-2]), tally, pa.array([chance])], names=names)

    def chunk(packed: list[bytes]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([*(pa.array([x], pa.binary()) for x in packed), pa.array([None], pa.list_(struct)), pa.array([0.0])], names=names)

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, chance = Sums(), 0.0

        def out(ec, code, *points) -> pa.RecordBatch:
            nonlocal chance
            at, given = np.r_[0, np.flatnonzero(ec[1:] != ec[:-1]) + 1, len(ec)], np.empty(len(ec), np.int64)
            for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
                given[a:b] = np.random.default_rng([seed, int(ec[a])]).permutation(code[a:b])
            group, place = _spread(np.diff(at))
            order = _order(group, code)
            new = np.flatnonzero(np.r_[True, (np.diff(group[order]) != 0) | (np.diff(code[order]) != 0)])
            own, owner, room = code[order][new], group[order][new], np.diff(np.r_[new, len(ec)])
            chance += float((room**2 / np.diff(at)[owner]).sum())
            order = _order(group, *points)
            group, code, given, place, *points = (c[order] for c in (group, code, given, place, *points))
            new = np.r_[True, np.logical_or.reduce([np.diff(c) != 0 for c in (group, *points)])]
            sums.add(points, given, np.ones(len(ec)), len(ec), len(ec), int((given == code).sum()))
            cells = np.flatnonzero(new)
            n_groups = len(at) - 1
            parts = (np.bincount(group[cells], minlength=n_groups), np.bincount(owner, minlength=n_groups), np.diff(np.r_[cells, len(ec)]), own, room, code, place, given)
            return chunk([*map(_bytes, parts), *(x[cells].astype(np.int64).tobytes() for x in points)])

        held, size = [], 0
        for batch in batches:
            held.append([c.to_numpy(zero_copy_only=False) for c in batch.columns])
            size += len(batch)
            if size >= CHUNK_ROWS:
                columns = [np.concatenate(c) for c in zip(*held, strict=True)]
                # the last group may go on
                new = np.flatnonzero(columns[0][1:] != columns[0][:-1])
                last = int(new[-1]) + 1 if len(new) else 0
                if last:
                    yield out(*(c[:last] for c in columns))
                held = [[c[last:] for c in columns]]
                size = len(held[0][0])
        if size:
            yield out(*(np.concatenate(c) for c in zip(*held, strict=True)))
        yield sums.batch(chance)

    def by_groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        filling, code, points = shards.value
        held = [[c.to_numpy() for c in batch.columns] for batch in batches if len(batch)]
        if held:
            shard, cell = (np.concatenate(c) for c in zip(*held, strict=True))
            ec = filling.groups(int(shard[0]), cell)
            order = _order(ec)
            ec, cell = ec[order], cell[order]
            for i in range(0, len(ec), CHUNK_ROWS):
                some = cell[i : i + CHUNK_ROWS]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in (ec[i : i + CHUNK_ROWS], code[some], *(x[some] for x in points))], names=["ec", "code", *axes])

    def counted(state: DataFrame, entries: int) -> tuple[list[tuple[np.ndarray, np.ndarray]], list[int]]:
        """Each axis's values with their counts by sensitive value, and rows, moved rows and hits. entries: at most as many counts of all tasks, which few are summed here."""
        found = state.where("tally is not null").select(F.inline("tally"))
        if entries > MAX_SMALL:
            found = found.groupBy("axis", "value", "sa").agg(F.sum("n").alias("n")).limit(MAX_SMALL + 1)  # axes' domains x values
        found = found.toArrow()
        if len(found) > MAX_SMALL:
            raise ValueError("the axes have too many values for a model; coarsen them")
        axis, value, sa, n = (found.column(c).to_numpy() for c in ("axis", "value", "sa", "n"))
        table, totals = [], np.zeros(3, np.int64)
        np.add.at(totals, value[axis == 0], n[axis == 0])
        for i in range(len(axes)):
            own = axis == i + 1
            held, at = np.unique(value[own], return_inverse=True)
            per = np.zeros((len(held), m))
            np.add.at(per, (at, sa[own]), n[own])
            table.append((held, per))
        return table, totals.tolist()

    if isinstance(rows, Dealt):
        code_of = {v: i for i, v in enumerate(values)}
        shards = spark.sparkContext.broadcast((rows.filling, np.array([code_of[v] for v in rows.sa], np.int64), rows.points))
        state = settle(rows.table.mapInArrow(lambda batches: first(by_groups(batches)), schema))
    else:
        kind = rows.schema["sa"].dataType.simpleString()
        codes = spark.createDataFrame([(v, i) for i, v in enumerate(values)], f"_sa {kind}, code long")
        coded = rows.select("row_key", *axes, "ec", "sa").join(F.broadcast(codes), F.col("sa").eqNullSafe(F.col("_sa"))).select(F.col("ec").cast("long").alias("ec"), "row_key", "code", *(F.col(x).cast("long").alias(x) for x in axes))
        # as many tasks as keep all cores busy in a round, but none for few rows
        cores, n = spark.sparkContext.defaultParallelism, sum(k for _, k in counts)
        n_parts = max(1, min(-(-n // FEW_ROWS), cores * -(-n // (PART_ROWS * cores))))
        state = settle(coded.repartition(n_parts, "ec").sortWithinPartitions("ec", "row_key").drop("row_key").mapInArrow(first, schema))
    table, (total, changed, hit) = counted(state, MAX_SMALL + 1)
    # a task's counts in a round: three totals, and its part of the axes' domains x values
    entries = len(rows.filling.nodes if isinstance(rows, Dealt) else range(n_parts)) * (3 + m * sum(len(held) for held, _ in table))
    chance = state.agg(F.sum("chance")).first()[0]
    taken = 0
    while taken < rounds and changed > stop * total:
        taken += 1
        size = table[-1][1].sum(0)
        conds = [(held, np.log(np.maximum(n / np.maximum(size, 1), FLOOR))) for held, n in table]
        model = spark.sparkContext.broadcast((conds, np.log(np.maximum(size, 1) / size.sum())))

        def again(batches: Iterator[pa.RecordBatch], model=model) -> Iterator[pa.RecordBatch]:
            conds, prior = model.value
            sums = Sums()
            for batch in batches:
                for i in range(len(batch)):
                    packed = [batch.column(j)[i].as_py() for j in range(len(names) - 2)]
                    if packed[0] is None:
                        continue
                    n_cells, n_own, length, own, room, code, place, before = map(_numbers, packed[:8])
                    n_cells, n_own, length, own, room = (x.astype(np.int64) for x in (n_cells, n_own, length, own, room))
                    points = [np.frombuffer(x, np.int64) for x in packed[8:]]
                    spots = [np.searchsorted(held, x) for x, (held, _) in zip(points, conds, strict=True)]
                    done = []
                    c, v, r = (np.r_[0, np.cumsum(x)] for x in (n_cells, n_own, length))
                    # blocks of whole groups with at most PAIRS pairs, or of one group
                    pairs, a = np.cumsum(n_cells * n_own), 0
                    while a < len(n_cells):
                        b = max(a + 1, int(np.searchsorted(pairs, (pairs[a - 1] if a else 0) + PAIRS, "right")))
                        cells = slice(c[a], c[b])

                        def score(cell, value, spots=spots, cells=cells):
                            out = prior[value]
                            for spot, (_, cond) in zip(spots, conds, strict=True):
                                out += cond[spot[cells][cell], value]
                            return out

                        cell, value, n = _serve(score, n_cells[a:b], n_own[a:b], length[cells], own[v[a] : v[b]], room[v[a] : v[b]], place[r[c[a]] : r[c[b]]])
                        done.append((cell + c[a], value, n))
                        a = b
                    cell, value, n = (np.concatenate(x) for x in zip(*done, strict=True))
                    given = np.repeat(value.astype(code.dtype), n)
                    sums.add([x[cell] for x in points], value, n, len(code), int((given != before).sum()), int((given == code).sum()))
                    packed[7] = _bytes(given)
                    yield chunk(packed)
            yield sums.batch()

        old, state = state, settle(state.mapInArrow(again, schema))
        table, (total, changed, hit) = counted(state, entries)
        forget(old)
        model.unpersist()
    return float(hit / total), float(chance / total), taken, changed / max(1, total)


def exchange_attack_on(df: DataFrame, spec: ReleaseSpec, beta: float) -> tuple[float, float, int, float]:
    """The attack on the release of df by rank dealing. df is encoded and kept by columns once; where it has few cells, their counts plan the release and deal its rows."""
    spec.validate(df)
    encoded, axes = settle_columns(encode(df, spec)), spec.axes
    cells = cells_of(encoded, axes, MAX_SMALL)
    surveyed = survey(encoded if cells is None else df.sparkSession.createDataFrame(cells), spec)
    d = planned_on(encoded, spec, *surveyed, beta)
    if cells is None:
        return exchange_attack(deal_rank(d), axes, counts=d.counts)
    n = sum(k for _, k in d.counts)
    shard_rows = max(FEW_ROWS, min(PART_ROWS, -(-n // df.sparkSession.sparkContext.defaultParallelism)))
    return exchange_attack(deal_cells(d, cells, shard_rows), axes, counts=d.counts)


def corruption(hist: DataFrame, known: int) -> DataFrame:
    """Per group: the largest posterior of a value for a victim after the `known` most helpful others have been learned."""
    top = hist.groupBy("ec").agg(F.max("n").alias("n_max"), F.max("size").alias("size"))
    rest = F.greatest(F.col("size") - known, F.col("n_max"))
    return top.select("ec", "size", (F.col("n_max") / F.col("size")).alias("before"), (F.col("n_max") / rest).alias("after"))


def corruption_randomised(r: Randomiser, counts: dict, known: int) -> list[tuple]:
    """Per published value: the posterior that it is the true one, before and after `known` rows of other values are learned, and whether the bound holds."""
    total = sum(counts.values())
    pull = sum(counts[v] * o for v, o in zip(r.values, r.off, strict=True))
    out = []
    for v, keep, off, f in zip(r.values, r.keep, r.off, r.f, strict=True):
        own, others = counts[v] * keep, pull - counts[v] * off
        rest = others * max(total - counts[v] - known, 0) / (total - counts[v])
        out.append((v, own / (own + others), own / (own + rest), own / (own + others) <= f + 1e-9))
    return out


def composition(first: DataFrame, second: DataFrame) -> DataFrame:
    """Rows by how many sensitive values two releases of them leave possible. Both: (row_key, ec, sa)."""
    sets = [r.groupBy("ec").agg(F.collect_set("sa").alias("s")) for r in (first, second)]
    both = first.select("row_key", F.col("ec").alias("e1")).join(second.select("row_key", F.col("ec").alias("e2")), "row_key").groupBy("e1", "e2").agg(F.count("*").alias("n"))
    met = both.join(sets[0].select(F.col("ec").alias("e1"), F.col("s").alias("s1")), "e1").join(sets[1].select(F.col("ec").alias("e2"), F.col("s").alias("s2")), "e2")
    return met.groupBy(F.size(F.array_intersect("s1", "s2")).alias("possible")).agg(F.sum("n").alias("n_rows"))


def linkage(people: DataFrame, published: DataFrame, axis: str) -> DataFrame:
    """Candidates of each person by containment of a public attribute in the boxes. people: (person, value); published: (ec, size, boxes).

    Boxes become running sums over the axis's values, and a person looks up its own value."""
    lo, hi = F.col(f"{axis}_lo").cast("long"), F.col(f"{axis}_hi").cast("long")
    steps = F.array(F.struct(lo.alias("at"), F.col("size").alias("d"), F.lit(1).alias("g")), F.struct((hi + 1).alias("at"), (-F.col("size")).alias("d"), F.lit(-1).alias("g")))
    edges = published.select(F.explode(steps).alias("s")).groupBy(F.col("s.at").alias("at")).agg(F.sum("s.d").alias("d"), F.sum("s.g").alias("g"))
    # one row for each value of the axis at which a box begins or ends
    w = Window.partitionBy(F.lit(0)).orderBy("at")
    runs = edges.select("at", F.sum("d").over(w).alias("candidates"), F.sum("g").over(w).alias("groups"), F.lead("at").over(w).alias("next")).where("groups > 0 and next is not null")
    by_value = runs.select(F.explode(F.sequence(F.col("at"), F.col("next") - 1)).alias("value"), "candidates", "groups")
    return people.join(by_value, "value", "left").select("person", F.coalesce("candidates", F.lit(0)).cast("long").alias("candidates"), F.coalesce("groups", F.lit(0)).cast("long").alias("groups"))
