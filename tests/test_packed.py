"""Releases from a packed table: the same groups as by sorting all rows again."""

import pathlib
import threading

import numpy as np
import pytest
from pyspark.sql import functions as F

from gainbound.operators import deal, emddeal, grouped, packed
from gainbound.operators.search import beside, grid_of, search
from gainbound.plans import sizetree
from gainbound.plans.spec import Attribute, ReleaseSpec
from gainbound.queries.attacks import Compared

SPEC = ReleaseSpec((Attribute("a"), Attribute("b")), "s", "row_key")


@pytest.fixture(scope="module")
def people(spark):
    # hot cells, a null sensitive value and ties along the curve
    s = F.when(F.col("id") % 7 == 0, F.lit(None)).otherwise((F.col("id") * F.col("id") % 9).cast("int"))
    return spark.range(3000).select(F.md5(F.col("id").cast("string")).alias("row_key"), (F.col("id") * 37 % 50).cast("int").alias("a"), F.when(F.col("id") % 3 == 0, 5).otherwise((F.col("id") * 11 % 20).cast("int")).alias("b"), s.cast("int").alias("s"))


def _plain(rows, axes):
    return sorted(tuple(map(str, r)) for r in grouped.pairs(rows.withColumn("n", F.lit(1)), axes).groupBy("ec", "sa").agg(F.sum("n"), *(f for x in axes for f in (F.min(f"{x}_lo"), F.max(f"{x}_hi")))).collect())


def _merged(rows, axes):
    return sorted(tuple(map(str, r)) for r in rows.groupBy("ec", "sa").agg(F.sum("n"), *(f for x in axes for f in (F.min(f"{x}_lo"), F.max(f"{x}_hi")))).collect())


@pytest.mark.parametrize("shard_rows", [150, 1000, 1 << 17])
def test_packed_release_is_the_dealt_one(spark, people, shard_rows, monkeypatch):
    monkeypatch.setattr(packed, "CHUNK_ROWS", 200)
    d = deal.prepare(people, SPEC, 2.0)
    values = [v for v, _ in d.counts]
    own = packed.pack(deal.keyed(d, "hilbert"), SPEC.axes, values)
    assert own.counts.sum() == 3000
    assert _merged(packed.release(own, d, "curve", shard_rows=shard_rows), SPEC.axes) == _plain(deal.deal(d, "curve", shard_rows=shard_rows), SPEC.axes)


def test_packed_ranks_are_the_dealt_ones(spark, people):
    d = emddeal.prepare(people, SPEC, 0.2)
    own = packed.pack(deal.keyed(d, "zorder"), SPEC.axes, [v for v, _ in d.counts])
    assert _merged(packed.release(own, d, "rank"), SPEC.axes) == _plain(deal.deal(d, "rank"), SPEC.axes)


@pytest.mark.parametrize(("draw", "shard_rows"), [("curve", 150), ("curve", 1 << 17), ("rank", 150)])
def test_groups_of_several_plans_are_judged_in_one_job(spark, people, draw, shard_rows, monkeypatch):
    monkeypatch.setattr(packed, "CHUNK_ROWS", 200)
    monkeypatch.setattr(packed, "BLOCK_COUNTS", 50)
    # the loosest plan cuts, the tightest is one group
    ds = [deal.prepare(people, SPEC, b) for b in (3.0, 1.0, 0.01)]
    own = packed.pack(deal.keyed(ds[0], "zorder" if draw == "rank" else "hilbert"), SPEC.axes, [v for v, _ in sorted(ds[0].counts, key=lambda x: (x[0] is None, x[0]))])
    judged = packed.judge(own, ds, draw, shard_rows=shard_rows)
    for i, d in enumerate(ds):
        plain = grouped.judged(grouped.pairs(deal.deal(d, draw, shard_rows=shard_rows).withColumn("n", F.lit(1)), SPEC.axes), SPEC.axes, d.counts)
        got = judged.where(F.col("plan") == i).select(*plain.columns)
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, plain.collect())) and got.count() == d.tree.n_leaves


@pytest.mark.parametrize(("n", "buckets", "keys"), [(300, 4, 7), (2000, 9, 1), (4000, 20, 300), (3000, 5, 3000)])
def test_search_on_counts_fills_the_same_groups(n, buckets, keys):
    random = np.random.default_rng(n)
    key = np.sort(random.integers(0, 10 * keys, keys)[random.integers(0, keys, n)])
    bucket = np.minimum(random.integers(0, buckets, n), random.integers(0, buckets, n))
    sizes = tuple(np.bincount(bucket, minlength=buckets).tolist())
    leaves = sizetree.grow(sizes, sizetree.gain_rule(tuple(min(1.0, 2 * s / n) for s in sizes))).leaf_vectors()
    parts = [np.flatnonzero(bucket == j) for j in range(buckets)]
    plain = np.empty(n, np.int64)
    for leaf, _, rows in deal.fill_curve(parts, [key[r] for r in parts], leaves, 3, 1):
        plain[rows] = leaf
    assert (deal.fill_counts(bucket, key, leaves, 3, 1) == plain).all()


def test_midpoints_are_measured_ahead():
    """A search of 20 steps asks for its measures in one job for the grid and seven for the steps."""
    jobs, ready = [], set()

    def ahead(xs):
        jobs.append(len(xs))
        ready.update(xs)

    def measure(x):
        assert x in ready
        return x

    assert search(measure, lambda v: v <= 1.234, 0.0, 2.0, steps=20, grid=16, ahead=ahead)[0] == pytest.approx(1.234, abs=1e-5)
    assert jobs == [17, 7, 7, 7, 7, 7, 7, 3]


def test_a_table_is_sorted_once_for_all_releases(spark, people, monkeypatch):
    sorts, whole = [], deal.rank_in_bucket
    monkeypatch.setattr(deal, "rank_in_bucket", lambda *a, **k: sorts.append(1) or whole(*a, **k))
    monkeypatch.setattr(packed, "pack", lambda *a, pack=packed.pack: sorts.append(1) or pack(*a))
    c = Compared(spark, "", SPEC, people)
    got = beside(lambda b: c.measured("ours", b), [0.5, 1.0, 2.0, 2.0])
    assert got[2] == got[3] and all(m["beta"] <= b + 1e-6 for m, b in zip(got, (0.5, 1.0, 2.0), strict=False))
    assert len(sorts) == 1


def test_grid_is_measured_several_at_a_time():
    met = threading.Barrier(3, timeout=20)
    points = set(grid_of(0.0, 2.0, 2))

    def measure(x):
        if x in points:
            met.wait()  # passes only if all of the grid is under way at once
        return x

    assert search(measure, lambda v: v <= 1.5, 0.0, 2.0, steps=6, grid=2)[0] == pytest.approx(1.5, abs=0.04)


def test_exchange_rounds_shuffle_no_rows(spark, people, monkeypatch):
    """Whole groups are packed once; a round moves the model's counts only."""
    from gainbound.operators import attack

    monkeypatch.setattr(attack, "CHUNK_ROWS", 300)
    settled, whole = [], attack.settle
    monkeypatch.setattr(attack, "settle", lambda df: settled.append(df._jdf.queryExecution().toString()) or whole(df))
    d = deal.prepare(people.where("s is not null"), SPEC, 2.0)
    hit, chance, rounds, changed = attack.exchange_attack(deal.deal(d, "rank"), SPEC.axes, rounds=3)
    assert 0 <= hit <= 1 and 0 < chance < 1 and rounds <= 3 and 0 <= changed <= 1
    assert len(settled) == rounds + 1 and all("Exchange" not in plan and "FlatMapGroups" not in plan for plan in settled[1:])


def test_exchange_rounds_take_few_tasks_and_leave_no_files(spark, people, monkeypatch, tmp_path):
    """3,000 rows are one task's work, and a round's table goes when the next one stands."""
    from gainbound.operators import attack

    parts, whole = [], attack.settle
    monkeypatch.setattr(attack, "settle", lambda df: parts.append(df.rdd.getNumPartitions()) or whole(df))
    d = deal.prepare(people, SPEC, 2.0)
    rows = deal.deal(d, "rank").localCheckpoint()
    shared = pathlib.Path(spark.sparkContext.getCheckpointDir().removeprefix("file:"))
    before = set(shared.glob("*/rdd-*")) | set(shared.glob("rdd-*"))
    rounds = attack.exchange_attack(rows, SPEC.axes, rounds=3)[2]
    left = (set(shared.glob("*/rdd-*")) | set(shared.glob("rdd-*"))) - before
    assert rounds == 3 and parts == [1] * 4 and len(left) == 1


@pytest.mark.parametrize(("groups", "rows", "cells", "values", "levels"), [(200, 40, 6, 9, 4), (300, 12, 3, 5, 50), (3, 400, 30, 12, 6), (150, 30, 1, 8, 3)])
def test_cells_are_served_as_their_rows_would_be(groups, rows, cells, values, levels):
    """Values go to rows by best score, equal scores by row and then by value; few levels make many ties between cells."""
    from gainbound.operators import attack

    random = np.random.default_rng(rows)
    scores = random.integers(0, levels, (cells, values)).astype(float)
    cell, code = random.integers(0, cells, (groups, rows)), random.integers(0, values, (groups, rows))
    want, parts = [], []
    for g in range(groups):
        own, room = np.unique(code[g], return_counts=True)
        free, given, left = [True] * rows, np.empty(rows, np.int64), room.copy()
        for _, r, j in sorted((-scores[cell[g, r], v], r, j) for r in range(rows) for j, v in enumerate(own.tolist())):
            if free[r] and left[j]:
                free[r], given[r] = False, own[j]
                left[j] -= 1
        order = np.argsort(cell[g], kind="stable")
        held, length = np.unique(cell[g], return_counts=True)
        want.append(given[order])
        parts.append((held, length, own, room, order))
    held, length, own, room, place = (np.concatenate(x) for x in zip(*parts, strict=True))
    asked = []
    found, value, n = attack._serve(lambda c, v: asked.append(len(c)) or scores[held[c], v], np.array([len(p[0]) for p in parts]), np.array([len(p[2]) for p in parts]), length, own, room, place)
    assert (np.repeat(value, n) == np.concatenate(want)).all() and (np.bincount(found, n) == length).all()
    assert sum(asked) == sum(len(p[0]) * len(p[2]) for p in parts)


@pytest.mark.parametrize("shard_rows", [100, 700, 5000])
def test_rows_dealt_by_cells_are_in_the_groups_of_their_ranks(spark, people, shard_rows):
    """Keys that a shard's end cuts are ranked, the others are not; nulls are a value."""
    d = deal.prepare(people, SPEC, 3.0)
    dealt = deal.deal_cells(d, deal.cells_of(d.encoded, SPEC.axes, 10_000), shard_rows)
    plain = deal.deal(d, "rank").orderBy("ec", "row_key").collect()
    want = [(r.ec, r.x1, r.x2, r.sa) for r in plain]
    got, parts = [], dealt.table.rdd.glom().collect()
    for part in parts:
        cell = np.array([r.cell for r in part])
        assert len({r.shard for r in part}) == 1
        ec = dealt.filling.groups(part[0].shard, cell)
        order = np.argsort(ec, kind="stable")
        got += [(int(ec[i]), *(int(x[cell[i]]) for x in dealt.points), dealt.sa[cell[i]]) for i in order]
    assert got == want and (len(parts) > 1) == (shard_rows < 3000)
    assert deal.cells_of(d.encoded, SPEC.axes, 10) is None
