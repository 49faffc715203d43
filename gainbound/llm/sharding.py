"""Sharding by minimax contiguous partition of atomic groups.

Documents of equal text form an atomic group; groups stand in the order of their smallest
doc_id. The order is cut into `shards` runs so that the largest run is as small as it can
be: a binary search over the capacity, each candidate checked by filling shards greedily.

The groups are never sorted globally nor collected. The driver sees sums over at most
some thousand intervals of the order. A capacity is certainly feasible if greedy filling that
may only cut at known interval borders succeeds, and certainly not if filling that may cut
anywhere fails; the two bounds leave a few intervals in which a cut can fall, and
only those are split further, until the smallest feasible capacity is exact. A round is one
aggregation, and each narrows an interval by a factor of SPLIT.

Slots number a shard's documents by doc_id without gaps: counts by interval of doc_id give
offsets, and a window ranks only within an interval, so no task holds a shard.

Edge cases: a null text has no bytes and its checksum is 0; null texts are one group, apart from empty ones. Rows
with a null doc_id are placed as if theirs were the smallest long. Repeated rows are placed each, with slots of their
own. Fewer groups than shards leave the last shards empty. A zero-size weight can't occur, as each row counts one byte more than its text.
"""

from __future__ import annotations

import bisect

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gainbound.llm.common import fresh, integer_id, settle, small_join

SPLIT = 512
#: Rows that an interval of doc_id should have when slots are numbered, and the bounds of the number of intervals.
RANK_ROWS, MIN_RANKS, MAX_RANKS = 1 << 18, 1024, 8192
_NULL_ID = -(1 << 63)


def capacity_of(sizes: list[int], shards: int) -> int:
    """Smallest capacity with which greedy filling needs at most `shards` runs."""
    low, high = max([0, *sizes, -(-sum(sizes) // shards)]), sum(sizes)
    while low < high:
        mid = (low + high) // 2
        runs, room = 1, mid
        for s in sizes:
            if s > room:
                runs, room = runs + 1, mid
            room -= s
        low, high = (low, mid) if runs <= shards else (mid + 1, high)
    return low


class _Known:
    """What the driver knows of the order: intervals [first, end) with their sums; `whole` ones hold a single group."""

    def __init__(self, intervals: list[tuple[int, int, int, int, int]]):
        self.intervals = intervals  # first key, end key, total, largest group, groups
        self.before = [0]
        for x in intervals:
            self.before.append(self.before[-1] + x[2])

    def greedy(self, capacity: int, shards: int, anywhere: bool) -> tuple[bool, list[int]]:
        """Whether filling reaches the end, and the filled prefix after each shard. anywhere: in an interval of many groups a cut may be at any byte."""
        at, ends = 0, []
        for _ in range(shards):
            want = at + capacity
            i = bisect.bisect_right(self.before, want) - 1  # intervals before i fit whole
            if i >= len(self.intervals):
                at = self.before[-1]
            elif anywhere and self.intervals[i][4] > 1:
                at = want
            else:
                at = max(at, self.before[i])
            ends.append(at)
        return at >= self.before[-1], ends

    def smallest(self, low: int, shards: int, anywhere: bool) -> int:
        high = max(low, self.before[-1])
        while low < high:
            mid = (low + high) // 2
            low, high = (low, mid) if self.greedy(mid, shards, anywhere)[0] else (mid + 1, high)
        return low


def plan_cuts(groups: DataFrame, shards: int) -> tuple[int, list[int]]:
    """The smallest capacity, and the first key of each shard but the first. groups: key long (unique), size long."""

    def summed(split: list[tuple[int, int]]) -> list:
        """Sums of each of the SPLIT parts of the intervals: first and last key, total, largest group, groups."""
        first = np.array([a for a, _ in split], np.int64)
        last = np.array([b - 1 for _, b in split], np.int64)
        width = np.array([-(-(b - a) // SPLIT) for a, b in split], np.uint64)

        def run(batches):
            for batch in batches:
                key, size = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
                at = np.maximum(np.searchsorted(first, key, "right") - 1, 0)
                inside = (key >= first[at]) & (key <= last[at])
                key, size, at = key[inside], size[inside], at[inside]
                # unsigned differences, as keys may lie 2**63 apart
                part = at * (SPLIT + 1) + ((key.view(np.uint64) - first[at].view(np.uint64)) // width[at]).astype(np.int64)
                by = np.lexsort((key, part))
                key, size, part = key[by], size[by], part[by]
                head = np.flatnonzero(np.concatenate(([True], part[1:] != part[:-1]))) if len(part) else np.zeros(0, np.int64)
                tail = np.append(head[1:], len(part))[: len(head)] - 1
                yield pa.RecordBatch.from_arrays([pa.array(part[head]), pa.array(key[head]), pa.array(key[tail]), pa.array(np.add.reduceat(size, head) if len(head) else size), pa.array(np.maximum.reduceat(size, head) if len(head) else size), pa.array(tail - head + 1)], names=["part", "first", "last", "total", "most", "n"])

        parts = groups.select("key", "size").mapInArrow(run, "part long, first long, last long, total long, most long, n long")
        return parts.groupBy("part").agg(F.min("first").alias("first"), F.max("last").alias("last"), F.sum("total").alias("total"), F.max("most").alias("most"), F.sum("n").alias("n")).collect()

    ends = groups.agg(F.min("key"), F.max("key")).first()
    if ends[0] is None:
        return 0, []
    split = [(ends[0], ends[1] + 1)]
    intervals: list[tuple[int, int, int, int, int]] = []
    while True:
        # one aggregation refines all intervals in which a cut can fall
        new = [(r["first"], r["last"] + 1, r["total"], r["most"], r["n"]) for r in summed(split)]
        intervals = sorted([x for x in intervals if (x[0], x[1]) not in set(split)] + new)
        known = _Known(intervals)
        low = max([x[3] for x in intervals] + [-(-known.before[-1] // shards)])
        sure, possible = known.smallest(low, shards, False), known.smallest(low, shards, True)
        early, late = known.greedy(possible, shards, False)[1], known.greedy(sure, shards, True)[1]
        split = []
        for i, x in enumerate(intervals):
            if x[4] > 1 and any(known.before[i] <= b and a <= known.before[i + 1] for a, b in zip(early, late, strict=True)):
                split.append((x[0], x[1]))
        if not split or sure == possible and all(e == f for e, f in zip(known.greedy(sure, shards, False)[1], late, strict=True)):
            cuts = []
            for end in known.greedy(sure, shards, False)[1][:-1]:
                i = bisect.bisect_left(known.before, end)
                if i < len(intervals):
                    cuts.append(intervals[i][0])
            return sure, cuts


def slots(placed: DataFrame, order: str = "doc_id") -> DataFrame:
    """placed with `slot`: the row's number within its shard by `order`, from 0."""
    part = parts_of(placed, order)
    placed = placed.withColumn("_part", part(F.col(order)))
    counts = placed.groupBy("shard", "_part").count().collect()  # at most shards * MAX_RANKS rows
    return numbered(placed, counts, order)


def parts_of(rows: DataFrame, order: str):
    """A function from the column `order` to the number of its interval: about RANK_ROWS rows each."""
    ranks = max(MIN_RANKS, min(MAX_RANKS, rows.count() // RANK_ROWS))
    steps = rows.agg(F.percentile_approx(order, [i / ranks for i in range(1, ranks)], 10 * ranks)).first()[0] or []
    steps = np.array(sorted(set(steps)), np.int64)

    @F.pandas_udf("int")
    def part(x: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(steps, x.to_numpy(), "left").astype(np.int32))

    return part


def numbered(placed: DataFrame, counts: list, order: str) -> DataFrame:
    """placed (shard, _part) with `slot`, given the rows of each (shard, _part)."""
    offset, total = [], {}
    for s, p, n in sorted(counts):
        offset.append((s, p, total.get(s, 0)))
        total[s] = total.get(s, 0) + n
    at = placed.sparkSession.createDataFrame(offset or [(0, 0, 0)], "shard int, _part int, _before long")
    within = F.row_number().over(Window.partitionBy("shard", "_part").orderBy(order)) - 1
    return placed.withColumn("_n", within).join(F.broadcast(at), ["shard", "_part"]).withColumn("slot", F.col("_n") + F.col("_before")).drop("_n", "_part", "_before")


def sized(docs: DataFrame, *columns: str) -> DataFrame:
    """doc_id, `columns`, _id (never null), size, text_crc32 and the digest of the text."""
    return docs.select(
        F.col("doc_id"), *columns, F.coalesce(F.col("doc_id").cast("long"), F.lit(_NULL_ID)).alias("_id"), (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long").alias("size"),
        F.coalesce(F.crc32("text"), F.lit(0)).cast("long").alias("text_crc32"), F.coalesce(F.unhex(F.sha2("text", 256)), F.lit(b"")).alias("_digest"),
    )


def assign_shards(docs: DataFrame, shards: int = 16, carry: bool = False) -> DataFrame:
    """doc_id, size, text_crc32, law (`bytes`), shard, slot and grown_shard (null) of each document.

    carry: the columns of docs come first, and the new ones have more underscores where docs has such a column. Plans are made
    of digests; with carry the texts are shuffled once, into their shards."""
    integer_id(docs)
    rows = settle(sized(docs))
    groups = settle(rows.groupBy("_digest").agg(F.min("_id").alias("key"), F.sum("size").alias("size"), F.count("*").alias("n")))
    _, cuts = plan_cuts(groups.groupBy("key").agg(F.sum("size").alias("size")), shards)
    n = groups.where("n > 1").count()
    # a text that stands once needs no look-up: its key is its own id
    shared = settle(groups.where("n > 1").select("_digest", "key"))

    def placed(some: DataFrame, *columns: str) -> DataFrame:
        keyed = small_join(some, shared, "_digest", "left", n, 56).withColumn("key", F.coalesce("key", "_id"))
        shard = F.lit(0)
        for c in cuts:
            shard = shard + (F.col("key") >= F.lit(c)).cast("int")
        return keyed.select(*columns, "_id", "size", "text_crc32", shard.cast("int").alias("shard"))

    own = ["size", "text_crc32", "law", "shard", "slot", "grown_shard"]
    result = [F.col("size"), F.col("text_crc32"), F.lit("bytes"), F.col("shard"), F.col("slot").cast("long"), F.lit(None).cast("int")]
    slim = settle(placed(rows, "doc_id"))
    if not carry:
        return slots(slim, "_id").select("doc_id", *(c.alias(n) for c, n in zip(result, own, strict=True)))
    part = parts_of(slim, "_id")
    counts = slim.withColumn("_part", part(F.col("_id"))).groupBy("shard", "_part").count().collect()
    # the document's columns travel in one struct, so that none of their names is in the way
    whole = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_row"), "doc_id", "text")
    whole = sized(whole, "_row")
    out = numbered(placed(whole, "_row").withColumn("_part", part(F.col("_id"))), counts, "_id")
    return out.select(*(F.col("_row")[c].alias(c) for c in docs.columns), *(c.alias(fresh(docs.columns, n)) for c, n in zip(result, own, strict=True)))
