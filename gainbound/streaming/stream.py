"""Streams: monitoring gains against a frozen prior, randomising rows, and dealing groups as rows arrive.

A stream is one release: its prior is frozen before it starts, and coins are keyed by the row,
so a replayed row is published with the same value and an observer can't average coins away.
"""

from __future__ import annotations

import uuid
from collections import Counter
from collections.abc import Iterable, Iterator
from contextlib import contextmanager
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from gainbound.functions.bounds import gain_expr
from gainbound.operators.model import audit, histogram
from gainbound.operators.perturb import Randomiser, randomise
from gainbound.operators.settle import shared
from gainbound.sources.tables import SCHEMAS


def events_stream(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """A stream of event files with the declared schema. path: a folder, or a single file, which is then watched for in its folder."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    reader = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files)
    if not where.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(where).isDirectory():
        folder, _, name = path.rpartition("/")
        reader, path = reader.option("pathGlobFilter", name), folder
    # event time must be an instant; the files' times have no zone, and are read in the session's
    return reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def window_counts(events: DataFrame, sa: str, window: str = "1 day", slide: str | None = None, watermark: str = "1 hour") -> DataFrame:
    """begin, end, sa and n of each window; rows later than the watermark are dropped by a stream."""
    marked = events.withWatermark("ts", watermark) if events.isStreaming else events
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    return marked.groupBy(w.alias("w"), F.col(sa).alias("sa")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("begin"), F.col("w.end").alias("end"), "sa", "n")


def window_gains(counts: DataFrame, prior: DataFrame) -> DataFrame:
    """Largest gain of each window over the frozen prior (sa, p). For finished windows: a batch, or inside foreachBatch."""
    # a window has one row for each value
    rows = counts.withColumn("size", F.sum("n").over(Window.partitionBy("begin", "end"))).join(F.broadcast(prior.select("sa", "p")), "sa")
    q = F.col("n") / F.col("size")
    return rows.groupBy("begin", "end").agg(F.max("size").alias("size"), F.max(gain_expr(F.col("p"), q)).alias("max_gain"))


def sessions(events: DataFrame, gap: str = "30 minutes", watermark: str = "1 hour") -> DataFrame:
    """user_id, begin, end and n of each user's sessions."""
    marked = events.withWatermark("ts", watermark) if events.isStreaming else events
    return marked.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("begin"), F.col("w.end").alias("end"), "n")


def deduplicated(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """Events by id, once; state is kept for as long as the watermark allows."""
    if not events.isStreaming:
        return events.dropDuplicates(["event_id"])
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def randomise_stream(events: DataFrame, sa: str, key: str, r: Randomiser, secret: str) -> DataFrame:
    """The row randomiser on a stream: a map, so any output mode and any restart give the same rows."""
    return randomise(events, sa, key, r, secret)


class _Dealer(StatefulProcessor):
    """Rows of a shard wait by bucket until a planned vector can be filled, and leave as a group.

    Each vector is used as often as the plan has it; then all begin anew."""

    def __init__(self, vectors: dict[tuple[int, ...], int], columns: list[str]):
        self.vectors, self.columns = vectors, columns

    def init(self, handle: StatefulProcessorHandle) -> None:
        row = T.StructType([T.StructField("row_key", T.StringType()), T.StructField("sa", T.IntegerType())])
        self.waiting = [handle.getListState(f"bucket{j}", row) for j in range(len(next(iter(self.vectors))))]
        self.made = handle.getValueState("made", T.StructType([T.StructField("n", T.LongType()), T.StructField("used", T.StringType())]))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        have = [[tuple(x) for x in s.get()] for s in self.waiting]
        for pdf in rows:
            for r in pdf.sort_values("row_key").itertuples(index=False):
                have[r.bucket].append((r.row_key, int(r.sa)))
        n, used = self.made.get() if self.made.exists() else (0, "")
        left = list(map(int, used.split(","))) if used else list(self.vectors.values())
        out, at = [], [0] * len(have)
        while True:
            fits = [i for i, v in enumerate(self.vectors) if left[i] and all(len(h) - a >= need for h, a, need in zip(have, at, v, strict=True))]
            if not fits:
                break
            i = max(fits, key=lambda i: left[i])
            for j, need in enumerate(list(self.vectors)[i]):
                out += [(f"{key[0]}-{n}", k, v) for k, v in have[j][at[j] : at[j] + need]]
                at[j] += need
            left[i] -= 1
            n += 1
            if not any(left):
                left = list(self.vectors.values())
        for s, h, a in zip(self.waiting, have, at, strict=True):
            s.put(h[a:]) if h[a:] else s.clear()
        self.made.update((n, ",".join(map(str, left))))
        yield pd.DataFrame(out, columns=["ec", "row_key", "sa"])

    def close(self) -> None:
        pass


def deal_stream(rows: DataFrame, vectors: Iterable[tuple[int, ...]]) -> DataFrame:
    """Groups dealt from a stream of (shard, bucket, row_key, sa): each draws one of the planned vectors of rows from the buckets.

    vectors: all leaves of a plan. A group is emitted only when full, so it keeps the bound that its vector keeps; what waits at the end is for `merge_left`."""
    counted = dict(Counter(tuple(int(x) for x in v) for v in vectors if any(v)))
    return rows.groupBy("shard").transformWithStateInPandas(_Dealer(counted, rows.columns), "ec string, row_key string, sa int", "Append", "None")


def merge_left(rows: DataFrame, dealt: DataFrame, prior: DataFrame, beta: float) -> tuple[DataFrame, DataFrame]:
    """After a stream's end: the rows that wait, as one group if it keeps the bound, and those that stay unpublished. rows: all (row_key, sa)."""
    rest = rows.join(dealt.select("row_key"), "row_key", "left_anti").select(F.lit("rest").alias("ec"), "row_key", "sa")
    ok = not audit(histogram(rest, "sa"), prior, beta).where("ok").isEmpty()
    return (rest, rest.limit(0)) if ok else (rest.limit(0), rest)


def with_prior(events: DataFrame, prior: DataFrame, sa: str) -> DataFrame:
    """A stream-static join with the frozen prior."""
    return events.join(F.broadcast(prior.select(F.col("sa").alias(sa), "p")), sa)


def within(left: DataFrame, right: DataFrame, key: str, seconds: int, watermark: str = "1 hour") -> DataFrame:
    """Pairs of a key's rows of two streams, the right one at most so many seconds after the left one."""
    if left.isStreaming:
        left, right = left.withWatermark("ts", watermark), right.withWatermark("ts", watermark)
    a, b = left.alias("a"), right.alias("b")
    near = F.expr(f"b.ts >= a.ts AND b.ts <= a.ts + interval {seconds} seconds")
    return a.join(b, (F.col(f"a.{key}") == F.col(f"b.{key}")) & near)


@contextmanager
def rocksdb(spark: SparkSession) -> Iterator[None]:
    """The state store that arbitrary stateful operators need, for streams that start inside."""
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        yield
    finally:
        spark.conf.set(key, before)


def drain(stream: DataFrame, name: str, mode: str = "append", keys: list[str] | None = None) -> DataFrame:
    """Runs a stream over what there is into a folder of its own in the shared one, and returns the rows written.

    append: the file sink. complete: each batch's whole result, of which the last one counts. update: the
    newest row of each value of keys. A batch that is run again overwrites what it wrote before."""
    spark = stream.sparkSession
    folder = f"{shared(spark)}/{name}-{uuid.uuid4().hex}"
    if mode == "append":
        to_parquet(stream, f"{folder}/rows", f"{folder}/log")
        return spark.read.schema(stream.schema).parquet(f"{folder}/rows")
    if mode == "update" and not keys:
        raise ValueError("update mode needs the keys whose newest rows are wanted")
    written: list[int] = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/rows/{number}")
        written.append(number)

    stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{folder}/log").trigger(availableNow=True).start().awaitTermination()
    if not written:
        return spark.createDataFrame([], stream.schema)
    if mode == "complete":
        return spark.read.schema(stream.schema).parquet(f"{folder}/rows/{max(written)}")
    every = reduce(DataFrame.union, (spark.read.schema(stream.schema).parquet(f"{folder}/rows/{i}").withColumn("_batch", F.lit(i)) for i in sorted(set(written))))
    newest = every.groupBy(*keys).agg(F.max_by(F.struct(*stream.columns), "_batch").alias("_row"))
    return newest.select("_row.*")


def to_parquet(stream: DataFrame, path: str, checkpoint: str) -> int:
    """Runs a stream over what there is into a folder, once for each row whatever happens; returns how many rows came later than the watermark (of the run's last 100 batches, as many as Spark remembers)."""
    q = stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return sum(o.numRowsDroppedByWatermark for p in q.recentProgress for o in p.stateOperators)
