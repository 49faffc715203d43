"""Reading, cutting lineage and choosing joins; used by the operators of this subpackage."""

from __future__ import annotations

import tempfile
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gainbound.llm import bytetext as bt

#: A side of a join is broadcast only if its rows, counted first, fit in this many bytes.
BROADCAST_BYTES = 32 << 20
#: Most rows of an Arrow batch of texts: by Spark's default of 10,000, texts of a few kilobytes make batches of tens of megabytes on both sides.
BATCH_ROWS = 2_000
#: Most values of a class label.
MAX_CLASSES = 10_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all machines share; one of our own only where none is set."""
    found = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        found = tempfile.mkdtemp(prefix="gainbound-")
        spark.sparkContext.setCheckpointDir(found)
    return found


def shared_uri(spark: SparkSession) -> str:
    """The shared folder as a URI that tasks can open."""
    path = shared_dir(spark)
    return "file://" + path.removeprefix("file:") if path.startswith("file:/") and not path.startswith("file://") else path if "://" in path else "file://" + path


def bound_batches(spark: SparkSession) -> None:
    """Lowers the session's rows of an Arrow batch to BATCH_ROWS, a setting that may change while a session runs."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= BATCH_ROWS:
        spark.conf.set(key, str(BATCH_ROWS))


def settle(df: DataFrame) -> DataFrame:
    """df computed once and kept in the shared folder, where the loss of executors can't reach it."""
    bound_batches(df.sparkSession)
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def small_join(left: DataFrame, right: DataFrame, on, how: str, rows: int, row_bytes: int) -> DataFrame:
    """A join that broadcasts right while rows * row_bytes is small and shuffles both sides beyond it."""
    return left.join(F.broadcast(right) if rows * row_bytes <= BROADCAST_BYTES else right, on, how)


def in_fold(df: DataFrame, folds: int, fold: int, key: str = "doc_id"):
    """Whether a row is in the held-out fold; rows without a key are, so nothing is learned from them."""
    return F.coalesce(F.crc32(F.col(key).cast("string")) % folds == fold, F.lit(True))


def bounded_sample(df: DataFrame, bound: int, by: str | None = None, key: str = "doc_id") -> DataFrame:
    """About bound rows at most (of each value of by), chosen by a hash of the key alone."""
    keyed = df.withColumn("_h", F.pmod(F.xxhash64(F.col(key), F.lit(77)), F.lit(1 << 30)))
    if by is None:
        n = df.count()
        return keyed.where(F.col("_h") < int((1 << 30) * min(1.0, bound / max(1, n)))).drop("_h")
    counts = keyed.where(F.col(by).isNotNull()).groupBy(by).count().limit(MAX_CLASSES + 1).collect()
    if len(counts) > MAX_CLASSES:
        raise ValueError(f"{by} has more than {MAX_CLASSES} values; it can't be a class label")
    if not counts:
        return keyed.where(F.lit(False)).drop("_h")
    limit = F.create_map(*[F.lit(x) for r in counts for x in (r[0], int((1 << 30) * min(1.0, bound / r[1])))])
    return keyed.where(F.col("_h") < limit[F.col(by)]).drop("_h")


def with_judged(docs: DataFrame, judge: Callable[[pa.RecordBatch], list[pa.Array]], new: list[tuple[str, str]], piece: int = 1 << 20) -> DataFrame:
    """docs with the columns `new` (name, type) that judge makes of a batch of its texts: every row carries its own verdict, whatever its doc_id.

    Only texts go to the Python workers, and only verdicts come back. A batch is judged in pieces of so many bytes of text."""
    ddl = ", ".join(f"v{i} {k}" for i, (_, k) in enumerate(new))
    names = [f"v{i}" for i in range(len(new))]

    @F.arrow_udf(ddl)
    def run(text: pa.Array) -> pa.Array:
        if isinstance(text, pa.ChunkedArray):
            text = text.combine_chunks()
        batch = pa.RecordBatch.from_arrays([text], names=["text"])
        parts = [pa.StructArray.from_arrays(judge(part), names=names) for part in bt.pieces(batch, 0, piece)]
        return pa.concat_arrays(parts) if parts else pa.StructArray.from_arrays(judge(batch), names=names)

    bound_batches(docs.sparkSession)
    held = fresh([*docs.columns, *(n for n, _ in new)], "_verdict")
    judged = docs.withColumn(held, run(F.col("text")))
    return judged.select(*(F.col(f"`{c}`") for c in docs.columns), *(F.col(held)[v].alias(n) for v, (n, _) in zip(names, new, strict=True)))


def integer_id(df: DataFrame, key: str = "doc_id") -> None:
    """Refuses a key that isn't an integer: orders and places are made of it."""
    kind = df.schema[key].dataType
    if not isinstance(kind, T.IntegralType):
        raise TypeError(f"{key} has type {kind.simpleString()}; this operator needs an integer")


def fresh(columns: list[str], name: str) -> str:
    """name, with underscores in front until no column is called so."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name = "_" + name
    return name
