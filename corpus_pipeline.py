"""The corpus pipeline: toxicity, near duplicates, contamination, mixing, sharding.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before it kept. The first four
return the columns of documents; the last adds the shard and slot of each row. Rows are lost only by a
stage's own decision about their own text: toxic documents, documents of a group of near duplicates other than
the one with its smallest doc_id, and contaminated ones. A null or repeated doc_id changes nothing in that. Mixing repeats rows and drops none.
An empty table passes as an empty table; extra columns go through.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gainbound.llm import decontaminate, jaccard, mixing, sharding, toxicity
from gainbound.llm.common import fresh, shared_dir, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose text the factorisation machine scores below the threshold; a null or empty text is scored by the bias alone."""
    return toxicity.without_toxic(docs, table(spark, sf_dir, "labels"))


def keep_one_of_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates, that with the smallest doc_id (rows without one last); null texts stay."""
    return jaccard.one_of_each(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of which benchmark phrases cover less than a twentieth; null and empty texts stay."""
    return decontaminate.without_contaminated(docs, table(spark, sf_dir, "benchmark"))


def mix_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents repeated by rates, each at least 1, that bring the languages' expected tokens to smoothed shares; texts without words stay once."""
    mixed, _, _ = mixing.mix(docs)
    copies = fresh(docs.columns, "_copies")
    again = fresh([*docs.columns, *mixed.columns], "_again")
    return mixed.where(F.col(copies) > 0).withColumn(again, F.explode(F.sequence(F.lit(1), F.col(copies)))).select(*docs.columns)


def cut_shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents with size, text_crc32, law, shard, slot and grown_shard; rows of equal texts share a shard. A null text has no bytes."""
    return sharding.assign_shards(docs, 16, carry=True)


STAGES = [
    ("toxicity", drop_toxic),
    ("ngram_jaccard", keep_one_of_near_duplicates),
    ("decontamination", drop_contaminated),
    ("mixing", mix_languages),
    ("sharding", cut_shards),
]

#: Two stages apply trained models, which SQL can't express; tests compare each stage with a plain version of it.
ORACLE_SQL = None


def _remove(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each one's rows are written to the shared folder and read by the next, and go once that one is written."""
    docs, folder, before = table(spark, sf_dir, "documents"), f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}", None
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        path = f"{folder}/{i}-{name}"
        docs.write.parquet(path)
        docs = spark.read.parquet(path)
        if before:
            _remove(spark, before)
        before = path
    return docs
