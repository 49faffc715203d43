"""Microdata views over the given tables: one row per individual, with its quasi-identifiers and sensitive columns."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gainbound.plans.hierarchy import Hierarchy
from gainbound.plans.spec import CATEGORICAL, Attribute, ReleaseSpec
from gainbound.sources.tables import table

LINE_STATUS = Hierarchy("l_linestatus", ("any", "F", "O"))
PART_TYPE = Hierarchy("p_type", ("any", ("SIZED", "SMALL", "MEDIUM", "LARGE"), ("PRICED", "STANDARD", "ECONOMY", "PROMO")))
#: Nations of each region, in order of name, under three declared super-regions.
_NATIONS = {
    "AMERICA": ("NATION_1", "NATION_11", "NATION_16", "NATION_21", "NATION_6"),
    "EUROPE": ("NATION_13", "NATION_18", "NATION_23", "NATION_3", "NATION_8"),
    "AFRICA": ("NATION_0", "NATION_10", "NATION_15", "NATION_20", "NATION_5"),
    "MIDDLE EAST": ("NATION_14", "NATION_19", "NATION_24", "NATION_4", "NATION_9"),
    "ASIA": ("NATION_12", "NATION_17", "NATION_2", "NATION_22", "NATION_7"),
}
NATION = Hierarchy("nation", ("any", *((name, *((r, *_NATIONS[r]) for r in regions)) for name, regions in (("WEST", ("AMERICA", "EUROPE")), ("SOUTH", ("AFRICA", "MIDDLE EAST")), ("EAST", ("ASIA",))))))
SOURCE = Hierarchy("source", ("any", *(f"src{i}" for i in range(20))))

CENSUS = ReleaseSpec((Attribute("ship_month"), Attribute("l_linestatus", CATEGORICAL, LINE_STATUS), Attribute("disc_pct"), Attribute("p_type", CATEGORICAL, PART_TYPE), Attribute("nation", CATEGORICAL, NATION)), "price_class", "row_key")
CENSUS3 = CENSUS.with_qi(3)
ORDERS = ReleaseSpec((Attribute("order_day"), Attribute("price_cents"), Attribute("nation", CATEGORICAL, NATION)), "o_orderpriority", "row_key")
CUSTOMERS = ReleaseSpec((Attribute("balance_cents"), Attribute("nation", CATEGORICAL, NATION)), "c_mktsegment", "row_key")
EVENTS = ReleaseSpec((Attribute("hour"), Attribute("day"), Attribute("k")), "value_band", "row_key")
DOCS = ReleaseSpec((Attribute("n_chars"), Attribute("source", CATEGORICAL, SOURCE)), "lang", "row_key")
TALK = ReleaseSpec((Attribute("turn"), Attribute("text_length")), "role", "row_key")


def _hundredths(c: str):
    return F.round(F.col(c) * 100).cast("long")


def census_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per line item: the stand-in for a census table, with three sensitive columns."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linestatus", "l_shipdate")
    order = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    customer = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    nation = table(spark, sf_dir, "nation").select("n_nationkey", F.col("n_name").alias("nation"))
    part = table(spark, sf_dir, "part").select("p_partkey", "p_type", "p_size")
    u = (F.col("l_extendedprice") - 900) / 104100
    month = (F.year("l_shipdate") - 1995) * 12 + F.month("l_shipdate") - 1
    price = F.least(F.lit(49), F.floor(50 * ((-0.1 + F.sqrt(0.01 + 3.6 * u)) / 1.8)).cast("int"))
    rows = (
        line.join(order, F.col("l_orderkey") == F.col("o_orderkey")).join(customer.join(nation, F.col("c_nationkey") == F.col("n_nationkey")), F.col("o_custkey") == F.col("c_custkey"))
        .join(part, F.col("l_partkey") == F.col("p_partkey"))
        .withColumn("ship_month", month.cast("int")).withColumn("price_class", price)
    )
    return rows.select(
        F.md5(F.concat_ws("|", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", *(_hundredths(c) for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax")), F.unix_date(F.to_date("l_shipdate")))).alias("row_key"),
        "ship_month", "l_linestatus", F.round(F.col("l_discount") * 100).cast("int").alias("disc_pct"), "p_type", "nation", "price_class", "p_size",
        F.floor((F.col("price_class") + F.floor(F.col("ship_month") * 50 / 83)) / 2).cast("int").alias("corr_class"),
    )


def orders_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    nation = table(spark, sf_dir, "nation").select("n_nationkey", F.col("n_name").alias("nation"))
    customer = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey").join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
    return table(spark, sf_dir, "orders").join(customer, F.col("o_custkey") == F.col("c_custkey")).select(
        F.md5(F.col("o_orderkey").cast("string")).alias("row_key"), F.unix_date(F.to_date("o_orderdate")).alias("order_day"), _hundredths("o_totalprice").alias("price_cents"), "nation", "o_orderpriority",
    )


def customer_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    nation = table(spark, sf_dir, "nation").select("n_nationkey", F.col("n_name").alias("nation"))
    return table(spark, sf_dir, "customer").join(nation, F.col("c_nationkey") == F.col("n_nationkey")).select(F.md5(F.col("c_custkey").cast("string")).alias("row_key"), _hundredths("c_acctbal").alias("balance_cents"), "nation", "c_mktsegment")


def events_of(events: DataFrame) -> DataFrame:
    """The columns of the events view, for a batch or a stream."""
    return events.select(
        F.md5(F.col("event_id").cast("string")).alias("row_key"), "event_id", "ts", "user_id", F.hour("ts").alias("hour"), F.dayofmonth("ts").alias("day"), F.get_json_object("props", "$.k").cast("int").alias("k"),
        F.floor(F.col("value") / 10).cast("int").alias("value_band"), "event_type", "value",
    )


def events_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    return events_of(table(spark, sf_dir, "events"))


def docs_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = table(spark, sf_dir, "labels").groupBy("doc_id").agg(F.max("quality").alias("quality"), F.max("toxic").alias("toxic"))
    return table(spark, sf_dir, "documents").select("doc_id", "n_chars", "source", "lang").join(labels, "doc_id", "left").select(F.md5(F.col("doc_id").cast("string")).alias("row_key"), "n_chars", "source", "lang", "quality", "toxic")


def talk_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "conversations").select(F.md5(F.concat_ws("|", "conv_id", "turn")).alias("row_key"), "turn", F.length("text").alias("text_length"), "role")


def vector_view(spark: SparkSession, sf_dir: str, dims: int = 3) -> DataFrame:
    """The first components of the embeddings, in thousandths, and their label."""
    parts = [F.floor(F.col("embedding")[i].cast("double") * 1000).cast("int").alias(f"v{i + 1}") for i in range(dims)]
    return table(spark, sf_dir, "embeddings").select(F.md5(F.col("vec_id").cast("string")).alias("row_key"), *parts, "label")


def vector_spec(dims: int = 3) -> ReleaseSpec:
    return ReleaseSpec(tuple(Attribute(f"v{i + 1}") for i in range(dims)), "label", "row_key")
