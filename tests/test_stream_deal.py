"""Dealing from a stream loses no rows that the plan places; streams drain into folders in every output mode."""

from gainbound.operators import model
from gainbound.streaming import stream


def test_all_leaves_are_dealt_and_the_rest_is_merged(spark, tmp_path):
    rows = spark.createDataFrame([(0, b, f"{i:03d}", b) for i, b in enumerate([0] * 11 + [1] * 10)], "shard int, bucket int, row_key string, sa int")
    rows.coalesce(1).write.parquet(str(tmp_path / "in"))
    source = spark.readStream.schema(rows.schema).parquet(str(tmp_path / "in"))
    with stream.rocksdb(spark):
        dealt = stream.drain(stream.deal_stream(source, [(3, 3), (2, 2), (3, 2), (2, 2)]), "dealt_all").collect()
    sizes = {}
    for r in dealt:
        sizes[r.ec] = sizes.get(r.ec, 0) + 1
    assert sorted(sizes.values()) == [4, 4, 5, 6]
    assert len({r.row_key for r in dealt}) == 19
    prior = model.prior_frame(spark, [(0, 11), (1, 10)], "int")
    merged, left = stream.merge_left(rows, spark.createDataFrame(dealt), prior, 2.0)
    assert merged.count() == 2 and left.count() == 0
    some = spark.createDataFrame(dealt).unionByName(merged.where("sa = 1"))
    merged, left = stream.merge_left(rows, some, prior, 0.5)
    assert merged.count() == 0 and left.count() == 1


def test_drains_agree_in_every_mode(spark, tmp_path):
    for part in ([(1, "a"), (2, "b")], [(3, "a")], [(4, "c"), (5, "a")]):
        spark.createDataFrame(part, "k long, v string").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    source = spark.readStream.schema("k long, v string").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    counts = source.groupBy("v").count()
    wanted = {("a", 3), ("b", 1), ("c", 1)}
    assert {tuple(r) for r in stream.drain(counts, "whole", "complete").collect()} == wanted
    newest = stream.drain(counts, "newest", "update", ["v"]).collect()
    assert {tuple(r) for r in newest} == wanted and len(newest) == 3
    assert {r.k for r in stream.drain(source, "rows").collect()} == {1, 2, 3, 4, 5}


def test_streams_without_rows_drain_to_empty_tables(spark, tmp_path):
    (tmp_path / "none").mkdir()
    source = spark.readStream.schema("k long, v string").parquet(str(tmp_path / "none"))
    assert stream.drain(source, "none").columns == ["k", "v"]
    for mode, keys in (("append", None), ("complete", None), ("update", ["v"])):
        rows = source if mode == "append" else source.groupBy("v").count()
        assert stream.drain(rows, "none", mode, keys).count() == 0
