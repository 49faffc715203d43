"""Archives, the pipeline and the registered queries."""

import base64
import gzip
import hashlib
import io

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from gainbound.llm import decontaminate, entries, jaccard, sharding, toxicity, warc
from gainbound.llm.common import table
from tests.llm.helpers import SCHEMA, corpus, frame, with_clashes
from tests.oracle import check, connect

SF = "/root/testdata/sf0.001"
ODD_PAGES = [(8, "http://f.example", "twice"), (8, "http://f.example", "twice"), (8, None, "twice"), (7, None, "twice"), (None, "a", "none"), (None, "b", "none"), (None, None, "twice")]
PAGES = [(1, "http://a.example/x?y=1", "<p>é</p>"), (2, "http://b.example/", "<p>é</p>"), (3, None, None), (4, "not a url [", ""), (5, "http://c.example", "long " * 50000), (6, "http://d.example", "\r\n\r\nWARC/1.1\r\n\r\n"), (None, "http://e.example", "<p>é</p>")]


def _expected(pages, least):
    groups = {}
    for page, _, html in pages:
        groups.setdefault(html or "", []).append(page)
    out = []
    for page, _, html in pages:
        raw = (html or "").encode()
        holder = max((p for p in groups[html or ""] if p is not None), default=None)
        again = len(groups[html or ""]) > 1 and len(raw) >= least and page != holder
        out.append((page, len(raw), base64.b32encode(hashlib.sha1(raw).digest()).decode(), "revisit" if again else "response", holder if again else None))
    return sorted(out, key=str)


@pytest.mark.parametrize("least", [0, 5])
def test_archives_round_trip(spark, least):
    pages = with_clashes(spark.createDataFrame(PAGES, "page_id long, url string, html string").repartition(3))
    assert sorted((tuple(r) for r in warc.archive_and_read(pages, least).collect()), key=str) == _expected(PAGES, least)


def test_every_row_is_a_capture(spark):
    """Repeated page_ids and rows without one: as many rows as pages, all with records of their own."""
    pages = spark.createDataFrame(ODD_PAGES, "page_id long, url string, html string").repartition(3)
    got = warc.archive_and_read(pages).collect()
    assert sorted((tuple(r) for r in got), key=str) == _expected(ODD_PAGES, 0)
    records = warc.read_records(warc.write_archives(pages))
    assert records.count() == records.select("record_id").distinct().count() == 3 * len(ODD_PAGES)
    with pytest.raises(TypeError):
        warc.archive_and_read(pages.withColumn("page_id", F.col("page_id").cast("string")))


def test_payloads_and_captures_survive(spark):
    pages = spark.createDataFrame(PAGES[:6], "page_id long, url string, html string")
    archives = warc.write_archives(pages, archive_bytes=1)
    assert archives.agg(F.sum("records")).first()[0] == 18 and archives.count() >= 6
    captures = warc.assemble(warc.read_records(archives, with_payload=True)).collect()
    assert len(captures) == 6 and all(c.request and c.metadata for c in captures)
    got = {c.metadata.page_id: c.main for c in captures}
    for page, _, html in PAGES[:6]:
        if got[page].kind == "response":
            assert bytes(got[page].payload) == (html or "").encode()
    assert sum(c.main.kind == "revisit" for c in captures) == 2
    assert warc.archive_and_read(pages.where("false")).count() == 0


def test_parser():
    records = warc.capture_records(7, "http://x/", b"body", "D" * 32, None)
    stream = gzip.GzipFile(fileobj=io.BytesIO(b"".join(gzip.compress(r) for r in records)))
    kinds = [(h["warc-type"], len(b)) for h, b in warc.parse(stream)]
    assert [k for k, _ in kinds] == ["response", "request", "metadata"]
    with pytest.raises(ValueError):
        list(warc.parse(io.BytesIO(b"junk\r\n")))


def test_missing_records(spark):
    rows = [("request", "r1", "c1"), ("response", "c2", "c2"), ("metadata", "m2", "c2")]
    df = spark.createDataFrame([(k, i, c, None, None, None, None, None, None, None, None) for k, i, c in rows], warc._RECORD)
    got = {r.capture_id: r for r in warc.assemble(df).collect()}
    assert got["c1"].main is None and got["c1"].request.record_id == "r1" and got["c2"].request is None and got["c2"].metadata


@pytest.fixture(scope="module")
def duck():
    return connect(SF)


@pytest.mark.parametrize("name", sorted(entries.ORACLE))
def test_query_matches_its_sql(spark, duck, name):
    check(spark, duck, SF, entries.QUERIES[name], entries.ORACLE[name])


@pytest.mark.parametrize("name", sorted(set(entries.QUERIES) - set(entries.ORACLE)))
def test_query_returns_each_row(spark, name):
    got = entries.QUERIES[name](spark, SF)
    key = "conv_id" if name.startswith("op6") else "doc_id"
    source = table(spark, SF, "conversations" if key == "conv_id" else "documents").select(key).distinct()
    assert got.select(key).distinct().count() == source.count() and got.count() == source.count()


def test_pipeline_stages(spark):
    docs = table(spark, SF, "documents")
    state = docs
    labels, benchmark = table(spark, SF, "labels"), table(spark, SF, "benchmark")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, state, SF).cache()
        assert out.columns == docs.columns
        lost = {r.doc_id for r in state.select("doc_id").distinct().exceptAll(out.select("doc_id").distinct()).collect()}
        if name == "toxicity":
            assert lost == {r.doc_id for r in toxicity.classify(state, labels).where("predicted = 1").collect()}
        elif name == "ngram_jaccard":
            assert lost == {r.doc_id for r in jaccard.similarity_classes(state).where("class_id <> doc_id").collect()}
        elif name == "decontamination":
            assert lost == {r.doc_id for r in decontaminate.contamination(state, benchmark).where(decontaminate.is_contaminated()).collect()}
        else:
            assert not lost and out.count() >= state.count()
        state = out
    got = corpus_pipeline.STAGES[-1][1](spark, state, SF)
    assert got.count() == state.count() and got.select("shard", "slot").distinct().count() == state.count()
    assert corpus_pipeline.run(spark, SF).count() == state.count()


def test_pipeline_stages_on_odd_tables(spark):
    rows = corpus(20)
    rows += [rows[0], rows[0]]
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, with_clashes(frame(spark, rows)), SF).count() > 0
        assert stage(spark, spark.createDataFrame([], SCHEMA), SF).count() == 0
    kept = corpus_pipeline.keep_one_of_near_duplicates(spark, frame(spark, rows), SF)
    assert kept.where("doc_id = 0").count() == 1 and kept.where("doc_id is null").count() == 1


def test_rows_are_judged_by_their_own_text(spark):
    """A clean text that shares the doc_id of a toxic or contaminated one stays, and a row without a doc_id is judged too."""
    toxic, clean = "vile " * 12, "plain words about the harbour and its boats in spring"
    rows = [(i, toxic + f"w{i}" if i % 2 else clean + f" w{i}", "en", "s", 0) for i in range(400)]
    labels = spark.createDataFrame([(i, i % 2) for i in range(400)], "doc_id long, toxic int")
    odd = [(1, clean, "en", "x", 7), (None, toxic, "en", "x", 8), (1, toxic, "en", "x", 9)]
    kept = {(r.doc_id, r.text) for r in toxicity.without_toxic(with_clashes(frame(spark, rows + odd)), labels).where("source = 'x'").collect()}
    assert kept == {(1, clean)}
    item = " ".join(f"q{i}" for i in range(13))
    benchmark = spark.createDataFrame([(1, item)], "item_id long, text string")
    odd = [(1, clean, "en", "x", 7), (None, item, "en", "x", 8), (1, item + " more", "en", "x", 9), (2, None, "en", "x", 1)]
    kept = {(r.doc_id, r.text) for r in decontaminate.without_contaminated(with_clashes(frame(spark, odd)), benchmark).collect()}
    assert kept == {(1, clean), (2, None)}


def test_pipeline_keeps_the_corpus(spark):
    docs = frame(spark, corpus(30))
    out = corpus_pipeline.cut_shards(spark, with_clashes(docs), SF)
    assert out.columns == [*with_clashes(docs).columns, "_size", "text_crc32", "law", "_shard", "_slot", "grown_shard"]
    assert sorted(map(str, out.select("doc_id", "text", "lang").collect())) == sorted(map(str, docs.select("doc_id", "text", "lang").collect()))
    plain = {(r.doc_id, r.text_crc32, r.shard) for r in sharding.assign_shards(docs, 16).collect()}
    assert plain == {(r.doc_id, r.text_crc32, r._shard) for r in out.collect()}
