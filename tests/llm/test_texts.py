"""Text primitives, passage removal, decontamination, similarity and sharding against brute force."""

import hashlib
import itertools
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from gainbound.llm import bytetext as bt
from gainbound.llm import decontaminate, jaccard, sharding, substrings
from tests.llm.helpers import ALNUM, GRAPHIC, corpus, frame, lower, with_clashes

any_text = st.text(alphabet=st.sampled_from("abAB1 \n\t.é漢\x0b"), max_size=40)


@settings(max_examples=80, deadline=None)
@given(st.lists(st.one_of(st.none(), any_text), max_size=6))
def test_words_are_those_of_the_patterns(texts):
    t = bt.texts_of(pa.array(texts, pa.string()))
    for member, pattern in ((bt.GRAPHIC, GRAPHIC), (bt.ALNUM, ALNUM)):
        start, end, ranges = bt.find_words(t, member)
        for i, text in enumerate(texts):
            got = [bytes(t.buf[a:b]).decode() for a, b in zip(start[ranges[i] : ranges[i + 1]], end[ranges[i] : ranges[i + 1]], strict=True)]
            # the second pattern is for lower-cased texts
            assert [lower(w) for w in got] == pattern.findall(lower(text)) if pattern is ALNUM else got == pattern.findall(text or "")


def test_hashes_depend_on_content_alone(monkeypatch):
    text = " ".join(random.Random(2).choices(["aa", "b", "longer", "é"], k=500))
    t = bt.texts_of(pa.array([text, "b longer"]))
    start, end, _ = bt.find_words(t, bt.GRAPHIC)
    whole = bt.hash_spans(t.buf, start, end)
    words = [bytes(t.buf[a:b]) for a, b in zip(start, end, strict=True)]
    by = {w: h for w, h in zip(words, whole, strict=True)}
    assert len(set(by.values())) == len(by) and all(by[w] == h for w, h in zip(words, whole, strict=True))
    windows = bt.hash_windows(whole, 3, 1)
    monkeypatch.setattr(bt, "_BLOCK", 16)
    assert (bt.hash_spans(t.buf, start, end) == whole).all() and (bt.hash_windows(whole, 3, 1) == windows).all()
    seen = {}
    for i, h in enumerate(windows.tolist()):
        assert seen.setdefault(tuple(words[i : i + 3]), h) == h
    assert len(set(seen.values())) == len(seen)


def brute_removal(rows, size):
    seen, out = set(), {}
    for doc_id, text, *_ in sorted((r for r in rows if r[0] is not None), key=lambda r: r[0]):
        words = GRAPHIC.findall(text or "")
        gone = [False] * len(words)
        for i in range(len(words) - size + 1):
            key = tuple(words[i : i + size])
            if key in seen:
                gone[i : i + size] = [True] * size
            seen.add(key)
        kept = " ".join(w for w, g in zip(words, gone, strict=True) if not g)
        out[doc_id] = (len(words), sum(gone), hashlib.sha256(kept.encode()).hexdigest(), kept)
    return out


@pytest.mark.parametrize(("size", "chunk"), [(3, 1 << 23), (20, 1 << 12)])
def test_passages_are_removed_exactly(spark, size, chunk, monkeypatch):
    monkeypatch.setattr(substrings, "CELL_BYTES", 1 << 10)
    rows = corpus()
    got = substrings.dedup_substrings(with_clashes(frame(spark, rows)), size, with_text=True).collect()
    want = brute_removal(rows, size)
    assert len(got) == len(rows) and sum(r.n_removed for r in got) > 100
    for r in got:
        if r.doc_id is None:
            assert r.n_removed == 0 and r.n_words == 35
        else:
            assert (r.n_words, r.n_removed, r.kept_sha256, r.kept_text) == want[r.doc_id]


def test_repeated_rows_do_not_remove_each_other(spark):
    text = " ".join(f"u{i}" for i in range(30))
    got = substrings.dedup_substrings(frame(spark, [(1, text, "en", "s", 0), (1, text, "en", "s", 0), (2, text, "en", "s", 0)])).collect()
    assert sorted((r.doc_id, r.n_removed) for r in got) == [(1, 0), (1, 0), (2, 30)]
    assert substrings.dedup_substrings(frame(spark, [])).count() == 0


def test_texts_that_share_a_doc_id_are_told_apart(spark):
    w, u = " ".join(f"w{i}" for i in range(60)), " ".join(f"u{i}" for i in range(60))
    got = substrings.dedup_substrings(frame(spark, [(1, w, "en", "s", 0), (2, w, "en", "s", 0), (2, u, "en", "s", 0), (3, u, "en", "s", 0), (None, u, "en", "s", 0)]), with_text=True).collect()
    assert sorted((str(r.doc_id), r.n_words, r.n_removed, r.kept_text) for r in got) == [("1", 60, 0, w), ("2", 60, 0, u), ("2", 60, 60, ""), ("3", 60, 60, ""), ("None", 60, 0, u)]
    with pytest.raises(TypeError):
        substrings.dedup_substrings(frame(spark, []).withColumn("doc_id", F.col("doc_id").cast("string")))


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(0, 3), max_size=60), st.integers(1, 4), st.integers(0, 10**6))
def test_index_finds_what_is_there(symbols, length, seed):
    text = np.array(symbols, np.int64)
    index = decontaminate.FmIndex(text, 3)
    order = decontaminate.suffix_order(np.append(text, 0))
    assert sorted(order.tolist()) == list(range(len(text) + 1))
    phrases = np.random.default_rng(seed).integers(1, 4, (6, length))
    alive, low, high = index.ranges(phrases, length)
    found = {int(k): sorted(index.locate(np.arange(a, b)).tolist()) for k, a, b in zip(alive, low, high, strict=True)}
    for k, p in enumerate(phrases.tolist()):
        assert found.get(k, []) == [i for i in range(len(symbols) - length + 1) if symbols[i : i + length] == p]


def brute_contamination(rows, items, window):
    phrases = {}
    for item, text in items:
        words = ALNUM.findall(lower(text))
        k = min(window, len(words))
        for i in range(len(words) - k + 1 if k else 0):
            phrases.setdefault(tuple(words[i : i + k]), set()).add(str(item))
    out = []
    for doc_id, text, *_ in rows:
        words = ALNUM.findall(lower(text))
        hit, found = [False] * len(words), set()
        for k in {len(p) for p in phrases}:
            for i in range(len(words) - k + 1):
                if names := phrases.get(tuple(words[i : i + k])):
                    hit[i : i + k] = [True] * k
                    found |= names
        out.append((doc_id, len(words), sum(hit), tuple(sorted(found))))
    return sorted(out, key=str)


@pytest.mark.parametrize("block", [1 << 24, 40])
def test_contamination_is_exact(spark, block, monkeypatch):
    monkeypatch.setattr(decontaminate, "BLOCK_BYTES", block)
    monkeypatch.setattr(decontaminate, "SHARD_WORDS", 3000)
    rows = corpus()
    r = random.Random(4)
    items = [(i, " ".join((rows[i * 7][1]).split()[:30])) for i in range(6)] + [(90, "W3 w4"), (91, "W3 w4!"), (92, None), (93, "..."), (94, " ".join(r.choices([f"w{i}" for i in range(40)], k=13)))]
    benchmark = spark.createDataFrame(items, "item_id long, text string")
    got = decontaminate.contamination(with_clashes(frame(spark, rows)), benchmark, 5).collect()
    assert sorted(((x.doc_id, x.n_words, x.n_hit, tuple(x["items"])) for x in got), key=str) == brute_contamination(rows, items, 5)
    for x in got:
        assert sum(s.end - s["first"] for s in x.spans) == x.n_hit
    assert decontaminate.contamination(frame(spark, []), benchmark).count() == 0
    assert {x.n_hit for x in decontaminate.contamination(frame(spark, rows[:5]), benchmark.where("false")).collect()} == {0}


def brute_classes(rows, size=5, threshold=0.8):
    texts = {}
    for doc_id, text, *_ in rows:
        if text is not None:
            texts.setdefault(text, []).append(doc_id)
    sets = {}
    for t in texts:
        w = GRAPHIC.findall(t)
        k = min(size, len(w))
        sets[t] = {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if k else set()
    root = {t: t for t in texts}
    links = {t: set() for t in texts}

    def find(t):
        while root[t] != t:
            t = root[t]
        return t

    for a, b in itertools.combinations(texts, 2):
        u = len(sets[a] | sets[b])
        if u and len(sets[a] & sets[b]) * 10 >= threshold * 10 * u:
            links[a].add(b), links[b].add(a)
            root[find(a)] = find(b)
    out = []
    for doc_id, text, *_ in rows:
        if text is None:
            out.append((doc_id, doc_id, 0, 0))
        else:
            members = [d for t in texts if find(t) == find(text) for d in texts[t] if d is not None]
            out.append((doc_id, min(members, default=None), sum(len(texts[t]) for t in links[text]) + len(texts[text]) - 1, len(links[text])))
    return sorted(out, key=str)


@pytest.mark.parametrize("block", [384, 3])
def test_similarity_classes_are_exact(spark, block, monkeypatch):
    monkeypatch.setattr(jaccard, "BLOCK_TEXTS", block)
    monkeypatch.setattr(jaccard, "BLOCK_MEMBERS", block)
    rows, r = corpus(60, seed=6), random.Random(7)
    for k in range(12):
        words = rows[k][1].split()
        words[r.randrange(len(words))] = "changed"
        rows.append((2000 + k, " ".join(words), "en", "s", 0))
    base = [f"b{i}" for i in range(100)]
    for k in range(14):  # a chain and a cluster of near copies
        rows.append((3000 + k, " ".join(base[:k] + ["z"] + base[k:]), "en", "s", 0))
    got = jaccard.similarity_classes(with_clashes(frame(spark, rows))).collect()
    assert sorted(((x.doc_id, x.class_id, x.n_links, x.n_text_links) for x in got), key=str) == brute_classes(rows)
    assert jaccard.similarity_classes(frame(spark, [])).count() == 0


def test_bands_reach_the_recall():
    for threshold, recall in ((0.8, 0.9999), (0.6, 0.99), (0.95, 0.999)):
        bands, rows = jaccard.bands_for(threshold, recall)
        assert bands * rows <= jaccard.HASHES and 1 - (1 - threshold**rows) ** bands >= recall


def test_a_shared_passage_ties_nothing(spark):
    """Texts that share 30 of 60 words agree on bands, but none is near another."""
    r = random.Random(3)
    shared = " ".join(f"common{i}" for i in range(30))
    rows = [(i, shared + " " + " ".join(f"own{i}x{r.randrange(10**6)}" for _ in range(30)), "en", "s", 0) for i in range(1500)]
    twin = rows[7][1].split()
    twin[45] = "changed"
    rows.append((5000, " ".join(twin), "en", "s", 0))
    bands, size = jaccard.bands_for(jaccard.THRESHOLD, jaccard.RECALL)
    keyed = jaccard._keyed(frame(spark, rows))
    nodes = keyed.select("node", "id", "text").mapInArrow(jaccard._sign(bands, size, 5), "node binary, id long, bytes long, bands array<long>, " + jaccard._PLANES_SQL).cache()
    shared_keys = nodes.select(F.explode("bands").alias("k")).groupBy("k").count().where("count > 10").count()
    near = jaccard.components(jaccard.ties(nodes, jaccard.agreement_for(jaccard.THRESHOLD, bands * size) + 192 - bands * size, 8))
    assert shared_keys > 0 and near.count() == 2
    got = {x.doc_id: x for x in jaccard.similarity_classes(frame(spark, rows)).collect()}
    assert got[5000].class_id == 7 and got[7].n_links == 1 and sum(x.n_links for x in got.values()) == 2


def test_one_of_each_judges_rows(spark):
    text, other = " ".join(f"a{i}" for i in range(30)), " ".join(f"b{i}" for i in range(30))
    near = text.replace("a29", "zz")
    rows = [(5, text, "en", "x", 0), (3, near, "en", "x", 0), (5, other, "en", "y", 0), (3, near, "fr", "z", 1), (None, text, "en", "x", 0), (None, None, "en", "n", 0), (None, None, "en", "n", 0), (9, "", "en", "e", 0), (10, "", "en", "e", 0)]
    kept = sorted(((x.doc_id, x.text) for x in jaccard.one_of_each(with_clashes(frame(spark, rows))).collect()), key=str)
    assert kept == sorted([(3, near), (5, other), (None, None), (None, None), (9, "")], key=str)
    with pytest.raises(TypeError):
        jaccard.similarity_classes(frame(spark, rows).withColumn("doc_id", F.col("doc_id").cast("string")))


def test_components_of_a_path_and_a_star(spark):
    edges = [(i + 1, i) for i in range(40)] + [(100 + i, 100) for i in range(1, 50)]
    got = {r.node: r.root for r in jaccard.components(spark.createDataFrame(edges, "node int, root int")).collect()}
    assert all(got[i] == 0 for i in range(41)) and all(got[100 + i] == 100 for i in range(50))


@pytest.mark.parametrize("spread", [1, 10**6, 1 << 54])
def test_smallest_capacity_is_found(spark, spread, monkeypatch):
    monkeypatch.setattr(sharding, "SPLIT", 4)
    r = random.Random(spread)
    keys = sorted(r.sample(range(500), 120))
    sizes = [r.choice([1, 5, 9, 400]) for _ in keys]
    groups = spark.createDataFrame([(k * spread - (1 << 60), s) for k, s in zip(keys, sizes, strict=True)], "key long, size long")
    for shards in (1, 7, 16, 200):
        capacity, cuts = sharding.plan_cuts(groups, shards)
        assert capacity == sharding.capacity_of(sizes, shards)
        runs = [0] * (len(cuts) + 1)
        for k, s in zip(keys, sizes, strict=True):
            runs[sum(k * spread - (1 << 60) >= c for c in cuts)] += s
        assert max(runs) == capacity and len(runs) <= shards
    assert sharding.plan_cuts(groups.where("false"), 3) == (0, [])


def test_shards(spark):
    rows = corpus()
    rows += [rows[3], rows[3]]
    got = sharding.assign_shards(with_clashes(frame(spark, rows)), 6).collect()
    assert len(got) == len(rows)
    text = {r[0]: r[1] for r in rows}
    where = {}
    for x in got:
        t = text[x.doc_id]
        assert x.size == len((t or "").encode()) + 1 and x.text_crc32 == zlib.crc32((t or "").encode()) and x.law == "bytes" and x.grown_shard is None
        assert where.setdefault(t, x.shard) == x.shard
    for s in range(6):
        assert sorted(x.slot for x in got if x.shard == s) == list(range(sum(x.shard == s for x in got)))
    assert sharding.assign_shards(frame(spark, []), 4).count() == 0
    _ = F
