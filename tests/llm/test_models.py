"""Trained operators: held-out accuracy, exact counts, constraints, and odd cases."""

import itertools

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from gainbound.llm import boosting, chat, langid, mixing, quality, toxicity
from gainbound.llm import bytetext as bt
from gainbound.llm.common import table
from tests.llm.helpers import GRAPHIC, corpus, frame, with_clashes

SF = "/root/testdata/sf0.1"


def test_language_of_held_out_texts(spark):
    docs = table(spark, SF, "documents")
    got = langid.classify(with_clashes(docs)).join(docs.select("doc_id", "lang"), "doc_id")
    r = got.where("held_out").agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double")), F.min("score"), F.max("score")).first()
    assert r[0] > 0.99 and r[1] >= 0 and r[2] <= 1


def test_language_of_odd_texts(spark):
    rows = [(i, "the cat and the dog " * 5, "en", "s", 0) for i in range(20)] + [(50 + i, "le chat et le chien " * 5, "fr", "s", 0) for i in range(20)]
    rows += [(100, None, "en", "s", 0), (101, "", "en", "s", 0), (102, "12 % ...", "fr", "s", 0), (103, "Le CHAT", None, "s", 0), (None, "the dog", "en", "s", 0), (104, "漢字", None, "s", 0)]
    got = {r.doc_id: r for r in langid.classify(frame(spark, rows)).collect()}
    assert [got[k].lang_pred for k in (100, 101, 102)] == ["und"] * 3 and {got[k].score for k in (100, 101, 102)} == {0.0}
    assert got[103].lang_pred == "fr" and got[None].lang_pred == "en" and got[None].held_out
    assert got[104].lang_pred in ("en", "fr") and len(got) == len(rows)
    assert {r.lang_pred for r in langid.classify(frame(spark, [(1, "abc", None, "s", 0)])).collect()} == {"und"}
    assert langid.classify(frame(spark, [])).count() == 0


def test_ngrams_against_a_plain_count():
    texts = ["Ab a.b", "été", "", None, "a"]
    doc, gram, count = langid.ngram_counts(texts)
    code = lambda c: 1 if not c.isalpha() else ord(c) + 2
    for i, text in enumerate(texts):
        s = " " + (text or "").lower() + " "
        marks = [code(c) for c in s]
        marks = [m for k, m in enumerate(marks) if not (m == 1 and k and marks[k - 1] == 1)]
        want = {}
        for n in (1, 2, 3):
            for k in range(len(marks) - n + 1):
                g = marks[k : k + n]
                if g == [1] or n == 3 and g[1] == 1 or n == 2 and g == [1, 1]:
                    continue
                want[sum(m << (14 * (n - 1 - j)) for j, m in enumerate(g))] = want.get(sum(m << (14 * (n - 1 - j)) for j, m in enumerate(g)), 0) + 1
        assert dict(zip(gram[doc == i].tolist(), count[doc == i].tolist(), strict=True)) == want


def test_toxicity_of_held_out_texts(spark):
    docs, labels = table(spark, SF, "documents"), table(spark, SF, "labels")
    got = toxicity.classify(with_clashes(docs), labels).join(labels.groupBy("doc_id").agg(F.max("toxic").alias("y")), "doc_id").where("held_out")
    t = {(r.y, r.predicted): r["count"] for r in got.groupBy("y", "predicted").count().collect()}
    assert t[1, 1] / (t[1, 1] + t.get((1, 0), 0)) > 0.85 and t.get((0, 1), 0) / (t[0, 0] + t.get((0, 1), 0)) < 0.02


def test_toxicity_learns_pairs(spark):
    """Either word alone is harmless."""
    rows, labels = [], []
    for i in range(1600):
        a, b = i % 2, i // 2 % 2
        rows.append((i, f"f{i % 7} {'zorb' if a else ''} {'quux' if b else ''} g{i % 5}", "en", "s", 0))
        labels.append((i, a & b))
    got = {r.doc_id: r for r in toxicity.classify(frame(spark, rows), spark.createDataFrame(labels, "doc_id long, toxic int")).collect()}
    held = [i for i in range(1600) if got[i].held_out]
    assert len(held) > 200 and np.mean([got[i].predicted == labels[i][1] for i in held]) > 0.98


def test_toxicity_of_odd_tables(spark):
    rows = corpus(20)
    labels = spark.createDataFrame([(0, 1), (0, 0), (3, None), (None, 1), (6, 0), (9, 0), (12, 1)], "doc_id long, toxic int")
    got = toxicity.classify(frame(spark, rows), labels).collect()
    assert len(got) == len(rows) and all(0 <= r.score <= 1 for r in got)
    assert {r.predicted for r in toxicity.classify(frame(spark, rows), labels.where("false")).collect()} == {0}
    assert toxicity.classify(frame(spark, []), labels).count() == 0


def test_statistics_against_a_plain_count():
    texts = [r[1] for r in corpus(40)] + ["a b c d e a b c d e", "x\nx\n\n \n x\nx", "#tag $5 | <b>", "é ü", "one"]
    counts, features = quality.statistics(bt.texts_of(pa.array(texts, pa.string())))
    assert np.isfinite(features).all()
    for text, got in zip(texts, counts.tolist(), strict=True):
        text = text or ""
        words = GRAPHIC.findall(text)
        seen, dup = set(), 0
        for line in text.split("\n"):
            if GRAPHIC.search(line):
                dup += line in seen
                seen.add(line)
        windows = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
        twice = {w for w in windows if windows.count(w) > 1} if len(windows) < 3000 else None
        if twice is None:
            from collections import Counter

            twice = {w for w, n in Counter(windows).items() if n > 1}
        hit = [False] * len(words)
        for i, w in enumerate(windows):
            if w in twice:
                hit[i : i + 5] = [True] * 5
        assert got == [len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), dup, sum(hit)]


def test_trees_respect_constraints():
    r = np.random.default_rng(0)
    x = r.random((3000, 3))
    y = (x[:, 0] + 0.3 * np.sin(9 * x[:, 1]) + 0.1 * r.standard_normal(3000) > 0.6).astype(float)
    model = boosting.fit(x, y, {0: 1, 1: -1})
    assert ((model.probability(x) > 0.5) == y).mean() > 0.8
    grid = np.linspace(0, 1, 50)
    for base in r.random((40, 3)):
        for j, sign in ((0, 1), (1, -1)):
            line = np.tile(base, (50, 1))
            line[:, j] = grid
            assert (np.diff(model.raw(line)) * sign >= -1e-9).all()
    assert boosting.fit(np.zeros((0, 2)), np.zeros(0)).probability(np.zeros((2, 2))).tolist() == [0.5, 0.5]


def test_quality(spark):
    docs, labels = table(spark, SF, "documents"), table(spark, SF, "labels")
    got = quality.judge(with_clashes(docs), labels).join(labels.groupBy("doc_id").agg(F.max("quality").alias("q")), "doc_id")
    r = got.where("not base_failed").agg(F.avg((F.col("kept") == (F.col("q") == 1)).cast("double"))).first()
    assert r[0] > 0.97
    odd = quality.judge(frame(spark, corpus(10)), labels.where("false")).collect()
    assert all(x.base_failed and not x.kept for x in odd if x.n_words < 10) and all(x.kept for x in odd if not x.base_failed)
    assert quality.judge(frame(spark, []), labels).count() == 0


def _cheapest(roles):
    """Exhaustive search over relabelling, merging and insertion."""
    best = 1 << 30
    legal = {(None, "system"), (None, "user"), ("system", "user"), ("user", "assistant"), ("assistant", "user")}

    def go(i, last, cost):
        nonlocal best
        if cost >= best:
            return
        if i == len(roles):
            best = min(best, cost + {None: 0, "assistant": 0, "user": 3, "system": 6}[last])
            return
        for r in chat.ROLES:
            c = cost + (0 if r == roles[i] else 2)
            if (last, r) in legal:
                go(i + 1, r, c)
            if last == r:
                go(i + 1, r, c + 1)
            for x in chat.ROLES:
                if (last, x) in legal and (x, r) in legal and (last, r) not in legal:
                    go(i + 1, r, c + 3)

    go(0, None, 0)
    return best


def test_repairs_are_cheapest_and_legal(spark):
    rows = []
    for k, roles in enumerate(itertools.chain.from_iterable(itertools.product(["system", "user", "assistant", "robot", None], repeat=n) for n in (1, 2, 3))):
        rows += [(k, i, r, f"t{i}" if i else None) for i, r in enumerate(roles)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    whole = {r.conv_id: r for r in chat.repair_roles(with_clashes(df)).collect()}
    blocks = {}
    for r in chat.repair_roles(df, block_turns=1).orderBy("conv_id", "part").collect():
        blocks.setdefault(r.conv_id, []).append(r)
    for k, r in whole.items():
        roles = [x[2] for x in rows if x[0] == k]
        assert r.cost == _cheapest(roles) == sum(x.cost for x in blocks[k]) and r.n_turns == len(roles) and r.part == 0
        for text in (r.rendered, "".join(x.rendered for x in blocks[k])):
            turns = [t.split("\n", 1)[0].strip("<|>") for t in text.split("<|end|>\n")[:-1]]
            assert turns[-1] == "assistant" and all((a, b) in {("system", "user"), ("user", "assistant"), ("assistant", "user")} for a, b in zip(turns, turns[1:], strict=False))
            assert all(f"t{i}" in text for i in range(1, len(roles)))
    assert chat.repair_roles(df.where("false")).count() == 0


def test_conversation_in_blocks(spark):
    rows = [(1, i, "user" if i % 3 else "assistant", f"m{i}") for i in range(500)] + [(None, 0, "user", "x"), (None, 1, "assistant", "y"), (2, None, "user", "z")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    whole = {r.conv_id: r for r in chat.repair_roles(df, 10_000).collect()}
    parts = chat.repair_roles(df, 16).where("conv_id = 1").orderBy("part").collect()
    assert len(parts) == 32 and sum(p.cost for p in parts) == whole[1].cost
    assert whole[None].cost == 0 and whole[None].n_turns == 2 and whole[2].n_insert == 1


def test_blocks_are_cut_by_rank(spark):
    """Null and repeated turn numbers, or no conversation at all, gather nowhere; runs of blocks are reduced in turn."""
    rows = [(None, None, ("user", "assistant", None)[i % 3], f"m{i % 50}") for i in range(700)] + [(4, 3, "user" if i % 2 else "assistant", "same") for i in range(300)] + [(5, 1, "user", "x"), (5, 2, "assistant", "y")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    whole = {r.conv_id: r for r in chat.repair_roles(df, 10_000).collect()}
    parts = {}
    for r in chat.repair_roles(df.repartition(7), 16, 4).orderBy("conv_id", "part").collect():
        parts.setdefault(r.conv_id, []).append(r)
    for k, n in ((None, 700), (4, 300), (5, 2)):
        assert [p.part for p in parts[k]] == list(range(-(-n // 16))) and all(p.n_turns <= 16 for p in parts[k])
        assert sum(p.n_turns for p in parts[k]) == whole[k].n_turns == n and sum(p.cost for p in parts[k]) == whole[k].cost
    assert "".join(p.rendered for p in parts[5]) == whole[5].rendered


def test_samples_keep_their_bound(spark):
    """A doc_id that many rows have counts once."""
    rows = [(1, f"word{i} vile text", "en", "s", 0) for i in range(500)] + [(2, "calm text", "en", "s", 0)]
    labels = spark.createDataFrame([(1, 1, 0), (2, 0, 1)], "doc_id long, toxic int, quality int")
    assert toxicity.train(frame(spark, rows), labels, bound=10).known.size <= 3
    trees = quality.train(quality.measure(frame(spark, rows)), labels, bound=10)
    assert np.isfinite(trees.probability(np.zeros((1, len(quality.FEATURES))))).all()


def test_score_of_the_machine_is_the_plain_sum():
    """Bias, weights and all pairs' inner products, term by term."""
    texts = ["insult group word insult", "group", "", None, "Insulting groups", "calm insult"]
    r = np.random.default_rng(2)
    _, h = toxicity.terms(bt.texts_of(pa.array(texts, pa.string())))
    known = np.unique(h)
    m = toxicity.Machine(known, -0.3, r.normal(size=len(known)), r.normal(size=(len(known), 3)))
    doc, h = toxicity.terms(bt.texts_of(pa.array(texts, pa.string())))
    want = []
    for i in range(len(texts)):
        at = [int(np.searchsorted(known, x)) for x in h[doc == i]]
        raw = m.bias + sum(m.weight[a] for a in at) + sum(float(m.factor[a] @ m.factor[b]) for a, b in itertools.combinations(at, 2))
        want.append(1 / (1 + np.exp(-raw)))
    assert m.score(bt.texts_of(pa.array(texts, pa.string()))) == pytest.approx(want)


def test_terms_of_a_wide_vocabulary(spark):
    """Some thousand words of noise don't hide the telling ones."""
    r = np.random.default_rng(4)
    rows, labels = [], []
    for i in range(2400):
        y = i % 8 == 0
        rows.append((i, " ".join([*(f"noise{k}" for k in r.integers(0, 6000, 25)), *(["grobian"] if y else [])]), "en", "s", 0))
        labels.append((i, int(y)))
    got = {x.doc_id: x for x in toxicity.classify(frame(spark, rows), spark.createDataFrame(labels, "doc_id long, toxic int")).where("held_out").collect()}
    found = [got[i].predicted for i in got if labels[i][1]]
    alarms = [got[i].predicted for i in got if not labels[i][1]]
    assert np.mean(found) > 0.95 and np.mean(alarms) < 0.05


def test_distances_against_a_plain_version(spark):
    """The out-of-place distance, gram by gram, decides the language."""
    docs = table(spark, "/root/testdata/sf0.001", "documents")
    known = langid.profiles(docs.where(~F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(True))))
    judge, size = langid.Judge(known, langid.PROFILE), langid.PROFILE
    texts = [r.text for r in docs.orderBy("doc_id").limit(60).collect()]
    lang, _ = judge.predict(texts)
    for text, got in zip(texts, lang, strict=True):
        _, gram, count = langid.ngram_counts([text])
        own = [g for _, g in sorted(zip((-count).tolist(), gram.tolist(), strict=True))][:size]
        if not own:
            assert got == "und"
            continue
        away = {name: sum(abs(grams.index(g) - k) if g in grams else size for k, g in enumerate(own)) for name, grams in known.items()}
        assert got == min(sorted(away), key=away.get)


def test_rates_against_dense_least_squares(spark):
    """Expected domain totals are those of nonnegative least squares solved in one piece."""
    docs = table(spark, "/root/testdata/sf0.001", "documents").select("doc_id", "text", "lang")
    mixed, model, fit = mixing.mix(docs, weights={"en": 0.1, "fr": 0.5, "de": 0.2, "es": 0.2}, least=0.0)
    rows = mixed.collect()
    n, p = model.posteriors(bt.texts_of(pa.array([x.text for x in rows], pa.string())))
    a, x = (p * n[:, None]).T, np.ones(len(rows))
    size = np.linalg.eigvalsh((p * n[:, None]).T @ p)[-1]
    for _ in range(3000):  # plain projected gradient, scaled by length as the operator is
        x = np.maximum(0, x - p @ (a @ x - fit.targets) / size)
    scale = fit.targets.sum()
    assert np.abs(a @ x - fit.targets).sum() < 1e-3 * scale and np.abs(fit.reached - a @ np.array([r._rate for r in rows])).sum() < 1e-6 * scale
    assert np.abs(fit.reached - fit.targets).sum() < 1e-3 * scale and min(r._rate for r in rows) >= 0


def test_mixing_meets_its_targets(spark):
    docs = table(spark, "/root/testdata/sf0.01", "documents").select("doc_id", "text", "lang")
    mixed, model, fit = mixing.mix(with_clashes(docs), weights={"en": 0.4, "fr": 0.2, "de": 0.2, "es": 0.2}, budget=300_000, least=0.0)
    assert model.domains == ["de", "en", "es", "fr"]
    assert np.abs(fit.reached - fit.targets).sum() < 0.01 * fit.targets.sum()
    rate = "__rate" if "__rate" in mixed.columns else "_rate"
    r = mixed.agg(F.min(rate), F.count("*")).first()
    assert r[0] >= 0 and r[1] == docs.count()
    kept, _, fit = mixing.mix(docs)
    assert kept.agg(F.min("_rate"), F.min("_copies")).first()[:] == pytest.approx((1.0, 1.0), abs=1e-6)
    assert np.abs(fit.reached - fit.targets).sum() < 0.01 * fit.targets.sum()
    with pytest.raises(ValueError):
        mixing.mix(docs, weights={"xx": 1.0})


def test_mixing_of_odd_tables(spark):
    mixed, _, _ = mixing.mix(frame(spark, corpus(20)))
    assert mixed.count() == len(corpus(20)) and mixed.where("_rate is null").isEmpty()
    empty, _, _ = mixing.mix(frame(spark, []))
    assert empty.count() == 0
    plain, _, _ = mixing.mix(frame(spark, [(1, "a b", None, "s", 0), (2, None, None, "s", 0)]))
    assert {r._rate for r in plain.collect()} == {1.0}
