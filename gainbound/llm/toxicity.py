"""Toxicity: a factorisation machine over hashed terms.

Terms are the lower-cased words of a text and the first four, five and six bytes of its
longer words (so that inflected forms share a term), each hashed to 64 bits. On a bounded
sample of labelled documents (TRAIN_ROWS) the terms that tell the label most are chosen by their likelihood-ratio
statistic, and the machine learns a weight for each and a short vector
for each, whose inner products weigh pairs of terms that stand in one text. Every whole text is then scored by the terms that it holds.

Edge cases: a null or empty text is scored by the bias alone, as any text without known terms. With no
labelled row all scores are 0. A document that is labelled twice is toxic if one label says so. Repeated rows are scored each; extra columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainbound.llm import bytetext as bt
from gainbound.llm.common import bounded_sample, fresh, in_fold, settle, with_judged

TRAIN_ROWS = 20_000
TERMS = 1024
FACTORS = 4
PIECE = 1 << 20
PREFIXES = (4, 5, 6)
THRESHOLD = 0.3
#: Terms must tell this share of what the luckiest of as many meaningless terms would.
SURPRISE = 0.5
#: Fewest texts of each label that must be set apart for choosing an epoch.
MIN_APART = 10


def terms(t: bt.Texts, known: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Each text's distinct terms, as text numbers and hashes; only the known (sorted) ones if given."""
    start, end, ranges = bt.find_words(t, bt.ALNUM)
    buf, doc = bt.LOWER[t.buf], bt.text_of_word(ranges)
    texts, hashes = [], []
    for size in (None, *PREFIXES):
        some = slice(None) if size is None else np.flatnonzero(end - start > size)
        s, d = start[some], doc[some]
        h = bt.hash_spans(buf, s, end[some] if size is None else s + size)
        if size:
            h = bt.mix64(h + np.uint64(size))
        if known is not None:
            have = bt.member_of(h, known)
            d, h = d[have], h[have]
        texts.append(d), hashes.append(h)
    d, h = np.concatenate(texts).astype(np.int64), np.concatenate(hashes)
    _, first = np.unique(h ^ bt.mix64(d), return_index=True)
    return d[first], h[first]


@dataclass
class Machine:
    known: np.ndarray  # sorted term hashes
    bias: float
    weight: np.ndarray
    factor: np.ndarray

    def score(self, t: bt.Texts) -> np.ndarray:
        doc, h = terms(t, self.known)
        at = np.searchsorted(self.known, h)
        n = len(t)
        out = self.bias + np.bincount(doc, self.weight[at], n)
        for f in range(self.factor.shape[1]):
            v = self.factor[at, f]
            out += 0.5 * (np.bincount(doc, v, n) ** 2 - np.bincount(doc, v * v, n))
        return 1 / (1 + np.exp(-np.clip(out, -40, 40)))


def _telling(n: int, n_positive: int):
    """Likelihood-ratio statistic of a term's 2 x 2 table, from the columns present and positive."""
    present, positive = F.col("present").cast("double"), F.col("positive").cast("double")

    def part(seen, rows, cols):
        return F.when(seen > 0, seen * F.ln(seen * n / (rows * cols))).otherwise(0.0)

    n_negative = float(n - n_positive)
    return 2 * (part(positive, present, float(n_positive)) + part(present - positive, present, n_negative) + part(n_positive - positive, n - present, float(n_positive)) + part(n_negative - present + positive, n - present, n_negative))


def fit(doc: np.ndarray, at: np.ndarray, y: np.ndarray, known: np.ndarray, factors: int = FACTORS, epochs: int = 20, rate: float = 0.02, l2: float = 2e-5, seed: int = 5) -> Machine:
    """Logistic loss, Adam on minibatches. doc and at: which texts hold which of the known terms.

    An eighth of the texts is set apart, and the epoch that does best on it is kept, so that a sample's chance terms aren't learned by heart."""
    n = len(y)
    if not n or not len(known):
        return Machine(np.zeros(0, np.uint64), -40.0 if not n else float(np.log((y.sum() + 1) / (n - y.sum() + 1))), np.zeros(0), np.zeros((0, factors)))
    x = np.zeros((n, len(known)), np.uint8)
    x[doc, at] = 1
    random = np.random.default_rng(seed)
    apart = random.random(n) < 1 / 8
    if min(y[apart].sum(), (1 - y[apart]).sum()) < MIN_APART:
        apart[:] = False
    theta = [np.zeros(1, np.float32), np.zeros(len(known), np.float32), random.normal(0, 0.01, (len(known), factors)).astype(np.float32)]
    m, v = [np.zeros_like(a) for a in theta], [np.zeros_like(a) for a in theta]

    def raw(xb: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        b, w, f = theta
        xf = xb @ f
        return b + xb @ w + 0.5 * ((xf**2).sum(1) - xb @ (f**2).sum(1)), xf

    def loss_apart() -> float:
        some, total = np.flatnonzero(apart), 0.0
        for start in range(0, len(some), 4096):
            rows = some[start : start + 4096]
            sign = 2 * y[rows] - 1
            total += float(np.logaddexp(0, -sign * raw(x[rows].astype(np.float32))[0]).sum())
        return total

    step, best, train_rows = 0, (np.inf, None), np.flatnonzero(~apart)
    for _ in range(epochs):
        rows = random.permutation(train_rows)
        for start in range(0, len(rows), 256):
            some = rows[start : start + 256]
            xb = x[some].astype(np.float32)
            guess, xf = raw(xb)
            w, f = theta[1:]
            g = (1 / (1 + np.exp(-np.clip(guess, -40, 40))) - y[some]).astype(np.float32) / len(some)
            grads = [np.array([g.sum()], np.float32), xb.T @ g + l2 * w, xb.T @ (g[:, None] * xf) - (xb.T @ g)[:, None] * f + l2 * f]
            step += 1
            for i, d in enumerate(grads):
                m[i] = 0.9 * m[i] + 0.1 * d
                v[i] = 0.999 * v[i] + 0.001 * d * d
                theta[i] = theta[i] - rate * (m[i] / (1 - 0.9**step)) / (np.sqrt(v[i] / (1 - 0.999**step)) + 1e-8)
        now = loss_apart() if apart.any() else -step
        if now < best[0]:
            best = (now, [a.copy() for a in theta])
    bias, weight, factor = best[1] or theta
    return Machine(known, float(bias[0]), weight.astype(float), factor.astype(float))


def _count_terms(batches):
    for batch in batches:
        for part in bt.pieces(batch, 1, PIECE):
            doc, h = terms(bt.texts_of(part.column(1)))
            y = part.column(0).to_numpy()
            names, at = np.unique(h, return_inverse=True)
            at = at.reshape(-1)
            yield pa.RecordBatch.from_arrays([pa.array(names.view(np.int64)), pa.array(np.bincount(at, minlength=len(names))), pa.array(np.bincount(at, y[doc], len(names)).astype(np.int64))], names=["term", "present", "positive"])


def train(docs: DataFrame, labels: DataFrame, bound: int = TRAIN_ROWS, size: int = TERMS) -> Machine:
    """The machine for the label toxic, from at most about `bound` labelled documents of `docs`, one text of each doc_id.

    Terms are counted and chosen in Spark; the driver gets the chosen ones' places in the sample."""
    known = labels.where("toxic is not null and doc_id is not null").groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    labelled = docs.select("doc_id", "text").where("text is not null").join(F.broadcast(bounded_sample(known, bound)), "doc_id")
    sample = settle(labelled.groupBy("doc_id").agg(F.max("toxic").alias("toxic"), F.min("text").alias("text")).select("toxic", "text"))
    n, positive = sample.agg(F.count("*"), F.coalesce(F.sum("toxic"), F.lit(0))).first()
    counts = sample.mapInArrow(_count_terms, "term long, present long, positive long").groupBy("term").agg(F.sum("present").alias("present"), F.sum("positive").alias("positive")).where("present >= 3")
    best = []
    if 0 < positive < n:
        told = settle(counts.withColumn("told", _telling(n, positive)))
        # the largest statistic that chance gives among so many terms that tell nothing
        chance = 2 * float(np.log(max(2, told.count())))
        best = told.where(F.col("told") > chance * SURPRISE).orderBy(F.desc("told"), "term").limit(size).select("term").collect()
    chosen = np.sort(np.array([r.term for r in best], np.int64).view(np.uint64))
    model = docs.sparkSession.sparkContext.broadcast(chosen)

    def places(batches):
        for batch in batches:
            for part in bt.pieces(batch, 1, PIECE):
                doc, h = terms(bt.texts_of(part.column(1)), model.value)
                by = np.argsort(doc, kind="stable")
                cut = np.searchsorted(doc[by], np.arange(len(part) + 1)).astype(np.int32)
                lists = pa.ListArray.from_arrays(cut, pa.array(np.searchsorted(model.value, h)[by].astype(np.int32)))
                yield pa.RecordBatch.from_arrays([part.column(0), lists], names=["toxic", "at"])

    rows = sample.mapInArrow(places, "toxic int, at array<int>").toArrow()
    y, at = rows.column("toxic").to_numpy().astype(float), rows.column("at").combine_chunks()
    return fit(np.repeat(np.arange(len(y)), np.diff(at.offsets.to_numpy())), at.flatten().to_numpy(), y, chosen)


def score(docs: DataFrame, machine: Machine, key: list[str]) -> DataFrame:
    """The columns `key` of each document and its score."""
    model = docs.sparkSession.sparkContext.broadcast(machine)

    def run(batches):
        for batch in batches:
            for part in bt.pieces(batch, len(key), PIECE):
                yield pa.RecordBatch.from_arrays([*part.columns[:-1], pa.array(model.value.score(bt.texts_of(part.column(len(key)))))], names=[*key, "score"])

    kinds = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in key)
    return docs.select(*key, "text").mapInArrow(run, kinds + ", score double")


def _machine(docs: DataFrame, labels: DataFrame, bound: int) -> Machine:
    return train(docs, labels.where(~in_fold(labels, 4, 2)), bound)


def without_toxic(docs: DataFrame, labels: DataFrame, bound: int = TRAIN_ROWS) -> DataFrame:
    """The rows of docs whose own text scores below the threshold, as they are."""
    model, name = docs.sparkSession.sparkContext.broadcast(_machine(docs, labels, bound)), fresh(docs.columns, "_score")
    scored = with_judged(docs, lambda part: [pa.array(model.value.score(bt.texts_of(part.column(0))))], [(name, "double")], PIECE)
    return scored.where(F.col(name) < THRESHOLD).drop(name)


def classify(docs: DataFrame, labels: DataFrame, bound: int = TRAIN_ROWS) -> DataFrame:
    """doc_id, held_out, score and predicted of each document; nothing is learned from held-out labels."""
    machine = _machine(docs, labels, bound)
    marked = docs.select("doc_id", "text").withColumn("held_out", in_fold(docs, 4, 2))
    return score(marked, machine, ["doc_id", "held_out"]).withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))
