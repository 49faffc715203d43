"""Mixing sources to target weights with soft membership.

A classifier trained on labelled rows gives every document posteriors over the domains, so
a document counts towards several of them. Rates x of the documents are then fitted so that
the expected tokens of each domain, sum of x * tokens * posterior, match the targets: least
squares over x >= least, solved by accelerated projected gradient steps.

The rates, one for each document, never leave the executors. A step needs only the residual of
each domain, so a document's rate is a function of its own posteriors and of the short history
of residuals, and an iteration is one pass over a small table of posteriors that returns one vector from each partition. The
steps are scaled by document length, so that a rate doesn't depend on it.

The classifier is multinomial naive Bayes over hashed words, learned from a bounded sample of
labelled rows (TRAIN_ROWS a domain); its evidence is capped at SOFT_WORDS words, which keeps posteriors soft.

Edge cases: a null or empty text has no tokens and the domains' priors. Domains without labelled rows can't be matched and are an error
in targets. Repeated rows are documents of their own. With no labelled row at all every rate is the least one or 1. Extra columns pass through.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainbound.llm import bytetext as bt
from gainbound.llm.common import bounded_sample, fresh, settle, with_judged

TRAIN_ROWS = 2_000
#: Most domains: the classifier holds a row of 65,536 weights for each.
MAX_DOMAINS = 256
SOFT_WORDS = 24
BUCKET_BITS = 16
PIECE = 1 << 20


def _words(t: bt.Texts) -> tuple[np.ndarray, np.ndarray]:
    start, end, ranges = bt.find_words(t, bt.ALNUM)
    return (bt.hash_spans(bt.LOWER[t.buf], start, end) >> np.uint64(64 - BUCKET_BITS)).astype(np.int32), ranges


@dataclass
class Classifier:
    domains: list[str]
    prior: np.ndarray
    weight: np.ndarray  # domains x buckets, log probabilities

    def posteriors(self, t: bt.Texts) -> tuple[np.ndarray, np.ndarray]:
        """Tokens of each text, and its posteriors (texts x domains)."""
        bucket, ranges = _words(t)
        n = np.diff(ranges)
        doc = bt.text_of_word(ranges)
        told = np.stack([np.bincount(doc, w[bucket], len(n)) for w in self.weight], 1)
        told = told / np.maximum(n, 1)[:, None] * np.minimum(n, SOFT_WORDS)[:, None] + np.log(self.prior)
        p = np.exp(told - told.max(1, keepdims=True))
        return n, p / p.sum(1, keepdims=True)


def train(docs: DataFrame, domain: str, bound: int = TRAIN_ROWS) -> Classifier:
    """Naive Bayes for the column `domain` on at most about `bound` labelled documents of each."""
    labelled = docs.where(F.col(domain).isNotNull()).groupBy(domain).count().limit(MAX_DOMAINS + 1).collect()
    if len(labelled) > MAX_DOMAINS:
        raise ValueError(f"{domain} has more than {MAX_DOMAINS} values; group them into domains")
    domains = sorted(str(r[0]) for r in labelled)
    sample = bounded_sample(docs.where(F.col(domain).isNotNull() & F.col("text").isNotNull()).select("doc_id", F.col(domain).cast("string").alias("domain"), "text"), bound, "domain")

    def count(batches):
        for batch in batches:
            for part in bt.pieces(batch, 1, PIECE):
                bucket, ranges = _words(bt.texts_of(part.column(1)))
                names = part.column(0).to_pylist()
                which = np.array([domains.index(x) for x in names], np.int64)
                key, n = np.unique(np.repeat(which, np.diff(ranges)) << BUCKET_BITS | bucket, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(n.astype(np.int64))], names=["key", "n"])

    rows = sample.select("domain", "text").mapInArrow(count, "key long, n long").groupBy("key").agg(F.sum("n").alias("n")).toArrow()
    total = np.zeros(max(1, len(domains)) << BUCKET_BITS)
    total[rows.column("key").to_numpy()] = rows.column("n").to_numpy()
    total = total.reshape(-1, 1 << BUCKET_BITS) + 0.05
    prior = np.array([r["count"] for r in sorted(labelled, key=lambda r: str(r[0]))], float) if domains else np.ones(1)
    return Classifier(domains or ["none"], prior / prior.sum(), np.log(total / total.sum(1, keepdims=True)))


@dataclass
class Fit:
    """What determines all rates: the scaled residual and momentum of each step."""

    least: float
    steps: list[tuple[np.ndarray, float]] = field(default_factory=list)
    reached: np.ndarray | None = None
    targets: np.ndarray | None = None

    def rates(self, p: np.ndarray, ahead: bool = False) -> np.ndarray:
        """The rates of documents with posteriors p; ahead: the extrapolated point at which the next residual is taken."""
        x = np.full(len(p), max(1.0, self.least))
        y = x
        for residual, momentum in self.steps:
            new = np.maximum(self.least, y - p @ residual)
            x, y = new, new + momentum * (new - x)
        return y if ahead else x


def posterior_table(docs: DataFrame, model: Classifier) -> DataFrame:
    """doc_id, tokens and posteriors of each document, settled."""
    known = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            for part in bt.pieces(batch, 1, PIECE):
                n, p = known.value.posteriors(bt.texts_of(part.column(1)))
                lists = pa.ListArray.from_arrays(np.arange(0, p.size + 1, p.shape[1], dtype=np.int32), pa.array(p.ravel()))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(n.astype(np.int64)), lists], names=["doc_id", "tokens", "posteriors"])

    return settle(docs.select("doc_id", "text").mapInArrow(run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, tokens long, posteriors array<double>"))


def _sums(table: DataFrame, k: int, fit: Fit, gram: bool = False) -> np.ndarray:
    """Sum of tokens * y * posterior over all documents at the fit's next point, or the tokens' Gram matrix of posteriors."""

    def run(batches):
        total = np.zeros(k * k if gram else k)
        for batch in batches:
            t = batch.column(0).to_numpy().astype(float)
            p = np.array(batch.column(1).flatten()).reshape(-1, k)
            total += ((p * t[:, None]).T @ p).ravel() if gram else (t * fit.rates(p, ahead=True)) @ p
        yield pa.RecordBatch.from_arrays([pa.array([total.tolist()], pa.list_(pa.float64()))], names=["v"])

    parts = table.select("tokens", "posteriors").mapInArrow(run, "v array<double>").collect()  # a vector from each partition
    return np.array([math.fsum(r.v[i] for r in parts) for i in range(k * k if gram else k)])


def solve(table: DataFrame, k: int, targets: np.ndarray, least: float = 0.0, iterations: int = 60, tolerance: float = 1e-4) -> Fit:
    """Accelerated projected gradient for the rates; stops when the totals are within tolerance of the targets."""
    fit = Fit(least, targets=targets)
    size = float(np.linalg.eigvalsh(_sums(table, k, fit, gram=True).reshape(k, k))[-1])
    scale = max(float(np.abs(targets).sum()), 1.0)
    t, last = 1.0, np.inf
    for _ in range(iterations):
        residual = _sums(table, k, fit) - targets
        error = float(np.abs(residual).sum()) / scale
        if error <= tolerance or size <= 0:
            break
        if error > last:  # momentum has overshot
            t = 1.0
        last = error
        after = (1 + math.sqrt(1 + 4 * t * t)) / 2
        fit.steps.append((residual / size, (t - 1) / after))
        t = after
    if fit.steps:
        fit.steps[-1] = (fit.steps[-1][0], 0.0)
    fit.reached = _sums(table, k, fit)
    return fit


def smoothed_targets(table: DataFrame, k: int, power: float = 0.7, least: float = 1.0) -> np.ndarray:
    """Token targets whose shares are the present ones to a power, scaled so that no domain needs a rate under `least`."""
    now = _sums(table, k, Fit(0.0))
    share = now / max(now.sum(), 1e-9)
    want = np.where(share > 0, share**power, 0)
    want = want / max(want.sum(), 1e-9)
    ratio = np.divide(now, want, out=np.zeros(k), where=want > 0)
    return want * ratio.max(initial=0.0) * least


def apply_rates(docs: DataFrame, model: Classifier, fit: Fit, seed: int = 17) -> DataFrame:
    """docs with _tokens, _domain (likeliest), _rate and _copies (more underscores where docs has such a column).

    Copies are the rate's whole part, plus one by a hash of the doc_id against its fraction."""
    known = docs.sparkSession.sparkContext.broadcast((model, fit))
    names = docs.columns
    tokens, domain, rate, copies = (fresh(names, c) for c in ("_tokens", "_domain", "_rate", "_copies"))
    def judge(part: pa.RecordBatch) -> list[pa.Array]:
        m, f = known.value
        n, p = m.posteriors(bt.texts_of(part.column(0)))
        return [pa.array(n.astype(np.int64)), pa.array([m.domains[i] for i in p.argmax(1)], pa.string()), pa.array(f.rates(p))]

    out = with_judged(docs, judge, [(tokens, "long"), (domain, "string"), (rate, "double")], PIECE)
    u = F.pmod(F.xxhash64("doc_id", F.lit(seed)), F.lit(1 << 30)) / float(1 << 30)
    return out.withColumn(copies, (F.floor(rate) + (u < F.col(rate) - F.floor(rate)).cast("int")).cast("int"))


def mix(docs: DataFrame, domain: str = "lang", weights: dict[str, float] | None = None, budget: float | None = None, least: float = 1.0) -> tuple[DataFrame, Classifier, Fit]:
    """The documents with their rates, and how they came about.

    weights: shares of the domains (by default the present ones to the power 0.7); budget: all
    tokens after mixing (by default, without weights, as few as keep every domain at rate `least`, or as many as now if that is 0)."""
    model = train(docs, domain)
    k = len(model.domains)
    table = posterior_table(docs, model)
    if weights is None:
        targets = smoothed_targets(table, k, least=least or 1.0)
        if not least:
            targets = targets / max(targets.sum(), 1e-9) * (_sums(table, k, Fit(0.0)).sum() if budget is None else budget)
    else:
        if missing := set(weights) - set(model.domains):
            raise ValueError(f"no labelled row of {sorted(missing)}")
        now = _sums(table, k, Fit(0.0))
        share = np.array([weights.get(d, 0.0) for d in model.domains])
        targets = share / share.sum() * (now.sum() if budget is None else budget)
    fit = solve(table, k, targets, least)
    return apply_rates(docs, model, fit), model, fit
