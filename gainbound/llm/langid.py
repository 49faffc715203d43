"""Language identification by rank-order profiles.

A profile is the list of a language's most frequent character n-grams (one to three
letters, word borders marked), in order of frequency. A document gets such a list from its
whole text, and its distance to a profile is the sum, over its n-grams, of how far each
one is out of place, with a fixed penalty for one that the profile lacks. The nearest
profile names the language.

Letters are Unicode letters in lower case; all else is a word border. n-grams are counted
by sorting 64-bit keys (text, n-gram), so that a batch needs a few numpy passes.
Profiles are learned from a bounded sample of labelled documents (TRAIN_ROWS for each language), counted in Spark.

Edge cases: a null text, or one without a letter, is `und` with score 0. With no labelled row everything
is `und`. A tie goes to the language that sorts first. Rows are judged each; extra columns are ignored.
"""

from __future__ import annotations

from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gainbound.llm import bytetext as bt
from gainbound.llm.common import bounded_sample, in_fold

TRAIN_ROWS = 4_000
#: n-grams of a profile, and of a document's list.
PROFILE = 400
PIECE = 1 << 20
_BITS = 14  # of a letter's code; three letters take 42 bits
_MASK = np.int64((1 << 42) - 1)


@cache
def _letter_code() -> np.ndarray:
    """Code of each code point: 1 for a word border, 2 and above for letters (hashed beyond the first planes' start)."""
    point = np.arange(0x110000)
    letter = np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)
    code = np.where(point < (1 << _BITS) - 2, point + 2, point % ((1 << _BITS) - 514) + 514)
    return np.where(letter, code, 1).astype(np.int64)


def ngram_counts(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Text number, n-gram and count, for all n-grams of one to three characters, ordered by text."""
    raw = [b"\x20\0\0\0" + (x or "").lower().encode("utf-32-le", "surrogatepass") + b"\x20\0\0\0" for x in texts]
    size = np.array([len(x) // 4 for x in raw], np.int64)
    code = _letter_code()[np.frombuffer(b"".join(raw), "<u4")]
    doc = np.repeat(np.arange(len(texts), dtype=np.int64), size)
    border = code == 1
    keep = ~(border & np.concatenate(([False], border[:-1])) & np.concatenate(([False], doc[1:] == doc[:-1])))
    code, doc, border = code[keep], doc[keep], border[keep]
    if len(texts) >= 1 << 21:
        raise ValueError("a piece holds too many texts")
    tag = doc << np.int64(42)
    one = (tag | code)[~border]
    pair = (doc[1:] == doc[:-1]) & ~(border[1:] & border[:-1])
    two = (tag[1:] | (code[:-1] << _BITS) | code[1:])[pair]
    trio = (doc[2:] == doc[:-2]) & ~border[1:-1]
    three = (tag[2:] | (code[:-2] << (2 * _BITS)) | (code[1:-1] << _BITS) | code[2:])[trio]
    keys = np.sort(np.concatenate((one, two, three)))
    new = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1]))) if len(keys) else np.zeros(0, int)
    return keys[new] >> np.int64(42), keys[new] & _MASK, np.diff(np.append(new, len(keys)))


def ranked(doc: np.ndarray, gram: np.ndarray, count: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The `most` most frequent n-grams of each text and their ranks from 0; ties go to the smaller n-gram."""
    by = np.lexsort((-count, doc))  # stable, so n-grams stay in order
    doc, gram = doc[by], gram[by]
    head = np.searchsorted(doc, doc, "left")
    rank = np.arange(len(doc)) - head
    keep = rank < most
    return doc[keep], gram[keep], rank[keep]


def _count(batches):
    for batch in batches:
        labels = batch.column(0).to_pylist()
        for part in bt.pieces(batch, 1, PIECE):
            doc, gram, count = ngram_counts(part.column(1).to_pylist())
            names = sorted(set(labels))
            which = np.array([names.index(x) for x in part.column(0).to_pylist()])[doc]
            pair, at = np.unique(which.astype(np.int64) << np.int64(42) | gram, return_inverse=True)
            total = np.bincount(at.reshape(-1), count).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array([names[i] for i in (pair >> np.int64(42))], pa.string()), pa.array(pair & _MASK), pa.array(total)], names=["lang", "gram", "n"])


def profiles(docs: DataFrame, size: int = PROFILE, bound: int = TRAIN_ROWS) -> dict[str, list[int]]:
    """Each language's most frequent n-grams in order, from at most about `bound` documents of each."""
    rows = bounded_sample(docs.where("lang is not null and text is not null").select("doc_id", "lang", "text"), bound, "lang")
    counts = rows.select("lang", "text").mapInArrow(_count, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    order = Window.partitionBy("lang").orderBy(F.desc("n"), "gram")
    best = counts.withColumn("r", F.row_number().over(order)).where(F.col("r") <= size).collect()
    out: dict[str, list[int]] = {}
    for r in sorted(best, key=lambda r: (r.lang, r.r)):
        out.setdefault(r.lang, []).append(r.gram)
    return out


class Judge:
    def __init__(self, known: dict[str, list[int]], size: int):
        self.names, self.size = sorted(known), size
        self.grams = np.unique(np.array([g for v in known.values() for g in v], np.int64))
        self.rank = np.full((len(self.names), len(self.grams) + 1), size, np.int64)
        self.absent = len(self.grams)
        for i, name in enumerate(self.names):
            self.rank[i, np.searchsorted(self.grams, known[name])] = np.arange(len(known[name]))

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        n = len(texts)
        doc, gram, rank = ranked(*ngram_counts(texts), self.size)
        listed = np.bincount(doc, minlength=n)
        if not self.names:
            return ["und"] * n, np.zeros(n)
        at = np.minimum(np.searchsorted(self.grams, gram), len(self.grams) - 1)
        at = np.where(self.grams[at] == gram, at, self.absent)
        away = np.stack([np.bincount(doc, np.where(r[at] == self.size, self.size, np.abs(r[at] - rank)), n) for r in self.rank])
        nearest = np.argmin(away, 0)
        # share of the evidence that the winner has, as a softmax of the mean distances
        mean = away / np.maximum(listed, 1) / self.size
        weight = np.exp(-24 * (mean - mean.min(0)))
        score = np.where(listed > 0, 1 / weight.sum(0), 0.0)
        return [self.names[k] if m else "und" for k, m in zip(nearest.tolist(), listed.tolist(), strict=True)], score


def identify(docs: DataFrame, known: dict[str, list[int]], key: list[str], size: int = PROFILE) -> DataFrame:
    """The columns `key` of each document, lang_pred and score."""
    judge = docs.sparkSession.sparkContext.broadcast(Judge(known, size))

    def run(batches):
        for batch in batches:
            for part in bt.pieces(batch, len(key), PIECE):
                lang, score = judge.value.predict(part.column(len(key)).to_pylist())
                yield pa.RecordBatch.from_arrays([*part.columns[:-1], pa.array(lang, pa.string()), pa.array(score)], names=[*key, "lang_pred", "score"])

    kinds = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in key)
    return docs.select(*key, "text").mapInArrow(run, kinds + ", lang_pred string, score double")


def classify(docs: DataFrame, bound: int = TRAIN_ROWS) -> DataFrame:
    """doc_id, held_out, lang_pred and score; profiles come from rows that aren't held out."""
    known = profiles(docs.where(~in_fold(docs, 5, 0)), bound=bound)
    return identify(docs.select("doc_id", "text").withColumn("held_out", in_fold(docs, 5, 0)), known, ["doc_id", "held_out"])
