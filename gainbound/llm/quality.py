"""Quality rules: document statistics, fixed base rules, and boosted trees over the statistics.

Statistics are computed on whole texts in one pass of numpy over bytes. The trees are
fitted on a bounded sample of labelled documents (TRAIN_ROWS); the rest of the method sees
every row. Repetition, duplicate lines and symbols can only lower a score (monotone constraints).

Edge cases: a null text has no words and fails the base rules; an empty one too. With no labelled row of both kinds the
trees say nothing, and the base rules alone decide. Repeated rows are scored each; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainbound.llm import boosting
from gainbound.llm import bytetext as bt
from gainbound.llm.common import bounded_sample, integer_id, settle

TRAIN_ROWS = 20_000
PIECE = 2 << 20
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
FEATURES = ["log_words", "word_length", "symbol_share", "dup_line_share", "repeat_share", "upper_share", "digit_share", "punctuation_share", "wide_share", "line_words", "distinct_share", "bar_share"]
#: A rise of these may only lower the score.
MONOTONE = {FEATURES.index(k): -1 for k in ("symbol_share", "dup_line_share", "repeat_share")}


def _class(chars: bytes) -> np.ndarray:
    out = np.zeros(256, bool)
    out[np.frombuffer(chars, np.uint8)] = True
    return out


_SYMBOL = _class(b"#*$%&|<>")
_UPPER, _DIGIT = _class(bytes(range(0x41, 0x5B))), _class(bytes(range(0x30, 0x3A)))
_PUNCTUATION = _class(b"!?.,;:'\"()-")
_LEAD = ~((np.arange(256) >= 0x80) & (np.arange(256) < 0xC0))


def statistics(t: bt.Texts) -> tuple[np.ndarray, np.ndarray]:
    """The counts (texts x COUNTS) and the trees' features (texts x FEATURES)."""
    n = len(t)
    start, end, ranges = bt.find_words(t, bt.GRAPHIC)
    words = np.diff(ranges)
    inside = bt.GRAPHIC[t.buf]
    count = lambda flags: bt.per_text(flags, t.off)
    word_chars = count(inside & _LEAD[t.buf])
    symbols = count(_SYMBOL[t.buf])

    # lines that hold a word
    line_end = np.flatnonzero(t.buf == 0x0A)
    line_start = np.concatenate(([0], line_end[:-1] + 1)) if len(line_end) else line_end
    worded = np.searchsorted(start, line_end) > np.searchsorted(start, line_start)
    line_start, line_end = line_start[worded], line_end[worded]
    line_text = np.searchsorted(t.off, line_start, "right") - 1
    key = bt.hash_spans(t.buf, line_start, line_end) ^ bt.mix64(line_text)
    twice = np.flatnonzero(bt.repeated(key))
    _, first = np.unique(key[twice], return_index=True)
    again = np.ones(len(twice), bool)
    again[first] = False
    dup_lines = np.bincount(line_text[twice[again]], minlength=n)

    # words in five-word windows that occur twice or more in the text
    word = bt.hash_spans(t.buf, start, end)
    doc = bt.text_of_word(ranges)
    at = bt.window_starts(ranges, 5)
    window = bt.hash_windows(word, 5, 3)[at] ^ bt.mix64(doc[at])
    repeat = bt.per_text(bt.covered(len(start), at[bt.repeated(window)], 5), ranges) if len(start) else np.zeros(n, np.int64)

    own = word ^ bt.mix64(doc)
    distinct = np.bincount(doc[np.unique(own, return_index=True)[1]], minlength=n) if len(own) else np.zeros(n)
    counts = np.stack([words, word_chars, symbols, dup_lines, repeat], 1).astype(np.int64)
    w, c = np.maximum(words, 1), np.maximum(word_chars, 1)
    lines = np.maximum(np.bincount(line_text, minlength=n), 1)
    features = np.stack([np.log1p(words), word_chars / w, symbols / c, dup_lines / lines, repeat / w, count(_UPPER[t.buf]) / c, count(_DIGIT[t.buf]) / c, count(_PUNCTUATION[t.buf]) / c, count(t.buf >= 0x80) / c, words / lines, distinct / w, count(t.buf == 0x7C) / c], 1)
    return counts, features


def _measure(batches):
    kinds = pa.schema([("doc_id", pa.int64()), *((c, pa.int64()) for c in COUNTS), ("features", pa.list_(pa.float64()))])
    for batch in batches:
        for part in bt.pieces(batch, 1, PIECE):
            counts, features = statistics(bt.texts_of(part.column(1)))
            lists = pa.ListArray.from_arrays(np.arange(0, features.size + 1, features.shape[1], dtype=np.int32), pa.array(features.ravel()))
            yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), *(pa.array(counts[:, i]) for i in range(len(COUNTS))), lists], schema=kinds)


def measure(docs: DataFrame) -> DataFrame:
    """doc_id, the counts, and the features of each document's whole text."""
    return docs.select("doc_id", "text").mapInArrow(_measure, "doc_id long, " + ", ".join(f"{c} long" for c in COUNTS) + ", features array<double>")


def base_failed():
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def train(measured: DataFrame, labels: DataFrame, bound: int = TRAIN_ROWS) -> boosting.Ensemble:
    """Trees for the label quality, on at most about `bound` labelled documents, one text of each doc_id."""
    known = bounded_sample(labels.where("quality is not null and doc_id is not null").groupBy("doc_id").agg(F.max("quality").alias("quality")), bound)
    rows = measured.join(F.broadcast(known), "doc_id").groupBy("doc_id").agg(F.max("quality").alias("quality"), F.min("features").alias("features")).orderBy("doc_id").toArrow()
    y = rows.column("quality").to_numpy().astype(float)
    x = np.array(rows.column("features").combine_chunks().flatten()).reshape(-1, len(FEATURES)) if len(y) else np.zeros((0, len(FEATURES)))
    return boosting.fit(x, y, MONOTONE)


def judge(docs: DataFrame, labels: DataFrame, threshold: float = 0.5) -> DataFrame:
    """doc_id, the counts, base_failed, score (probability of good quality) and kept."""
    integer_id(docs)
    measured = settle(measure(docs))
    trees = docs.sparkSession.sparkContext.broadcast(train(measured, labels))
    names = measured.schema.names

    def score(batches):
        for batch in batches:
            x = np.array(batch.column(names.index("features")).flatten()).reshape(-1, len(FEATURES))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(trees.value.probability(x))], names=[*names[:-1], "score"])

    kinds = ", ".join(f"{c} {measured.schema[c].dataType.simpleString()}" for c in names[:-1])
    return measured.mapInArrow(score, kinds + ", score double").withColumn("base_failed", base_failed()).withColumn("kept", ~F.col("base_failed") & (F.col("score") >= threshold))


__all__ = ["judge", "measure", "statistics", "train"]
