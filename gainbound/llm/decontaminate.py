"""Benchmark decontamination through an FM-index of each training shard.

Texts are lower-cased (A-Z) and cut into runs of letters and digits. A phrase is 13
consecutive words of a benchmark item, or the whole item if it has fewer. A task gathers
texts into shards of about a quarter of a million words. A shard's words are numbered by the
vocabulary of the phrases; words that no phrase has, and text ends, become separators,
which no phrase crosses. The suffixes of that sequence are sorted, the last column of the
sorted rotations goes into a wavelet matrix, and all phrases are searched backwards at
once, each step narrowing a row range by two ranks. Rows of matching ranges walk back to the
nearest sampled suffix, which gives their positions; the hits of a text merge into spans.

A benchmark of at most BLOCK_BYTES of text is one block, broadcast. A larger one is cut into such blocks by
tasks, each block a file in the shared folder; a shard is then larger too, is indexed once over its own
words, and reads one block after the other. So the benchmark's size has no bearing on memory, and documents are never shuffled.

Edge cases: a null or empty text has no words and can't be contaminated; a null or empty
item has no phrase. Items with equal texts are all reported. Repeated rows are judged each, and
rows that share a doc_id by their own texts. Extra columns are ignored. Words are compared by 64-bit hashes.
"""

from __future__ import annotations

import pickle
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.fs as fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainbound.llm import bytetext as bt
from gainbound.llm.common import fresh, settle, shared_uri, with_judged

WINDOW = 13
SHARD_WORDS = 1 << 18
PIECE = 1 << 20
BLOCK_BYTES = 16 << 20
#: Shards are larger by up to this factor where there are many blocks.
MANY_BLOCKS = 8
SAMPLE = 8


def suffix_order(text: np.ndarray) -> np.ndarray:
    """Suffixes of a sequence in order; zeros are separators, each smaller than all symbols and than later zeros.

    Prefix doubling, in which only the suffixes that are still tied are sorted again."""
    n = len(text)
    zero = np.flatnonzero(text == 0)
    key = text.astype(np.int64) + len(zero)
    key[zero] = np.arange(len(zero))
    order = np.argsort(key, kind="stable")
    rank = np.empty(n, np.int64)

    def number(rows: np.ndarray, base: np.ndarray, value: np.ndarray) -> np.ndarray:
        """Ranks for rows sorted by value: base plus the distance to the first row of the same value."""
        new = np.concatenate(([True], value[1:] != value[:-1]))
        first = np.flatnonzero(new)
        rank[rows] = np.repeat(base[first], np.diff(np.append(first, len(rows))))
        size = np.diff(np.append(first, len(rows)))
        return np.repeat(size > 1, size)

    place = np.arange(n)
    tied = number(order, place, key[order])
    step = 1
    while tied.any():
        place, rows = place[tied], order[place[tied]]
        after = rank[np.minimum(rows + step, n - 1)]
        pair = rank[rows] * (n + 1) + after
        by = np.argsort(pair, kind="stable")
        rows, pair = rows[by], pair[by]
        order[place] = rows
        tied = number(rows, place, pair)
        step *= 2
    return order


class WaveletMatrix:
    """Ranks of symbols in a sequence, one bit level at a time."""

    def __init__(self, symbols: np.ndarray, levels: int):
        self.levels, self.zeros = levels, []
        for bit in range(levels - 1, -1, -1):
            one = (symbols >> bit & 1).astype(bool)
            before = np.zeros(len(symbols) + 1, np.int32)
            np.cumsum(~one, out=before[1:])
            self.zeros.append(before)
            symbols = np.concatenate((symbols[~one], symbols[one]))

    def rank(self, symbol: np.ndarray, *upto: np.ndarray) -> list[np.ndarray]:
        """How often symbol stands before each position."""
        start, at = np.zeros(len(symbol), np.int64), list(upto)
        for level, before in enumerate(self.zeros):
            one = (symbol >> (self.levels - 1 - level) & 1).astype(bool)
            start, *at = (np.where(one, before[-1] + x - before[x], before[x]) for x in (start, *at))
        return [x - start for x in at]

    def access(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The symbols at these positions, and how often each stands before its own."""
        symbol, start = np.zeros(len(at), np.int64), np.zeros(len(at), np.int64)
        for before in self.zeros:
            one = before[at + 1] == before[at]
            symbol = symbol * 2 + one
            start, at = (np.where(one, before[-1] + x - before[x], before[x]) for x in (start, at))
        return symbol, at - start


class FmIndex:
    """Backward search and location over one sequence of symbols, in which 0 separates."""

    def __init__(self, text: np.ndarray, symbols: int):
        text = np.append(text, 0) if not len(text) or text[-1] else text
        order = suffix_order(text)
        before = text[order - 1]
        self.first = np.concatenate(([0], np.cumsum(np.bincount(text, minlength=symbols + 1))))
        self.matrix = WaveletMatrix(before.astype(np.int32), max(1, int(symbols).bit_length()))
        # run starts are sampled too, so that no walk crosses a separator
        sampled = (order % SAMPLE == 0) | (before == 0)
        self.sampled = sampled
        self.nth = np.cumsum(sampled) - 1
        self.sample = order[sampled]

    def ranges(self, phrases: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The phrases (rows of length symbols) that occur, with their row ranges."""
        alive = np.arange(len(phrases))
        symbol = phrases[:, length - 1]
        low, high = self.first[symbol], self.first[symbol + 1]
        for j in range(length - 2, -2, -1):
            some = low < high
            alive, low, high = alive[some], low[some], high[some]
            if j < 0 or not len(alive):
                break
            symbol = phrases[alive, j]
            low, high = (self.first[symbol] + x for x in self.matrix.rank(symbol, low, high))
        return alive, low, high

    def locate(self, rows: np.ndarray) -> np.ndarray:
        out, walked, left = np.empty(len(rows), np.int64), 0, np.arange(len(rows))
        while len(left):
            done = self.sampled[rows]
            out[left[done]] = self.sample[self.nth[rows[done]]] + walked
            left, rows = left[~done], rows[~done]
            symbol, nth = self.matrix.access(rows)
            rows = self.first[symbol] + nth
            walked += 1
        return out


def phrases_of(items: pa.RecordBatch, window: int) -> dict:
    """The distinct phrases of items (item_id string, text) by length, in numbers of their vocabulary, and each one's items."""
    t = bt.texts_of(items.column(1))
    start, end, ranges = bt.find_words(t, bt.ALNUM)
    vocabulary, number = np.unique(bt.hash_spans(bt.LOWER[t.buf], start, end), return_inverse=True)
    number = number.astype(np.int64).reshape(-1) + 1
    n = np.diff(ranges)
    by_length = {}
    for length in np.unique(np.minimum(n, window)[n > 0]).tolist():
        items_of = np.flatnonzero(np.minimum(n, window) == length)
        many = n[items_of] - length + 1
        own = np.repeat(items_of, many)
        first = np.repeat(ranges[items_of] - (np.cumsum(many) - many), many) + np.arange(many.sum())
        distinct, which = np.unique(number[first[:, None] + np.arange(length)], axis=0, return_inverse=True)
        by = np.argsort(which.reshape(-1), kind="stable")
        by_length[length] = (distinct, np.searchsorted(which.reshape(-1)[by], np.arange(len(distinct) + 1)), own[by])
    return {"vocabulary": vocabulary, "items": items.column(0).to_pylist(), "phrases": by_length}


class Shard:
    """The index of some texts, given as word hashes. Words that aren't in the vocabulary become separators; by default it is the shard's own."""

    def __init__(self, words: np.ndarray, ranges: np.ndarray, vocabulary: np.ndarray | None = None):
        self.ranges, self.vocabulary = ranges, np.unique(words) if vocabulary is None else vocabulary
        known = np.flatnonzero(bt.member_of(words, self.vocabulary))
        self.index = None
        if not len(known):
            return
        doc = bt.text_of_word(ranges)[known]
        gap = np.ones(len(known), bool)
        gap[:-1] = (known[1:] != known[:-1] + 1) | (doc[1:] != doc[:-1])
        spot = np.arange(len(known)) + np.cumsum(gap) - gap
        text = np.zeros(len(known) + int(gap.sum()), np.int64)
        text[spot] = np.searchsorted(self.vocabulary, words[known]) + 1
        self.word_at = np.zeros(len(text), np.int64)
        self.word_at[spot] = known
        self.index = FmIndex(text, len(self.vocabulary))

    def search(self, block: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Occurrences of a block's phrases: text, first word within all, length, item."""
        found = []
        if self.index is not None and block["phrases"]:
            at = np.minimum(np.searchsorted(self.vocabulary, block["vocabulary"]), len(self.vocabulary) - 1)
            symbol = np.concatenate(([0], np.where(self.vocabulary[at] == block["vocabulary"], at + 1, 0)))
            for length, (phrases, cut, own) in block["phrases"].items():
                here = symbol[phrases]
                some = np.flatnonzero((here > 0).all(1))
                which, low, high = self.index.ranges(here[some], length) if len(some) else (some, some, some)
                count = high - low
                if not count.sum():
                    continue
                rows = np.repeat(low - (np.cumsum(count) - count), count) + np.arange(count.sum())
                first = self.word_at[self.index.locate(rows)]
                which = np.repeat(some[which], count)
                many = cut[which + 1] - cut[which]
                item = own[np.repeat(cut[which] - (np.cumsum(many) - many), many) + np.arange(many.sum())]
                first = np.repeat(first, many)
                found.append((np.searchsorted(self.ranges, first, "right") - 1, first, np.full(len(first), length), item))
        return tuple(np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.zeros(0, np.int64),) * 4


def _words(part: pa.RecordBatch, at: int) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of a batch's texts, and each text's number of words."""
    t = bt.texts_of(part.column(at))
    start, end, ranges = bt.find_words(t, bt.ALNUM)
    return bt.hash_spans(bt.LOWER[t.buf], start, end), np.diff(ranges)


def _shards(batches, at: int, most: int):
    """Runs of rows of about `most` words: the ids, word hashes and numbers of words of each piece."""
    held, words = [], 0
    for batch in batches:
        for part in bt.pieces(batch, at, PIECE):
            held.append((part.column(0), *_words(part, at)))
            words += len(held[-1][1])
            if words >= most:
                yield held
                held, words = [], 0
    if held:
        yield held


def _hits(words: np.ndarray, n: np.ndarray, blocks: Blocks) -> tuple[np.ndarray, np.ndarray, list[set[str]]]:
    """Of texts of n words each: which words are hit, the texts' ranges, and the items found in each."""
    ranges = np.concatenate(([0], np.cumsum(n)))
    edge, names = np.zeros(len(words) + 1, np.int64), [set() for _ in range(len(n))]
    shard = None
    for block in blocks.each():
        shard = shard or Shard(words, ranges, block["vocabulary"] if blocks.single else None)
        doc, first, length, item = shard.search(block)
        np.add.at(edge, first, 1)
        np.add.at(edge, first + length, -1)
        for pair in np.unique(doc * (len(block["items"]) + 1) + item).tolist():
            d, i = divmod(pair, len(block["items"]) + 1)
            names[d].add(block["items"][i])
    return np.cumsum(edge[:-1]) > 0, ranges, names


def _locate(blocks: Blocks, id_type: pa.DataType, most: int):
    kinds = pa.schema([("doc_id", id_type), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("items", pa.list_(pa.string())), ("spans", pa.list_(pa.struct([("first", pa.int64()), ("end", pa.int64())])))])

    def run(batches):
        for held in _shards(batches, 1, most):
            words, n = np.concatenate([h[1] for h in held]), np.concatenate([h[2] for h in held])
            hit, ranges, names = _hits(words, n, blocks)
            n_hit = bt.per_text(hit, ranges)
            spans = [None] * len(n)
            for d in range(len(n)):
                spans[d] = []
                if n_hit[d]:
                    x = np.flatnonzero(np.diff(hit[ranges[d] : ranges[d + 1]].astype(np.int8), prepend=0, append=0))
                    spans[d] = [{"first": int(x[i]), "end": int(x[i + 1])} for i in range(0, len(x), 2)]
            ids = pa.concat_arrays([h[0] for h in held]).cast(id_type)
            yield pa.RecordBatch.from_arrays([ids, pa.array(n, pa.int64()), pa.array(n_hit, pa.int64()), pa.array([sorted(x) for x in names], kinds.field("items").type), pa.array(spans, kinds.field("spans").type)], schema=kinds)

    return run


class Blocks:
    """The benchmark's phrases: one block that is broadcast, or files of blocks that are read one at a time."""

    def __init__(self, single, paths: list[str]):
        self.single, self.paths = single, paths

    def each(self):
        if self.single:
            yield self.single.value
        for path in self.paths:
            system, name = fs.FileSystem.from_uri(path)
            with system.open_input_stream(name, compression=None) as raw:
                yield pickle.loads(raw.read())  # written by this job a moment ago


_ITEMS = pa.schema([("item_id", pa.string()), ("text", pa.string())])


def benchmark_blocks(benchmark: DataFrame, window: int, limit: int | None = None) -> Blocks:
    """The phrases in blocks of at most `limit` bytes of item text; a longer item is a block by itself."""
    limit = BLOCK_BYTES if limit is None else limit
    context = benchmark.sparkSession.sparkContext
    items = benchmark.select(F.col("item_id").cast("string").alias("item_id"), "text").where("item_id is not null and text is not null")
    # an empty item counts too
    total = items.agg(F.coalesce(F.sum(F.octet_length("text") + F.octet_length("item_id")), F.lit(0))).first()[0]
    if total <= limit:
        return Blocks(context.broadcast(phrases_of(pa.RecordBatch.from_pylist([r.asDict() for r in items.collect()], _ITEMS), window)) if total else None, [])
    folder = f"{shared_uri(benchmark.sparkSession)}/phrases-{uuid.uuid4().hex}"

    def write(batches):
        system, root = fs.FileSystem.from_uri(folder)
        system.create_dir(root, recursive=True)

        def close(held) -> pa.RecordBatch:
            name = f"{uuid.uuid4().hex}.block"
            block = phrases_of(pa.Table.from_batches(held).combine_chunks().to_batches()[0], window)
            with system.open_output_stream(f"{root}/{name}", compression=None) as out:
                out.write(pickle.dumps(block))
            return pa.RecordBatch.from_arrays([pa.array([f"{folder}/{name}"])], names=["path"])

        held, weight = [], 0
        for batch in batches:
            for part in bt.pieces(batch, 1, max(1, limit // 4)):
                size = part.column(1).nbytes
                if held and weight + size > limit:
                    yield close(held)
                    held, weight = [], 0
                held.append(part.cast(_ITEMS))
                weight += size
        if held:
            yield close(held)

    # only the files of attempts that ended are named
    return Blocks(None, [r.path for r in settle(items.mapInArrow(write, "path string")).collect()])


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, n_words, n_hit, items (found in it) and spans (merged intervals of hit words) of each document."""
    from pyspark.sql.pandas.types import to_arrow_type

    blocks, kind = benchmark_blocks(benchmark, window), docs.schema["doc_id"].dataType
    most = SHARD_WORDS * max(1, min(MANY_BLOCKS, len(blocks.paths)))
    return docs.select("doc_id", "text").mapInArrow(_locate(blocks, to_arrow_type(kind), most), f"doc_id {kind.simpleString()}, n_words long, n_hit long, items array<string>, spans array<struct<first:long,end:long>>")


def without_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, percent: int = 5) -> DataFrame:
    """The rows of docs whose own text isn't contaminated, as they are; a shard is what of an Arrow batch comes to so many words."""
    blocks = benchmark_blocks(benchmark, window)

    def judge(part: pa.RecordBatch) -> list[pa.Array]:
        words, n = _words(part, 0)
        hit, ranges, _ = _hits(words, n, blocks)
        return [pa.array(n, pa.int64()), pa.array(bt.per_text(hit, ranges), pa.int64())]

    found = [fresh(docs.columns, c) for c in ("_words", "_hit")]
    # about six bytes a word
    judged = with_judged(docs, judge, [(c, "long") for c in found], 6 * SHARD_WORDS * max(1, min(MANY_BLOCKS, len(blocks.paths))))
    return judged.where(~is_contaminated(percent, *found)).select(*(F.col(f"`{c}`") for c in docs.columns))


def is_contaminated(percent: int = 5, n_words: str = "n_words", n_hit: str = "n_hit"):
    """Hit words are at least this share of the text's words."""
    return (F.col(n_hit) > 0) & (F.col(n_hit) * 100 >= F.col(n_words) * percent)
