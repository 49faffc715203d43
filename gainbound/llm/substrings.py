"""Removal of repeated passages: Rabin-Karp hashes of every token window, counted in Spark.

Every window of `size` words of every text is hashed. A window is removed when the same
word sequence starts earlier: in a text with a smaller doc_id, or earlier in its own text.
The words under removed windows form maximal intervals, and those words go.

How it runs. A task hashes a few megabytes of text at a time and keeps, of each hash, the
earliest window there; later ones are already known to be repeats, so a passage that half
of all texts share crosses the network once for each such chunk and not once for each
text. The hashes travel as packed arrays, one for each chunk and cell of the hash space (8
bytes a window plus compressed positions), not as rows. A cell's task finds each hash's
earliest window and sends the others' positions home by text. Cells are as many as the
input needs, and a task holds one cell at a time. The cell number and the 64 bits that
travel come from two separate hashes: with 2**c cells, 64 + c bits decide.

Edge cases: a null or empty text has no words and its digest is that of the empty string.
A row whose doc_id is null is kept whole and never compared. Rows that repeat a doc_id and text are the
same occurrence, so neither removes the other, and each is returned. Rows that share a doc_id but not the text are
documents of their own, in the order of a mark (a hash of the text); where no doc_id has two texts all marks are 0. doc_id is an
integer (a column of another type is refused). Extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainbound.llm import bytetext as bt
from gainbound.llm.common import integer_id, settle, small_join

CHUNK = 4 << 20
#: Bytes of text for each cell, and the most cells of a task; a cell has about a million windows.
CELL_BYTES, TASK_CELLS = 8 << 20, 64


def _pack(a: np.ndarray) -> bytes:
    return pa.compress(np.ascontiguousarray(a).view(np.uint8), codec="zstd", asbytes=True)


def _unpack(blob: bytes, kind, n: int) -> np.ndarray:
    return np.frombuffer(pa.decompress(blob, n * np.dtype(kind).itemsize, codec="zstd", asbytes=True), kind)


#: A text: its doc_id and mark, in the order of both.
TEXT = np.dtype([("id", np.int64), ("mark", np.int64)])


def _changes(doc: np.ndarray) -> np.ndarray:
    """Whether each entry but the first has another text than the one before."""
    return (doc["id"][1:] != doc["id"][:-1]) | (doc["mark"][1:] != doc["mark"][:-1])


def _order(doc: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Places in the order of text and start; marks are sorted by only where there are any."""
    return np.lexsort((start, doc["mark"], doc["id"]) if doc["mark"].any() else (start, doc["id"]))


def _spots(doc: np.ndarray, start: np.ndarray) -> dict:
    """Positions (in order) as the distinct texts, how many positions each has, and the positions' steps."""
    head = np.flatnonzero(np.concatenate(([True], _changes(doc)))) if len(doc) else np.zeros(0, int)
    count = np.diff(np.append(head, len(doc))).astype(np.uint32)
    step = np.diff(start, prepend=0).astype(np.int64)
    step[head] = start[head]
    of = doc[head]
    return {"texts": len(head), "n": len(doc), "docs": _pack(np.concatenate((of["id"], of["mark"]))), "counts": _pack(count), "steps": _pack(step.astype(np.uint32).view(np.uint8).reshape(-1, 4).T)}


def _places(r: dict) -> tuple[np.ndarray, np.ndarray]:
    both, counts = _unpack(r["docs"], np.int64, 2 * r["texts"]), _unpack(r["counts"], np.uint32, r["texts"])
    docs = np.empty(r["texts"], TEXT)
    docs["id"], docs["mark"] = both[: r["texts"]], both[r["texts"] :]
    step = np.ascontiguousarray(_unpack(r["steps"], np.uint8, 4 * r["n"]).reshape(4, -1).T).view(np.uint32).ravel().astype(np.int64)
    head = np.cumsum(counts, dtype=np.int64) - counts
    total = np.cumsum(step)
    return np.repeat(docs, counts), total - np.repeat(total[head] - step[head] if len(head) else total[:0], counts)


_SPOTS = "texts int, n int, docs binary, counts binary, steps binary"


def _rows(rows: list[dict], kinds: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_pylist(rows, kinds)


_KINDS = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}


def _schema(text: str) -> pa.Schema:
    return pa.schema([(n, _KINDS[k]) for n, k in (x.split() for x in text.split(", "))])


def _chunks(batches: Iterator[pa.RecordBatch], size: int) -> Iterator[tuple]:
    """Texts of about CHUNK bytes: ids, window hashes (two each), text numbers and starts."""
    held, weight = [], 0

    def out():
        ids = np.concatenate([h[0] for h in held])
        shift = np.cumsum([0] + [len(h[0]) for h in held])
        return ids, *(np.concatenate([h[k] for h in held]) for k in (1, 2)), np.concatenate([h[3] + s for h, s in zip(held, shift, strict=False)]), np.concatenate([h[4] for h in held])

    for batch in batches:
        for part in bt.pieces(batch.select(["doc_id", "text", "mark"]), 1, CHUNK // 4):
            t = bt.texts_of(part.column(1))
            start, end, ranges = bt.find_words(t, bt.GRAPHIC)
            word = bt.hash_spans(t.buf, start, end)
            at = bt.window_starts(ranges, size)
            doc = bt.text_of_word(ranges)[at]
            own = np.empty(len(t), TEXT)
            own["id"], own["mark"] = (part.column(k).to_numpy(zero_copy_only=False) for k in (0, 2))
            held.append((own, bt.hash_windows(word, size, 1)[at], bt.hash_windows(word, size, 2)[at], doc.astype(np.int64), at - ranges[doc]))
            weight += len(t.buf)
            if weight >= CHUNK:
                yield out()
                held, weight = [], 0
    if held:
        yield out()


def _first(hashes: np.ndarray, order: np.ndarray, same: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Indices of each hash's first entry, and of the entries that a different, earlier one precedes.

    order: the entries by place; same: whether an entry is at the same place as the one before."""
    h = hashes[order]
    by = np.argsort(h, kind="stable")
    hb = h[by]
    new = np.concatenate(([True], hb[1:] != hb[:-1])) if len(hb) else np.zeros(0, bool)
    place = np.cumsum(~same)[by]  # equal for entries at one place
    lead = np.repeat(np.flatnonzero(new), np.diff(np.append(np.flatnonzero(new), len(hb))))
    return order[by[new]], order[by[place != place[lead]]] if len(hb) else order


def _ship(size: int, cells: int, span: int):
    kinds = _schema("task int, cell int, hashes binary, " + _SPOTS + ", gone_texts int, gone_n int, gone_docs binary, gone_counts binary, gone_steps binary")

    def run(batches):
        for ids, h1, h2, doc, start in _chunks(batches, size):
            if not len(h1):
                continue
            cell = (h2 % np.uint64(cells)).astype(np.int64)
            by_id = _order(ids, np.arange(len(ids)))
            rank = np.empty(len(ids), np.int64)
            rank[by_id] = np.arange(len(ids))
            order = np.argsort(rank[doc], kind="stable")  # starts are in order within a text
            same = np.zeros(len(order), bool)
            if not _changes(ids[by_id]).all():  # repeated rows
                order = _order(ids[doc], start)
                s = start[order]
                same[1:] = ~_changes(ids[doc[order]]) & (s[1:] == s[:-1])
            keep, gone = _first(h1 ^ bt.mix64(h2), order, same)
            position = np.empty(len(order), np.int64)
            position[order] = np.arange(len(order))
            sides = []
            for some in (keep, gone):
                some = some[np.lexsort((position[some], cell[some]))]
                sides.append((some, np.searchsorted(cell[some], np.arange(cells + 1))))
            out, weight = [], 0
            for c in range(cells):
                (k, kb), (g, gb) = sides
                k, g = k[kb[c] : kb[c + 1]], g[gb[c] : gb[c + 1]]
                if len(k):
                    lost = _spots(ids[doc[g]], start[g])
                    out.append({"task": c // span, "cell": c, "hashes": h1[k].tobytes()} | _spots(ids[doc[k]], start[k]) | {f"gone_{n}": v for n, v in lost.items()})
                    weight += 8 * len(k)
                    if weight > 2 << 20:
                        yield _rows(out, kinds)
                        out, weight = [], 0
            if out:
                yield _rows(out, kinds)

    return run


def _judge(homes: int):
    kinds = _schema("home int, " + _SPOTS)

    def cell_rows(held):
        doc, start, h = [], [], []
        lost_doc, lost_start = [], []
        for r in held:
            d, s = _places(r)
            doc.append(d), start.append(s), h.append(np.frombuffer(r["hashes"], np.uint64))
            if r["gone_n"]:
                d, s = _places({k: r[f"gone_{k}"] for k in ("texts", "n", "docs", "counts", "steps")})
                lost_doc.append(d), lost_start.append(s)
        doc, start, h = np.concatenate(doc), np.concatenate(start), np.concatenate(h)
        twice = np.flatnonzero(bt.repeated(h))  # the rest can't have an earlier equal
        doc, start, h = doc[twice], start[twice], h[twice]
        order = _order(doc, start)
        same = np.zeros(len(order), bool)
        same[1:] = ~_changes(doc[order]) & (start[order][1:] == start[order][:-1])
        _, gone = _first(h, order, same)
        d, s = np.concatenate([doc[gone], *lost_doc]), np.concatenate([start[gone], *lost_start])
        home = (bt.mix64(d["id"] ^ d["mark"]) % np.uint64(homes)).astype(np.int64)
        by = _order(d, s)
        by = by[np.argsort(home[by], kind="stable")]
        d, s, home = d[by], s[by], home[by]
        cut = np.searchsorted(home, np.arange(homes + 1))
        return [{"home": i} | _spots(d[cut[i] : cut[i + 1]], s[cut[i] : cut[i + 1]]) for i in range(homes) if cut[i + 1] > cut[i]]

    def run(batches):
        held, at = [], None
        for batch in batches:
            for r in batch.to_pylist():
                if r["cell"] != at and held:
                    yield _rows(cell_rows(held), kinds)
                    held = []
                at = r["cell"]
                held.append(r)
        if held:
            yield _rows(cell_rows(held), kinds)

    return run


def _merge(size: int):
    kinds = pa.schema([("doc_id", pa.int64()), ("mark", pa.int64()), ("spans", pa.binary())])

    def run(batches):
        doc, start = [], []
        for batch in batches:
            for r in batch.to_pylist():
                d, s = _places(r)
                doc.append(d), start.append(s)
        if not doc:
            return
        doc, start = np.concatenate(doc), np.concatenate(start)
        by = _order(doc, start)
        doc, start = doc[by], start[by]
        # a run of windows without a gap between them is one interval
        new = np.concatenate(([True], _changes(doc) | (start[1:] > start[:-1] + size)))
        first = np.flatnonzero(new)
        last = np.append(first[1:], len(doc)) - 1
        spans = np.stack([start[first], start[last] + size], 1).astype(np.int32)
        ids = doc[first]
        head = np.flatnonzero(np.concatenate(([True], _changes(ids))))
        tail = np.append(head[1:], len(ids))
        for at in range(0, len(head), 4096):
            some = range(at, min(at + 4096, len(head)))
            of = ids[head[at : at + 4096]]
            yield pa.RecordBatch.from_arrays([pa.array(of["id"].copy()), pa.array(of["mark"].copy()), pa.array([spans[head[i] : tail[i]].tobytes() for i in some], pa.binary())], schema=kinds)

    return run


def marked(docs: DataFrame) -> DataFrame:
    """doc_id (long), text and mark: a hash of the text where its doc_id has several texts, and else 0."""
    integer_id(docs)
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    mark = F.xxhash64("text")
    clash = settle(plain.where("doc_id is not null").groupBy("doc_id").agg(F.min(mark).alias("a"), F.max(mark).alias("b")).where("a <> b").select("doc_id", F.lit(True).alias("clash")))
    n = clash.count()
    if not n:
        return plain.withColumn("mark", F.lit(0).cast("long"))
    return small_join(plain, clash, "doc_id", "left", n, 17).select("doc_id", "text", F.when(F.col("clash"), mark).otherwise(0).alias("mark"))


def repeated_spans(docs: DataFrame, size: int = 20) -> DataFrame:
    """doc_id, mark and the packed int32 (first, end) word intervals that repeat earlier windows; texts without any are absent. docs: as from `marked`."""
    parts = docs.sparkSession.conf.get("spark.sql.shuffle.partitions")
    need = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    cells = max(1, need // CELL_BYTES)
    tasks = int(min(1 << 16, max(int(parts), 16, cells)))
    span = int(max(1, min(TASK_CELLS, -(-cells // tasks))))
    judged = (
        docs.where("doc_id is not null").select("doc_id", "text", "mark")
        .mapInArrow(_ship(size, tasks * span, span), "task int, cell int, hashes binary, " + _SPOTS + ", gone_texts int, gone_n int, gone_docs binary, gone_counts binary, gone_steps binary")
        .repartitionById(tasks, "task").sortWithinPartitions("cell")
        .mapInArrow(_judge(tasks), "home int, " + _SPOTS)
    )
    return judged.repartitionById(tasks, "home").mapInArrow(_merge(size), "doc_id long, mark long, spans binary")


def _strip(batches):
    kinds = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string()), ("kept_text", pa.string()), ("spans", pa.binary())])
    for batch in batches:
        with_text = "keep_text" in batch.schema.names
        for part in bt.pieces(batch, batch.schema.get_field_index("text"), CHUNK // 4):
            t = bt.texts_of(part.column("text"))
            start, end, ranges = bt.find_words(t, bt.GRAPHIC)
            spans = part.column("spans").to_pylist()
            keep = np.ones(len(start), bool)
            for i, s in enumerate(spans):
                if s:
                    for a, b in np.frombuffer(s, np.int32).reshape(-1, 2):
                        keep[ranges[i] + a : ranges[i] + b] = False
            edge = np.zeros(len(t.buf) + 1, np.int8)
            edge[start[keep]] += 1
            np.subtract.at(edge, end[keep] + 1, 1)
            inside = np.cumsum(edge[:-1], dtype=np.int8).view(bool)
            line = bt.SPACED[t.buf[inside]]
            line[line == 0x0A] = 0x20
            stop = np.concatenate(([0], np.cumsum(inside)))[t.off]
            view = memoryview(line)
            bodies = [view[a : max(a, b - 1)] for a, b in zip(stop[:-1].tolist(), stop[1:].tolist(), strict=True)]
            n, kept = np.diff(ranges), bt.per_text(keep, ranges)
            texts = [str(x, "utf-8") for x in bodies] if with_text else [None] * len(bodies)
            yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), pa.array(n, pa.int64()), pa.array(n - kept, pa.int64()), pa.array([hashlib.sha256(x).hexdigest() for x in bodies]), pa.array(texts, pa.string()), part.column("spans")], schema=kinds)


def dedup_substrings(docs: DataFrame, size: int = 20, with_text: bool = False) -> DataFrame:
    """Each document with its number of words, of removed words, the digest of what is kept (and the kept text) and the removed intervals."""
    texts = marked(docs)
    found = settle(repeated_spans(texts, size))
    stats = found.agg(F.count("*"), F.coalesce(F.avg(F.length("spans")), F.lit(0.0))).first()
    if with_text:
        texts = texts.withColumn("keep_text", F.lit(True))
    both = small_join(texts, found, ["doc_id", "mark"], "left", stats[0], 24 + int(stats[1]))
    return both.mapInArrow(_strip, "doc_id long, n_words long, n_removed long, kept_sha256 string, kept_text string, spans binary")
