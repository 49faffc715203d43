"""N-gram Jaccard join by MinHash banding, verified on full n-gram sets.

Words are what stands between ASCII white space; a text's set holds its runs of five words
(a text of fewer words is one run). Texts of equal bytes form one node with a copy count. Each node's MinHash
signature is cut into bands; the number of bands and rows is the most selective that reaches the target recall at
the threshold within HASHES hashes. Nodes that agree on a band meet in that band's bucket.

Pairs are never listed. A node also carries two bits of each of its hashes. In a bucket, members whose bits
agree often enough for the threshold (six standard deviations below what a pair at the threshold has) are
near; the bits cost 48 bytes, so no text travels for a bucket. Members near to the bucket's smallest node are tied to it at once.
Only buckets with members far from it are looked at pair by pair, in blocks if they are large. Texts that share a
passage but little else therefore fall apart here, and only components of near nodes go on: a
component's texts meet in one task, or, if it is large, in a grid of tasks of two blocks each, dealt evenly,
so that every pair meets exactly once whatever the component's size. There all pairs' similarities are
computed from the full sets, and only each node's number of links and its smallest linked node leave the task.
Classes are the components of verified links alone.

Edge cases: a null text has no links and is a class of its own. An empty text, or one
without words, is linked only to texts of equal bytes. Repeated rows are copies, and reach a block's task once from each task that reads them.
A class is named by the smallest doc_id in it; rows without a doc_id rank last and carry a null class if there is no other. doc_id is an
integer (a column of another type is refused). Extra columns are ignored.
"""

from __future__ import annotations

import math
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gainbound.llm import bytetext as bt
from gainbound.llm.common import fresh, integer_id, settle, small_join

WORDS = 5
THRESHOLD = 0.8
RECALL = 0.9999
HASHES = 192
PIECE = 1 << 20
#: Most texts and bytes of one block of a component, most members of one block of a bucket.
BLOCK_TEXTS, BLOCK_BYTES, BLOCK_MEMBERS = 384, 16 << 20, 256
#: Standard deviations below the expected agreement at which two nodes count as far, and the columns of the bits (two planes of three words).
SIGMAS = 6
PLANES = ["a0", "a1", "a2", "b0", "b1", "b2"]
_NO_ID = (1 << 63) - 1


def bands_for(threshold: float, recall: float, most: int = HASHES) -> tuple[int, int]:
    """Bands and rows: the most selective rows for which the bands that reach the recall need at most `most` hashes."""
    for rows in range(most, 0, -1):
        agree = threshold**rows
        bands = 1 if agree >= 1 else math.ceil(math.log(1 - recall) / math.log1p(-agree)) if agree > 1e-12 else most + 1
        if bands * rows <= most:
            return bands, rows
    raise ValueError("no banding of so few hashes reaches the recall")


def shingles(t: bt.Texts, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Text number and hash of each run of words, in the texts' order, with repeats."""
    start, end, ranges = bt.find_words(t, bt.GRAPHIC)
    word = bt.hash_spans(t.buf, start, end)
    doc, n = bt.text_of_word(ranges), np.diff(ranges)
    at = bt.window_starts(ranges, size)
    texts, hashes = [doc[at]], [bt.hash_windows(word, size, 4)[at]]
    for length in range(1, size):
        short = np.flatnonzero(n == length)
        if len(short):
            texts.append(short.astype(np.int32))
            hashes.append(bt.hash_windows(word, length, 4 + length)[ranges[short]])
    doc, hashed = np.concatenate(texts), np.concatenate(hashes)
    by = np.argsort(doc, kind="stable")
    return doc[by].astype(np.int64), hashed[by]


def _multipliers(count: int) -> np.ndarray:
    return bt.mix64(np.arange(1, count + 1, dtype=np.uint64) * np.uint64(0xD1B54A32D192ED03)) | np.uint64(1)


def agreement_for(threshold: float, hashes: int) -> int:
    """Fewest hashes of which both bits must agree for two nodes to be near: two bits agree by chance in a quarter of the rest."""
    p = threshold + (1 - threshold) / 4
    return max(0, math.floor(hashes * p - SIGMAS * math.sqrt(hashes * p * (1 - p))))


def _packed(least: np.ndarray) -> np.ndarray:
    """Two bits of each hash, as texts x 6 words: a plane of first bits and a plane of second ones."""
    mixed = bt.mix64(least.ravel()).reshape(least.shape)
    out = np.zeros((len(least), len(PLANES)), np.int64)
    for plane in range(2):
        bits = np.zeros((len(least), 192), np.uint8)
        bits[:, : least.shape[1]] = mixed >> np.uint64(plane) & np.uint64(1)
        out[:, 3 * plane : 3 * plane + 3] = np.packbits(bits, axis=1, bitorder="little").view(np.int64)
    return out


def band_keys(n: int, doc: np.ndarray, hashed: np.ndarray, bands: int, rows: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The texts that have shingles, their band keys (texts x bands) and the bits of their hashes."""
    have, first = np.unique(doc, return_index=True)
    if not len(have):
        return have, np.zeros((0, bands), np.uint64), np.zeros((0, len(PLANES)), np.int64)
    least = np.empty((len(have), bands * rows), np.uint64)
    # by runs of whole texts that fit a cache
    cut = [0]
    while cut[-1] < len(have):
        cut.append(max(cut[-1] + 1, int(np.searchsorted(first, first[cut[-1]] + (1 << 15), "right")) - 1))
    stops = np.append(first, len(hashed))
    for a, b in zip(cut[:-1], cut[1:], strict=True):
        lo, hi = stops[a], stops[b]
        for k, m in enumerate(_multipliers(bands * rows)):
            least[a:b, k] = np.minimum.reduceat(hashed[lo:hi] * m, first[a:b] - lo)
    keys = np.zeros((len(have), bands), np.uint64)
    for r in range(rows):
        keys = bt.mix64(keys.ravel()).reshape(keys.shape) ^ least[:, r::rows]
    return have, bt.mix64((keys + np.arange(1, bands + 1, dtype=np.uint64)).ravel()).reshape(keys.shape), _packed(least)


_PLANES_SQL = ", ".join(f"{c} long" for c in PLANES)


def _sign(bands: int, rows: int, size: int):
    kinds = pa.schema([("node", pa.binary()), ("id", pa.int64()), ("bytes", pa.int64()), ("bands", pa.list_(pa.int64())), *((c, pa.int64()) for c in PLANES)])

    def run(batches):
        for batch in batches:
            for part in bt.pieces(batch, 2, PIECE):
                t = bt.texts_of(part.column(2))
                have, keys, packed = band_keys(len(t), *shingles(t, size), bands, rows)
                count, bits = np.zeros(len(t), np.int32), np.zeros((len(t), len(PLANES)), np.int64)
                count[have] = bands
                bits[have] = packed
                lists = pa.ListArray.from_arrays(np.concatenate(([0], np.cumsum(count))).astype(np.int32), pa.array(keys.ravel().view(np.int64)))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(np.diff(t.off)), lists, *(pa.array(bits[:, k]) for k in range(len(PLANES)))], schema=kinds)

    return run


def _agreeing(left: str, right: str):
    """Hashes of which both bits agree, between the planes of two sides; the unused places always agree."""
    same = [F.bit_count(F.bitwise_not(F.col(f"{left}a{k}").bitwiseXOR(F.col(f"{right}a{k}")).bitwiseOR(F.col(f"{left}b{k}").bitwiseXOR(F.col(f"{right}b{k}"))))) for k in range(3)]
    return same[0] + same[1] + same[2]


def _meet(limit: int):
    """Ties of the pairs of a bucket's block pair of which one member is far from the bucket's smallest: each node to the smallest of its component there."""
    kinds = pa.schema([("node", pa.binary()), ("root", pa.binary())])

    def group(rows: list[tuple]) -> pa.RecordBatch | None:
        far = [r for r in rows if r[3]]
        every = [r for r in rows if r[4]]
        if not far or not every:
            return None
        bits = [np.array([r[5:] for r in side], np.int64) for side in (far, every)]
        x = (bits[0][:, None, :3] ^ bits[1][None, :, :3]) | (bits[0][:, None, 3:] ^ bits[1][None, :, 3:])
        near = np.bitwise_count(~x).sum(2) >= limit
        names = sorted({r[2] for r in far} | {r[2] for r in every})
        number = {v: i for i, v in enumerate(names)}
        a, b = np.nonzero(near)
        a, b = np.array([number[r[2]] for r in far])[a], np.array([number[r[2]] for r in every])[b]
        label = _labels(len(names), a, b)
        moved = np.flatnonzero(label != np.arange(len(names)))
        if not len(moved):
            return None
        return pa.RecordBatch.from_arrays([pa.array([names[k] for k in moved], pa.binary()), pa.array([names[k] for k in label[moved]], pa.binary())], schema=kinds)

    def run(batches):
        held, at = [], None
        for batch in batches:
            for r in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if r[:2] != at:
                    if held and (out := group(held)) is not None:
                        yield out
                    held, at = [], r[:2]
                held.append(r)
        if held and (out := group(held)) is not None:
            yield out

    return run


def _labels(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The smallest member of each of n nodes' component, under the edges (a, b)."""
    label = np.arange(n)
    while True:
        least = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, a, least)
        np.minimum.at(new, b, least)
        new = new[new]
        if (new == label).all():
            return label
        label = new


def _grid(blocks, salt, parts: int):
    """Struct i, j, at for each pair of blocks that a row of block `_block` belongs to; at deals the pairs of one group evenly over the tasks."""
    i, j = F.least("_block", "_k"), F.greatest("_block", "_k")
    pair = i * (2 * blocks - i - 1) / F.lit(2) + j
    return i.cast("int").alias("i"), j.cast("int").alias("j"), F.pmod(F.pmod(F.xxhash64(salt), F.lit(parts)) + pair.cast("long"), F.lit(parts)).cast("int").alias("at")


def ties(nodes: DataFrame, limit: int, parts: int) -> DataFrame:
    """node and root (smaller) whose components join all near nodes that agree on a band. nodes: node, bands, the planes."""
    exploded = nodes.select("node", *PLANES, F.explode("bands").alias("key"))
    # a node with the same band key twice can't be: the band's number is part of it
    keys = settle(nodes.select(F.explode("bands").alias("key")).groupBy("key").agg(F.count("*").alias("n")).where("n > 1"))
    members = settle(small_join(exploded, keys, "key", "inner", keys.count(), 16))
    first = F.min(F.struct("node", *PLANES)).alias("f")
    reps = settle(members.groupBy("key").agg(first).select("key", F.col("f.node").alias("root"), *(F.col(f"f.{c}").alias(f"r_{c}") for c in PLANES)))
    against = small_join(members, reps, "key", "inner", reps.count(), 96).withColumn("near", _agreeing("", "r_") >= limit)
    direct = against.where("near and node <> root").select("node", "root")
    far = settle(against.where("not near").groupBy("key").agg(F.count("*").alias("n_far")))
    n_open = far.count()
    if not n_open:
        return direct
    # blocks grow with the bucket, so that a few large buckets still make many blocks to deal
    split = lambda n: F.ceil(F.col(n) / F.least(F.greatest(2 * F.sqrt(n), F.lit(64)), F.lit(BLOCK_MEMBERS))).cast("int")
    wide = small_join(against.drop("root"), far, "key", "inner", n_open, 16).withColumn("_all", split("n")).withColumn("_far", split("n_far"))
    hashed = F.xxhash64("node")
    # a task has one block of far members and one block of all: a far member goes to all blocks, and every member to all blocks of far ones
    own, spot = F.pmod(hashed, F.col("_all")).cast("int"), F.pmod(hashed, F.col("_far")).cast("int")
    as_far = F.when(~F.col("near"), F.transform(F.sequence(F.lit(0), F.col("_all") - 1), lambda k: F.struct((spot * F.col("_all") + k).alias("cell"), F.lit(True).alias("is_far"), F.lit(False).alias("is_any")))).otherwise(F.array())
    as_any = F.transform(F.sequence(F.lit(0), F.col("_far") - 1), lambda k: F.struct((k * F.col("_all") + own).alias("cell"), F.lit(False).alias("is_far"), F.lit(True).alias("is_any")))
    cells = wide.withColumn("c", F.explode(F.concat(as_far, as_any))).select("key", F.col("c.cell").alias("cell"), "node", F.col("c.is_far").alias("is_far"), F.col("c.is_any").alias("is_any"), *PLANES)
    dealt = cells.withColumn("at", F.pmod(F.pmod(F.xxhash64("key"), F.lit(parts)) + F.col("cell"), F.lit(parts)).cast("int")).repartitionById(parts, "at").drop("at")
    met = dealt.sortWithinPartitions("key", "cell").mapInArrow(_meet(limit), "node binary, root binary")
    return direct.union(met)


def components(edges: DataFrame) -> DataFrame:
    """node and root (the smallest node) for each node of the edges (node, root), root < node: star contraction.

    Each round hangs a node's edges on its roots' smallest roots, then joins a node's roots to the smallest of
    them; rounds grow with the logarithm of the number of nodes. A root with very many
    nodes is never gathered: edges look up their root in a table of one row a node, broadcast if
    small and else joined by a shuffle whose large partitions Spark can split."""
    edges = settle(edges.where("node <> root").distinct())
    state = None
    while True:
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("node", "root").cast("decimal(38,0)"))).first()
        if not now[0]:
            return edges
        if now == state:
            return edges.union(edges.select(F.col("root").alias("node"), "root").distinct())
        state = now
        least = settle(edges.groupBy("node").agg(F.min("root").alias("least")).withColumnRenamed("node", "root"))
        hung = small_join(edges, least, "root", "left", least.count(), 72).select("node", F.coalesce("least", "root").alias("root")).distinct()
        lowest = hung.withColumn("least", F.min("root").over(Window.partitionBy("node")))
        edges = settle(lowest.select("root", "least").union(lowest.select("node", "least")).toDF("node", "root").where("node <> root").distinct())


def _verify(size: int, threshold: float):
    limit = Fraction(str(threshold))
    kinds = pa.schema([("node", pa.binary()), ("text_links", pa.int64()), ("links", pa.int64()), ("root", pa.binary())])

    def group(held: list[dict]) -> pa.RecordBatch:
        n = len(held)
        t = bt.texts_of(pa.array([r["text"] for r in held], pa.string()))
        doc, hashed = shingles(t, size)
        block = np.array([r["block"] for r in held])
        may = block[:, None] != block[None, :] if held[0]["i"] != held[0]["j"] else ~np.eye(n, dtype=bool)
        # distinct shingles of each text, then those that two texts hold
        by = np.lexsort((hashed, doc))
        doc, hashed = doc[by], hashed[by]
        new = np.concatenate(([True], (doc[1:] != doc[:-1]) | (hashed[1:] != hashed[:-1]))) if len(doc) else np.zeros(0, bool)
        doc, hashed = doc[new], hashed[new]
        total = np.bincount(doc, minlength=n)
        _, number, count = np.unique(hashed, return_inverse=True, return_counts=True)
        number = number.reshape(-1)
        shared = count[number] > 1
        doc, number = doc[shared], number[shared]
        order = np.argsort(number, kind="stable")
        doc, number = doc[order], np.unique(number[order], return_inverse=True)[1].reshape(-1)
        common = np.zeros((n, n), np.float64)
        width = 4096
        for at in range(0, int(number[-1]) + 1 if len(number) else 0, width):
            a, b = np.searchsorted(number, (at, at + width))
            held_by = np.zeros((n, width), np.float32)
            held_by[doc[a:b], number[a:b] - at] = 1
            common += held_by @ held_by.T
        union = total[:, None] + total[None, :] - common
        link = may & (union > 0) & (common * limit.denominator >= limit.numerator * union)
        copies = np.array([r["copies"] for r in held])
        label = np.arange(n)
        while True:
            least = np.where(link, label[None, :], n).min(1, initial=n)
            least = np.minimum(label, least)
            least = least[least]
            if (least == label).all():
                break
            label = least
        return pa.RecordBatch.from_arrays([pa.array([r["node"] for r in held], pa.binary()), pa.array(link.sum(1), pa.int64()), pa.array(link @ copies, pa.int64()), pa.array([held[k]["node"] for k in label], pa.binary())], schema=kinds)

    def run(batches):
        held, at = [], None
        for batch in batches:
            for r in batch.to_pylist():
                key = (r["root"], r["i"], r["j"])
                if key != at and held:
                    yield group(held)
                    held = []
                at = key
                if not held or held[-1]["node"] != r["node"]:  # repeated rows
                    held.append(r)
        if held:
            yield group(held)

    return run


def _once(batches):
    """The rows of a task without later ones of a node that it has seen."""
    seen: set[bytes] = set()
    for batch in batches:
        new = []
        for k, node in enumerate(batch.column(0).to_pylist()):
            if node not in seen:
                seen.add(node)
                new.append(k)
        if new:
            yield batch.take(pa.array(new))


def _keyed(docs: DataFrame) -> DataFrame:
    integer_id(docs)
    return docs.select("doc_id", F.coalesce(F.col("doc_id").cast("long"), F.lit(_NO_ID)).alias("id"), F.unhex(F.md5("text")).alias("node"), "text")


def classes(docs: DataFrame, threshold: float = THRESHOLD, size: int = WORDS, recall: float = RECALL) -> DataFrame:
    """node (digest of a text), class_id, leader (the node of the class's smallest doc_id), n_links and n_text_links of each text that has copies or links; settled."""
    bands, rows = bands_for(threshold, recall)
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    keyed = _keyed(docs)
    signed = keyed.where("text is not null").select("node", "id", "text").mapInArrow(_sign(bands, rows, size), "node binary, id long, bytes long, bands array<long>, " + _PLANES_SQL)
    nodes = settle(signed.groupBy("node").agg(F.min("id").alias("id"), F.count("*").alias("copies"), *(F.first(c).alias(c) for c in ("bytes", "bands", *PLANES))))
    near = settle(components(ties(nodes, agreement_for(threshold, bands * rows) + 192 - bands * rows, parts)))

    sizes = near.join(nodes.select("node", "bytes"), "node").groupBy("root").agg(F.count("*").alias("n"), F.sum("bytes").alias("b"))
    # a component of many blocks is cut finer while tasks would else stand idle
    finer = F.least(F.ceil(F.col("n") / 32), F.lit(math.ceil(math.sqrt(6 * parts))))
    cut = F.when((F.col("n") > BLOCK_TEXTS) | (F.col("b") > BLOCK_BYTES), F.greatest(F.ceil(F.col("n") / BLOCK_TEXTS), F.ceil(F.col("b") / BLOCK_BYTES), finer)).otherwise(1)
    sizes = settle(sizes.select("root", cut.cast("int").alias("blocks")))
    # looked up as roots are, since one component can hold a large share of the nodes
    active = settle(small_join(near, sizes, "root", "inner", sizes.count(), 40).join(nodes.select("node", "id", "copies"), "node").withColumn("_block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")))
    n_active = active.count()
    texts = small_join(keyed.select("node", "id", "text"), active, ["node", "id"], "inner", n_active, 72).select("node", "root", "blocks", "_block", "copies", "text")
    texts = texts.mapInArrow(_once, "node binary, root binary, blocks int, _block int, copies long, text string")
    met = texts.withColumn("_k", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select("root", *_grid(F.col("blocks"), "root", parts), F.col("_block").alias("block"), "node", "copies", "text")
    met = met.repartitionById(parts, "at").drop("at").sortWithinPartitions("root", "i", "j", "node")
    found = settle(met.mapInArrow(_verify(size, threshold), "node binary, text_links long, links long, root binary"))

    joined = settle(components(found.select("node", "root")))
    links = found.groupBy("node").agg(F.sum("text_links").alias("text_links"), F.sum("links").alias("links")).where("text_links > 0")
    # what differs from a text that stands alone: copies, or links
    told = nodes.where("copies > 1").select("node", "copies").join(links, "node", "full").join(joined, "node", "left")
    told = told.select("node", F.coalesce("root", "node").alias("class"), (F.coalesce("links", F.lit(0)) + F.coalesce("copies", F.lit(1)) - 1).alias("n_links"), F.coalesce("text_links", F.lit(0)).alias("n_text_links"))
    told = settle(told.join(nodes.select("node", "id"), "node"))
    least = settle(told.groupBy("class").agg(F.min(F.struct("id", "node")).alias("f")).select("class", F.col("f.id").alias("class_id"), F.col("f.node").alias("leader")))
    # a class can hold a large share of the texts: its name is looked up, and never gathered with them
    return settle(small_join(told, least, "class", "inner", least.count(), 72).select("node", "class_id", "leader", "n_links", "n_text_links"))


def similarity_classes(docs: DataFrame, threshold: float = THRESHOLD, size: int = WORDS, recall: float = RECALL) -> DataFrame:
    """doc_id, class_id, n_links (other documents at least that similar, copies included), n_text_links (other texts) of each document."""
    told = classes(docs, threshold, size, recall)
    out = small_join(_keyed(docs).drop("text"), told, "node", "left", told.count(), 72)
    named = F.when(F.col("class_id").isNull(), F.col("id")).otherwise(F.col("class_id"))
    return out.select("doc_id", F.when(named != _NO_ID, named).alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("n_text_links", F.lit(0)).cast("long").alias("n_text_links"))


def one_of_each(docs: DataFrame, threshold: float = THRESHOLD, size: int = WORDS, recall: float = RECALL) -> DataFrame:
    """docs with one row of each class: that of the smallest doc_id, rows without one last; rows with a null text stay.

    Rows are judged by their own text and doc_id, so a row that shares its doc_id with another class's stays or goes by itself."""
    told = classes(docs, threshold, size, recall).select("node", "class_id", "leader")
    integer_id(docs)
    node, leader, named, own = (fresh(docs.columns, c) for c in ("_node", "_leader", "_class", "_id"))
    told = told.toDF(node, named, leader)
    rows = docs.withColumn(node, F.unhex(F.md5("text"))).withColumn(own, F.coalesce(F.col("doc_id").cast("long"), F.lit(_NO_ID)))
    rows = small_join(rows, told, node, "left", told.count(), 56)
    alone = rows.where(F.col(named).isNull())
    leaders = rows.where((F.col(node) == F.col(leader)) & (F.col(own) == F.col(named))).dropDuplicates([node])
    return alone.union(leaders).select(*(F.col(f"`{c}`") for c in docs.columns))
