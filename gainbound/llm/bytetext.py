"""Vectorised text primitives on UTF-8 bytes.

A batch of texts is one byte buffer in which every text is followed by a newline, so
words, lines and windows of all its texts are found by a handful of numpy passes and no
Python object is made per word. Word classes are ASCII classes: every byte of a
multi-byte character belongs to words, which is exact for both word definitions used.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U64 = np.uint64
#: Elements of a pass; tables of powers, which a worker keeps, are twice as long.
_BLOCK = 1 << 16


def _splitmix(x: np.ndarray) -> np.ndarray:
    """The published 64-bit finaliser; a bijection."""
    x = x.astype(U64, copy=True)
    x ^= x >> U64(30)
    x *= U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


mix64 = _splitmix

#: Words of letters and digits: ASCII letters, digits and everything beyond ASCII.
ALNUM = np.zeros(256, bool)
ALNUM[0x30:0x3A] = ALNUM[0x41:0x5B] = ALNUM[0x61:0x7B] = ALNUM[0x80:] = True
#: Words between ASCII white space.
GRAPHIC = np.ones(256, bool)
GRAPHIC[[0x20, *range(0x09, 0x0E)]] = False
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32
SPACED = np.arange(256, dtype=np.uint8)
SPACED[0x09:0x0E] = 0x20


def _base(seed: int) -> int:
    return int(_splitmix(np.array([seed * 2 + 1], U64))[0]) | 5


def _powers(base: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i < n."""
    key = base
    have = _POWERS.get(key)
    if have is None or len(have[0]) < n:
        out = []
        for b in (base, pow(base, -1, 1 << 64)):
            x = np.full(max(n, 2 * _BLOCK), b, U64)
            x[0] = 1
            out.append(np.multiply.accumulate(x))
        have = _POWERS[key] = (out[0], out[1])
    return have


_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}
_BYTE_BASE = _base(11)
_BYTE = _splitmix(np.arange(1, 257, dtype=U64) * U64(0x9E3779B97F4A7C15))


@dataclass
class Texts:
    """Texts as one buffer: text i is buf[off[i] : off[i + 1] - 1], then a newline."""

    buf: np.ndarray
    off: np.ndarray

    def __len__(self) -> int:
        return len(self.off) - 1


def texts_of(column: pa.Array) -> Texts:
    """The column's texts; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column.cast(pa.large_binary()), b"")
    column = pc.binary_join_element_wise(column, pa.scalar(b"", pa.large_binary()), pa.scalar(b"\n", pa.large_binary()))
    off = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    if not len(column):
        return Texts(np.zeros(0, np.uint8), np.zeros(1, np.int64))
    buf = np.frombuffer(column.buffers()[2], np.uint8)[off[0] : off[-1]]
    return Texts(buf, off - off[0])


def tidy() -> None:
    """Hands freed memory back to the system: workers are kept between tasks, and so is what their allocators hold."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def pieces(batch: pa.RecordBatch, text: int, limit: int) -> Iterator[pa.RecordBatch]:
    """The batch in runs of rows whose texts have at most limit bytes; a longer text is alone."""
    size = pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    total = np.cumsum(size)
    row = 0
    while row < len(size):
        done = total[row - 1] if row else 0
        end = max(row + 1, int(np.searchsorted(total, done + limit, "right")))
        yield batch.slice(row, end - row)
        row = end
    tidy()


def find_words(t: Texts, member: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First byte and end byte of each word, and each text's range of words."""
    inside = member[t.buf]
    edge = np.flatnonzero(inside[1:] != inside[:-1]) + 1
    if len(inside) and inside[0]:
        edge = np.concatenate(([0], edge))
    start, end = edge[0::2], edge[1::2]
    return start, end, np.searchsorted(start, t.off)


def hash_spans(buf: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the bytes of each span; the spans are in order and apart."""
    out = np.empty(len(start), U64)
    at = 0
    while at < len(start):
        lo = int(start[at])
        upto = max(at + 1, int(np.searchsorted(end, lo + _BLOCK, "right")))
        s, e = start[at:upto] - lo, end[at:upto] - lo
        n = int(e[-1])
        power, inverse = _powers(_BYTE_BASE, n + 1)
        total = np.zeros(n + 1, U64)
        np.cumsum(_BYTE[buf[lo : lo + n]] * power[:n], out=total[1:])
        out[at:upto] = _splitmix((total[e] - total[s]) * inverse[s] + (e - s).astype(U64) * U64(0x9E3779B97F4A7C15))
        at = upto
    return out


def hash_windows(word: np.ndarray, size: int, seed: int) -> np.ndarray:
    """Rolling polynomial hash of every run of size words, texts disregarded."""
    n = len(word) - size + 1
    if n <= 0:
        return np.zeros(0, U64)
    base = _base(seed)
    power, inverse = _powers(base, _BLOCK + size + 1)
    out = np.empty(n, U64)
    for at in range(0, n, _BLOCK):
        m = min(_BLOCK, n - at)
        total = np.zeros(m + size, U64)
        np.cumsum(word[at : at + m + size - 1] * power[: m + size - 1], out=total[1:])
        out[at : at + m] = _splitmix((total[size:] - total[:m]) * inverse[:m])
    return out


def text_of_word(words: np.ndarray) -> np.ndarray:
    """The text's number for each word, from the texts' ranges of words."""
    return np.repeat(np.arange(len(words) - 1, dtype=np.int32), np.diff(words))


def window_starts(words: np.ndarray, size: int) -> np.ndarray:
    """Numbers of the words at which a window of size words of one text starts."""
    doc = text_of_word(words)
    if len(doc) < size:
        return np.zeros(0, np.int64)
    return np.flatnonzero(doc[: len(doc) - size + 1] == doc[size - 1 :])


def repeated(values: np.ndarray) -> np.ndarray:
    """Which values occur more than once."""
    ordered = np.sort(values)
    return member_of(values, np.unique(ordered[1:][ordered[1:] == ordered[:-1]]))


def member_of(values: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Which 64-bit hashes are among the sorted keys."""
    if not len(keys):
        return np.zeros(len(values), bool)
    bits = max(10, min(24, len(keys).bit_length() + 4))
    seen = np.zeros(1 << bits, bool)
    seen[(keys >> U64(64 - bits)).astype(np.int64)] = True
    out = seen[(values >> U64(64 - bits)).astype(np.int64)]
    maybe = np.flatnonzero(out)
    at = np.minimum(np.searchsorted(keys, values[maybe]), len(keys) - 1)
    out[maybe] = keys[at] == values[maybe]
    return out


def covered(n: int, start: np.ndarray, length) -> np.ndarray:
    """Which of n words lie in one of the runs that begin at start."""
    edge = np.zeros(n + 1, np.int32)
    np.add.at(edge, start, 1)
    np.add.at(edge, start + length, -1)
    return np.cumsum(edge[:-1]) > 0


def per_text(flags: np.ndarray, ranges: np.ndarray) -> np.ndarray:
    """Sum of flags in each text's range."""
    total = np.concatenate(([0], np.cumsum(flags, dtype=np.int64)))
    return total[ranges[1:]] - total[ranges[:-1]]
