"""Words, hashes and shingles of whole Arrow columns at once.

Texts are read as one byte buffer. A word is a run of bytes other than the six
ASCII white-space bytes, which for UTF-8 is the same as a run of such characters.
Nulls count as empty texts. Texts are taken in blocks of bounded size, save that
a text which alone is larger makes a block of its own.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_BASE = np.uint64(0x9E3779B97F4A7C15)
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
BLOCK_BYTES = 1 << 18


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambler of 64-bit values (the splitmix finaliser)."""
    x = (x ^ (x >> np.uint64(30))) * _M1
    x = (x ^ (x >> np.uint64(27))) * _M2
    return x ^ (x >> np.uint64(31))


def tidy() -> None:
    """Give freed memory back to the machine: workers live on between tasks."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def unit(x: np.ndarray) -> np.ndarray:
    """Doubles in (0, 1) from 64-bit values."""
    return ((x >> np.uint64(12)).astype(np.float64) + 0.5) * 2.0**-52


@dataclass
class Block:
    """Texts `first` to `last` (exclusive) of a column, as bytes."""

    first: int
    last: int
    data: np.ndarray  # uint8
    bounds: np.ndarray  # int64, one more than texts


@dataclass
class Words:
    start: np.ndarray  # byte offset in the block
    length: np.ndarray
    hash: np.ndarray  # uint64
    doc: np.ndarray  # text number in the block
    first: np.ndarray  # of each text, its first word; one more than texts

    @property
    def count(self) -> np.ndarray:
        return np.diff(self.first)


def _powers(n: int, cache: dict = {}) -> np.ndarray:  # noqa: B006  kept between calls on purpose
    if len(cache.get("p", ())) < n:
        p = np.full(max(n, 256), _BASE, dtype=np.uint64)
        p[0] = 1
        cache["p"] = np.multiply.accumulate(p)
    return cache["p"][:n]


def blocks(column: pa.Array, size: int = BLOCK_BYTES) -> Iterator[Block]:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string()).fill_null("")
    n = len(column)
    if not n:
        return
    bounds = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + n + 1]
    raw = column.buffers()[2]
    data = np.frombuffer(raw, dtype=np.uint8) if raw is not None else np.zeros(0, dtype=np.uint8)
    lo = 0
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(bounds, bounds[lo] + size, side="right")) - 1)
        yield Block(lo, hi, data[bounds[lo] : bounds[hi]], bounds[lo : hi + 1] - bounds[lo])
        lo = hi
    tidy()


def words(block: Block, data: np.ndarray | None = None) -> Words:
    """`data`: other bytes to hash in place of the block's own, position by position."""
    raw = block.data
    n_docs = len(block.bounds) - 1
    inside = ~_SPACE[raw]
    if not inside.any():
        none = np.zeros(0, dtype=np.int64)
        return Words(none, none, none.astype(np.uint64), none, np.zeros(n_docs + 1, dtype=np.int64))
    opens = inside.copy()
    opens[1:] &= ~inside[:-1]
    edge = block.bounds[:-1][np.diff(block.bounds) > 0]
    opens[edge] = inside[edge]
    start = np.flatnonzero(opens)
    number = np.cumsum(opens) - 1
    length = np.bincount(number[inside], minlength=len(start))
    place = np.arange(len(raw)) - start[np.maximum(number, 0)]
    use = np.flatnonzero(inside)
    place = place[use]
    value = (data if data is not None else raw)[use].astype(np.uint64) + np.uint64(1)
    value *= _powers(int(length.max()))[place]
    at = np.concatenate(([0], np.cumsum(length)[:-1]))
    hashed = mix(np.add.reduceat(value, at) + length.astype(np.uint64))
    first = np.searchsorted(start, block.bounds).astype(np.int64)
    return Words(start, length, hashed, np.repeat(np.arange(n_docs), np.diff(first)), first)


def shingles(w: Words, size: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """(hash, text number) of each run of `size` words, in order.

    A text of fewer words, but one at least, has one shingle of all its words.
    """
    n, count = len(w.hash), w.count
    out_hash, out_doc = [], []
    if n >= size:
        total = np.zeros(n - size + 1, dtype=np.uint64)
        for j in range(size):
            total = mix(total + w.hash[j : n - size + 1 + j])
        same = w.doc[: n - size + 1] == w.doc[size - 1 :]
        out_hash.append(total[same])
        out_doc.append(w.doc[: n - size + 1][same])
    short = np.flatnonzero((count > 0) & (count < size))
    if len(short):
        total = np.full(len(short), 77, dtype=np.uint64)
        for j in range(size - 1):
            has = count[short] > j
            total[has] = mix(total[has] + w.hash[w.first[short[has]] + j])
        out_hash.append(total)
        out_doc.append(short)
    if not out_hash:
        return np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)
    hashes, docs = np.concatenate(out_hash), np.concatenate(out_doc)
    order = np.argsort(docs, kind="stable")
    return hashes[order], docs[order]


def counted(hashes: np.ndarray, docs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (hash, text number) with multiplicity, ordered by text and hash."""
    if not len(hashes):
        return hashes, docs, np.zeros(0, dtype=np.int64)
    order = np.lexsort((hashes, docs))
    h, d = hashes[order], docs[order]
    new = np.ones(len(h), dtype=bool)
    new[1:] = (h[1:] != h[:-1]) | (d[1:] != d[:-1])
    at = np.flatnonzero(new)
    return h[at], d[at], np.diff(np.append(at, len(h)))
