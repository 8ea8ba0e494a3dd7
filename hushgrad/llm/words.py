r"""White-space words of whole Arrow batches, in vectorised numpy.

A word is a maximal run of bytes outside 0x20 and 0x09-0x0D.  Documents lie
side by side in one byte buffer; everything below works on that buffer at once,
so there is no loop over words or documents.  Work goes in slices of about half
a megabyte (a longer document is one slice), which bounds memory.
"""

from __future__ import annotations

import ctypes
import functools
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

SLICE_BYTES = 1 << 19
U = np.uint64
_BASE = {0: 0x9E3779B97F4A7C15, 1: 0xD6E8FEB86659FD93, 2: 0xA0761D6478BD642F}
_MASK = (1 << 64) - 1
_tables: dict[int, tuple[np.ndarray, np.ndarray]] = {}

SPACE = np.zeros(256, dtype=bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def give_back() -> None:
    """Freed memory back to the system: workers are used again by later tasks, and what one has freed still counts as theirs."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def tidy(f: Callable) -> Callable:
    """A function over batches that gives freed memory back when its task ends."""

    @functools.wraps(f)
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from f(batches)
        give_back()

    return run


def tidy_group(f: Callable) -> Callable:
    """A function of one or two tables (Spark counts its arguments) that gives freed memory back after each group."""

    def one(table: pa.Table) -> pa.Table:
        out = f(table)
        give_back()
        return out

    def two(table: pa.Table, side: pa.Table) -> pa.Table:
        out = f(table, side)
        give_back()
        return out

    return one if f.__code__.co_argcount == 1 else two


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


def powers(n: int, which: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i below n (base is odd)."""
    have = _tables.get(which)
    if have is None or len(have[0]) < n:
        size = max(SLICE_BYTES + 4096, n)
        base = _BASE[which]
        inverse = pow(base, -1, 1 << 64)
        both = []
        for b in (base, inverse):
            p = np.ones(size, dtype=U)
            done = 1
            while done < size:  # doubling: p[done:2*done] = p[:done] * b**done
                step = min(done, size - done)
                p[done : done + step] = p[:step] * U(pow(b, done, 1 << 64))
                done += step
            both.append(p)
        have = _tables[which] = (both[0], both[1])
    return have


def span_hash(values: np.ndarray, starts: np.ndarray, ends: np.ndarray, which: int) -> np.ndarray:
    """64-bit hash of values[s:e] for each span, equal for equal contents wherever they lie."""
    n = len(values)
    up, down = powers(n + 1, which)
    total = np.zeros(n + 1, dtype=U)
    np.cumsum((values.astype(U) + U(1)) * up[:n], out=total[1:])
    h = (total[ends] - total[starts]) * down[starts]
    return mix(h + (ends - starts).astype(U) * U(0x2545F4914F6CDD1D))


@dataclass
class Scan:
    """Words of a slice.  doc, start, end are per word; first[d]:first[d+1] are document d's words."""

    buf: np.ndarray
    offsets: np.ndarray
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray
    space: np.ndarray

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    @property
    def doc(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), self.counts)

    def hashes(self, which: int = 0) -> np.ndarray:
        return span_hash(self.buf, self.start, self.end, which)

    def windows(self, k: int, words: np.ndarray, which: int = 1) -> tuple[np.ndarray, np.ndarray]:
        """(first word, hash) of every run of k words that lies in one document."""
        n = len(words)
        if n < k:
            return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=U)
        doc = self.doc
        at = np.flatnonzero(doc[: n - k + 1] == doc[k - 1 :])
        return at, span_hash(words, at, at + k, which)

    def covered(self, at: np.ndarray, k: int) -> np.ndarray:
        """Which words lie in one of the k-word windows that begin at `at`."""
        step = np.zeros(len(self.start) + 1, dtype=np.int64)
        step[at] += 1  # windows begin at distinct words
        step[at + k] -= 1
        return np.cumsum(step[:-1]) > 0


def scan(buf: np.ndarray, offsets: np.ndarray, lower: bool = False) -> Scan:
    if lower:
        buf = LOWER[buf]
    n = len(buf)
    space = SPACE[buf]
    word = ~space
    begin, stop = word.copy(), np.zeros(n + 1, dtype=bool)
    begin[1:] &= space[:-1]
    stop[1:n] = word[:-1] & space[1:]
    if n:
        stop[n] = word[-1]
        cut = offsets[(offsets > 0) & (offsets < n)]
        begin[cut] = word[cut]
        stop[cut] = word[cut - 1]
    start, end = np.flatnonzero(begin), np.flatnonzero(stop)
    return Scan(buf, offsets, start, end, np.searchsorted(start, offsets), space)


def as_texts(column: pa.Array | pa.ChunkedArray) -> pa.Array:
    """One string array, null as empty, with plain offsets from 0."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    if column.null_count:
        column = column.fill_null("")
    return column


def raw(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string or binary array without nulls."""
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    kind = np.int64 if wide else np.int32
    if len(column) == 0:
        return np.zeros(0, dtype=np.uint8), np.zeros(1, dtype=np.int64)
    _, off, data = column.buffers()
    offsets = np.frombuffer(off, dtype=kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    whole = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, dtype=np.uint8)
    return whole[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(column: pa.Array, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of about `limit` bytes."""
    _, offsets = raw(column)
    at, n = 0, len(column)
    while at < n:
        to = int(np.searchsorted(offsets, offsets[at] + limit, side="right")) - 1
        to = min(max(to, at + 1), n)
        yield at, to
        at = to


def scans(column: pa.Array, lower: bool = False) -> Iterator[tuple[int, int, Scan]]:
    """(from row, to row, Scan) over a text column."""
    for a, b in slices(column):
        buf, offsets = raw(column.slice(a, b - a))
        yield a, b, scan(buf, offsets, lower)


def shingles(s: Scan, k: int, which: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """(hash, document) of k-word shingles; a document of fewer words has its whole sequence as one."""
    words = s.hashes()
    at, h = s.windows(k, words, which)
    doc = s.doc[at]
    short = np.flatnonzero((s.counts > 0) & (s.counts < k))
    if len(short):
        h2 = span_hash(words, s.first[short], s.first[short + 1], which)
        h, doc = np.concatenate([h, h2]), np.concatenate([doc, short])
        order = np.argsort(doc, kind="stable")
        h, doc = h[order], doc[order]
    return h, doc


def distinct_in_docs(h: np.ndarray, doc: np.ndarray, n_docs: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct hashes of each document, and where each document's begin."""
    order = np.lexsort((h, doc))
    h, doc = h[order], doc[order]
    new = np.ones(len(h), dtype=bool)
    new[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
    h, doc = h[new], doc[new]
    return h, np.searchsorted(doc, np.arange(n_docs + 1))


def per_doc_min(values: np.ndarray, first: np.ndarray, empty: int) -> np.ndarray:
    """Minimum of each document's run; `empty` where it has none."""
    out = np.full(len(first) - 1, empty, dtype=values.dtype)
    some = np.flatnonzero(np.diff(first) > 0)
    if len(some):
        out[some] = np.minimum.reduceat(values, first[some])
    return out
