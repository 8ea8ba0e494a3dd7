"""Exact removal of repeated 20-word passages, behind a count-min prefilter.

The texts are dealt once into slices of some megabytes, by a hash of the row's
identity; that one shuffle serves every pass, and no pass sends texts again.

Pass 1: every slice sketches its windows (`rows` rows of cells, counts up to
two) and sends the cells it touched to the part of the sketch that owns them.
The parts merge the partial sketches, so a cell's count is never below the true
count, and send each slice one bit for every cell it had sent: counted twice or
more.  Nobody holds the whole sketch, so it grows with the text and neither the
driver, a broadcast nor a worker's memory limits it.
Pass 2: only windows whose cells all say "twice or more" are grouped, exactly,
by a 128-bit hash; the smallest (document, start) of each is its first
occurrence.  Pass 3: a window that passed the sketch and isn't a first
occurrence is a repeat; its words go.

Nothing is lost: a window that occurs twice always passes the sketch.  One that
passes by overestimation is its own first occurrence and stays.

A slice and a part of the sketch exchange one row, so their number is kept where
a row still holds about `part_entries` cells; slices grow from 8 to 64 MB of
text with the table.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hushgrad.llm import store, words

U = np.uint64
LEAST = -(1 << 63)
BYTES_PER_WINDOW = 6.4
MOST_PART_LOG2 = 26
PACKED = 1_000_000


@dataclass(frozen=True)
class Params:
    window: int = 20
    rows: int = 2
    cells_per_window: int = 4
    slice_bytes: int = 8 << 20
    part_entries: int = 2048


@dataclass(frozen=True)
class Shape:
    """Sizes of one job: partitions and slices of the texts, cells in a row of the sketch and in a part of a row, and how parts are written."""

    partitions: int
    slices: int
    cells_log2: int
    part_log2: int
    wide: bool

    @classmethod
    def of(cls, size: int, partitions: int, p: Params) -> Shape:
        """For `size` bytes of text."""
        share = min(8 * p.slice_bytes, int(p.slice_bytes * max(1.0, math.sqrt(size / (1 << 36)))))
        slices = max(3 * partitions, -(-size // share))
        windows = max(1.0, size / BYTES_PER_WINDOW)
        cells_log2 = max(10, int(windows * p.cells_per_window).bit_length())
        full = windows / (slices * p.part_entries)  # parts of a row whose exchanged rows are well filled
        parts_log2 = max(int(math.log2(max(1.0, full))), math.ceil(math.log2(max(1.0, partitions / p.rows))), cells_log2 - MOST_PART_LOG2)
        # where a slice's cells lie far apart, their low two bytes are written plainly, else one
        apart = (1 << cells_log2) * slices / windows
        return cls(partitions, slices, cells_log2, max(8, cells_log2 - parts_log2), apart > 2048)


def cells(h1: np.ndarray, h2: np.ndarray, rows: int, log2: int) -> list[np.ndarray]:
    """The cell of each window in each row."""
    return [((h1 if r == 0 else words.mix(h2 + U(r - 1))) >> U(64 - log2)).astype(np.int64) for r in range(rows)]


def _binary(data: np.ndarray, edges: np.ndarray) -> pa.Array:
    return pa.Array.from_buffers(pa.binary(), len(edges) - 1, [None, pa.py_buffer(edges.astype(np.int32)), pa.py_buffer(np.ascontiguousarray(data).tobytes())])


def _padded(bits: np.ndarray, size: np.ndarray, value: np.ndarray | int = 1) -> pa.Array:
    """Bitmaps of `size` bits, each from a byte on; bits are places counted through all of them."""
    room = -(-size // 8) * 8
    before, to = np.cumsum(size) - size, np.concatenate([[0], np.cumsum(room)])
    owner = np.searchsorted(before, bits, side="right") - 1 if len(bits) else bits
    flat = np.zeros(int(to[-1]), dtype=np.uint8)
    flat[bits - before[owner] + to[:-1][owner]] = value
    return _binary(np.packbits(flat), to // 8)


def compact(values: np.ndarray, counts: np.ndarray, part_log2: int, wide: bool) -> tuple[pa.Array, pa.Array]:
    """Increasing numbers below 2**part_log2 in groups of `counts` numbers, as (low bytes, bitmaps of the high parts).

    The low one or two bytes stand as they are; of the rest, a bitmap has a 1 for
    each number after as many zeros as its high part."""
    low_bits = 16 if wide else 8
    before = np.cumsum(counts) - counts
    low = (values & ((1 << low_bits) - 1)).astype("<u2" if wide else "u1")
    size = counts + ((1 << part_log2) >> low_bits) + 1
    group = np.repeat(np.arange(len(counts)), counts)
    place = (values >> low_bits) + np.arange(len(values)) - before[group] + (np.cumsum(size) - size)[group]
    edges = np.concatenate([[0], np.cumsum(counts)]) * (low_bits // 8)
    return _binary(low, edges), _padded(place, size)


def expand(low: bytes, high: bytes, wide: bool) -> np.ndarray:
    a = np.frombuffer(low, dtype="<u2" if wide else "u1").astype(np.int64)
    ones = np.flatnonzero(np.unpackbits(np.frombuffer(high, dtype=np.uint8)))
    return (ones - np.arange(len(a)) << (16 if wide else 8)) + a


class Windows:
    """The windows of a slice: row of the table, start and two hashes of each, and the scans they were read from."""

    def __init__(self, texts: pa.ChunkedArray, k: int) -> None:
        self.scans: list[tuple[int, words.Scan]] = []
        parts, base = [], 0
        for chunk in texts.chunks:
            for a, _, s in words.scans(words.as_texts(chunk)):
                w = s.hashes()
                at, h1 = s.windows(k, w, 1)
                _, h2 = s.windows(k, w, 2)
                doc = s.doc[at]
                parts.append((doc + base + a, at - s.first[doc], h1, h2))
                self.scans.append((base + a, s))
            base += len(chunk)
        none = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, U), np.zeros(0, U))
        self.row, self.start, self.h1, self.h2 = (np.concatenate([p[i] for p in [none, *parts]]) for i in range(4))


def _touched(c: np.ndarray, shape: Shape) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(distinct cells, which were hit twice, parts, cells in each part)."""
    c = np.sort(c)
    new = np.ones(len(c), dtype=bool)
    new[1:] = c[1:] != c[:-1]
    value = c[new]
    again = np.diff(np.append(np.flatnonzero(new), len(c))) > 1
    part, counts = np.unique(value >> shape.part_log2, return_counts=True)
    return value, again, part, counts


_SKETCH = "slice int, row int, part int, low binary, high binary, twice binary"
_FLAGS = "slice int, row int, part int, data binary"


def _sketch(p: Params, shape: Shape):
    @words.tidy_group
    def run(table: pa.Table) -> pa.Table:
        w = Windows(table.column("text"), p.window)
        slice_ = table.column("slice")[0].as_py()
        out = []
        for r, c in enumerate(cells(w.h1, w.h2, p.rows, shape.cells_log2) if len(w.row) else []):
            value, again, part, counts = _touched(c, shape)
            low, high = compact(value & ((1 << shape.part_log2) - 1), counts, shape.part_log2, shape.wide)
            n = len(part)
            out.append(
                pa.RecordBatch.from_arrays(
                    [pa.array(np.full(n, slice_, np.int32)), pa.array(np.full(n, r, np.int32)), pa.array(part.astype(np.int32)), low, high, _padded(np.flatnonzero(again), counts)],
                    ["slice", "row", "part", "low", "high", "twice"],
                )
            )
        return pa.Table.from_batches(out, _arrow(_SKETCH))

    return run


def _arrow(schema: str) -> pa.Schema:
    kinds = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary(), "string": pa.string()}
    return pa.schema([(n, kinds[k]) for n, k in (x.split() for x in schema.split(", "))])


def _merge(part_log2: int, wide: bool):
    """Partial sketches in order of (row, part), to what each slice hears back: a bit for each cell it sent, in its order."""

    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at: tuple[int, int] | None = None
        held: list[tuple[int, bytes, bytes]] = []
        count = np.zeros(1 << part_log2, dtype=np.uint8)

        def done() -> pa.RecordBatch:
            who, data = [], []
            for slice_, low, high in held:
                v = expand(low, high, wide)
                hot = count[v] > 1
                if hot.any():
                    who.append(slice_)
                    data.append(np.packbits(hot).tobytes())
            n = len(who)
            return pa.RecordBatch.from_arrays(
                [pa.array(who, pa.int32()), pa.array([at[0]] * n, pa.int32()), pa.array([at[1]] * n, pa.int32()), pa.array(data, pa.binary())], ["slice", "row", "part", "data"]
            )

        for batch in batches:
            for slice_, row, part, low, high, twice in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if (row, part) != at:
                    if at is not None:
                        yield done()
                    at = (row, part)
                    held = []
                    count[:] = 0
                v = expand(low, high, wide)
                count[v] = np.minimum(count[v] + 1, 2)
                count[v[np.unpackbits(np.frombuffer(twice, dtype=np.uint8))[: len(v)] == 1]] = 2
                held.append((slice_, low, high))
        if at is not None:
            yield done()

    return run


def _passing(w: Windows, side: pa.Table, p: Params, shape: Shape) -> np.ndarray:
    """Which windows have a cell counted twice or more in every row."""
    ok = np.ones(len(w.row), dtype=bool)
    if not len(ok):
        return ok
    told: dict[tuple[int, int], bytes] = {}
    for r, part, data in zip(*(side.column(c).to_pylist() for c in ("row", "part", "data")), strict=True):
        if r >= 0:
            told[r, part] = data
    for r, c in enumerate(cells(w.h1, w.h2, p.rows, shape.cells_log2)):
        value, _, part, counts = _touched(c, shape)
        hot = np.zeros(len(value), dtype=bool)
        for k, a, n in zip(part.tolist(), (np.cumsum(counts) - counts).tolist(), counts.tolist(), strict=True):
            data = told.get((r, k))
            if data is not None:
                hot[a : a + n] = np.unpackbits(np.frombuffer(data, dtype=np.uint8))[:n] == 1
        hot_cells = value[hot]
        if not len(hot_cells):
            return np.zeros(len(ok), dtype=bool)
        at = np.minimum(np.searchsorted(hot_cells, c), len(hot_cells) - 1)
        ok &= hot_cells[at] == c
    return ok


@dataclass(frozen=True)
class Spots:
    """How a place in the table is written: (id, start) in one long where ids are unique and it fits, else (id, digest, start)."""

    shift: int | None
    low: int

    def schema(self) -> str:
        return "h1 long, h2 long, spot long" if self.shift is not None else "h1 long, h2 long, doc long, g long, start long"


def _identity(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    ids = table.column("doc_id").combine_chunks().fill_null(LEAST).to_numpy(zero_copy_only=False).astype(np.int64)
    return ids, table.column("_g").to_numpy().astype(np.int64)


def _candidates(p: Params, shape: Shape, spots: Spots):
    @words.tidy_group
    def run(table: pa.Table, side: pa.Table) -> pa.Table:
        names = [x.split()[0] for x in spots.schema().split(", ")]
        if not table.num_rows:
            return pa.table({n: pa.array([], pa.int64()) for n in names})
        w = Windows(table.column("text"), p.window)
        ok = _passing(w, side, p, shape)
        row, start, h1, h2 = w.row[ok], w.start[ok], w.h1[ok], w.h2[ok]
        ids, g = _identity(table)
        doc, dig = ids[row], g[row]
        # of equal windows in a slice only the earliest can be a first occurrence
        if spots.shift is not None:
            spot = ((doc - spots.low) << spots.shift) | start
            order = np.lexsort((spot, h2, h1))
            cols = [spot]
        else:
            order = np.lexsort((start, dig, doc, h2, h1))
            cols = [doc, dig, start]
        x, y = h1[order], h2[order]
        new = np.ones(len(order), dtype=bool)
        new[1:] = (x[1:] != x[:-1]) | (y[1:] != y[:-1])
        keep = order[new]
        return pa.table([pa.array(c[keep].view(np.int64)) for c in (h1, h2, *cols)], names=names)

    return run


def _pack_firsts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(slice, numbers of a place...) to rows of _FLAGS with row -1: the places of a slice, in blocks."""
    held: list[np.ndarray] = []
    n = 0

    def flush() -> pa.RecordBatch:
        rows = np.concatenate(held)
        order = np.lexsort(rows.T[::-1])
        rows = rows[order]
        cut = np.flatnonzero(np.diff(rows[:, 0], prepend=rows[0, 0] - 1))
        edges = np.append(cut, len(rows)) * 8 * (rows.shape[1] - 1)
        who = rows[cut, 0].astype(np.int32)
        return pa.RecordBatch.from_arrays(
            [pa.array(who), pa.array(np.full(len(cut), -1, np.int32)), pa.array(np.zeros(len(cut), np.int32)), _binary(rows[:, 1:], edges)], ["slice", "row", "part", "data"]
        )

    for batch in batches:
        if batch.num_rows:
            held.append(np.stack([c.to_numpy(zero_copy_only=False).astype(np.int64) for c in batch.columns], axis=1))
            n += batch.num_rows
            if n >= PACKED:
                yield flush()
                held, n = [], 0
    if n:
        yield flush()


def _firsts(w: Windows, at: np.ndarray, table: pa.Table, side: pa.Table, spots: Spots) -> np.ndarray:
    """Which of the windows `at` are first occurrences."""
    data = b"".join(d for r, d in zip(side.column("row").to_pylist(), side.column("data").to_pylist(), strict=True) if r < 0)
    found = np.frombuffer(data, dtype=np.int64)
    ids, g = _identity(table)
    doc, start = ids[w.row[at]], w.start[at]
    if spots.shift is not None:
        return np.isin(((doc - spots.low) << spots.shift) | start, found)
    found = found.reshape(-1, 3)
    both = np.concatenate([np.stack([doc, g[w.row[at]], start], axis=1), found])
    code = np.unique(both, axis=0, return_inverse=True)[1].reshape(-1)
    return np.isin(code[: len(at)], code[len(at) :])


def _strip(p: Params, shape: Shape, spots: Spots, digest: bool, others: tuple[str, ...]):
    @words.tidy_group
    def run(table: pa.Table, side: pa.Table) -> pa.Table:
        kinds = [("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256" if digest else "kept_text", pa.string())]
        schema = pa.schema([*(pa.field(*k) for k in kinds), *(table.schema.field(c) for c in others)])
        if not table.num_rows:
            return schema.empty_table()
        w = Windows(table.column("text"), p.window)
        at = np.flatnonzero(_passing(w, side, p, shape))
        at = at[~_firsts(w, at, table, side, spots)]
        row, start = w.row[at], w.start[at]
        made = []
        for base, s in w.scans:
            n = len(s.first) - 1
            mine = (row >= base) & (row < base + n)
            begin = s.first[row[mine] - base] + start[mine]
            gone = s.covered(begin, p.window) if len(s.start) else np.zeros(0, dtype=bool)
            removed = np.concatenate([[0], np.cumsum(gone)])[s.first]
            kept = []
            for d in range(n):
                whole = s.buf[s.offsets[d] : s.offsets[d + 1]].tobytes().split()
                if removed[d + 1] > removed[d]:
                    stay = ~gone[s.first[d] : s.first[d + 1]]
                    whole = [x for x, y in zip(whole, stay.tolist(), strict=True) if y]
                text = b" ".join(whole)
                kept.append(hashlib.sha256(text).hexdigest() if digest else text)
            text = pa.array(kept, pa.string()) if digest else pa.array(kept, pa.binary()).cast(pa.string())
            made.append((s.counts.astype(np.int64), np.diff(removed).astype(np.int64), text))
        counts = [pa.array(np.concatenate([m[i] for m in made])) for i in (0, 1)]
        return pa.table([table.column("doc_id"), *counts, pa.chunked_array([m[2] for m in made]), *(table.column(c) for c in others)], schema=schema)

    return run


def _stripped(rows: DataFrame, p: Params, digest: bool, others: tuple[str, ...] = ()) -> DataFrame:
    """rows (doc_id, text, others...) as doc_id, n_words, n_removed, kept text or its digest, and the columns `others`."""
    n = store.partitions(rows)
    size = F.octet_length("text")
    st = rows.agg(F.sum(size), F.max(size), F.min("doc_id"), F.max("doc_id"), F.count(F.lit(1)), F.count_distinct("doc_id")).first()
    shape = Shape.of(st[0] or 0, n, p)
    shift = ((st[1] or 0) // 2 + 1).bit_length()
    plain = st[4] == st[5] and st[4] > 0 and shift + (st[3] - st[2]).bit_length() <= 62
    spots = Spots(shift, st[2]) if plain else Spots(None, 0)

    def slice_of(doc: Column, g: Column) -> Column:
        return F.pmod(F.xxhash64(doc, g), F.lit(shape.slices).cast("long")).cast("int")

    g = F.lit(0).cast("long") if plain else F.xxhash64("text")
    least = F.expr(f"cast({LEAST} as long)")
    tagged = rows.withColumn("_g", g).select(slice_of(F.coalesce("doc_id", least), F.col("_g")).alias("slice"), "doc_id", "_g", "text", *[c for c in rows.columns if c not in ("doc_id", "text")])
    # every pass asks for this exchange with all its columns, so Spark makes it once
    dealt = tagged.repartition(shape.partitions, "slice").groupBy("slice")

    parts = dealt.applyInArrow(_sketch(p, shape), _SKETCH).repartition(shape.partitions, "row", "part").sortWithinPartitions("row", "part")
    flags = parts.mapInArrow(_merge(shape.part_log2, shape.wide), _FLAGS).repartition(shape.partitions, "slice")
    found = dealt.cogroup(flags.groupBy("slice")).applyInArrow(_candidates(p, shape, spots), spots.schema())
    if plain:
        firsts = found.groupBy("h1", "h2").agg(F.min("spot").alias("spot"))
        firsts = firsts.select(slice_of(F.shiftrightunsigned("spot", shift) + F.lit(spots.low), F.lit(0).cast("long")).alias("slice"), "spot")
    else:
        firsts = found.groupBy("h1", "h2").agg(F.min(F.struct("doc", "g", "start")).alias("x"))
        firsts = firsts.select(slice_of(F.col("x.doc"), F.col("x.g")).alias("slice"), "x.doc", "x.g", "x.start")
    side = flags.unionByName(firsts.mapInArrow(_pack_firsts, _FLAGS)).repartition(shape.partitions, "slice")
    extra = [rows.schema[c] for c in others]
    long = [T.StructField(c, T.LongType()) for c in ("doc_id", "n_words", "n_removed")]
    out = T.StructType([*long, T.StructField("kept_sha256" if digest else "kept_text", T.StringType()), *extra])
    return dealt.cogroup(side.groupBy("slice")).applyInArrow(_strip(p, shape, spots, digest, others), out)


def strip_repeats(docs: DataFrame, params: Params = Params(), id_col: str = "doc_id", text_col: str = "text", digest: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed, and kept_text (or kept_sha256 with digest).

    Words of kept_text are joined by one space.  Null texts are empty; texts
    shorter than a window never change; an empty table gives no rows.  A null id
    counts as the least long and comes back as null.  Rows that share an id (or
    have none) are separate documents in order of a digest of their texts; rows
    equal in id and text are one document and stay alike.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return _stripped(rows, params, digest)


def filter_documents(docs: DataFrame, params: Params = Params(), id_col: str = "doc_id", text_col: str = "text", length_col: str | None = "n_chars") -> DataFrame:
    """docs with repeated passages cut from the texts, in the columns of docs.

    Only documents that lose words change (their words are then joined by one
    space); one that loses every word goes.  Rows travel whole, in one shuffle.
    """
    rest = [c for c in docs.columns if c != text_col]
    row = F.struct(*rest, F.col(text_col).isNull().alias("_hg_null")).alias("_hg_row")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"), row)
    out = _stripped(rows, params, False, ("_hg_row", "text")).filter("n_removed = 0 or kept_text <> ''")
    cut = F.col("n_removed") > 0
    made = []
    for name in docs.columns:
        if name == text_col:
            made.append(F.when(cut, F.col("kept_text")).when(~F.col("_hg_row._hg_null"), F.col("text")).alias(name))
            continue
        old = F.col("_hg_row").getField(name)
        if length_col and name == length_col:
            made.append(F.when(cut, F.char_length("kept_text").cast(docs.schema[name].dataType)).otherwise(old).alias(name))
        else:
            made.append(old.alias(name))
    return out.select(*made)
