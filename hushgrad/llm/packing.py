"""Packing documents into fixed-length sequences by minimum bin slack.

Documents are cut only where they exceed a sequence, into full pieces and a
rest.  Which bins to build depends on the lengths alone, so the plan is made
from their histogram, which has at most `capacity` entries at any table size.
Each bin starts with the longest length left; a subset-sum over the available
lengths, kept as one bitset of reachable sums after each length, finds the
fullest feasible filling of the rest.  The combination found is removed as many
times as the counts allow, so the plan has few distinct combinations.

Every piece then looks up its place by its length and its rank among the pieces
of that length; ranks come from counts of small groups and their prefix sums.
A length has as many groups as its pieces need.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hushgrad.llm import bpe, store, words

CAPACITY = 4096
END = 1
ROWS_PER_GROUP = 20_000
LEAST = -(1 << 63)


def fullest(lengths: list[int], counts: dict[int, int], room: int) -> dict[int, int]:
    """The combination of available lengths with the largest sum up to room, as {length: number}.

    lengths in falling order.  bits holds the reachable sums; a length with
    count c enters as powers of two copies, so each step is a shift and an or.
    """
    mask = (1 << (room + 1)) - 1
    bits = 1
    trail: list[tuple[int, int, int]] = []  # (length, copies, sums reachable before)
    for length in lengths:
        if length > room:
            continue
        left = min(counts[length], room // length)
        copies = 1
        while left > 0:
            take = min(copies, left)
            trail.append((length, take, bits))
            bits |= (bits << (length * take)) & mask
            left -= take
            copies *= 2
        if bits >> room & 1:
            break
    at = bits.bit_length() - 1
    out: dict[int, int] = {}
    for length, take, before in reversed(trail):
        if not before >> at & 1:
            at -= length * take
            out[length] = out.get(length, 0) + take
    return out


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[dict[int, int], int]]:
    """[(combination, times)]: minimum bin slack over a histogram of lengths of at most capacity."""
    counts = {k: v for k, v in histogram.items() if v > 0}
    order = sorted(counts, reverse=True)
    out = []
    while order:
        top = order[0]
        counts[top] -= 1
        found = fullest([x for x in order if counts[x] > 0], counts, capacity - top) if capacity > top else {}
        found[top] = found.get(top, 0) + 1
        counts[top] += 1
        times = min(counts[k] // n for k, n in found.items())
        for k, n in found.items():
            counts[k] -= n * times
        out.append((found, times))
        order = [x for x in order if counts[x] > 0]
    return out


_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def _pieces(spec, style: str, capacity: int, end_id: int):  # noqa: ANN001
    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = bpe.encoder(spec.value, style)
        for batch in batches:
            who = batch.column(0).to_numpy(zero_copy_only=False)
            for a, b, ids, offsets in bpe.encoded(words.as_texts(batch.column(1)), enc):
                full = np.insert(ids, offsets[1:], end_id).astype("<u4")
                off = offsets + np.arange(b - a + 1)
                flat = full.tobytes()
                size = np.diff(off)
                n = -(-size // capacity)
                doc = np.repeat(np.arange(b - a), n)
                piece = np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n)
                begin = piece * capacity
                length = np.minimum(size[doc] - begin, capacity)
                at = off[doc] + begin
                crc = [zlib.crc32(flat[4 * x : 4 * (x + y)]) for x, y in zip(at.tolist(), length.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(who[a:b][doc]), pa.array(piece.astype(np.int32)), pa.array(begin), pa.array(length), pa.array(crc, pa.int64())],
                    ["doc_id", "piece", "start", "length", "ids_crc32"],
                )

    return run


class Layout:
    """For each length, where its pieces go by rank: arrays sorted by (length, first rank)."""

    def __init__(self, combinations: list[tuple[dict[int, int], int]]) -> None:
        used: dict[int, int] = {}
        rows = []
        sequence = 0
        for found, times in combinations:
            offset = 0
            for length in sorted(found, reverse=True):
                n = found[length]
                first = used.get(length, 0)
                rows.append((length, first, n, sequence, offset))
                used[length] = first + n * times
                offset += n * length
            sequence += times
        rows.sort()
        self.sequences = sequence
        self.key = np.array([(r[0] << 48) + r[1] for r in rows], dtype=np.int64)
        self.first, self.n, self.sequence, self.offset = (np.array([r[i] for r in rows], dtype=np.int64) for i in (1, 2, 3, 4))

    def place(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(sequence, offset) of the piece of that length and rank."""
        at = np.searchsorted(self.key, (length << 48) + rank, side="right") - 1
        k = rank - self.first[at]
        return self.sequence[at] + k // self.n[at], self.offset[at] + k % self.n[at] * length


def _placed(layout):  # noqa: ANN001
    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, rank = batch.column(3).to_numpy(), batch.column(5).to_numpy()
            seq, offset = layout.value.place(length, rank) if len(length) else (length, rank)
            yield pa.RecordBatch.from_arrays(
                [*batch.columns[:5], pa.array(seq), pa.array(offset)], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
            )

    return run


def pack(docs: DataFrame, path: str, capacity: int = CAPACITY, end_id: int = END, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset: one row for each piece.

    A null text is empty: one piece with the end id alone.  A null id comes back
    as null; rows that repeat an id are packed each; an empty table gives no rows.
    """
    spark = docs.sparkSession
    spec = bpe.vocabulary_text(path)
    shared = spark.sparkContext.broadcast(spec)
    rows = docs.select(F.coalesce(F.col(id_col).cast("long"), F.expr(f"cast({LEAST} as long)")).alias("doc_id"), F.col(text_col).alias("text"))
    pieces = store.settle(rows.mapInArrow(_pieces(shared, bpe.style_of(spec), capacity, end_id), _PIECES), "pieces")
    # at most `capacity` lengths; each has as many groups as its pieces need
    lengths = store.settle(pieces.groupBy("length").agg(F.count(F.lit(1)).alias("n")), "lengths")
    layout = spark.sparkContext.broadcast(Layout(plan({r["length"]: r["n"] for r in lengths.collect()}, capacity)))
    groups = F.broadcast(lengths.select("length", F.ceil(F.col("n") / ROWS_PER_GROUP).alias("_groups")))
    grouped = pieces.join(groups, "length").withColumn("g", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.col("_groups")).cast("int")).drop("_groups")
    counts = store.settle(grouped.groupBy("length", "g").agg(F.count(F.lit(1)).alias("n")), "length-counts")
    before = counts.select("length", "g", F.expr("coalesce(sum(n) over (partition by length order by g rows between unbounded preceding and 1 preceding), 0L)").alias("_before"))
    ranked = (
        grouped.withColumn("_r", F.expr("row_number() over (partition by length, g order by doc_id, piece, ids_crc32)"))
        .join(before, ["length", "g"])
        .select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("_before") + F.col("_r") - 1).alias("rank"))
    )
    out = ranked.mapInArrow(_placed(layout), _PIECES + ", sequence_id long, offset long")
    return out.withColumn("doc_id", F.when(F.col("doc_id") != F.expr(f"cast({LEAST} as long)"), F.col("doc_id")))
