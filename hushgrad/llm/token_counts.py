"""Token counts per document without making ids.

Every distinct pre-token of the table gets its number of pieces once, by one
run of the merges.  Documents contribute pre-token frequencies.  Both meet in a
join on the pre-token's hash, and sums per document come out.

Frequencies travel packed: a block of documents sends one row to each bucket of
the hash space, with the block's distinct pre-tokens of that bucket and, for
each, (place in block, count) pairs.  A bucket's piece counts are read first and
its frequency rows stream past them, so a task holds one bucket's counts and one
row.  Blocks are dealt to several copies of a bucket when there are many, so a
pre-token that every document has can't load one task.

Pre-tokens that are vocabulary entries are looked up in the vocabulary's own
table of piece counts and don't travel.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hushgrad.llm import bpe, pretokens, store, words

U = np.uint64
BLOCK = 4 << 20
MAX_DOCS = 60_000
TASKS_PER_COPY = 2048


class Known:
    """Piece counts of the pre-tokens that are vocabulary entries, by hash."""

    def __init__(self, enc: bpe.Encoder) -> None:
        back = {c: i for i, c in enumerate(bpe.byte_names())}
        entries = [(t, bytes(back[c] for c in t)) for t in enc.whole.get_vocab(with_added_tokens=False) if all(c in back for c in t)]
        raw = b"".join(b for _, b in entries)
        end = np.cumsum([len(b) for _, b in entries])
        h = words.span_hash(np.frombuffer(raw, dtype=np.uint8), end - np.array([len(b) for _, b in entries]), end, 0)
        pieces = np.array([len(enc.last.tokenize(t)) for t, _ in entries], dtype=np.int64)
        order = np.argsort(h)
        self.slots = 1 << 20
        self.key = np.zeros(self.slots, dtype=U)
        self.value = np.zeros(self.slots, dtype=np.int64)
        at = (h[order] & U(self.slots - 1)).astype(np.int64)
        # entries that share a slot with another just travel
        self.key[at], self.value[at] = h[order], pieces[order]

    def look(self, h: np.ndarray) -> np.ndarray:
        at = (h & U(self.slots - 1)).astype(np.int64)
        return np.where(self.key[at] == h, self.value[at], 0)


_known: dict[int, Known] = {}


def known(enc: bpe.Encoder) -> Known:
    if id(enc) not in _known:
        _known[id(enc)] = Known(enc)
    return _known[id(enc)]


def _piece_bytes(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> pa.Array:
    """The spans as a binary array."""
    size = end - start
    off = np.concatenate([[0], np.cumsum(size)])
    flat = data[np.repeat(start - off[:-1], size) + np.arange(off[-1])]
    return pa.Array.from_buffers(pa.binary(), len(start), [None, pa.py_buffer(off.astype(np.int32)), pa.py_buffer(flat.tobytes())])


def _unique_spans(h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(an index of each distinct hash, the number of each entry's distinct hash)."""
    order = np.argsort(h)
    s = h[order]
    new = np.ones(len(s), dtype=bool)
    new[1:] = s[1:] != s[:-1]
    group = np.empty(len(h), dtype=np.int64)
    group[order] = np.cumsum(new) - 1
    return order[new], group


def _travelling(texts: list[str], enc: bpe.Encoder, style: str):  # noqa: ANN202
    """Pre-tokens of texts that aren't in the vocabulary: (tokens, their index, hash, document, pieces already counted per text)."""
    shaped = [pretokens.lowered(t) for t in texts] if style == "word" else texts
    t = pretokens.split(shaped, style)
    odd = enc.odd(texts, t.odd)
    h = words.span_hash(t.data, t.start, t.end, 0)
    doc = np.repeat(np.arange(len(texts)), np.diff(t.first))
    pieces = known(enc).look(h)
    pieces[odd[doc]] = 0
    done = np.bincount(doc, pieces, minlength=len(texts)).astype(np.int64)
    for i in np.flatnonzero(odd):
        done[i] = len(enc.whole.encode(texts[i], add_special_tokens=False).ids)
    away = np.flatnonzero((pieces == 0) & ~odd[doc])
    return t, away, h[away], doc[away], done


def _bucket_of(h: np.ndarray, buckets: int) -> np.ndarray:
    return ((h >> U(40)) % U(buckets)).astype(np.int64)


def _distinct(spec, style: str, buckets: int):  # noqa: ANN001
    """(bucket, sizes, bytes): the task's distinct travelling pre-tokens, about once each."""

    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = bpe.encoder(spec.value, style)
        recent = np.zeros(1 << 21, dtype=U)  # what this task has sent, as far as slots go
        for batch in batches:
            column = words.as_texts(batch.column(0))
            for a, b in words.slices(column, BLOCK):
                t, away, h, _, _ = _travelling(column.slice(a, b - a).to_pylist(), enc, style)
                slot = (h & U(len(recent) - 1)).astype(np.int64)
                fresh = np.flatnonzero(recent[slot] != h)
                recent[slot[fresh]] = h[fresh]
                pick, _ = _unique_spans(h[fresh])
                pick = fresh[pick]
                bucket = _bucket_of(h[pick], buckets)
                order = np.argsort(bucket, kind="stable")
                bucket, at = bucket[order], away[pick[order]]
                packed = _piece_bytes(t.data, t.start[at], t.end[at])
                size = (t.end[at] - t.start[at]).astype("<u4")
                flat, off = words.raw(packed)
                edges = np.searchsorted(bucket, np.arange(buckets + 1))
                some = np.flatnonzero(np.diff(edges))
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(some.astype(np.int32)),
                        pa.array([size[edges[i] : edges[i + 1]].tobytes() for i in some], pa.binary()),
                        pa.array([flat[off[edges[i]] : off[edges[i + 1]]].tobytes() for i in some], pa.binary()),
                    ],
                    ["bucket", "sizes", "data"],
                )

    return run


def _count_pieces(spec, style: str):  # noqa: ANN001
    """Rows of _distinct in order of bucket; yields (bucket, hashes, pieces), each pre-token counted once."""

    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = bpe.encoder(spec.value, style)
        at, have = None, np.zeros(0, dtype=U)
        for batch in batches:
            for bucket, sizes, data in zip(*batch.columns, strict=True):
                if bucket.as_py() != at:
                    at, have = bucket.as_py(), np.zeros(0, dtype=U)
                raw = np.frombuffer(data.as_buffer(), dtype=np.uint8)
                end = np.cumsum(np.frombuffer(sizes.as_buffer(), dtype="<u4").astype(np.int64))
                start = np.concatenate([[0], end[:-1]])
                h = words.span_hash(raw, start, end, 0)
                if len(have):
                    spot = np.minimum(np.searchsorted(have, h), len(have) - 1)
                    new = np.flatnonzero(have[spot] != h)
                else:
                    new = np.arange(len(h))
                if not len(new):
                    continue
                first, _ = _unique_spans(h[new])
                new = new[first]
                text = raw.tobytes()
                pieces = [len(enc.last.tokenize(text[a:b].decode("latin-1").translate(enc.name))) for a, b in zip(start[new].tolist(), end[new].tolist(), strict=True)]
                have = np.sort(np.concatenate([have, h[new]]))
                yield pa.RecordBatch.from_arrays(
                    [pa.array([at], pa.int32()), pa.array([h[new].tobytes()], pa.binary()), pa.array([np.array(pieces, dtype="<u4").tobytes()], pa.binary())],
                    ["bucket", "hashes", "pieces"],
                )

    return run


COUNTS, POSTINGS, DOCUMENTS = 0, 1, 2
_ROW = "bucket int, part int, kind int, block long, p1 binary, p2 binary, p3 binary, p4 binary"


def _frequencies(spec, style: str, buckets: int):  # noqa: ANN001
    """For each block of documents: a POSTINGS row for each bucket, and a DOCUMENTS row."""

    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        enc = bpe.encoder(spec.value, style)
        # named by the scan's partition: a task that runs again gives the same rows
        task, serial = TaskContext.get().partitionId(), 0
        for batch in batches:
            column = words.as_texts(batch.column(1))
            _, offsets = words.raw(column)
            ids = batch.column(0).to_numpy(zero_copy_only=False).astype("<i8")
            for a, b in words.slices(column, BLOCK):
                for lo in range(a, b, MAX_DOCS):
                    hi = min(lo + MAX_DOCS, b)
                    n = hi - lo
                    _, _, h, doc, done = _travelling(column.slice(lo, n).to_pylist(), enc, style)
                    pick, group = _unique_spans(h)
                    uniq = h[pick]
                    bucket = _bucket_of(uniq, buckets)
                    order = np.argsort(bucket, kind="stable")
                    rank = np.empty(len(order), dtype=np.int64)
                    rank[order] = np.arange(len(order))
                    uniq, bucket = uniq[order], bucket[order]
                    pair = np.sort(rank[group] * n + doc)
                    at = np.flatnonzero(np.concatenate([[True], pair[1:] != pair[:-1]])) if len(pair) else np.zeros(0, dtype=np.int64)
                    count = np.diff(at, append=len(pair))
                    g, place = pair[at] // n, (pair[at] % n).astype("<u2")
                    # a count above 255 is spread over several pairs
                    over = (count - 1) // 255
                    if over.any():
                        g, place = np.repeat(g, over + 1), np.repeat(place, over + 1)
                        spread = np.full(len(g), 255, dtype=np.int64)
                        spread[np.cumsum(over + 1) - 1] = count - over * 255
                        count = spread
                    pairs = np.bincount(g, minlength=len(uniq))
                    ends = np.concatenate([[0], np.cumsum(pairs)])
                    edges = np.searchsorted(bucket, np.arange(buckets + 1))
                    some = np.flatnonzero(np.diff(edges))
                    count = count.astype(np.uint8)
                    block = (task << 32) | serial
                    serial += 1
                    rows = [
                        [int(i) for i in some] + [block % buckets],
                        [POSTINGS] * len(some) + [DOCUMENTS],
                        [uniq[edges[i] : edges[i + 1]].tobytes() for i in some] + [ids[lo:hi].tobytes()],
                        [pairs[edges[i] : edges[i + 1]].astype("<u4").tobytes() for i in some] + [np.diff(offsets[lo : hi + 1]).astype("<i8").tobytes()],
                        [place[ends[edges[i]] : ends[edges[i + 1]]].tobytes() for i in some] + [done.astype("<i8").tobytes()],
                        [count[ends[edges[i]] : ends[edges[i + 1]]].tobytes() for i in some] + [b""],
                    ]
                    m = len(some) + 1
                    yield pa.RecordBatch.from_arrays(
                        [
                            pa.array(rows[0], pa.int32()),
                            pa.array(np.full(m, task // TASKS_PER_COPY, dtype=np.int32)),
                            pa.array(rows[1], pa.int32()),
                            pa.array(np.full(m, block)),
                            *(pa.array(r, pa.binary()) for r in rows[2:]),
                        ],
                        ["bucket", "part", "kind", "block", "p1", "p2", "p3", "p4"],
                    )

    return run


@words.tidy
def _joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows in order of (bucket, part, kind): a bucket's counts, then what is to be looked up in them."""
    at, keys, values, ready = None, [], [], False
    key = value = np.zeros(0)
    for batch in batches:
        cols = batch.columns
        head = zip(cols[0].to_pylist(), cols[1].to_pylist(), cols[2].to_pylist(), cols[3].to_pylist(), strict=True)
        for i, (bucket, part, kind, block) in enumerate(head):
            if (bucket, part) != at:
                at, keys, values, ready = (bucket, part), [], [], False
            p = [cols[c][i].as_buffer() for c in (4, 5, 6, 7)]
            if kind == COUNTS:
                keys.append(np.frombuffer(p[0], dtype=U))
                values.append(np.frombuffer(p[1], dtype="<u4"))
                continue
            if kind == POSTINGS:
                if not ready:
                    key, value = np.concatenate(keys), np.concatenate(values)
                    order = np.argsort(key)
                    key, value, ready = key[order], value[order].astype(np.int64), True
                h = np.frombuffer(p[0], dtype=U)
                spot = np.minimum(np.searchsorted(key, h), len(key) - 1)
                if (key[spot] != h).any():
                    raise ValueError("a pre-token has no piece count")
                per = np.repeat(value[spot], np.frombuffer(p[1], dtype="<u4"))
                sums = np.bincount(np.frombuffer(p[2], dtype="<u2"), per * np.frombuffer(p[3], dtype=np.uint8))
                p = [sums.astype("<u4").tobytes(), b"", b""]
            yield pa.RecordBatch.from_arrays(
                [pa.array([-kind], pa.int32()), pa.array([block], pa.int64()), *(pa.array([bytes(x)], pa.binary()) for x in p[:3])],
                ["kind", "block", "p1", "p2", "p3"],
            )


@words.tidy
def _summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows in order of (block, kind): a block's documents, then its partial sums."""
    at, ids, size, total = None, None, None, None

    def done() -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(ids), pa.array(size), pa.array(total)], ["doc_id", "n_bytes", "n_tokens"])

    for batch in batches:
        cols = batch.columns
        for i, (kind, block) in enumerate(zip(cols[0].to_pylist(), cols[1].to_pylist(), strict=True)):
            p = [cols[c][i].as_buffer() for c in (2, 3, 4)]
            if kind == -DOCUMENTS:
                if at is not None:
                    yield done()
                at, ids, size = block, *(np.frombuffer(x, dtype="<i8") for x in p[:2])
                total = np.frombuffer(p[2], dtype="<i8").copy()
            else:
                s = np.frombuffer(p[0], dtype="<u4")
                total[: len(s)] += s
    if at is not None:
        yield done()


LEAST = -(1 << 63)


def count_tokens(docs: DataFrame, path: str, limit: int = 512, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit (more than `limit` tokens), as the tokenizers library counts.

    Null texts are empty (0 bytes, 0 tokens); a null id comes back as null; rows
    that repeat an id are each counted; an empty table gives no rows.
    """
    spark = docs.sparkSession
    spec = bpe.vocabulary_text(path)
    style = bpe.style_of(spec)
    shared = spark.sparkContext.broadcast(spec)
    n = store.partitions(docs)
    rows = docs.select(F.coalesce(F.col(id_col).cast("long"), F.expr(f"cast({LEAST} as long)")).alias("doc_id"), F.col(text_col).alias("text"))
    counts = (
        rows.select("text")
        .mapInArrow(_distinct(shared, style, n), "bucket int, sizes binary, data binary")
        .repartition(n, "bucket")
        .sortWithinPartitions("bucket")
        .mapInArrow(_count_pieces(shared, style), "bucket int, hashes binary, pieces binary")
    )
    copies = rows.rdd.getNumPartitions() // TASKS_PER_COPY + 1
    empty = F.lit(b"")
    counts = counts.select(
        "bucket", F.explode(F.array(*[F.lit(i) for i in range(copies)])).alias("part"), F.lit(COUNTS).alias("kind"), F.lit(0).cast("long").alias("block"),
        F.col("hashes").alias("p1"), F.col("pieces").alias("p2"), empty.alias("p3"), empty.alias("p4"),
    )
    frequencies = rows.mapInArrow(_frequencies(shared, style, n), _ROW)
    partial = (
        counts.unionByName(frequencies)
        .repartition(n, "bucket", "part")
        .sortWithinPartitions("bucket", "part", "kind", "block")
        .mapInArrow(_joined, "kind int, block long, p1 binary, p2 binary, p3 binary")
    )
    total = partial.repartition(n, "block").sortWithinPartitions("block", "kind").mapInArrow(_summed, "doc_id long, n_bytes long, n_tokens long")
    return total.select(
        F.when(F.col("doc_id") != F.expr(f"cast({LEAST} as long)"), F.col("doc_id")).alias("doc_id"),
        "n_bytes",
        "n_tokens",
        (F.col("n_tokens") > F.lit(limit)).alias("over_limit"),
    )
