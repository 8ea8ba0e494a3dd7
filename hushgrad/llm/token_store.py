"""Token ids on disk: frequency-ranked, in byte-aligned variable-length coding.

Ids are ranked by how often the corpus uses them, and ranks are written in one
to four little-endian bytes.  The lengths stand apart, two bits each, four to a
control byte, so decoding needs no branch: a table of 256 entries says how many
bytes a control byte stands for and where each of its four values ends.

The container is Parquet, one row for a block of documents in ascending order of
id: range, block, start (ids before the block in its range), the documents' ids
and lengths, control bytes, data bytes.  Files ascend by id as well.  Parquet gives the framing, splitting
and atomic commit on any store Spark can write.  The rank table lies beside it.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hushgrad.llm import bpe, fingerprints, store, words

END = 1
BLOCK_IDS = 200_000
LEAST = -(1 << 63)


def byte_lengths(values: np.ndarray) -> np.ndarray:
    return 1 + (values > 0xFF).astype(np.int64) + (values > 0xFFFF) + (values > 0xFFFFFF)


def coded(values: np.ndarray, off: np.ndarray) -> tuple[pa.Array, pa.Array]:
    """(control bytes, data bytes) of each document; document d's values are values[off[d]:off[d + 1]], unsigned 32 bits.

    A document's last control byte is padded, so documents can follow one another as they are."""
    size = byte_lengths(values)
    count = np.diff(off)
    to = np.concatenate([[0], np.cumsum(-(-count // 4))])
    code = np.zeros(int(to[-1]) * 4, dtype=np.uint8)
    code[np.repeat(to[:-1] * 4 - off[:-1], count) + np.arange(off[-1])] = size - 1
    code = code.reshape(-1, 4)
    control = code[:, 0] | code[:, 1] << 2 | code[:, 2] << 4 | code[:, 3] << 6
    wide = values.astype("<u4").view(np.uint8).reshape(-1, 4)
    data = wide[np.arange(4) < size[:, None]]
    place = np.concatenate([[0], np.cumsum(size)])[off]
    binary = lambda edges, raw: pa.Array.from_buffers(pa.binary(), len(count), [None, pa.py_buffer(edges.astype(np.int32)), pa.py_buffer(raw.astype(np.uint8).tobytes())])
    return binary(to, control), binary(place, data)


#: For each control byte, the lengths of its four values.
LENGTHS = np.stack([(np.arange(256) >> s & 3) + 1 for s in (0, 2, 4, 6)], axis=1)


def decoded(control: bytes, data: bytes, count: np.ndarray) -> np.ndarray:
    """The values of documents of `count` values each, by table lookup of each control byte."""
    length = LENGTHS[np.frombuffer(control, dtype=np.uint8)].reshape(-1)
    slots = -(-count // 4) * 4
    off = np.concatenate([[0], np.cumsum(count)])
    # a document's last control byte is padded
    real = np.repeat(np.cumsum(slots) - slots - off[:-1], count) + np.arange(off[-1])
    length = length[real]
    end = np.cumsum(length)
    begin = end - length
    raw = np.frombuffer(data, dtype=np.uint8)
    out = raw[begin].astype(np.uint32)
    for k in (1, 2, 3):
        more = np.flatnonzero(length > k)
        out[more] |= raw[begin[more] + k].astype(np.uint32) << np.uint32(8 * k)
    return out


def _histogram(spec, style: str, end_id: int):  # noqa: ANN001
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = bpe.encoder(spec.value, style)
        total = np.zeros(enc.vocabulary, dtype=np.int64)
        for batch in batches:
            for a, b, ids, _ in bpe.encoded(words.as_texts(batch.column(0)), enc):
                total += np.bincount(ids, minlength=enc.vocabulary)
                total[end_id] += b - a
        some = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int64)), pa.array(total[some])], ["id", "n"])

    return run


def ranks(texts: DataFrame, spec, style: str, end_id: int) -> DataFrame:  # noqa: ANN001
    """(id, n, rank): ids by falling frequency, ties by id.  At most one row for each vocabulary entry."""
    counts = texts.mapInArrow(_histogram(spec, style, end_id), "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))
    return counts.select("id", "n", (F.expr("row_number() over (order by n desc, id)") - 1).alias("rank"))


def _encode(spec, style: str, end_id: int, rank, bounds: np.ndarray):  # noqa: ANN001
    """(range, doc_id, n_tokens, control, data) of each document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = bpe.encoder(spec.value, style)
        to = rank.value
        for batch in batches:
            column = words.as_texts(batch.column(1))
            who = batch.column(0)
            key = who.fill_null(LEAST).to_numpy(zero_copy_only=False)
            for a, b, ids, offsets in bpe.encoded(column, enc):
                # the end id follows each document's ids
                full = np.insert(to[ids], offsets[1:], to[end_id])
                off = offsets + np.arange(b - a + 1)
                part = np.searchsorted(bounds, key[a:b], side="right") - 1
                yield pa.RecordBatch.from_arrays(
                    [pa.array(part.astype(np.int32)), who.slice(a, b - a), pa.array(np.diff(off)), *coded(full, off)], ["range", "doc_id", "n_tokens", "control", "data"]
                )

    return run


_BLOCK = "range int, block int, start long, n_ids long, n_null int, doc_ids binary, lengths binary, control binary, data binary"


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Documents in order of (range, id); yields blocks.  A document's control bytes are whole, so they just follow each other."""
    at, block, start, n = None, 0, 0, 0
    ids: list[int | None] = []
    size: list[int] = []
    control: list[bytes] = []
    data: list[bytes] = []

    def done() -> pa.RecordBatch:
        known = np.array([LEAST if i is None else i for i in ids], dtype="<i8")
        values = [at, block, start, n, ids.count(None), known.tobytes(), np.array(size, dtype="<u4").tobytes(), b"".join(control), b"".join(data)]
        kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), *[pa.binary()] * 4]
        return pa.RecordBatch.from_arrays(
            [pa.array([v], k) for v, k in zip(values, kinds, strict=True)], ["range", "block", "start", "n_ids", "n_null", "doc_ids", "lengths", "control", "data"]
        )

    for batch in batches:
        for r, doc, m, c, d in zip(*(x.to_pylist() for x in batch.columns), strict=True):
            if ids and (r != at or n >= BLOCK_IDS):
                yield done()
                block, start = (block + 1, start + n) if r == at else (0, 0)
                ids, size, control, data, n = [], [], [], [], 0
            at = r
            ids.append(doc)
            size.append(m)
            control.append(c)
            data.append(d)
            n += m
    if ids:
        yield done()


def write(docs: DataFrame, folder: str, path: str, end_id: int = END, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Encode the texts with the vocabulary at path and write folder/blocks and folder/ranks.

    Two passes over the texts: one counts ids, one encodes.  Ranges of ids in
    rising order are the parts in order of their names, so files, blocks and
    documents all ascend by id.  Null texts are empty (just the end id); null ids
    come first, and a block says how many of its first ids are null; rows that
    repeat an id all stay, next to each other; an empty table writes no blocks.
    """
    spark = docs.sparkSession
    spec = bpe.vocabulary_text(path)
    style = bpe.style_of(spec)
    shared = spark.sparkContext.broadcast(spec)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    ranks(rows.select("text"), shared, style, end_id).coalesce(1).write.parquet(f"{folder}/ranks")
    table = spark.read.parquet(f"{folder}/ranks").toPandas()  # bounded by the vocabulary
    to = np.zeros(int(table["id"].max()) + 1 if len(table) else 1, dtype=np.uint32)
    to[table["id"]] = table["rank"]
    least = F.expr(f"cast({LEAST} as long)")
    bounds = fingerprints.id_bounds(rows.select(F.coalesce("doc_id", least).alias("doc_id")), 3 * store.partitions(docs))
    ids = rows.mapInArrow(_encode(shared, style, end_id, spark.sparkContext.broadcast(to), bounds), "range int, doc_id long, n_tokens long, control binary, data binary")
    # the range is the part's number
    dealt = ids.repartitionById(max(1, len(bounds)), F.col("range")).sortWithinPartitions("doc_id", "n_tokens", "data")
    blocks = dealt.mapInArrow(_blocks, _BLOCK)
    blocks.write.option("compression", "none").parquet(f"{folder}/blocks")


def _decode(table):  # noqa: ANN001
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids_of = table.value
        for batch in batches:
            cols = batch.columns
            for i in range(batch.num_rows):
                r, start, n_null = (cols[k][i].as_py() for k in range(3))
                docs = np.frombuffer(cols[3][i].as_buffer(), dtype="<i8")
                size = np.frombuffer(cols[4][i].as_buffer(), dtype="<u4").astype(np.int64)
                flat = ids_of[decoded(cols[5][i].as_buffer(), cols[6][i].as_buffer(), size)].astype("<u4").tobytes()
                off = np.concatenate([[0], np.cumsum(size)])
                parts = [flat[4 * off[j] : 4 * off[j + 1]] for j in range(len(docs))]
                who = pa.array(docs, mask=np.arange(len(docs)) < n_null)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.full(len(docs), r, dtype=np.int32)), who, pa.array(start + off[:-1]), pa.array(size), pa.array(parts, pa.binary())],
                    ["range", "doc_id", "start", "n_tokens", "ids"],
                )

    return run


def _crc(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        crc = pa.array([zlib.crc32(x.as_buffer()) for x in batch.column(4)], pa.int64())
        yield pa.RecordBatch.from_arrays([*batch.columns[:4], crc], ["range", "doc_id", "start", "n_tokens", "ids_crc32"])


def read(spark: SparkSession, folder: str, digest: bool = False) -> DataFrame:
    """doc_id, start (ids of all documents before it), n_tokens, and ids (or ids_crc32)."""
    table = spark.read.parquet(f"{folder}/ranks").orderBy("rank").toPandas()
    shared = spark.sparkContext.broadcast(table["id"].to_numpy(dtype=np.uint32))
    schema = T._parse_datatype_string(_BLOCK)
    blocks = spark.read.schema(schema).parquet(f"{folder}/blocks")
    # one row for each range; their number is fixed when the files are written
    sizes = blocks.groupBy("range").agg(F.sum("n_ids").alias("n"))
    before = sizes.select("range", F.expr("coalesce(sum(n) over (order by range rows between unbounded preceding and 1 preceding), 0L)").alias("_before"))
    decode = _decode(shared)
    source = blocks.select("range", "start", "n_null", "doc_ids", "lengths", "control", "data")
    if digest:
        rows = source.mapInArrow(lambda b: _crc(decode(b)), "range int, doc_id long, start long, n_tokens long, ids_crc32 long")
    else:
        rows = source.mapInArrow(decode, "range int, doc_id long, start long, n_tokens long, ids binary")
    return rows.join(F.broadcast(before), "range").withColumn("start", F.col("start") + F.col("_before")).drop("range", "_before")
