"""Quality classifier: logistic regression on hashed word n-grams, trained with
follow-the-regularised-leader updates and scored as sparse dot products.

The n-grams are single words and pairs of neighbours, of two readings of the
text: the words themselves (lower case) and their shapes (runs of letters,
digits and each other sign reduced to one mark); pairs also enter by whether
both words are the same.  A document's vector holds, for
each hashed n-gram, the square root of its share of the document's n-grams, and
a constant.

Training runs once, on a bounded sample of labelled rows (`max_rows`, chosen by a
hash of the id); scoring is a map over the whole table.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hushgrad.llm import words

U = np.uint64


@dataclass(frozen=True)
class Params:
    """max_rows bounds the training sample: the labelled rows used."""

    bits: int = 18
    max_rows: int = 6_000
    epochs: int = 4
    alpha: float = 0.5
    beta: float = 1.0
    l1: float = 1e-4
    l2: float = 1e-4
    threshold: float = 0.3
    seed: int = 11


#: shape classes of bytes: letters by case, digits, bytes of other alphabets, and each sign by itself
SHAPE = np.arange(256, dtype=np.uint8)
SHAPE[97:123] = ord("a")
SHAPE[65:91] = ord("A")
SHAPE[48:58] = ord("0")
SHAPE[128:] = ord("a")


def shape_hashes(s: words.Scan) -> np.ndarray:
    """A hash of each word's shape: its classes with runs of one class taken once."""
    cls = SHAPE[s.buf]
    keep = np.ones(len(cls), dtype=bool)
    keep[1:] = cls[1:] != cls[:-1]
    keep[s.start] = True
    total = np.concatenate([[0], np.cumsum(keep)])
    return words.span_hash(cls[keep], total[s.start], total[s.end], 2)


def grams(s: words.Scan, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(feature, document) of every n-gram of a slice."""
    doc = s.doc
    out_h, out_d = [], []
    for salt, h in enumerate((words.span_hash(words.LOWER[s.buf], s.start, s.end, 0), shape_hashes(s))):
        h = words.mix(h + U(salt + 1))
        out_h.append(h)
        out_d.append(doc)
        if len(h) > 1:
            pair = np.flatnonzero(doc[:-1] == doc[1:])
            out_h.append(words.mix(h[pair] * U(3) + h[pair + 1] + U(salt + 77)))
            out_d.append(doc[pair])
            if salt == 0:  # pairs once more, as "twice the same word" or "two words"
                same = (h[pair] == h[pair + 1]).astype(U)
                out_h.append(words.mix(same + U(991)))
                out_d.append(doc[pair])
    return (np.concatenate(out_h) >> U(64 - bits)).astype(np.int64), np.concatenate(out_d)


def vectors(s: words.Scan, bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sparse rows of a slice: (features, values, where each document's begin)."""
    n = len(s.first) - 1
    f, d = grams(s, bits)
    key = np.sort((d << bits) | f)
    new = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, dtype=np.int64)
    count = np.diff(new, append=len(key))
    key = key[new]
    d = key >> bits
    size = np.bincount(d, count, minlength=n)
    return key & ((1 << bits) - 1), np.sqrt(count / np.maximum(size[d], 1)).astype(np.float32), np.searchsorted(d, np.arange(n + 1))


def _vectors(bits: int):
    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, s in words.scans(words.as_texts(batch.column(1))):
                f, v, first = vectors(s, bits)
                off = pa.py_buffer((first * 4).astype(np.int32))
                packed = [pa.Array.from_buffers(pa.binary(), b - a, [None, off, pa.py_buffer(x.tobytes())]) for x in (f.astype("<i4"), v.astype("<f4"))]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), *packed], ["label", "f", "v"])

    return run


class Model:
    def __init__(self, weights: np.ndarray, bias: float, bits: int) -> None:
        self.weights, self.bias, self.bits = weights, bias, bits

    def score(self, s: words.Scan) -> np.ndarray:
        f, v, first = vectors(s, self.bits)
        dot = np.concatenate([[0.0], np.cumsum(self.weights[f].astype(np.float64) * v)])
        return 1 / (1 + np.exp(-(dot[first[1:]] - dot[first[:-1]] + self.bias)))


def follow_the_leader(rows: list[tuple[np.ndarray, np.ndarray, int]], p: Params) -> Model:
    """Per-coordinate FTRL-proximal over the rows, in a seeded order, some epochs."""
    size = 1 << p.bits
    z, n, w = np.zeros(size + 1), np.zeros(size + 1), np.zeros(size + 1)
    rng = np.random.default_rng(p.seed)
    rows = [(np.append(f, size), np.append(v, np.float32(1.0)), y) for f, v, y in rows]
    for _ in range(p.epochs):
        for i in rng.permutation(len(rows)):
            f, v, y = rows[i]
            zf, nf = z[f], n[f]
            root = np.sqrt(nf)
            wf = np.where(np.abs(zf) <= p.l1, 0.0, -(zf - np.sign(zf) * p.l1) / ((p.beta + root) / p.alpha + p.l2))
            margin = np.clip(float(wf @ v), -35, 35)
            g = (1 / (1 + np.exp(-margin)) - y) * v
            z[f] = zf + g - (np.sqrt(nf + g * g) - root) / p.alpha * wf
            n[f] = nf + g * g
    root = np.sqrt(n)
    w = np.where(np.abs(z) <= p.l1, 0.0, -(z - np.sign(z) * p.l1) / ((p.beta + root) / p.alpha + p.l2))
    return Model(w[:size].astype(np.float32), float(w[size]), p.bits)


def held_out(id_column: Column) -> Column:
    """The rows labels are never learnt from: crc32 of the id as text is 0 modulo 5."""
    return F.crc32(id_column.cast("string").cast("binary")) % 5 == 0


def train(docs: DataFrame, labels: DataFrame, params: Params = Params(), id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> Model:
    """Fit on at most max_rows labelled rows that aren't held out.

    Rows without a label, id or text don't take part; of rows that repeat an id
    in labels one counts.  Without any row the model gives 0.5 for every text.
    """
    p = params
    pool = labels.select(F.col(id_col).alias("_id"), F.col(label_col).cast("int").alias("_y")).filter("_id is not null and _y is not null")
    chosen = pool.filter(~held_out(F.col("_id"))).orderBy(F.xxhash64("_id", F.lit(p.seed)), "_id", "_y").limit(p.max_rows).dropDuplicates(["_id"])
    sample = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_t")).join(F.broadcast(chosen), "_id").filter("_t is not null")
    made = sample.select(F.struct("_id", "_y").alias("label"), "_t")
    made = made.mapInArrow(_vectors(p.bits), "label struct<_id: long, _y: int>, f binary, v binary")
    got = made.toArrow()
    rows = []
    for lab, f, v in zip(*(got.column(c).combine_chunks() for c in ("label", "f", "v")), strict=True):
        x = lab.as_py()
        rows.append((x["_id"], np.frombuffer(f.as_buffer(), dtype="<i4"), np.frombuffer(v.as_buffer(), dtype="<f4"), x["_y"]))
    rows.sort(key=lambda r: (r[0], r[3], r[1].tobytes()))
    return follow_the_leader([r[1:] for r in rows], p)


def _scored(model):  # noqa: ANN001
    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, s in words.scans(words.as_texts(batch.column(1))):
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(model.value.score(s))], ["doc_id", "score"])

    return run


def score(docs: DataFrame, model: Model, params: Params = Params(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, score, predicted.

    A null or empty text gets the constant's score; a null id is not held out;
    repeated rows score alike; an empty table gives no rows.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kind = docs.schema[id_col].dataType.simpleString()
    out = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(_scored(shared), f"doc_id {kind}, score double")
    return out.select(
        "doc_id",
        F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"),
        "score",
        (F.col("score") >= params.threshold).cast("int").alias("predicted"),
    )


def filter_documents(docs: DataFrame, model: Model, params: Params = Params(), text_col: str = "text") -> DataFrame:
    """The rows of docs that the model predicts as good, in the columns of docs."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def of(texts: pd.Series) -> pd.Series:
        column = words.as_texts(pa.array(texts, pa.large_string()))
        return pd.Series(np.concatenate([np.zeros(0), *(shared.value.score(s) for _, _, s in words.scans(column))]))

    return docs.filter(of(F.coalesce(F.col(text_col), F.lit(""))) >= params.threshold)
