"""MinHash document fingerprints.

A family of universal hash functions (multiply and add modulo 2**64, random odd
multipliers) permutes the distinct 5-word shingles of each text; the minima are
its signature.  Everything is one numpy pass over a slice of documents per
permutation.  A fingerprint writes 16 mixed bits of every minimum as hex; the
likeness of two is the share of equal coordinates.

`near_duplicates` joins bands of the full signature in Spark and verifies the
Jaccard index of the proposed pairs on the full sets.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hushgrad.llm import near_dedup, store, words

U = np.uint64
NONE = (1 << 64) - 1
EXACT = 1 << 53


@dataclass(frozen=True)
class Params:
    permutations: int = 128
    shingle: int = 5
    seed: int = 7


def family(p: Params) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(p.seed)
    a = rng.integers(0, 1 << 63, p.permutations, dtype=U) * U(2) + U(1)
    return a, rng.integers(0, 1 << 63, p.permutations, dtype=U)


def signatures(column: pa.Array, p: Params) -> np.ndarray:
    """(texts, permutations) minima; a text without words has NONE everywhere."""
    a, b = family(p)
    parts = []
    for lo, hi, s in words.scans(column):
        h, doc = words.shingles(s, p.shingle)
        first = np.searchsorted(doc, np.arange(hi - lo + 1))
        out = np.empty((hi - lo, p.permutations), dtype=U)
        for j in range(p.permutations):
            out[:, j] = words.per_doc_min(h * a[j] + b[j], first, NONE)
        parts.append(out)
    return np.concatenate(parts) if parts else np.zeros((0, p.permutations), dtype=U)


def short_code(sig: np.ndarray) -> np.ndarray:
    """16 bits of every minimum."""
    return (words.mix(sig) >> U(48)).astype(">u2")


def likeness(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return (x == y).mean(axis=1)


def _buckets(bounds: np.ndarray):
    """The bucket of an id; the least id of a bucket also goes to the one before, the least of all to the last."""

    @F.pandas_udf("array<int>")
    def of(ids: pd.Series) -> pd.Series:
        v = ids.to_numpy(dtype=np.int64)
        at = np.searchsorted(bounds, v, side="right") - 1
        lead = bounds[np.maximum(at, 0)] == v
        n = len(bounds)
        return pd.Series([[x, ~((x - 1) % n)] if y else [x] for x, y in zip(at.tolist(), lead.tolist(), strict=True)])

    return of


def id_bounds(ids: DataFrame, n: int) -> np.ndarray:
    """Least ids of at most n buckets of about equal size; every bound is an id of the table.

    Quantiles are ids as doubles, which are exact up to 2**53.  Beyond, they only
    part the table, and the least id of each part is its bound.
    """
    name = ids.columns[0]
    low, high = ids.agg(F.min(name), F.max(name)).first()
    if low is None:
        return np.zeros(0, dtype=np.int64)
    cuts = ids.approxQuantile(name, [i / n for i in range(1, n)], 0.2 / n) if n > 1 else []
    bounds = np.unique(np.array([low, *(min(max(int(c), low), high) for c in cuts)], dtype=np.int64))
    if -EXACT <= low and high <= EXACT:
        return bounds

    @F.pandas_udf("int")
    def part(v: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(bounds, v.to_numpy(dtype=np.int64), side="right").astype(np.int32))

    least = ids.groupBy(part(name).alias("part")).agg(F.min(name).alias("least")).collect()
    return np.array(sorted(r["least"] for r in least), dtype=np.int64)


_OUT = "doc_id long, n_chars long, edited_sha256 string, fp binary, edited_fp binary, near_edited double, near_next double"


def _with_next(p: Params):
    """Rows (bucket, lead, doc_id, text) by bucket, lead, id: within a bucket every row's next one follows it."""

    def emit(rows: list[tuple[int, int, int, str]]) -> Iterator[pa.RecordBatch]:
        # the last row only serves as the next of the one before it
        n = len(rows) - 1
        for i in range(n):
            if not rows[i][1] and rows[i][0] != rows[i + 1][0]:
                raise ValueError(f"no next document for {rows[i][2]}")
        texts = [r[3] for r in rows]
        cut = [t[: len(t) - len(t) // 4] + texts[i + 1][: len(t) // 4] for i, t in enumerate(texts[:n])]
        own = short_code(signatures(pa.array(texts, pa.large_string()), p))
        changed = short_code(signatures(pa.array(cut, pa.large_string()), p))
        use = [i for i in range(n) if not rows[i][1]]
        pick = np.array(use, dtype=np.int64)
        yield pa.RecordBatch.from_arrays(
            [
                pa.array([rows[i][2] for i in use], pa.int64()),
                pa.array([len(texts[i]) for i in use], pa.int64()),
                pa.array([hashlib.sha256(cut[i].encode()).hexdigest() for i in use], pa.string()),
                pa.array([own[i].tobytes() for i in use], pa.binary()),
                pa.array([changed[i].tobytes() for i in use], pa.binary()),
                pa.array(likeness(own[pick], changed[pick]) if len(pick) else [], pa.float64()),
                pa.array(likeness(own[pick], own[pick + 1]) if len(pick) else [], pa.float64()),
            ],
            ["doc_id", "n_chars", "edited_sha256", "fp", "edited_fp", "near_edited", "near_next"],
        )

    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[int, int, int, str]] = []
        size = 0
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                held.append(row)
                size += len(row[3])
                if size > words.SLICE_BYTES:
                    yield from emit(held)
                    held, size = held[-1:], len(row[3])
        if held and not held[-1][1]:
            raise ValueError(f"no next document for {held[-1][2]}")
        if len(held) > 1:
            yield from emit(held)

    return run


def fingerprint_with_edit(docs: DataFrame, params: Params = Params(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next.

    The edited text replaces the last quarter of the code points (rounded down)
    by as many first ones of the next document in order of id; the last
    document's next is the first.  Texts cross the network once, into ranges of
    ids; the first document of a range is also sent to the range before.

    Null texts are empty; empty texts are like each other (1) and unlike the
    rest (0); of rows that repeat an id each has the following one as its next; a null id counts as the least long and comes back as null; one
    document is its own next; an empty table gives no rows.
    """
    least = F.expr(f"cast({-(1 << 63)} as long)")
    rows = docs.select(F.coalesce(F.col(id_col).cast("long"), least).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    n = store.partitions(docs)
    bounds = id_bounds(rows.select("doc_id"), 3 * n)
    if not len(bounds):
        bounds = np.zeros(1, dtype=np.int64)
    dealt = (
        rows.withColumn("b", F.explode(_buckets(bounds)(F.col("doc_id"))))
        .select(F.when(F.col("b") < 0, F.bitwise_not("b")).otherwise(F.col("b")).alias("bucket"), (F.col("b") < 0).cast("int").alias("lead"), "doc_id", "text")
        .repartition(n, "bucket")
        .sortWithinPartitions("bucket", "lead", "doc_id", "text")
    )
    made = dealt.mapInArrow(_with_next(params), _OUT)
    return made.select(
        F.when(F.col("doc_id") != least, F.col("doc_id")).alias("doc_id"),
        "n_chars",
        "edited_sha256",
        F.lower(F.hex("fp")).alias("fingerprint"),
        F.lower(F.hex("edited_fp")).alias("edited_fingerprint"),
        "near_edited",
        "near_next",
    )


def near_duplicates(docs: DataFrame, percent: int = 80, params: Params = Params(), bands: int = 32, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Components of texts whose 5-word shingle sets have a Jaccard index of percent/100 or more.

    Words enter in lower case (A-Z).  Bands of the full minima propose pairs,
    joined in Spark, and the full sets verify them; columns and edge cases are those of `near_dedup.components`,
    which also keeps large groups from being paired in full.
    """
    rows = params.permutations // bands
    joined = near_dedup.Params(shingle=params.shingle, percent=percent, bands=bands, rows=rows)
    return near_dedup.components(docs, joined, id_col, text_col, signer=_minima(params))


def _minima(p: Params):
    def sign(h: np.ndarray, first: np.ndarray, k: int) -> np.ndarray:
        a, b = family(p)
        return np.stack([words.per_doc_min(h * a[j] + b[j], first, NONE) for j in range(k)], axis=1)

    return sign
