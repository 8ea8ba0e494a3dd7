r"""Quality rules: per-text counts, and the frequency of lines across documents.

Base rules look at one text.  The corpus rule hashes normalised lines, counts
in how many distinct documents of the same host each occurs, removes the lines
above the limit, and rejects a document of which too little is left.

Exact copies of a text count as one document, so a duplicated page does not
turn its own lines into boilerplate; where asked for, near copies count as one
as well.  The limit is a share of the host's distinct documents (with a floor),
so it means the same at every table size.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hushgrad.llm import near_dedup, store, words

SYMBOLS = np.zeros(256, dtype=bool)
SYMBOLS[[ord(c) for c in "#*$%&|<>"]] = True


@dataclass(frozen=True)
class Rules:
    """min_words, max_repeat_percent: base rules.  A line is above the limit in
    more than max(min_line_docs, line_share * the host's distinct documents)
    documents; a document is depleted when less than min_left of its words stay."""

    min_words: int = 10
    max_repeat_percent: int = 20
    repeat_window: int = 5
    min_line_docs: int = 20
    line_share: float = 0.08
    min_left: float = 0.2


_LINES = pa.list_(pa.struct([("hash", pa.int64()), ("n_words", pa.int64())]))
_SCHEMA = (
    "doc_id long, source string, text_hash long, n_words long, word_chars long, n_symbols long, n_dup_lines long, "
    "n_repeat_words long, lines array<struct<hash: long, n_words: long>>"
)


def _starts_char(buf: np.ndarray) -> np.ndarray:
    return (buf & 0xC0) != 0x80


def _between(flags: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(flags)])
    return total[ends] - total[starts]


def repeated(h: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Which entries share (document, hash) with another."""
    order = np.lexsort((h, doc))
    a, b = h[order], doc[order]
    same = (a[1:] == a[:-1]) & (b[1:] == b[:-1])
    flag = np.zeros(len(h), dtype=bool)
    flag[order[1:]] |= same
    flag[order[:-1]] |= same
    return flag


def later_repeat(h: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Which entries equal an earlier entry of their document (entries are in text order)."""
    order = np.lexsort((np.arange(len(h)), h, doc))
    a, b = h[order], doc[order]
    flag = np.zeros(len(h), dtype=bool)
    flag[order[1:]] = (a[1:] == a[:-1]) & (b[1:] == b[:-1])
    return flag


def line_spans(s: words.Scan) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    r"""Lines (split at \n) that have a word: start byte, end byte, document, first word, end word."""
    breaks = np.flatnonzero(s.buf == 10)
    starts = np.unique(np.concatenate([s.offsets[:-1], breaks + 1]))
    starts = starts[starts < len(s.buf)]
    stops = np.concatenate([starts[1:], [len(s.buf)]]) if len(starts) else starts
    ends = np.where(s.buf[np.maximum(stops - 1, 0)] == 10, stops - 1, stops) if len(starts) else stops
    doc = np.searchsorted(s.offsets, starts, side="right") - 1
    a, b = np.searchsorted(s.start, starts), np.searchsorted(s.start, ends)
    some = b > a
    return starts[some], ends[some], doc[some], a[some], b[some]


def measures(s: words.Scan, window: int) -> dict[str, np.ndarray]:
    """The base measures of every document of a slice, and the normalised line hashes."""
    n = len(s.first) - 1
    char = _starts_char(s.buf)
    hashes = s.hashes()
    at, win = s.windows(window, hashes)
    hit = at[repeated(win, s.doc[at])]
    covered = s.covered(hit, window) if len(hit) else np.zeros(len(s.start), dtype=bool)
    a, b, doc, wa, wb = line_spans(s)
    dup = later_repeat(words.span_hash(s.buf, a, b, 2), doc)
    # a normalised line: its words in lower case, whatever white space parts them
    folded = words.span_hash(words.LOWER[s.buf], s.start, s.end, 0)
    normal = words.span_hash(folded, wa, wb, 2)
    return {
        "n_words": s.counts,
        "word_chars": _between(char & ~s.space, s.offsets[:-1], s.offsets[1:]),
        "n_symbols": _between(SYMBOLS[s.buf], s.offsets[:-1], s.offsets[1:]),
        "n_dup_lines": np.bincount(doc[dup], minlength=n),
        "n_repeat_words": np.bincount(s.doc[covered], minlength=n),
        "line_doc": doc,
        "line_hash": normal,
        "line_words": wb - wa,
    }


def _measured(window: int):
    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            text = words.as_texts(batch.column(2))
            for a, b, s in words.scans(text):
                m = measures(s, window)
                n = b - a
                doc, h, w = m["line_doc"], m["line_hash"], m["line_words"]
                # one entry for each distinct line of a document, with the words of all its occurrences
                order = np.lexsort((h, doc))
                doc, h, w = doc[order], h[order], w[order]
                new = np.flatnonzero(np.concatenate([[True], (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])])) if len(h) else np.zeros(0, dtype=np.int64)
                per = np.add.reduceat(w, new) if len(new) else w
                first = np.searchsorted(doc[new], np.arange(n + 1))
                lines = pa.ListArray.from_arrays(
                    pa.array(first.astype(np.int32)),
                    pa.StructArray.from_arrays([pa.array(h[new].view(np.int64)), pa.array(per.astype(np.int64))], ["hash", "n_words"]),
                )
                cols = [m[k].astype(np.int64) for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")]
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(a, n), batch.column(1).slice(a, n), batch.column(3).slice(a, n), *map(pa.array, cols), lines],
                    ["doc_id", "source", "text_hash", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "lines"],
                )

    return run


def near_units(docs: DataFrame, near: near_dedup.Params, text_col: str = "text") -> DataFrame:
    """(text_hash, unit): the group of near copies of each distinct text."""
    texts = docs.select(F.coalesce(F.col(text_col), F.lit("")).alias("text"), _text_hash(text_col).alias("text_hash"))
    # equal ids are equal texts here, so repeated rows are one member of their group
    found = near_dedup.components(texts, near, "text_hash", "text")
    units = found.select(F.col("doc_id").alias("text_hash"), F.coalesce("component_id", "doc_id").alias("unit"))
    return store.settle(units.filter("text_hash is not null").distinct(), "near-units")


def frequent_lines(measured: DataFrame, rules: Rules, units: DataFrame | None = None) -> DataFrame:
    """(source, hash): lines above the limit of their host.  units: what counts as one document, if not a text."""
    each = measured.select("source", "text_hash", F.explode("lines").alias("l"))
    each = each.select("source", F.col("l.hash").alias("hash"), "text_hash").distinct()
    texts = measured.select("source", "text_hash").distinct()
    if units is not None:
        unit = F.coalesce("unit", "text_hash").alias("text_hash")
        each = each.join(units, "text_hash", "left").select("source", "hash", unit).distinct()
        texts = texts.join(units, "text_hash", "left").select("source", unit).distinct()
    counts = each.groupBy("source", "hash").agg(F.count(F.lit(1)).alias("n_docs")).filter(F.col("n_docs") > rules.min_line_docs)
    hosts = texts.groupBy("source").agg(F.count(F.lit(1)).alias("host_docs"))
    return (
        counts.join(hosts, "source")
        .filter(F.col("n_docs") > rules.line_share * F.col("host_docs"))
        .select("source", "hash", "n_docs")
    )


def evaluate(docs: DataFrame, rules: Rules = Rules(), id_col: str = "doc_id", text_col: str = "text", host_col: str | None = "source", near: near_dedup.Params | None = None) -> tuple[DataFrame, DataFrame]:
    """(verdicts, lines to remove).

    verdicts: doc_id, n_words, word_chars, n_symbols, n_dup_lines,
    n_repeat_words, base_failed, n_line_words_removed, kept, source.
    lines to remove: source, hash, n_docs.

    near: texts that it links count as one document of their host, so a large
    group of near copies doesn't turn the lines it shares into boilerplate.

    A null text is empty and fails the base rule; a null host is a host of its
    own; repeated rows are judged alike (they count as one document of their
    host); an empty table gives none.
    """
    host = F.coalesce(F.col(host_col).cast("string"), F.lit("")) if host_col else F.lit("")
    slim = docs.select(F.col(id_col).alias("doc_id"), host.alias("source"), F.col(text_col).alias("text"), _text_hash(text_col).alias("text_hash"))
    measured = store.settle(slim.mapInArrow(_measured(rules.repeat_window), _SCHEMA), "line-measures")
    units = near_units(slim, near) if near else None
    hot = store.settle(frequent_lines(measured, rules, units), "hot-lines")
    lost = (
        measured.select("doc_id", "text_hash", "source", F.explode("lines").alias("l"))
        .select("doc_id", "text_hash", "source", F.col("l.hash").alias("hash"), F.col("l.n_words").alias("w"))
        .join(hot, ["source", "hash"])
        .groupBy("doc_id", "text_hash", "source")
        .agg(F.sum("w").alias("lost"), F.count(F.lit(1)).alias("hits"), F.countDistinct("hash").alias("lines"))
        # repeated rows of one id and text meet here; each lost the same words
        .select(F.col("doc_id").alias("_id"), F.col("text_hash").alias("_h"), F.col("source").alias("_s"), F.expr("lost * lines div hits").alias("_lost"))
    )
    base = (F.col("n_words") < rules.min_words) | (100 * F.col("n_repeat_words") > rules.max_repeat_percent * F.col("n_words"))
    left = F.col("n_words") - F.col("n_line_words_removed")
    judged = (
        measured.drop("lines")
        .join(lost, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("text_hash") == F.col("_h")) & (F.col("source") == F.col("_s")), "left")
        .withColumn("n_line_words_removed", F.coalesce("_lost", F.lit(0)).cast("long"))
        .withColumn("base_failed", base)
        .withColumn("kept", ~F.col("base_failed") & (left >= rules.min_left * F.col("n_words")))
    )
    return (
        judged.select(
            "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept",
            "n_line_words_removed", "source", "text_hash",
        ),
        hot,
    )


@words.tidy
def _without_lines(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Columns: text, hashes of lines to remove.  Appends the cleaned text."""
    for batch in batches:
        texts = words.as_texts(batch.column(batch.schema.get_field_index("_hg_text"))).to_pylist()
        drops = batch.column(batch.schema.get_field_index("_hg_drop")).to_pylist()
        out = []
        for text, drop in zip(texts, drops, strict=True):
            if drop:
                gone = set(drop)
                lines = text.split("\n")
                col = pa.array(lines)
                _, _, s = next(words.scans(col)) if sum(map(len, lines)) * 4 < words.SLICE_BYTES else (0, 0, words.scan(*words.raw(col)))
                folded = words.span_hash(words.LOWER[s.buf], s.start, s.end, 0)
                h = words.span_hash(folded, s.first[:-1], s.first[1:], 2).view(np.int64)
                keep = [x for x, y, c in zip(lines, h.tolist(), s.counts.tolist(), strict=True) if not (c and y in gone)]
                text = "\n".join(keep)
            out.append(text)
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, pa.string())], [*batch.schema.names, "_hg_clean"])


def filter_documents(docs: DataFrame, rules: Rules = Rules(), id_col: str = "doc_id", text_col: str = "text", host_col: str | None = "source", length_col: str | None = "n_chars", near: near_dedup.Params | None = None) -> DataFrame:
    """The kept documents with the lines above the limit removed, in the columns of docs.

    Only texts that hold such a line change; length_col, where present, follows.
    """
    verdicts, hot = evaluate(docs, rules, id_col, text_col, host_col, near)
    # all columns travel in one struct, so no name of the input can clash
    packed = docs.select(
        F.col(id_col).alias("_hg_id"),
        (F.coalesce(F.col(host_col).cast("string"), F.lit("")) if host_col else F.lit("")).alias("_hg_host"),
        F.coalesce(F.col(text_col), F.lit("")).alias("_hg_text"),
        F.struct(*[F.col(c) for c in docs.columns if c != text_col]).alias("_hg_row"),
    )
    keep = verdicts.filter("kept").select(
        F.col("doc_id").alias("_k"), F.col("source").alias("_ks"), F.col("text_hash").alias("_kh"), (F.col("n_line_words_removed") > 0).alias("_cut")
    ).distinct()
    by_host = hot.groupBy("source").agg(F.collect_list("hash").alias("_hg_drop"))
    chosen = packed.withColumn("_hg_hash", _text_hash("_hg_text")).join(
        keep, F.col("_hg_id").eqNullSafe(F.col("_k")) & (F.col("_hg_host") == F.col("_ks")) & (F.col("_hg_hash") == F.col("_kh"))
    )
    joined = chosen.join(by_host, F.col("_hg_host") == by_host["source"], "left")
    ready = joined.select("_hg_row", "_hg_text", F.when(F.col("_cut"), F.col("_hg_drop")).alias("_hg_drop"))
    schema = T.StructType([*ready.schema.fields, T.StructField("_hg_clean", T.StringType())])
    cleaned = ready.mapInArrow(_without_lines, schema)
    out = []
    for name in docs.columns:
        if name == text_col:
            out.append(F.col("_hg_clean").alias(name))
        elif length_col and name == length_col:
            out.append(F.char_length("_hg_clean").cast(docs.schema[name].dataType).alias(name))
        else:
            out.append(F.col("_hg_row").getField(name).alias(name))
    return cleaned.select(*out)


def _text_hash(name: str) -> Column:
    """What says that two texts are equal: made where the text is read, without Python."""
    return F.xxhash64(F.coalesce(F.col(name), F.lit("")))
