"""Near-duplicate removal with circulant MinHash.

A document's set is its distinct 5-word shingles.  One permutation scatters
the set over 2**20 places; a second, read from ever another shift, gives all
signature coordinates: coordinate k is the smallest entry of the second
permutation at (place + k).  Bands of the signature propose pairs and the full
sets confirm them.

No pairs of a group are ever listed in full.  Documents with equal sets become
one class first.  In each bucket of a band, one member (the centre) is compared
with all others.  A bucket whose other members are then in one component is done.
The members of the rest are dealt into blocks of bounded size; each pair of
blocks is compared in one task, which only gives the links that join different
components there, fewer than it has members.  So every pair of a bucket is
compared, or its members are connected already: no component is ever split.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hushgrad.llm import store, words

U = np.uint64
PLACE_BITS = 20
PLACES = 1 << PLACE_BITS


@dataclass(frozen=True)
class Params:
    """Sets are linked at `percent` or more.  24 bands of 5 miss a pair at 0.85
    with probability (1 - 0.85**5)**24 < 1e-6.  block: members compared with one
    another in a task."""

    shingle: int = 5
    percent: int = 85
    bands: int = 24
    rows: int = 5
    block: int = 512
    seed: int = 20


_perm: dict[tuple[int, int], np.ndarray] = {}


def second_permutation(seed: int, extra: int) -> np.ndarray:
    """A permutation of the places, wrapped round by `extra` entries."""
    have = _perm.get((seed, extra))
    if have is None:
        p = np.random.default_rng(seed).permutation(PLACES).astype(np.uint32)
        have = _perm[seed, extra] = np.concatenate([p, p[:extra]])
    return have


def first_permutation(h: np.ndarray, seed: int) -> np.ndarray:
    """Scatter 64-bit shingle hashes over the places."""
    return (words.mix(h ^ U(seed * 0x9E3779B97F4A7C15 & (1 << 64) - 1)) >> U(64 - PLACE_BITS)).astype(np.int64)


def signatures(h: np.ndarray, first: np.ndarray, k: int, seed: int) -> np.ndarray:
    """(documents, k) circulant signature; a document without shingles has PLACES everywhere."""
    table = second_permutation(seed, k)
    place = first_permutation(h, seed)
    out = np.empty((len(first) - 1, k), dtype=np.uint32)
    for j in range(k):
        out[:, j] = words.per_doc_min(table[place + j], first, PLACES)
    return out


def set_digest(h: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit sums of mixed hashes: equal for equal sets, whatever the order."""
    both = []
    for salt in (0x51ED270B9F8E5A17, 0x7C0F3A2D94B1E683):
        m = np.concatenate([[U(0)], np.cumsum(words.mix(h ^ U(salt)))])
        both.append(words.mix(m[first[1:]] - m[first[:-1]] + np.diff(first).astype(U)))
    return both[0], both[1]


_SIGNED = "doc_id long, t long, n_shingles long, d1 long, d2 long, bands array<long>"


def circulant(p: Params):
    """The default signer: (set hashes, set starts, coordinates) to a signature matrix."""
    return lambda h, first, k: signatures(h, first, k, p.seed)


def _signed(p: Params, sign):  # noqa: ANN001
    k = p.bands * p.rows

    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, s in words.scans(words.as_texts(batch.column(1)), lower=True):
                n = b - a
                h, first = words.distinct_in_docs(*words.shingles(s, p.shingle), n)
                sig = sign(h, first, k).astype(U)
                band = np.empty((n, p.bands), dtype=U)
                for i in range(p.bands):
                    x = np.full(n, U(i + 1))
                    for j in range(p.rows):
                        x = words.mix(x * U(0x9E3779B97F4A7C15) + sig[:, i * p.rows + j])
                    band[:, i] = x
                d1, d2 = set_digest(h, first)
                some = np.diff(first) > 0
                off = np.concatenate([[0], np.cumsum(np.where(some, p.bands, 0))]).astype(np.int32)
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column(0).slice(a, n),
                        batch.column(2).slice(a, n),
                        pa.array(np.diff(first).astype(np.int64)),
                        pa.array(d1.view(np.int64)),
                        pa.array(d2.view(np.int64)),
                        pa.ListArray.from_arrays(pa.array(off), pa.array(band[some].reshape(-1).view(np.int64))),
                    ],
                    ["doc_id", "t", "n_shingles", "d1", "d2", "bands"],
                )

    return run


def _sets(p: Params):
    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, s in words.scans(words.as_texts(batch.column(1)), lower=True):  # (node, text)
                h, first = words.distinct_in_docs(*words.shingles(s, p.shingle), b - a)
                packed = pa.Array.from_buffers(
                    pa.binary(), b - a, [None, pa.py_buffer((first * 8).astype(np.int32)), pa.py_buffer(h.tobytes())]
                )
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), packed], ["node", "items"])

    return run


def _confirm(percent: int):
    """Columns a, b, set of a, set of b (sorted 64-bit hashes): keeps the pairs that are linked."""

    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            xs, ys = batch.column(2), batch.column(3)
            ok = np.zeros(batch.num_rows, dtype=bool)
            for i in range(batch.num_rows):
                x = np.frombuffer(xs[i].as_buffer(), dtype=U)
                y = np.frombuffer(ys[i].as_buffer(), dtype=U)
                if len(y) < len(x):
                    x, y = y, x
                if len(x) == 0 or 100 * len(x) < percent * len(y):
                    continue
                at = np.minimum(np.searchsorted(y, x), len(y) - 1)
                both = int((y[at] == x).sum())
                ok[i] = 100 * both >= percent * (len(x) + len(y) - both)
            yield batch.select(["a", "b"]).filter(pa.array(ok))

    return run


def _overlaps(sets: list[np.ndarray]) -> np.ndarray:
    """Intersection sizes of all pairs, from a 0/1 matrix of members and shared items, some thousand items at a time."""
    owner = np.repeat(np.arange(len(sets)), [len(x) for x in sets])
    items = np.concatenate(sets)
    order = np.argsort(items, kind="stable")
    items, owner = items[order], owner[order]
    new = np.ones(len(items), dtype=bool)
    new[1:] = items[1:] != items[:-1]
    column = np.cumsum(new) - 1
    shared = np.bincount(column) > 1  # an item of one member alone is in no intersection
    keep = shared[column]
    column, owner = (np.cumsum(shared) - 1)[column[keep]], owner[keep]
    out = np.zeros((len(sets), len(sets)), dtype=np.float32)
    for a in range(0, int(shared.sum()), 4096):
        some = (column >= a) & (column < a + 4096)
        m = np.zeros((len(sets), 4096), dtype=np.float32)
        m[owner[some], column[some] - a] = 1
        out += m @ m.T
    return out.astype(np.int64)


def _compare_blocks(percent: int):
    """Rows (band, i, j, node, c, items) in order of (band, i, j): links that join different components c."""

    def links(reps: list[int], comps: list[int], sets: list[np.ndarray]) -> list[tuple[int, int]]:
        if len(set(comps)) < 2:
            return []
        size = np.array([len(x) for x in sets])
        both = _overlaps(sets)
        a, b = np.nonzero(np.triu(100 * both >= percent * (size[:, None] + size[None, :] - both), 1))
        root = {c: c for c in comps}

        def find(c: int) -> int:
            while root[c] != c:
                root[c] = root[root[c]]
                c = root[c]
            return c

        out = []
        for x, y in zip(a.tolist(), b.tolist(), strict=True):
            p, q = find(comps[x]), find(comps[y])
            if p != q:
                root[max(p, q)] = min(p, q)
                out.append((reps[x], reps[y]))
        return out

    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, reps, comps, sets = None, [], [], []

        def done() -> pa.RecordBatch:
            found = links(reps, comps, sets)
            return pa.RecordBatch.from_arrays([pa.array([x[k] for x in found], pa.int64()) for k in (0, 1)], ["a", "b"])

        for batch in batches:
            cols = [batch.column(k).to_pylist() for k in range(5)]
            for k, key in enumerate(zip(*cols[:3], strict=True)):
                if key != at:
                    if at is not None:
                        yield done()
                    at, reps, comps, sets = key, [], [], []
                reps.append(cols[3][k])
                comps.append(cols[4][k])
                sets.append(np.frombuffer(batch.column(5)[k].as_buffer(), dtype=U).copy())
        if at is not None:
            yield done()

    return run


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("a", "b")), F.bit_xor(F.xxhash64("b", "a", F.lit(1)))).first())


def connected(edges: DataFrame) -> DataFrame:
    """(node, comp): the smallest node of each node's component, for nodes that have an edge.

    Alternates large-star and small-star steps until nothing changes; each step
    shuffles edges only and pre-aggregates minima before the shuffle.
    """
    now = store.settle(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a <> b").distinct(), "edges")
    mark = _mark(now)
    while True:
        both = now.select("a", "b").union(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("n"), F.least("a", "m").alias("m"))
        large = (
            both.join(least, F.col("a") == F.col("n"))
            .filter(F.col("b") > F.col("a"))
            .select(F.col("b").alias("a"), F.col("m").alias("b"))
            .filter("a <> b")
            .distinct()
        )
        large = store.settle(large, "large-star")
        lowest = large.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("n"), "m")
        small = (
            large.join(lowest, F.col("a") == F.col("n"))
            .select(F.explode(F.array(F.struct("a", "m"), F.struct(F.col("b").alias("a"), "m"))).alias("e"))
            .select(F.col("e.a").alias("a"), F.col("e.m").alias("b"))
            .filter("a <> b")
            .distinct()
        )
        small = store.settle(small, "small-star")
        store.drop(now)
        store.drop(large)
        before, mark = mark, _mark(small)
        now = small
        if mark == before:
            return now.select(F.col("a").alias("node"), F.col("b").alias("comp"))


SMALL_LOOKUP = 250_000


def components(docs: DataFrame, params: Params = Params(), id_col: str = "doc_id", text_col: str = "text", signer=None) -> DataFrame:  # noqa: ANN001
    """doc_id, n_shingles, component_id, kept, class_id, text_digest, first.

    class_id is the smallest id of the documents with the same set.  first marks
    the one row that stays of a component: that of the smallest id, and among
    equal ids of the smallest text_digest (rows equal in both are all marked).

    Null or wordless texts have an empty set and are linked with nothing; a null
    id is smaller than all others; rows that repeat an id are documents of their
    own; an empty table gives no rows.
    """
    p = params
    rows = _rows(docs, id_col, text_col)
    signed = store.settle(rows.select("doc_id", "text", "t").mapInArrow(_signed(p, signer or circulant(p)), _SIGNED), "signed")
    filled = signed.filter("n_shingles > 0")
    # one row per set: its smallest document, and a number that stands for it below
    classes = filled.groupBy("d1", "d2").agg(F.min(F.struct("doc_id", "t")).alias("head"))
    classes = store.settle(classes.select("d1", "d2", "head", F.monotonically_increasing_id().alias("node")), "classes")
    heads = (
        filled.join(classes, ["d1", "d2"])
        .filter(F.struct("doc_id", "t").eqNullSafe(F.col("head")))
        .select("node", F.col("n_shingles").alias("n"), "bands")
        .distinct()
        .select("node", "n", F.explode("bands").alias("band"))
    )
    heads = store.settle(heads, "heads")
    crowded = heads.groupBy("band").agg(F.count(F.lit(1)).alias("m")).filter("m > 1").select("band")
    buckets = store.settle(heads.join(crowded, "band"), "buckets")
    store.drop(heads)

    needed = classes.join(buckets.select("node").distinct(), "node").select("node", F.col("head.doc_id").alias("_d"), F.col("head.t").alias("_t"))
    needed = store.settle(needed, "needed")
    # 24 bytes for each: at most SMALL_LOOKUP of them are broadcast, more are joined
    wanted = F.broadcast(needed) if needed.count() <= SMALL_LOOKUP else needed
    texts = rows.join(wanted, F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("t") == F.col("_t"))).select("node", "text")
    sets = store.settle(texts.mapInArrow(_sets(p), "node long, items binary").dropDuplicates(["node"]), "sets")

    # the star of each bucket: its centre, the member of smallest number, against the others
    centre = store.settle(buckets.groupBy("band").agg(F.min(F.struct("node", "n")).alias("z")).select("band", F.col("z.node").alias("b"), F.col("z.n").alias("nb")), "centres")
    pairs = buckets.join(centre, "band").filter("node <> b")
    # sizes alone rule out many pairs exactly
    pairs = pairs.filter(100 * F.least("n", "nb") >= p.percent * F.greatest("n", "nb")).select(F.col("node").alias("a"), "b").distinct()
    pairs = store.settle(pairs, "pairs")
    with_a = pairs.join(sets.select(F.col("node").alias("a"), F.col("items").alias("xa")), "a")
    with_b = with_a.join(sets.select(F.col("node").alias("b"), F.col("items").alias("xb")), "b")
    linked = store.settle(with_b.select("a", "b", "xa", "xb").mapInArrow(_confirm(p.percent), "a long, b long"), "star-links")
    comp = connected(linked)

    # buckets whose other members are in several components go on, in blocks
    rest = buckets.join(centre.select("band", "b"), "band").filter("node <> b").drop("b")
    named_rest = comp.withColumnRenamed("node", "_node")
    rest = rest.join(named_rest, F.col("node") == F.col("_node"), "left").select("band", "node", F.coalesce("comp", "node").alias("c"))
    rest = store.settle(rest, "rest")
    open_ = rest.groupBy("band").agg(F.count(F.lit(1)).alias("m"), F.min("c").alias("lo"), F.max("c").alias("hi")).filter("lo <> hi").select("band", F.ceil(F.col("m") / p.block).cast("int").alias("nb"))
    dealt = rest.join(open_, "band").withColumn("k", F.pmod(F.xxhash64("node"), F.col("nb")).cast("int"))
    dealt = dealt.select("band", "node", "c", "k", F.explode(F.sequence(F.lit(0), F.col("nb") - 1)).alias("o"))
    dealt = dealt.select("band", F.least("k", "o").alias("i"), F.greatest("k", "o").alias("j"), "node", "c")
    full = dealt.join(sets, "node").select("band", "i", "j", "node", "c", "items")
    block_links = (
        full.repartition(store.partitions(docs), "band", "i", "j").sortWithinPartitions("band", "i", "j").mapInArrow(_compare_blocks(p.percent), "a long, b long")
    )
    block_links = store.settle(block_links.distinct(), "block-links")
    if not block_links.isEmpty():
        comp = connected(comp.select(F.col("node").alias("a"), F.col("comp").alias("b")).union(block_links))
    for t in (sets, buckets, pairs, rest):
        store.drop(t)

    # a component's smallest document among its sets' smallest
    with_roots = comp.union(comp.select(F.col("comp").alias("node"), "comp").distinct())
    in_one = classes.join(with_roots, "node")
    least = in_one.groupBy("comp").agg(F.min("head").alias("whole"))
    whole = in_one.join(least, "comp").select("node", "whole")
    named = store.settle(classes.join(whole, "node", "left").select("d1", "d2", "head", F.coalesce("whole", "head").alias("whole")), "named")
    out = signed.select("doc_id", "t", "n_shingles", "d1", "d2").join(named, ["d1", "d2"], "left")
    own = F.struct("doc_id", "t")
    top, head = F.coalesce("whole", own), F.coalesce("head", own)
    return out.select(
        "doc_id",
        "n_shingles",
        top["doc_id"].alias("component_id"),
        F.col("doc_id").eqNullSafe(top["doc_id"]).alias("kept"),
        head["doc_id"].alias("class_id"),
        F.col("t").alias("text_digest"),
        own.eqNullSafe(top).alias("first"),
    )


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("t"))


def deduplicate(docs: DataFrame, params: Params = Params(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without all but the first document of each component, in the columns of docs.

    Of rows equal in id and text, all stay or none; so do wordless texts, which
    are linked with nothing.
    """
    gone = components(docs, params, id_col, text_col).filter("not first").select(F.col("doc_id").alias("_hg_gone"), F.col("text_digest").alias("_hg_digest")).distinct()
    keyed = F.xxhash64(F.coalesce(F.col(text_col), F.lit("")))
    packed = docs.select(F.col(id_col).cast("long").alias("_hg_id"), keyed.alias("_hg_t"), F.struct(*docs.columns).alias("_hg_row"))
    left = packed.join(gone, F.col("_hg_id").eqNullSafe(F.col("_hg_gone")) & (F.col("_hg_t") == F.col("_hg_digest")), "left_anti")
    return left.select(*[F.col("_hg_row").getField(c).alias(c) for c in docs.columns])
