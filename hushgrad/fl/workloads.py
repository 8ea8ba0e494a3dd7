"""Training data from the given tables, in the form the training loop reads.

samples: client_id, seq (0.. within a client), features, label, part ('train' or
'test').  Every sample takes part; the ten clients' sizes are at most one apart,
natural clients have what they have, and `train.Run` weighs them by their sizes.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hushgrad.fl import losses, storage
from hushgrad.functions import digest
from hushgrad.sources.tables import load

CLIENTS = 10
BUCKETS = 65_536


def _rank(df: DataFrame, key: str, by: list[str], name: str) -> DataFrame:
    """df with a gapless rank by `key` within `by`, from digest buckets and the counts before them."""
    over = f"partition by {', '.join([*by, '_k'])}" if by else "partition by _k"
    df = df.withColumn("_u", digest.uniform(name, F.col(key))).withColumn("_k", F.floor(F.col("_u") * BUCKETS))
    counts = df.groupBy(*by, "_k").agg(F.count(F.lit(1)).alias("_n"))
    of = f"partition by {', '.join(by)}" if by else ""
    before = counts.select(*by, "_k", F.expr(f"coalesce(sum(_n) over ({of} order by _k rows between unbounded preceding and 1 preceding), 0L)").alias("_b"))
    out = df.withColumn("_r", F.expr(f"row_number() over ({over} order by _u, {key})")).join(before, [*by, "_k"])
    return out.withColumn(name, F.col("_b") + F.col("_r") - 1).drop("_u", "_k", "_b", "_r")


def dealt(df: DataFrame, key: str = "sample_id", clients: int = CLIENTS) -> DataFrame:
    """Rows with client_id, seq and part.  A fifth is for testing; the rest goes to `clients` clients of
    sizes at most one apart, by rank."""
    ranked = _rank(df, key, [], "place")
    parts = ranked.withColumn("part", F.when(F.col("place") % 5 == 0, "test").otherwise("train"))
    test = parts.filter("part = 'test'").withColumn("client_id", F.lit(0)).withColumn("seq", F.lit(0).cast("long"))
    train = parts.filter("part = 'train'")
    turn = F.col("place") - F.floor(F.col("place") / 5) - 1
    train = train.withColumn("client_id", (turn % clients).cast("int")).withColumn("seq", F.floor(turn / clients))
    return train.unionByName(test)


#: Vocabulary of the categorical features, pinned.
SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
WIDTH = 123


#: Indicator groups of a line: column, first value and number of values; values outside give no indicator.
GROUPS = [("q", 0, 10), ("d", 0, 11), ("t", 0, 9), ("e", 0, 10), ("ln", 0, 7), ("mo", 1, 12), ("yr", 0, 7), ("sz", 0, 10), ("na", 0, 25), ("pr", 49, 5), ("rf", 0, 3), ("ls", 0, 2), ("ms", 0, 5)]


#: Of each group its place in a line's code: (divisor, first value, number of values).  A digit of 0 says that no indicator is set.
DIGITS: dict[str, tuple[int, int, int]] = {}
for _name, _first, _n in GROUPS:
    DIGITS[_name] = (math.prod(n + 1 for _, _, n in GROUPS[: len(DIGITS)]), _first, _n)
#: Neighbouring digits that are looked up together, so that generated code stays short enough to be compiled.
PAIRS = [("q", "d"), ("t", "e"), ("ln", "mo"), ("yr", "sz"), ("na", "pr"), ("rf", "ls", "ms")]
KEY = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]
#: Samples of a client that are numbered in one task.
LARGE = 100_000


def _code(*names: str) -> Column:
    """The columns of these groups as digits of one number."""
    out = F.lit(0).cast("long")
    for name in names:
        div, first, n = DIGITS[name]
        v = F.col(name)
        out = out + F.when(v.between(first, first + n - 1), (v - first + 1).cast("long")).otherwise(0) * F.lit(div).cast("long")
    return out


def _tables() -> list[tuple[str, list[list[int]]]]:
    """For each of PAIRS its number out of a code (SQL, from 0) and, by that number, the positions of the indicators (-1: none)."""
    out, at = [], 0
    for names in PAIRS:
        rows = [[]]
        for name in names:
            n = DIGITS[name][2]
            # the first name is the lowest digit, so it runs fastest
            rows = [r + [at + k - 1 if k else -1] for k in range(n + 1) for r in rows]
            at += n
        out.append((f"cast((code div {DIGITS[names[0]][0]}L) % {len(rows)}L as int)", rows))
    return out


def _score() -> Column:
    """The planted teacher's score of a line's unit vector, from its code: no vector is needed."""
    teacher, score, hot = [digest.normal_value("teacher", j) for j in range(WIDTH)], [repr(teacher_bias()) + "D"], ["1"]
    for number, rows in _tables():
        entry = lambda values: f"element_at(array({', '.join(values)}), {number} + 1)"  # noqa: B023, E731
        score.append(entry([repr(float(sum(teacher[i] for i in r if i >= 0))) + "D" for r in rows]))
        hot.append(entry([str(sum(i >= 0 for i in r)) for r in rows]))
    return F.expr(f"({' + '.join(score)}) / sqrt({' + '.join(hot)})")


def _hot() -> Column:
    """Positions of the indicators that are set, a byte each, 255 where a group has none; the intercept is the last."""
    each = [f"substring(X'{bytes(i % 256 for r in rows for i in r).hex()}', {number} * {len(rows[0])} + 1, {len(rows[0])})" for number, rows in _tables()]
    return F.expr(f"concat({', '.join(each)}, X'{WIDTH - 1:02x}')")


def _vectors(rows: DataFrame) -> DataFrame:
    """Rows with the unit vector that `hot` stands for, made where it is read."""
    has = [F.contains(F.col("hot"), F.lit(bytes([i]))) for i in range(WIDTH)]
    one = 1.0 / F.sqrt(reduce(lambda s, h: s + F.when(h, 1).otherwise(0), has, F.lit(0)))
    return rows.withColumn("_one", one).withColumn("features", F.array(*[F.when(h, F.col("_one")).otherwise(0.0) for h in has])).drop("_one")


def _wide(rows: DataFrame) -> DataFrame:
    """Rows with `hot` in place of the code, and `features`, the same as a vector."""
    return _vectors(rows.withColumn("hot", _hot()).drop("code"))


def _lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(KEY, code) of every line with its order, customer and part.  What is shuffled is keys and codes."""
    li, o, c, p = (load(spark, sf_dir, t) for t in ("lineitem", "orders", "customer", "part"))
    at = lambda col, values: F.array_position(F.array(*map(F.lit, values)), F.col(col)) - 1
    li = li.select(
        *KEY,
        F.least(F.floor(F.col("l_quantity") / 5), F.lit(9)).alias("q"), F.round(F.col("l_discount") * 100).alias("d"), F.round(F.col("l_tax") * 100).alias("t"),
        F.least(F.floor(F.col("l_extendedprice") / 10500), F.lit(9)).alias("e"), (F.col("l_linenumber") - 1).alias("ln"), F.month("l_shipdate").alias("mo"),
        (F.year("l_shipdate") - 1995).alias("yr"), at("l_returnflag", "ANR").alias("rf"), at("l_linestatus", "FO").alias("ls"),
    )
    li = li.select(*KEY, _code("q", "d", "t", "e", "ln", "mo", "yr", "rf", "ls").alias("of_line"))
    c = c.select("c_custkey", F.col("c_nationkey").alias("na"), at("c_mktsegment", SEGMENTS).alias("ms")).select("c_custkey", _code("na", "ms").alias("of_customer"))
    o = o.select("o_orderkey", "o_custkey", F.ascii(F.substring("o_orderpriority", 1, 1)).alias("pr")).select("o_orderkey", "o_custkey", _code("pr").alias("of_order"))
    o = o.join(c, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", (F.col("of_order") + F.col("of_customer")).alias("of_order"))
    p = p.select("p_partkey", F.least(F.floor(F.col("p_size") / 5), F.lit(9)).alias("sz")).select("p_partkey", _code("sz").alias("of_part"))
    wide = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(p, F.col("l_partkey") == F.col("p_partkey"))
    return wide.select(*KEY, (F.col("of_line") + F.col("of_order") + F.col("of_part")).alias("code"))


def _placed(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(KEY, code, place, label) of every line, and the written table under it.

    Each shuffle is written out and its files let go before the next, so that the disk holds one at a time."""
    tasks = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    sample_id = F.concat_ws("|", *KEY)
    lines = storage.settle(_lines(spark, sf_dir), "lines")
    mid = lines.agg(F.percentile_approx(_score(), 0.5, 10_000)).first()[0]
    keyed = lines.withColumn("_u", digest.uniform("place", sample_id)).withColumn("_k", F.floor(F.col("_u") * BUCKETS).cast("int"))
    order = ", ".join(["_u", *KEY, "code"])
    ranked = keyed.repartition(tasks, "_k").withColumn("_r", F.expr(f"row_number() over (partition by _k order by {order})"))
    placed = storage.settle(ranked.select(*KEY, "code", "_k", "_r"), "placed")
    storage.drop(lines)
    counts = placed.groupBy("_k").agg(F.max("_r").alias("_n"))
    before = counts.select("_k", F.expr("coalesce(sum(_n) over (order by _k rows between unbounded preceding and 1 preceding), 0L)").alias("_b"))
    flip = F.when(digest.uniform("flip", sample_id) < 0.05, -1.0).otherwise(1.0)
    rows = placed.join(F.broadcast(before), "_k").select(*KEY, "code", (F.col("_b") + F.col("_r") - 1).alias("place"))
    return rows.withColumn("label", F.when(_score() > (F.lit(mid) if mid is not None else F.lit(0.0)), 1.0).otherwise(-1.0) * flip), placed


def tab_logistic(spark: SparkSession, sf_dir: str, clients: int = CLIENTS) -> DataFrame:
    """Lines with their order, customer and part as indicators, rows of unit norm, and a planted label:
    the sign of a digest-normal score against its median, one in twenty flipped by digest.

    Rows are moved and kept as one number with their indicators; vectors are made where they are read."""
    rows, placed = _placed(spark, sf_dir)
    test, turn = F.col("place") % 5 == 0, F.col("place") - F.floor(F.col("place") / 5) - 1
    out = rows.select(
        F.when(test, 0).otherwise(turn % clients).cast("int").alias("client_id"), F.when(test, 0).otherwise(F.floor(turn / clients)).cast("long").alias("seq"),
        "code", "label", F.when(test, "test").otherwise("train").alias("part"),
    )
    out = _wide(out)
    out._under = [placed]
    return out


def natural_clients(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, dict[int, int]]:
    """(training samples, test samples, sizes) of tab_logistic with a client for each supplier.

    A client's samples lie side by side in one task, or in one for every LARGE of them, so a round
    makes one vector for each run and client, however many tasks there are."""
    tasks = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    rows, placed = _placed(spark, sf_dir)
    test = storage.settle(rows.filter("place % 5 = 0").select(F.lit(0).alias("client_id"), F.lit(0).cast("long").alias("seq"), "code", "label"), "held-out")
    train = rows.filter("place % 5 <> 0")
    # one row for each client, as in the loop's own table of sizes
    names = storage.settle(_rank(train.groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n")), "l_suppkey", [], "client_id").withColumn("client_id", F.col("client_id").cast("long")), "clients")
    sizes = {r["client_id"]: r["n"] for r in names.collect()}
    u = digest.uniform("seq", F.concat_ws("|", *KEY))
    keyed = train.join(F.broadcast(names), "l_suppkey").select("client_id", "n", "code", "label", u.alias("_u")).withColumn("_k", F.floor(F.col("_u") * F.ceil(F.col("n") / LARGE)).cast("int"))
    ranked = keyed.repartition(tasks, "client_id", "_k").withColumn("_r", F.expr("row_number() over (partition by client_id, _k order by _u, code, label)"))
    train = storage.settle(ranked.select("client_id", "_k", "_r", "code", "label"), "samples")
    storage.drop(placed)
    storage.drop(names)
    kept = train
    if max(sizes.values(), default=0) > LARGE:
        counts = train.groupBy("client_id", "_k").agg(F.max("_r").alias("_n"))
        # of the clients in more than one part, at most a row for LARGE samples or so
        before = counts.withColumn("_b", F.expr("coalesce(sum(_n) over (partition by client_id order by _k rows between unbounded preceding and 1 preceding), 0L)")).filter("_b > 0").drop("_n")
        train = train.join(F.broadcast(before), ["client_id", "_k"], "left")
    else:
        train = train.withColumn("_b", F.lit(0).cast("long"))
    train = _wide(train.select("client_id", (F.coalesce("_b", F.lit(0)) + F.col("_r") - 1).alias("seq"), "code", "label"))
    test = _wide(held := test)
    train._under, test._under = [kept], [held]
    return train, test, sizes


def teacher_bias() -> float:
    """The planted teacher's entry for the intercept."""
    return digest.normal_value("teacher", WIDTH - 1)


def doc_logistic(spark: SparkSession, sf_dir: str, label: str = "lang") -> DataFrame:
    """Documents as counts of 122 hashed lower-case words, rows of unit norm, with an intercept.
    label 'lang': English or not; 'quality' or 'toxic': the labels table, with shares of letters, digits and other signs added.

    A document's counts are made from its own words, in place, so no text is shuffled."""
    d = load(spark, sf_dir, "documents")
    y = F.when(F.col("lang") == "en", 1.0).otherwise(-1.0)
    if label != "lang":
        d = d.join(load(spark, sf_dir, "labels"), "doc_id")
        y = F.when(F.col(label) == 1, 1.0).otherwise(-1.0)
    places = 122 if label == "lang" else 119
    words = F.filter(F.split(F.lower(F.coalesce("text", F.lit(""))), "\\s+"), lambda w: w != "")
    hashed = F.sort_array(F.transform(words, lambda w: F.pmod(F.xxhash64(w), F.lit(places)).cast("int")))
    v = F.col("v")
    shares = []
    if label != "lang":
        size = F.greatest(F.char_length("text"), F.lit(1)).cast("double")
        share = lambda pattern: F.char_length(F.regexp_replace("text", pattern, "")) / size
        shares = [share("[^\\p{L}]"), share("[^\\p{N}]"), share("[\\p{L}\\p{N}\\s]")]
    slim = d.select(F.col("doc_id").alias("sample_id"), y.alias("label"), hashed.alias("h"), *[x.alias(f"share{i}") for i, x in enumerate(shares)])
    # numbers of words by place, counted over the sorted places of one document
    counted = slim.mapInArrow(_counts(places), "sample_id long, label double, v array<double>" + "".join(f", share{i} double" for i in range(len(shares))))
    rows = counted.select("sample_id", "label", F.concat(v, F.array(*[F.col(f"share{i}") for i in range(len(shares))], F.lit(1.0))).alias("features"))
    return dealt(rows).select("client_id", "seq", "features", "label", "part")


def _counts(places: int):
    """The place lists of documents as count vectors of unit norm."""

    def go(batches):  # noqa: ANN001, ANN202
        for batch in batches:
            lists = batch.column(2)
            off = lists.offsets.to_numpy().astype(np.int64)
            flat = lists.values.to_numpy(zero_copy_only=False)[off[0] : off[-1]]
            n = batch.num_rows
            v = np.bincount(np.repeat(np.arange(n), np.diff(off)) * places + flat, minlength=n * places).reshape(n, places).astype(np.float64)
            norm = np.sqrt((v * v).sum(axis=1, keepdims=True))
            v = np.divide(v, norm, out=v, where=norm > 0)
            wide = pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * places), pa.array(v.reshape(-1)))
            yield pa.RecordBatch.from_arrays([*batch.columns[:2], wide, *batch.columns[3:]], ["sample_id", "label", "v", *batch.schema.names[3:]])

    return go


def vec_network(spark: SparkSession, sf_dir: str, planted: bool = True) -> DataFrame:
    """Embeddings with ten classes: the nearest of ten digest-normal directions, or the table's own labels."""
    e = load(spark, sf_dir, "embeddings")
    f = F.transform("embedding", lambda x: x.cast("double"))
    rows = e.select(F.col("vec_id").alias("sample_id"), f.alias("features"), F.col("label").cast("double").alias("raw"))
    if planted:
        score = [
            F.struct(F.aggregate(F.zip_with("features", F.array(*[F.lit(digest.normal_value("class", k, j)) for j in range(64)]), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v).alias("s"), F.lit(float(k)).alias("k"))
            for k in range(10)
        ]
        rows = rows.withColumn("label", F.array_max(F.array(*score))["k"])
    else:
        rows = rows.withColumn("label", F.col("raw"))
    return dealt(rows).select("client_id", "seq", "features", "label", "part")


@dataclass(frozen=True)
class Workload:
    name: str
    build: object
    loss: object
    d: int
    clip: float
    eps: tuple[float, ...]
    k: int


WORKLOADS = {
    "tab_logistic": Workload("tab_logistic", tab_logistic, losses.LogisticNonconvex(0.2), WIDTH, 0.5, (1.0, 5.0, 10.0), 6),
    "doc_logistic": Workload("doc_logistic", doc_logistic, losses.LogisticNonconvex(0.2), 123, 0.5, (1.0, 5.0, 10.0), 6),
    "doc_quality": Workload("doc_quality", lambda s, d: doc_logistic(s, d, "quality"), losses.LogisticNonconvex(0.2), 123, 0.5, (1.0, 5.0, 10.0), 6),
    "vec_network": Workload("vec_network", vec_network, losses.ShallowNet(), losses.ShallowNet().dimension(), 1.0, (1.0, 2.0, 4.0, 8.0, 16.0), 240),
    "vec_raw": Workload("vec_raw", lambda s, d: vec_network(s, d, False), losses.ShallowNet(), losses.ShallowNet().dimension(), 1.0, (1.0, 2.0, 4.0, 8.0, 16.0), 240),
}

#: The stepsizes tried for every method, the probability of the privacy guarantee, the methods compared.
STEPS = (0.01, 0.03, 0.06, 0.1, 0.3, 0.6, 1.0)
DELTA = 1e-3
COMPARED = ("direct_sgd", "shifted_sgd", "shifted_svrg", "ldp_sgd", "ldp_svrg")


def _ready(rows: DataFrame) -> tuple[DataFrame, DataFrame, dict[int, int]]:
    """(training samples, test samples, sizes of the clients), the first two persisted.

    A client's samples are dealt over tasks by seq, so there are as many tasks as
    the session has partitions, whatever the number of clients."""
    tasks = max(1, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    # kept without the vector where the indicators say the same
    slim = [c for c in rows.columns if c not in ("part", "features" if "hot" in rows.columns else "")]
    train = rows.filter("part = 'train'").select(*slim).repartition(tasks, "client_id", F.floor(F.col("seq") / 64)).persist()
    sizes = {r["client_id"]: r["count"] for r in train.groupBy("client_id").count().collect()}
    test = rows.filter("part = 'test'").select(*slim).persist()
    out = []
    for kept in (train, test):
        frame = _vectors(kept) if "hot" in slim else kept
        frame._under = [kept]
        out.append(frame)
    out[1]._under += rows.__dict__.get("_under", [])
    return *out, sizes


def prepare(spark: SparkSession, name: str, sf_dir: str) -> tuple[DataFrame, DataFrame, dict[int, int]]:
    return _ready(WORKLOADS[name].build(spark, sf_dir))


def prepare_single(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, dict[int, int]]:
    """tab_logistic with all samples on one node."""
    return _ready(tab_logistic(spark, sf_dir, clients=1))


def prepare_natural(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, dict[int, int]]:
    """tab_logistic with a client for each supplier."""
    return natural_clients(spark, sf_dir)


def release(*frames: DataFrame) -> None:
    for f in frames:
        for kept in f.__dict__.get("_under", [f]):
            kept.unpersist()
            storage.drop(kept)


def wide_network(spark: SparkSession, rows: int = 2000, inputs: int = 784) -> DataFrame:
    """Made-up samples for the network of 784 inputs: digest-seeded features of unit norm and classes of their largest of
    ten blocks.  It shows that the full size runs; it says nothing about accuracy on images."""

    def go(batches):  # noqa: ANN001, ANN202
        for batch in batches:
            ids = batch.column(0).to_numpy()
            a = np.stack([digest.philox(784, int(i)).standard_normal(inputs) for i in ids]) if len(ids) else np.zeros((0, inputs))
            y = np.abs(a[:, : inputs // 10 * 10]).reshape(len(ids), 10, -1).sum(axis=2).argmax(axis=1).astype(np.float64) if len(ids) else np.zeros(0)
            a = a / np.sqrt((a * a).sum(axis=1, keepdims=True)) if len(ids) else a
            wide = pa.ListArray.from_arrays(pa.array(np.arange(len(ids) + 1, dtype=np.int32) * inputs), pa.array(a.reshape(-1)))
            yield pa.RecordBatch.from_arrays([pa.array(ids), wide, pa.array(y)], ["sample_id", "features", "label"])

    return dealt(spark.range(rows).mapInArrow(go, "sample_id long, features array<double>, label double")).select("client_id", "seq", "features", "label", "part")


NETWORK_784 = Workload("wide_network", lambda spark, sf_dir: wide_network(spark), losses.ShallowNet(784), losses.ShallowNet(784).dimension(), 1.0, (1.0, 2.0, 4.0, 8.0, 16.0), 2544)
WORKLOADS["wide_network"] = NETWORK_784
