"""Rounds as DataFrame plans, for small models and exact comparison with SQL.

Every draw is a digest of its key, sums are made over whole billionths, and
what passes from one round to the next is rounded, so results don't depend on
partitioning and another engine can repeat them.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hushgrad.functions import digest
from hushgrad.sources.tables import load

D = 6
N = 10
UNIT = 1_000_000_000


@dataclass(frozen=True)
class Setting:
    """A small problem: k of 6 coordinates, batches of 64, clip bound 0.5, penalty weight 0.2."""

    k: int = 2
    b: int = 64
    clip: float = 0.5
    lam: float = 0.2
    eta: float = 0.3
    gamma: float = 0.25
    sigma: float = 0.05
    seed: int = 42


S = Setting()
START = [0.1, -0.2, 0.3, 0.0, 0.05, -0.1]
OTHER = [0.0, 0.1, -0.1, 0.2, 0.0, 0.1]


def samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """client_id, sample_id, f (6 features), y (+1 or -1): lines of orders; clients by supplier."""
    li = load(spark, sf_dir, "lineitem")
    q, p, c, t = F.col("l_quantity") / 50.0, F.col("l_extendedprice") / 110000.0, F.col("l_discount") * 10.0, F.col("l_tax") * 12.5
    flag = F.when(F.col("l_returnflag") == "R", 1.0).otherwise(0.0)
    return li.select(
        (F.col("l_suppkey") % N).cast("int").alias("client_id"),
        F.concat_ws("|", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber").alias("sample_id"),
        F.array(*[x * 0.4 for x in (q, p, c, t, flag, F.lit(1.0))]).alias("f"),
        F.when(q + c - t > 0.5, 1.0).otherwise(-1.0).alias("y"),
    )


def vector(values: list[float]) -> Column:
    return F.array(*[F.lit(float(v)) for v in values])


def model(spark: SparkSession, values: list[float], name: str = "x") -> DataFrame:
    return spark.range(1).select(vector(values).alias(name))


def dot(a: Column, b: Column) -> Column:
    """Written out over the D entries, which keeps it in generated code (higher-order functions are not)."""
    return reduce(lambda s, i: s + a[i] * b[i], range(D), F.lit(0.0))


def penalty_slope(v: Column, lam: float) -> Column:
    return F.lit(2 * lam) * v / ((F.lit(1.0) + v * v) * (F.lit(1.0) + v * v))


def gradient(f: Column, y: Column, x: Column, lam: float = S.lam) -> Column:
    """Written out as well: the weight is one subexpression, worked out once for a row."""
    w = -y / (F.lit(1.0) + F.exp(y * dot(f, x)))
    return F.array(*[w * f[i] + penalty_slope(x[i], lam) for i in range(D)])


def norm(g: Column) -> Column:
    return F.sqrt(reduce(lambda s, i: s + g[i] * g[i], range(D), F.lit(0.0)))


def clipped(df: DataFrame, column: str, bound: float) -> DataFrame:
    """df with its vector column scaled to a norm of at most bound; a zero vector stays."""
    n, g = F.col("_norm"), F.col(column)
    df = df.withColumn("_norm", norm(g)).withColumn("_scale", F.when(n > bound, F.lit(bound) / n).otherwise(F.lit(1.0)))
    return df.withColumn(column, F.array(*[g[i] * F.col("_scale") for i in range(D)])).drop("_norm", "_scale")


def units(c: Column) -> Column:
    return F.round(c * F.lit(float(UNIT))).cast("long")


def exact_sum(c: Column) -> Column:
    return F.sum(units(c)).cast("double") / F.lit(float(UNIT))


def ranked(df: DataFrame, t: int, b: int = S.b) -> DataFrame:
    """The batch of round t: for each client the b samples with the smallest digests.

    The rank is filtered where it is made, so Spark keeps b rows of each task and
    client before the shuffle."""
    draw = digest.uniform("batch", S.seed, t, F.col("client_id"), F.col("sample_id"))
    return (
        df.withColumn("_u", draw)
        .withColumn("rk", F.expr("row_number() over (partition by client_id order by _u, sample_id)"))
        .filter(F.col("rk") <= b)
        .drop("_u")
    )


def client_sums(df: DataFrame, column: str, per: int) -> DataFrame:
    """(client_id, coord, value): sums of a vector column over a client's rows, over `per`.

    The entries are added up as D aggregates of one row for each client, which only then become rows."""
    g = F.col(column)
    sums = df.groupBy("client_id").agg(*[F.sum(units(g[i])).alias(f"_{i}") for i in range(D)])
    long = sums.select("client_id", F.posexplode(F.array(*[f"_{i}" for i in range(D)])).alias("coord", "v"))
    return long.select("client_id", "coord", (F.col("v").cast("double") / F.lit(float(UNIT)) / F.lit(float(per))).alias("value"))


def perturbed(sums: DataFrame, t: int, sigma: float = S.sigma) -> DataFrame:
    noise = digest.normal("noise", S.seed, t, F.col("client_id"), F.col("coord"))
    return sums.withColumn("value", F.round(F.col("value") + F.lit(sigma) * noise, 9))


def random_k(vectors: DataFrame, t: int, k: int = S.k, d: int = D) -> DataFrame:
    """k coordinates of each client's vector, scaled by d/k."""
    draw = digest.uniform("mask", S.seed, t, F.col("client_id"), F.col("coord"))
    return (
        vectors.withColumn("_u", draw)
        .withColumn("rk", F.expr("row_number() over (partition by client_id order by _u, coord)"))
        .filter(F.col("rk") <= k)
        .select("client_id", "coord", F.round(F.col("value") * F.lit(float(d)) / F.lit(float(k)), 9).alias("value"))
    )


def quantized(vectors: DataFrame, t: int, levels: int = 4) -> DataFrame:
    """Each coordinate dithered to steps of the client's norm."""
    draw = digest.uniform("level", S.seed, t, F.col("client_id"), F.col("coord"))
    n = vectors.groupBy("client_id").agg(F.sqrt(exact_sum(F.col("value") * F.col("value"))).alias("n"))
    x = F.abs("value") / F.col("n") * F.lit(float(levels))
    q = F.floor(x) + F.when(draw < x - F.floor(x), 1.0).otherwise(0.0)
    return vectors.join(n, "client_id").select(
        "client_id", "coord", F.round(F.when(F.col("n") > 0, F.signum("value") * q * F.col("n") / F.lit(float(levels))).otherwise(0.0), 9).alias("value")
    )


def server_mean(messages: DataFrame, n: int = N) -> DataFrame:
    return messages.groupBy("coord").agg((exact_sum(F.col("value")) / F.lit(float(n))).alias("mean"))


@dataclass
class State:
    """x and the server's reference as one-row tables; the clients' references in long form (None: all zero)."""

    x: DataFrame
    ref: DataFrame
    shifts: DataFrame | None = None


def _gather(rows: DataFrame, name: str) -> DataFrame:
    """(coord, v) rows, at most D of them, as one array in order."""
    ordered = F.array_sort(F.collect_list(F.struct("coord", "v")))
    return rows.agg(F.transform(ordered, lambda z: z["v"]).alias(name))


def batch_gradient(data: DataFrame, t: int, x: DataFrame) -> DataFrame:
    """(client_id, coord, value): the batch's mean clipped gradient at the model."""
    batch = ranked(data, t).crossJoin(F.broadcast(x))  # one row
    return client_sums(clipped(batch.withColumn("g", gradient(F.col("f"), F.col("y"), F.col("x"))), "g", S.clip), "g", S.b)


def round_step(data: DataFrame, s: State, t: int, shifted: bool, squeeze: bool = True, estimate=batch_gradient) -> tuple[DataFrame, State]:  # noqa: ANN001
    """One round: (messages, next state).  estimate(data, t, x) gives the clients' estimates."""
    noisy = perturbed(estimate(data, t, s.x), t)
    if shifted and s.shifts is not None:
        noisy = noisy.join(s.shifts, ["client_id", "coord"], "left").withColumn("value", F.round(F.col("value") - F.coalesce("shift", F.lit(0.0)), 9)).drop("shift")
    messages = random_k(noisy, t) if squeeze else noisy
    mean = server_mean(messages)
    zero = data.sparkSession.range(D).select(F.col("id").cast("int").alias("coord"))
    base = zero.crossJoin(F.broadcast(s.x)).crossJoin(F.broadcast(s.ref)).join(F.broadcast(mean), "coord", "left").select(
        "coord", F.element_at("x", F.col("coord") + 1).alias("xv"), F.element_at("ref", F.col("coord") + 1).alias("rv"), F.coalesce("mean", F.lit(0.0)).alias("mean")
    )
    x = _gather(base.select("coord", F.round(F.col("xv") - F.lit(S.eta) * (F.col("rv") + F.col("mean")), 9).alias("v")), "x")
    if not shifted:
        return messages, State(x, s.ref)
    ref = _gather(base.select("coord", F.round(F.col("rv") + F.lit(S.gamma) * F.col("mean"), 9).alias("v")), "ref")
    moved = messages.select("client_id", "coord", F.round(F.lit(S.gamma) * F.col("value"), 9).alias("shift"))
    if s.shifts is not None:
        both = s.shifts.unionByName(moved)
        moved = both.groupBy("client_id", "coord").agg(F.round(exact_sum(F.col("shift")), 9).alias("shift"))
    return messages, State(x, ref, moved)


def start(spark: SparkSession) -> State:
    return State(model(spark, START), model(spark, [0.0] * D, "ref"))


def advance(spark: SparkSession, sf_dir: str, rounds: int, shifted: bool, squeeze: bool = True) -> tuple[DataFrame, State, list[State]]:
    data = samples(spark, sf_dir)
    s, seen, messages = start(spark), [], None
    for t in range(rounds):
        seen.append(s)
        messages, s = round_step(data, s, t, shifted, squeeze)
    return messages, s, [*seen, s]


def models(states: list[State]) -> DataFrame:
    """(round, coord, value) of the models visited."""
    rows = [s.x.select(F.lit(t).alias("round"), F.posexplode("x").alias("coord", "value")) for t, s in enumerate(states)]
    return reduce(DataFrame.unionByName, rows).select("round", "coord", "value")


def pair_estimate(data: DataFrame, t: int, x: Column, w: Column, held: DataFrame | None = None) -> DataFrame:
    """(client_id, coord, value): the batch's mean difference of clipped gradients at x and w, plus the mean one at w
    over all of a client's samples.  data may carry x and w as columns; batches are picked before gradients are made."""
    every = data if held is None else held
    batch = ranked(every, t)
    batch = batch.withColumn("gx", gradient(F.col("f"), F.col("y"), x)).withColumn("gw", gradient(F.col("f"), F.col("y"), w))
    batch = clipped(clipped(batch, "gx", S.clip), "gw", S.clip)
    g = F.array(*[F.col("gx")[i] - F.col("gw")[i] for i in range(D)])
    diff = client_sums(batch.withColumn("g", g), "g", S.b)
    rows = clipped(every.withColumn("gw", gradient(F.col("f"), F.col("y"), w)), "gw", S.clip)
    m = every.groupBy("client_id").agg(F.count(F.lit(1)).alias("m"))
    full = client_sums(rows, "gw", 1).join(F.broadcast(m), "client_id").select("client_id", "coord", (F.col("value") / F.col("m")).alias("full"))
    return diff.join(full, ["client_id", "coord"]).select("client_id", "coord", (F.col("value") + F.col("full")).alias("value"))


def _rounded(rows: DataFrame, digits: int) -> DataFrame:
    return rows.withColumn("value", F.round("value", digits))


def estimate_svrg(data: DataFrame, t: int, x: list[float], w: list[float]) -> DataFrame:
    """Batch difference to the snapshot plus the snapshot's full gradient."""
    return _rounded(pair_estimate(data, t, vector(x), vector(w)), 6)


def estimate_saga(data: DataFrame, t: int, x: list[float], past: list[list[float]]) -> DataFrame:
    """Batch difference to each sample's past point plus the mean over all past points.

    The past point of a sample is its last batch among rounds before t, else the first model.
    """
    points = F.array(*[vector(p) for p in past])
    held = saga_table(data, t).withColumn("w", F.element_at(points, F.col("last_round") + 1))
    return _rounded(pair_estimate(data, t, vector(x), F.col("w"), held), 6)


def saga_table(data: DataFrame, t: int) -> DataFrame:
    """data with last_round: the last of rounds 1..t-1 whose batch held the sample, else 0."""
    out = data.withColumn("last_round", F.lit(0))
    slim = data.select("client_id", "sample_id")
    for u in range(1, t):
        # b rows for each client
        drawn = F.broadcast(ranked(slim, u).select(F.col("sample_id").alias("_s"), F.col("client_id").alias("_c")))
        out = out.join(drawn, (F.col("sample_id") == F.col("_s")) & (F.col("client_id") == F.col("_c")), "left")
        out = out.withColumn("last_round", F.when(F.col("_s").isNotNull(), F.lit(u)).otherwise(F.col("last_round"))).drop("_s", "_c")
    return out


def moving_snapshot(t: int, p: float) -> int:
    """The round whose model the snapshot of round t holds: the last before t whose coin fell, else 0 (the first model)."""
    return max((u for u in range(t) if digest.uniform_value("coin", S.seed, u) < p), default=0)


def advance_reduced(spark: SparkSession, sf_dir: str, rounds: int, kind: str, shifted: bool, squeeze: bool = True, p: float = 0.5) -> tuple[DataFrame, State, list[State]]:
    """`rounds` rounds with the svrg or saga estimator, at the models that the run itself visits."""
    data = samples(spark, sf_dir)
    s, seen, messages = start(spark), [], None
    for t in range(rounds):
        seen.append(s)

        def estimate(data: DataFrame, t: int, x: DataFrame) -> DataFrame:
            if kind == "svrg":
                w = seen[moving_snapshot(t, p)].x.withColumnRenamed("x", "w")
                rows = data.crossJoin(F.broadcast(x)).crossJoin(F.broadcast(w))  # one row each
                return pair_estimate(rows, t, F.col("x"), F.col("w"))
            # models visited before, one row each, in an array by round
            rows = saga_table(data, max(t, 1)).crossJoin(F.broadcast(x))
            for u in range(max(t, 1)):
                rows = rows.crossJoin(F.broadcast(seen[u].x.withColumnRenamed("x", f"x{u}")))
            w = F.element_at(F.array(*[f"x{u}" for u in range(max(t, 1))]), F.col("last_round") + 1)
            return pair_estimate(rows.withColumn("w", w), t, F.col("x"), F.col("w"))

        messages, s = round_step(data, s, t, shifted, squeeze, estimate)
    return messages, s, [*seen, s]
