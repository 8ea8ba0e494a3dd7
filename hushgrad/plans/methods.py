"""The method queries on DataFrames; `oracle.SQL` says the same in SQL."""

from __future__ import annotations

from decimal import ROUND_HALF_UP, Decimal
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hushgrad.functions import digest
from hushgrad.plans import native as nt
from hushgrad.plans.native import D, N, OTHER, S, START
from hushgrad.sources.tables import load

PAST = [START, OTHER, [0.5 * v for v in START]]


def _grads(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.samples(spark, sf_dir).withColumn("g", nt.gradient(F.col("f"), F.col("y"), nt.vector(START)))


def loss_at_point(spark: SparkSession, sf_dir: str) -> DataFrame:
    each = nt.samples(spark, sf_dir).select("client_id", F.log(F.lit(1.0) + F.exp(-F.col("y") * nt.dot(F.col("f"), nt.vector(START)))).alias("l"))
    per = each.groupBy("client_id").agg((nt.exact_sum(F.col("l")) / F.count(F.lit(1))).alias("l"))
    extra = sum(S.lam * v * v / (1 + v * v) for v in START)
    return per.agg(F.round(nt.exact_sum(F.col("l")) / F.count(F.lit(1)) + F.lit(extra), 6).alias("loss"))


def full_gradient(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = _grads(spark, sf_dir)
    m = g.groupBy("client_id").agg(F.count(F.lit(1)).alias("m"))
    per = nt.client_sums(g, "g", 1).join(F.broadcast(m), "client_id").withColumn("value", F.col("value") / F.col("m"))
    return per.groupBy("coord").agg(F.round(nt.exact_sum(F.col("value")) / F.count(F.lit(1)), 6).alias("value"))


def clipped_gradient(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = _grads(spark, sf_dir)
    w = g.groupBy("client_id").agg(F.count(F.lit(1)).alias("m"), F.count_if(nt.norm(F.col("g")) > S.clip).alias("n_clipped"))
    sums = nt.client_sums(nt.clipped(g, "g", S.clip), "g", 1)
    return sums.join(F.broadcast(w), "client_id").select("client_id", "coord", F.round(F.col("value") / F.col("m"), 6).alias("value"), "n_clipped")


def minibatch_pick(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.ranked(nt.samples(spark, sf_dir), 1).select("client_id", "sample_id", F.col("rk").cast("long").alias("rank_in_client"))


def noise_draws(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The noise of a round in 50 coordinates for every supplier that has lines."""
    clients = load(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("client_id")).distinct()
    grid = clients.select("client_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(49).cast("long"))).alias("coord"))
    return grid.select("client_id", "coord", digest.normal("noise", S.seed, 0, F.col("client_id"), F.col("coord")).alias("noise"))


def _noisy(spark: SparkSession, sf_dir: str) -> DataFrame:
    batch = nt.ranked(nt.samples(spark, sf_dir), 0).withColumn("g", nt.gradient(F.col("f"), F.col("y"), nt.vector(START)))
    return nt.perturbed(nt.client_sums(nt.clipped(batch, "g", S.clip), "g", S.b), 0)


def randk_message(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.random_k(_noisy(spark, sf_dir), 0).select("client_id", "coord", "value")


def randk_pick(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.random_k(_noisy(spark, sf_dir), 0).groupBy("client_id").agg(F.count(F.lit(1)).alias("kept"), F.sum("coord").alias("coord_sum"))


def quantized_message(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.quantized(_noisy(spark, sf_dir), 0).select("client_id", "coord", "value")


def direct_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.models(nt.advance(spark, sf_dir, 1, False)[2])


def ldp_sgd_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.models(nt.advance(spark, sf_dir, 1, False, False)[2])


def shifted_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.advance(spark, sf_dir, 1, True)[1].shifts.select("client_id", "coord", "shift")


def two_round_direct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.models(nt.advance(spark, sf_dir, 2, False)[2])


def three_round_shifted(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.models(nt.advance(spark, sf_dir, 3, True)[2])


def shift_update(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.advance(spark, sf_dir, 3, True)[1].shifts.select("client_id", "coord", "shift")


def shift_mismatch(spark: SparkSession, sf_dir: str) -> DataFrame:
    shifts = nt.advance(spark, sf_dir, 3, True)[1].shifts
    g = _grads(spark, sf_dir)
    m = g.groupBy("client_id").agg(F.count(F.lit(1)).alias("m"))
    per = nt.client_sums(g, "g", 1).join(F.broadcast(m), "client_id").withColumn("value", F.col("value") / F.col("m"))
    gap = F.col("value") - F.coalesce("shift", F.lit(0.0))
    return per.join(shifts, ["client_id", "coord"], "left").agg(F.round(nt.exact_sum(gap * gap) / F.lit(float(N)), 6).alias("mismatch"))


def server_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.server_mean(nt.random_k(_noisy(spark, sf_dir), 0)).select("coord", F.round("mean", 6).alias("mean"))


def _two_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    data = nt.samples(spark, sf_dir)
    one, s = nt.round_step(data, nt.start(spark), 0, False)
    two, _ = nt.round_step(data, s, 1, False)
    return one.withColumn("round", F.lit(0)).unionByName(two.withColumn("round", F.lit(1)))


def comm_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    sent = _two_rounds(spark, sf_dir).groupBy("round").agg(F.count(F.lit(1)).alias("sent"))
    return sent.select(
        "round", "sent", (F.lit(32) * F.col("sent")).alias("value_bits"), (F.lit(3) * F.col("sent")).alias("index_bits"),
        F.expr("sum(32 * sent) over (order by round)").alias("total_value_bits"),
    )


def active_clients(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _two_rounds(spark, sf_dir).groupBy("coord").agg(F.countDistinct("client_id").alias("clients"), F.count(F.lit(1)).alias("messages"))


def svrg_estimate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.estimate_svrg(nt.samples(spark, sf_dir), 2, OTHER, START)


def svrg_refresh(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether the snapshot moves, for a round on every day that has orders (days since 1970)."""
    day = F.datediff(F.col("o_orderdate").cast("date"), F.lit("1970-01-01").cast("date")).cast("long")
    rounds = load(spark, sf_dir, "orders").select(day.alias("round")).distinct()
    return rounds.select("round", (digest.uniform("coin", S.seed, F.col("round")) < 0.2).alias("moves"))


def saga_refresh(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.saga_table(nt.samples(spark, sf_dir), 4).groupBy("client_id", "last_round").agg(F.count(F.lit(1)).alias("samples"))


def saga_estimate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nt.estimate_saga(nt.samples(spark, sf_dir), 3, [0.2] * D, PAST)


def drift_saga(spark: SparkSession, sf_dir: str) -> DataFrame:
    dist = F.array(*[F.lit(sum((0.2 - v) ** 2 for v in w)) for w in PAST])
    held = nt.saga_table(nt.samples(spark, sf_dir), 3).groupBy("last_round").agg(F.count(F.lit(1)).alias("c"))
    return held.agg(F.round(F.sum(F.col("c") * F.element_at(dist, F.col("last_round") + 1)) / F.sum("c"), 6).alias("drift"))


def drift_svrg(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Squared distance of the model of each of three rounds to the snapshot of that round."""
    seen = nt.advance_reduced(spark, sf_dir, 3, "svrg", True)[2]
    rows = None
    for t in range(3):
        w = seen[nt.moving_snapshot(t, 0.5)].x.withColumnRenamed("x", "w")
        one = seen[t].x.crossJoin(w).select(F.lit(t).alias("round"), F.round(reduce(lambda s, i: s + (F.col("x")[i] - F.col("w")[i]) * (F.col("x")[i] - F.col("w")[i]), range(D), F.lit(0.0)), 9).alias("drift"))
        rows = one if rows is None else rows.unionByName(one)
    return rows


def shifted_svrg_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Models of three shifted rounds whose estimates are snapshot-reduced; the snapshot moves by a shared coin."""
    return nt.models(nt.advance_reduced(spark, sf_dir, 3, "svrg", True)[2])


def shifted_saga_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Models of three shifted rounds whose estimates use a table of past points."""
    return nt.models(nt.advance_reduced(spark, sf_dir, 3, "saga", True)[2])


def ldp_svrg_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Models of two uncompressed, unshifted rounds with snapshot-reduced estimates."""
    return nt.models(nt.advance_reduced(spark, sf_dir, 2, "svrg", False, False)[2])


def max_row_norm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The largest squared norm of a sample's features and the smoothness that follows from it."""
    sq = nt.samples(spark, sf_dir).agg(F.max(nt.dot(F.col("f"), F.col("f"))).alias("v"))
    return sq.select(F.round("v", 9).alias("max_sq_norm"), F.round(F.col("v") / 4 + 2 * S.lam, 9).alias("smoothness"))


def half_up(v: float) -> float:
    """v to nine digits as SQL rounds it: halves away from zero, of the shortest decimal form."""
    return float(Decimal(repr(v)).quantize(Decimal("1e-9"), ROUND_HALF_UP))


def shift_cogroup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The references after three rounds, the last moved by meeting its messages client by client."""
    _, s, _ = nt.advance(spark, sf_dir, 2, True)
    messages, _ = nt.round_step(nt.samples(spark, sf_dir), s, 2, True)

    def meet(old, new):  # noqa: ANN001, ANN202
        have = dict(zip(old.column("coord").to_pylist(), old.column("shift").to_pylist(), strict=True))
        client = (old if old.num_rows else new).column("client_id")[0].as_py()
        for i, v in zip(new.column("coord").to_pylist(), new.column("value").to_pylist(), strict=True):
            have[i] = half_up(have.get(i, 0.0) + half_up(S.gamma * v))
        keys = sorted(have)
        return pa.table({"client_id": pa.array([client] * len(keys), pa.int32()), "coord": pa.array(keys, pa.int32()), "shift": pa.array([have[k] for k in keys], pa.float64())})

    return s.shifts.groupBy("client_id").cogroup(messages.groupBy("client_id")).applyInArrow(meet, "client_id int, coord int, shift double")


def compressor_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The mean relative squared error of random-k over the suppliers' mean feature vectors, beside its bound."""
    rows = nt.samples(spark, sf_dir).withColumn("client_id", F.split("sample_id", "\\|")[2].cast("long"))
    m = rows.groupBy("client_id").agg(F.count(F.lit(1)).alias("m"))
    v = nt.client_sums(rows, "f", 1).join(m, "client_id").select("client_id", "coord", F.round(F.col("value") / F.col("m"), 9).alias("value"))
    v = v.withColumn("sq", F.expr("sum(cast(round(value * value * 1000000000D) as bigint)) over (partition by client_id)").cast("double") / nt.UNIT)
    kept = nt.random_k(v, 0).withColumnRenamed("value", "sent")
    gap = F.coalesce("sent", F.lit(0.0)) - F.col("value")
    err = v.join(kept, ["client_id", "coord"], "left").groupBy("client_id").agg((nt.exact_sum(gap * gap) / F.any_value("sq")).alias("e"))
    return err.agg(F.round(nt.exact_sum(F.col("e")) / F.count(F.lit(1)), 6).alias("mean_error"), F.lit(D / S.k - 1).alias("omega"))


def dot_products(spark: SparkSession, sf_dir: str) -> DataFrame:
    margin = nt.dot(F.col("f"), nt.vector(START))
    return nt.samples(spark, sf_dir).groupBy("client_id").agg(F.round(nt.exact_sum(margin), 4).alias("margin_sum"), F.count(F.lit(1)).alias("n"))


def clip_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = nt.samples(spark, sf_dir).select("client_id", nt.norm(F.col("f")).alias("v"))
    scale = F.when(F.col("v") > S.clip, F.lit(S.clip) / F.col("v")).otherwise(1.0)
    return n.groupBy("client_id").agg(F.round(nt.exact_sum(scale), 4).alias("scale_sum"), F.count_if(F.col("v") > S.clip).alias("n_clipped"))


def logistic_grad(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _grads(spark, sf_dir).select("client_id", "sample_id", F.round(nt.norm(F.col("g")), 6).alias("grad_norm"))


def batch_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    data = nt.samples(spark, sf_dir)
    a, b = (nt.ranked(data, t).select("client_id", "sample_id") for t in (0, 1))
    count = lambda name, df: df.agg(F.lit(name).alias("part"), F.count(F.lit(1)).alias("n"))
    return count("both", a.intersect(b)).unionByName(count("first_only", a.exceptAll(b))).unionByName(count("either", a.union(b).distinct()))


def vector_long(spark: SparkSession, sf_dir: str) -> DataFrame:
    packed = nt.random_k(_noisy(spark, sf_dir), 0).groupBy("client_id").agg(F.array_sort(F.collect_list(F.struct("coord", "value"))).alias("z"))
    return packed.select("client_id", F.col("z")[0]["value"].alias("first_value"), F.size("z").cast("long").alias("n"))


def topk_shift_coords(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = nt.advance(spark, sf_dir, 3, True)[1].shifts
    best = s.withColumn("r", F.expr("row_number() over (partition by client_id order by abs(shift) desc, coord)")).filter("r <= 2")
    return best.select("client_id", "coord", "shift")


def grad_norm_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = _grads(spark, sf_dir).select("client_id", F.round(nt.norm(F.col("g")), 6).alias("v"))
    return n.groupBy("client_id").agg(
        F.round(F.avg("v"), 4).alias("mean_norm"), F.round(F.stddev_pop("v"), 4).alias("sd_norm"),
        F.round(F.percentile("v", 0.5), 4).alias("median_norm"), F.round(F.percentile("v", 0.9), 4).alias("p90_norm"),
    )


QUERIES = {
    f.__name__: f
    for f in (
        loss_at_point, full_gradient, clipped_gradient, minibatch_pick, noise_draws, randk_message, randk_pick, quantized_message, direct_round,
        ldp_sgd_round, shifted_round, two_round_direct, three_round_shifted, shift_update, shift_mismatch, server_mean, comm_bits, active_clients,
        svrg_estimate, svrg_refresh, saga_refresh, saga_estimate, drift_saga, drift_svrg, shifted_svrg_round, shifted_saga_round, ldp_svrg_round, max_row_norm, shift_cogroup, compressor_error, dot_products, clip_vectors, logistic_grad,
        batch_overlap, vector_long, topk_shift_coords, grad_norm_profile,
    )
}
