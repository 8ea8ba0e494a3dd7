"""The comparison experiments: sweeps, views by round and by bit, and rankings."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hushgrad.fl import compress, losses, theory, train, workloads

#: Measures that a run must have to be compared.
LEAST = 10


def theory_batch(method: str, w: workloads.Workload, n: int, m: int, eps: float | None, L: float) -> tuple[int | None, float | None]:
    """(b, p) by the formulas of the shifted methods: SGD's batch balances noise and sampling, SVRG's and SAGA's follow m."""
    kind = train.METHODS[method][0]
    if eps is None or kind == "gd":
        return None, None
    omega = compress.RandomK(k=w.k).omega(w.d) if train.METHODS[method][1] else 0.0
    q = theory.preset(kind, n, m, w.d, L, w.clip, omega, theory.PrivacySpec(eps, workloads.DELTA))
    return q.b, q.p


def runs(w: workloads.Workload, sizes: dict[int, int], methods, eps, steps, rounds: int, seeds=(1,), ratio: int = 20, L: float | None = None) -> list[train.Run]:  # noqa: ANN001
    """All runs of a sweep.  Uncompressed runs get rounds/ratio rounds, so that all send as many coordinates.
    With L, batches are those of the theory; without, the defaults of the estimators."""
    out = []
    m = max(sizes.values())
    for method in methods:
        long = train.METHODS[method][1]
        for e in eps:
            b, p = theory_batch(method, w, len(sizes), m, e, L) if L else (None, None)
            spec = theory.PrivacySpec(e, workloads.DELTA) if e is not None else None
            for step in steps:
                for seed in seeds:
                    name = f"{method}|{e}|{step}|{seed}"
                    t = rounds if long else max(1, rounds // ratio)
                    out.append(train.Run(name, method, t, step, w.clip, m, w.d, spec, compress.RandomK(k=w.k), seed=seed, b=b, p=p, sizes=sizes))
    return out


def smoothness(w: workloads.Workload, samples: DataFrame) -> float:
    """L from the data for the logistic loss (one scan); 1 for the network, whose constant isn't known."""
    return w.loss.smoothness(losses.max_sq_norm(samples)) if hasattr(w.loss, "smoothness") else 1.0


def advance(samples: DataFrame, test: DataFrame, w: workloads.Workload, grid: list[train.Run], measures: int = LEAST) -> list[tuple]:
    """Trains the grid with `measures` measures or more for every run: long and short runs by their own intervals."""
    out = []
    for length in sorted({r.rounds for r in grid}):
        some = [r for r in grid if r.rounds == length]
        out += train.train(samples, some, w.loss, eval_every=max(1, length // (measures - 1)), test=test)[1]
    return out


def sweep(spark: SparkSession, name: str, sf_dir: str, methods=workloads.COMPARED, eps=None, steps=workloads.STEPS, rounds: int = 200, seeds=(1,), ratio: int = 20) -> DataFrame:  # noqa: ANN001
    """The trace of every run of the grid, with the theory's batches.  ratio 1 gives all methods the same number of rounds."""
    w = workloads.WORKLOADS[name]
    samples, test, sizes = workloads.prepare(spark, name, sf_dir)
    grid = runs(w, sizes, methods, eps if eps is not None else w.eps, steps, rounds, seeds, ratio=ratio, L=smoothness(w, samples))
    trace = advance(samples, test, w, grid)
    workloads.release(samples, test)
    return spark.createDataFrame(trace, train.TRACE)


def tuned(trace: DataFrame, criterion: str = "mean_grad_sq") -> DataFrame:
    """The best stepsize of each method and eps, by the criterion at the last measured round.
    Choosing it looks at the data again and again and isn't covered by the privacy budget."""
    last = trace.groupBy("run").agg(F.max_by(F.struct("method", "eps", "round", "coords_sent", "loss", "accuracy", "grad_sq", "mean_grad_sq"), "round").alias("z"))
    rows = last.select("run", F.split("run", "\\|")[2].cast("double").alias("step"), "z.*")
    r = rows.withColumn("rank", F.expr(f"row_number() over (partition by method, eps order by {criterion}, step)"))
    return r.filter("rank = 1").drop("rank")


def per_round(trace: DataFrame) -> DataFrame:
    return trace.select("run", "method", "eps", "round", "grad_sq", "mean_grad_sq", "loss", "accuracy")


def per_bit(trace: DataFrame) -> DataFrame:
    return trace.select("run", "method", "eps", "value_bits", (F.col("value_bits") + F.col("index_bits")).alias("bits"), "grad_sq", "mean_grad_sq", "loss", "accuracy")


def first_reach(trace: DataFrame, target: float) -> DataFrame:
    """Rounds, bits and gradients to the first measure with a squared gradient norm of at most target."""
    hit = trace.filter(F.col("grad_sq") <= target)
    return hit.groupBy("run", "method", "eps").agg(F.min("round").alias("rounds"), F.min("value_bits").alias("bits"), F.min("grads").alias("grads"))


def compare(trace: DataFrame, least: int = LEAST) -> DataFrame:
    """Methods side by side at their best steps; runs of fewer than `least` measures are refused."""
    short = trace.groupBy("run").agg(F.count(F.lit(1)).alias("c")).filter(F.col("c") < least).select("run").first()
    if short is not None:
        raise ValueError(f"{short['run']} has fewer than {least} measures")
    return tuned(trace).select("method", "eps", "step", "round", "coords_sent", "mean_grad_sq", "loss", "accuracy")
