"""Views of a trace, on a hand-made one."""

import pytest

from hushgrad.fl import experiments, train, workloads


@pytest.fixture(scope="module")
def trace(spark):
    def row(method, step, t, grad, mean):
        return (f"{method}|1.0|{step}|1", method, 1.0, t, 60 * t, 1920 * t, 180 * t, 10 * t, 0, grad, mean, grad + 1, 0.5, 0.1, grad, None, 1.0, 5)

    rows = [row("direct_sgd", s, t, g, g) for s, gs in ((0.1, (1.0, 0.4)), (0.3, (1.0, 0.2))) for t, g in zip((0, 4), gs, strict=True)]
    rows += [row("shifted_sgd", 0.1, t, g, g) for t, g in ((0, 1.0), (4, 0.3))]
    return spark.createDataFrame(rows, train.TRACE)


def test_best_step_and_ranking(trace):
    best = {r["method"]: (r["step"], r["mean_grad_sq"]) for r in experiments.compare(trace, 2).collect()}
    assert best == {"direct_sgd": (0.3, 0.2), "shifted_sgd": (0.1, 0.3)}


def test_first_reach(trace):
    hit = {r["run"]: (r["rounds"], r["bits"], r["grads"]) for r in experiments.first_reach(trace, 0.3).collect()}
    assert hit == {"direct_sgd|1.0|0.3|1": (4, 7680, 40), "shifted_sgd|1.0|0.1|1": (4, 7680, 40)}


def test_views(trace):
    assert experiments.per_bit(trace).filter("bits <> value_bits").count() == 3
    assert experiments.per_round(trace).count() == 6


@pytest.mark.parametrize("name", ["tab_logistic", "doc_logistic", "doc_quality", "vec_network"])
def test_workloads(spark, sf_dir, name):
    """Every row takes part: a fifth for testing, the rest dealt to ten clients of sizes at most one apart."""
    w = workloads.WORKLOADS[name]
    samples, test, sizes = workloads.prepare(spark, name, sf_dir)
    source = {"tab_logistic": "lineitem", "doc_logistic": "documents", "doc_quality": "labels", "vec_network": "embeddings"}[name]
    n = spark.read.parquet(f"{sf_dir}/{source}.parquet").count()
    assert samples.count() + test.count() == n == sum(sizes.values()) + test.count()
    assert len(sizes) == 10 and max(sizes.values()) - min(sizes.values()) <= 1
    rows = samples.select("client_id", "seq").collect()
    assert sorted((r[0], r[1]) for r in rows) == [(c, s) for c in sorted(sizes) for s in range(sizes[c])]
    first = samples.first()
    assert w.loss.dimension(len(first["features"])) == w.d
    workloads.release(samples, test)


def test_a_clients_samples_lie_in_many_tasks(spark, sf_dir):
    from pyspark.sql import functions as F

    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "24")
    try:
        samples, test, sizes = workloads.prepare(spark, "tab_logistic", sf_dir)
        where = samples.withColumn("p", F.spark_partition_id()).groupBy("client_id").agg(F.count_distinct("p").alias("n")).collect()
        assert samples.rdd.getNumPartitions() > len(sizes) and min(r["n"] for r in where) > 1
        workloads.release(samples, test)
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def test_tab_logistic_vectors(spark, sf_dir):
    """Unit rows of indicators with an intercept, and labels that a linear model of the planted teacher mostly gets right."""
    import numpy as np

    from hushgrad.functions import digest

    samples, test, _ = workloads.prepare(spark, "tab_logistic", sf_dir)
    rows = samples.select("features", "label").toPandas()
    a, y = np.stack(rows["features"]), rows["label"].to_numpy()
    assert np.allclose((a * a).sum(axis=1), 1) and (a[:, -1] > 0).all() and ((a > 0).sum(axis=1) == 14).all()
    z = a @ np.array([digest.normal_value("teacher", j) for j in range(workloads.WIDTH)])
    assert 0.93 < ((z > np.median(z)) == (y > 0)).mean() < 0.97
    workloads.release(samples, test)


def test_theory_batches():
    w = workloads.WORKLOADS["tab_logistic"]
    sizes = dict.fromkeys(range(10), 4800)
    got = {r.method: (r.batch, r.refresh) for r in experiments.runs(w, sizes, workloads.COMPARED, [1.0], [0.1], 200, L=0.65)}
    svrg = int(4800 ** (2 / 3) / 4)
    assert got["shifted_svrg"] == got["ldp_svrg"] == (svrg, svrg / 4800)
    assert 1 <= got["shifted_sgd"][0] <= 4800 and got["shifted_sgd"][0] != got["ldp_sgd"][0]


def test_compare_refuses_short_runs(trace):
    with pytest.raises(ValueError, match="fewer than 10"):
        experiments.compare(trace)


def test_natural_clients_lie_in_one_task(spark, sf_dir):
    """A client's samples lie side by side, numbered without gaps, as indicators of one byte; nothing stays on disk."""
    import os

    from pyspark.sql import functions as F

    from hushgrad.fl import storage

    root = storage.folder(spark).removeprefix("file:") + "/hushgrad-fl"
    before = set(os.listdir(root)) if os.path.isdir(root) else set()
    samples, test, sizes = workloads.prepare_natural(spark, sf_dir)
    n = spark.read.parquet(f"{sf_dir}/lineitem.parquet").count()
    assert samples.count() + test.count() == n == sum(sizes.values()) + test.count()
    rows = samples.withColumn("p", F.spark_partition_id()).select("client_id", "seq", "p", F.length("hot").alias("w")).collect()
    assert sorted((r[0], r[1]) for r in rows) == [(c, s) for c in sorted(sizes) for s in range(sizes[c])]
    assert len({(r["client_id"], r["p"]) for r in rows}) == len(sizes) and {r["w"] for r in rows} == {14}
    workloads.release(samples, test)
    assert set(os.listdir(root)) <= before
