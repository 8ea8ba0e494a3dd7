"""Registered queries of costs, presets, the accountant, the network, and short trainings."""

from __future__ import annotations

import math
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hushgrad.fl import accountant, compress, experiments, losses, theory, train, workloads
from hushgrad.functions import digest
from hushgrad.sources.tables import load

SPEC = theory.PrivacySpec(1.0, 1e-3)
OMEGA = 19.5
CLIENTS = (1, 10, 100)


def _of_sizes(spark: SparkSession, sf_dir: str, rows_of, schema: str) -> DataFrame:  # noqa: ANN001
    """rows_of(m) for the least and the largest number of lines that a supplier has: m of the smallest and of the largest natural client."""
    per = load(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.count(F.lit(1)).cast("int").alias("m"))
    sizes = per.agg(F.array(F.min("m"), F.max("m")).alias("m")).select(F.explode(F.array_distinct("m")).alias("m")).filter("m is not null")
    kinds = {"string": pa.string(), "int": pa.int32(), "double": pa.float64(), "boolean": pa.bool_()}
    fields = [(c.split()[0], kinds[c.split()[1]]) for c in schema.split(", ")]

    def go(batches):  # noqa: ANN001, ANN202
        for batch in batches:
            rows = [r for m in batch.column(0).to_pylist() for r in rows_of(m)]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, (_, k) in zip(zip(*rows, strict=True), fields, strict=True)], [name for name, _ in fields])

    return sizes.mapInArrow(go, schema)


def _table(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def constants_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Constants of every estimator for clients of the lineitem table's size."""
    m = load(spark, sf_dir, "lineitem").agg(F.floor(F.count(F.lit(1)) / 10).alias("m"))
    rows = _table(spark, [("sgd", 128.0), ("gd", None), ("svrg", None), ("saga", None)], "kind string, fixed double")
    j = rows.crossJoin(F.broadcast(m))
    b = F.when(F.col("kind") == "sgd", F.col("fixed")).when(F.col("kind") == "gd", F.col("m")).when(F.col("kind") == "svrg", F.floor(F.pow("m", F.lit(2 / 3)) / 4)).otherwise(
        F.least(F.floor(3 * F.pow("m", F.lit(2 / 3))), F.col("m"))
    )
    j = j.withColumn("b", b.cast("double")).withColumn("p", F.col("b") / F.col("m"))
    reduced = F.col("kind").isin("svrg", "saga")
    return j.select(
        "kind", "m", "b",
        F.when(reduced, 1.0).otherwise(0.5).alias("ga"), F.when(reduced, 0.5).otherwise(0.0).alias("gb"),
        F.round(F.when(reduced, 1.0 / F.col("b")).otherwise(0.0), 9).alias("c1"),
        F.round(F.when(reduced, 0.0).otherwise((F.col("m") - F.col("b")) * 0.25 / (F.col("m") * F.col("b"))), 9).alias("c2"),
        F.round(F.when(F.col("kind") == "svrg", 2 * (1 - F.col("p")) / F.col("p")).when(F.col("kind") == "saga", 2 * (F.col("m") - F.col("b")) / F.col("b")).otherwise(0.0), 6).alias("c3_per_eta2"),
        F.when(reduced, 1.0).otherwise(0.0).alias("c4"),
        F.round(F.when(F.col("kind") == "svrg", F.col("p") / 2).when(F.col("kind") == "saga", F.col("b") / (2 * F.col("m"))).otherwise(1.0), 9).alias("theta"),
    )


def noise_variance_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The noise of the clients with the lines of the smallest and of the largest supplier."""

    def rows(m: int) -> list[tuple]:
        out = []
        for kind in ("sgd", "svrg", "saga"):
            for eps in (1.0, 5.0, 10.0):
                for rounds in (100, 400):
                    k = theory.constants(kind, 0.5, 1.0, m, 100, 0.1)
                    out.append((kind, m, eps, rounds, round(theory.noise_variance(k, rounds, m, theory.PrivacySpec(eps)), 9)))
        return out

    return _of_sizes(spark, sf_dir, rows, "kind string, m int, eps double, rounds int, variance double")


def preset_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The presets for 1, 10 and 100 clients with the lines of the smallest and of the largest supplier."""

    def rows(m: int) -> list[tuple]:
        out = []
        for kind in ("gd", "sgd", "svrg", "saga"):
            for n in CLIENTS:
                p = theory.preset(kind, n, m, 123, 1.0, 0.5, OMEGA, SPEC)
                out.append((kind, n, m, round(p.eta, 9), round(p.beta, 9), round(p.gamma, 9), p.b, round(p.rounds, 5), round(p.accuracy, 7)))
        return out

    return _of_sizes(spark, sf_dir, rows, "kind string, n int, m int, eta double, beta double, gamma double, b int, rounds double, accuracy double")


def cost_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The costs for 1, 10 and 100 clients with the lines of the smallest and of the largest supplier."""
    rows = lambda m: [(n, m, *[round(x, 5) if isinstance(x, float) else x for x in r]) for n in CLIENTS for r in theory.cost_rows(n, m, 123, OMEGA, SPEC)]
    return _of_sizes(spark, sf_dir, rows, "n int, m int, method string, setting string, accuracy double, communication double, derived boolean")


def gradient_cost_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The gradients for 1, 10 and 100 clients with the lines of the smallest and of the largest supplier."""
    rows = lambda m: [(n, m, k, round(v, 3)) for n in CLIENTS for k, v in theory.gradient_cost_rows(n, m, 123, 1.0, 0.5, OMEGA, 128, SPEC)]
    return _of_sizes(spark, sf_dir, rows, "n int, m int, method string, gradients double")


def m_dependence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rounds of direct and of shifted compression as the clients' data grows: squared against linear.  A client has the
    lines of the smallest or of the largest supplier, or of 10, 100 or 1000 such."""

    def rows(m: int) -> list[tuple]:
        out = []
        for k in (m, 10 * m, 100 * m, 1000 * m):
            direct, _ = theory.direct_bounds(10, k, 123, 1.0, 0.5, OMEGA, SPEC)
            out.append((k, round(direct, 3), round(theory.preset("svrg", 10, k, 123, 1.0, 0.5, OMEGA, SPEC).rounds, 3)))
        return out

    return _of_sizes(spark, sf_dir, rows, "m int, direct_rounds double, shifted_rounds double")


def privacy_spent(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The formula's eps beside what the accountant says the noise spends (no amplification claimed), for clients with the
    lines of the smallest and of the largest supplier."""

    def rows(m: int) -> list[tuple]:
        out = []
        for kind in ("sgd", "svrg", "saga"):
            for eps in (1.0, 5.0, 10.0):
                k = theory.constants(kind, 0.5, 1.0, m, 128, 128 / m)
                sigma = math.sqrt(theory.noise_variance(k, 400, m, theory.PrivacySpec(eps)))
                out.append((kind, m, eps, round(sigma, 9), round(accountant.spent(sigma, 400, accountant.sensitivity(k, m, 128), 1e-3), 6)))
        return out

    return _of_sizes(spark, sf_dir, rows, "kind string, m int, eps double, sigma double, spent double")


NET = losses.ShallowNet(64, 64, 10)


def _net_model() -> np.ndarray:
    """Digest-normal weights, without constants, of the whole 64-64-10 network."""
    x = np.zeros(NET.dimension())
    w1, _, w2, _ = NET.parts(x)
    w1[...] = [[digest.normal_value("w1", h, i) for i in range(NET.n_in)] for h in range(NET.hidden)]
    w2[...] = [[digest.normal_value("w2", o, h) for h in range(NET.hidden)] for o in range(NET.n_out)]
    return x


def _net(spark: SparkSession, sf_dir: str, what, schema: str) -> DataFrame:  # noqa: ANN001
    """what(ids, features, labels, model) over batches of the whole embeddings."""
    x = _net_model()

    def go(batches):  # noqa: ANN001, ANN202
        for batch in batches:
            if batch.num_rows:
                a = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(batch.num_rows, -1)
                yield pa.RecordBatch.from_arrays(what(batch.column(0), a, batch.column(2).to_numpy().astype(np.float64), x), [c.split()[0] for c in schema.split(", ")])

    return load(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label").mapInArrow(go, schema)


def net_forward(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _net(spark, sf_dir, lambda ids, a, y, x: [ids, pa.array(NET.values(a, y, x))], "vec_id long, loss double")
    return rows.select("vec_id", F.round("loss", 6).alias("loss"))


def net_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _net(spark, sf_dir, lambda ids, a, y, x: [pa.array(NET.correct(a, y, x))], "ok boolean")
    return rows.agg(F.count_if("ok").alias("right"), F.count(F.lit(1)).alias("n"))


def _net_sums(spark: SparkSession, sf_dir: str, clip: float | None) -> DataFrame:
    """(coord, grad, n_clipped): the mean of (clipped) gradients in all 4810 coordinates; a task sends one vector for a batch."""

    def sums(ids, a, y, x):  # noqa: ANN001, ANN202
        g, cut = losses.summed(NET, a, y, x, clip)
        return [pa.array([len(y)], pa.int64()), pa.array([cut], pa.int64()), pa.array([g.tolist()], pa.list_(pa.float64()))]

    rows = _net(spark, sf_dir, sums, "n long, cut long, g array<double>").select("n", "cut", F.posexplode("g").alias("coord", "v"))
    per = rows.groupBy("coord").agg((F.sum("v") / F.sum("n")).alias("grad"), F.sum("cut").alias("n_clipped"))
    return per.select("coord", F.round("grad", 6).alias("grad"), "n_clipped")


def net_gradient(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _net_sums(spark, sf_dir, None).drop("n_clipped")


def net_clipped_gradient(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _net_sums(spark, sf_dir, 1.0)


def _jobs(w: workloads.Workload, sizes: dict[int, int], methods: tuple[str, ...], eps: tuple[float, ...], rounds: int) -> list[train.Run]:
    m = max(sizes.values())
    return [
        train.Run(f"{k}|{e}", k, rounds, 0.1, w.clip, m, w.d, theory.PrivacySpec(e, workloads.DELTA), compress.RandomK(k=w.k), sizes=sizes) for k in methods for e in eps
    ]


def _short(name: str, methods: tuple[str, ...], rounds: int = 10, prepare=None, what: str = ""):  # noqa: ANN001
    """Some rounds of the methods on a workload at its least and largest eps, all in the same jobs, with a run without
    privacy.  They show that everything runs; `experiments.py` compares."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        w = workloads.WORKLOADS[name]
        samples, test, sizes = prepare(spark, sf_dir) if prepare else workloads.prepare(spark, name, sf_dir)
        jobs = _jobs(w, sizes, methods, (w.eps[0], w.eps[-1]), rounds)
        first = jobs[0]
        jobs.append(replace(first, name="not_private", privacy=None))
        if name == "tab_logistic":
            # direct compression by quantising instead of picking, and by picking without a server's reference
            jobs.append(replace(first, name="quantised_direct", method="direct_sgd", compressor=compress.RandomQuantizer(4)))
            jobs.append(replace(first, name="sparsified_direct", method="direct_sgd"))
        _, trace = train.train(samples, jobs, w.loss, eval_every=max(1, rounds // 2), test=test)
        workloads.release(samples, test)
        return spark.createDataFrame(trace, train.TRACE)

    run.__name__ = f"train_{what or name}"
    return run


def stepsize_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The five compared methods over all stepsizes at the largest eps, uncompressed ones for a twentieth of the rounds, with
    the best of each.  `experiments.sweep` takes all eps."""
    return experiments.compare(experiments.sweep(spark, "doc_logistic", sf_dir, eps=(10.0,), rounds=180))


TRAINED = [_short("tab_logistic", tuple(train.METHODS))] + [_short(n, workloads.COMPARED) for n in ("doc_logistic", "doc_quality", "vec_network", "vec_raw")]
TRAINED += [
    _short("wide_network", ("direct_sgd", "shifted_sgd"), 2),
    _short("tab_logistic", ("direct_sgd", "shifted_sgd", "shifted_svrg"), 5, workloads.prepare_natural, "natural_clients"),
    _short("tab_logistic", ("ldp_sgd", "ldp_gd"), 5, workloads.prepare_single, "single_node"),
]

QUERIES = {
    f.__name__: f
    for f in (
        constants_table, noise_variance_table, preset_table, cost_table, gradient_cost_table, m_dependence, privacy_spent, net_forward, net_accuracy,
        net_gradient, net_clipped_gradient, stepsize_sweep, *TRAINED,
    )
}


def _net_sql() -> str:
    """The network in long form: one row for each vector and unit."""
    u = "(CAST('0x' || substr(md5(concat_ws('|', {}, {}, {}, {})), 1, 13) AS BIGINT) / 4503599627370496.0)"
    normal = lambda name, a, b: f"round(sqrt(-2.0 * ln(1.0 - {u.format(chr(39) + 'radius' + chr(39), chr(39) + name + chr(39), a, b)})) * cos({2 * math.pi!r} * {u.format(chr(39) + 'angle' + chr(39), chr(39) + name + chr(39), a, b)}), 9)"
    return f"""WITH w1 AS (SELECT h, i, {normal('w1', 'h', 'i')} AS w FROM (SELECT unnest(range({NET.hidden})) AS h) CROSS JOIN (SELECT unnest(range({NET.n_in})) AS i)),
  w2 AS (SELECT o, h, {normal('w2', 'o', 'h')} AS w FROM (SELECT unnest(range({NET.n_out})) AS o) CROSS JOIN (SELECT unnest(range({NET.hidden})) AS h)),
  a AS (SELECT vec_id, label, unnest(range({NET.n_in})) AS i, unnest(embedding)::DOUBLE AS x FROM embeddings),
  hid AS (SELECT vec_id, label, h, 1.0 / (1.0 + exp(-sum(x * w))) AS v FROM a JOIN w1 USING (i) GROUP BY ALL),
  z AS (SELECT vec_id, label, o, sum(v * w) AS z FROM hid JOIN w2 USING (h) GROUP BY ALL),
  lp AS (SELECT vec_id, label, o, z, z - ln(sum(exp(z)) OVER (PARTITION BY vec_id)) AS lp FROM z)"""


def _net_gradient_sql(clip: float | None) -> str:
    """All four blocks of the gradient: first weights, first constants, second weights, second constants."""
    h, i, o = NET.hidden, NET.n_in, NET.n_out
    scale = "1.0" if clip is None else f"least(1.0, {clip!r} / nrm)"
    return _net_sql() + f""", d AS (SELECT vec_id, o, exp(lp) - (CASE WHEN o = label THEN 1.0 ELSE 0.0 END) AS delta FROM lp),
  back AS (SELECT vec_id, h, sum(delta * w) * any_value(v) * (1.0 - any_value(v)) AS bk, any_value(v) AS v FROM d JOIN w2 USING (o) JOIN hid USING (vec_id, h) GROUP BY vec_id, h),
  sizes AS (SELECT vec_id, sqrt(b2 * (a2 + 1) + d2 * (v2 + 1)) AS nrm FROM (SELECT vec_id, sum(bk * bk) AS b2, sum(v * v) AS v2 FROM back GROUP BY 1)
    JOIN (SELECT vec_id, sum(x * x) AS a2 FROM a GROUP BY 1) USING (vec_id) JOIN (SELECT vec_id, sum(delta * delta) AS d2 FROM d GROUP BY 1) USING (vec_id)),
  f AS (SELECT vec_id, {scale} AS f, nrm FROM sizes),
  g AS (SELECT h * {i} + i AS coord, sum(f * bk * x) AS s FROM back JOIN a USING (vec_id) JOIN f USING (vec_id) GROUP BY ALL
    UNION ALL SELECT {h * i} + h, sum(f * bk) FROM back JOIN f USING (vec_id) GROUP BY ALL
    UNION ALL SELECT {h * i + h} + o * {h} + h, sum(f * delta * v) FROM d JOIN back USING (vec_id) JOIN f USING (vec_id) GROUP BY ALL
    UNION ALL SELECT {h * i + h + o * h} + o, sum(f * delta) FROM d JOIN f USING (vec_id) GROUP BY ALL),
  n AS (SELECT count(*) AS n, count(*) FILTER ({"nrm > " + repr(clip) if clip else "false"}) AS c FROM f)
  SELECT coord::INTEGER AS coord, round(s / n, 6) AS grad{", c AS n_clipped" if clip else ""} FROM g, n"""


#: The numbers of lines of the suppliers with the fewest and the most.
_SIZES = "ms AS (SELECT min(m)::INTEGER AS m FROM (SELECT count(*) AS m FROM lineitem GROUP BY l_suppkey) UNION SELECT max(m)::INTEGER FROM (SELECT count(*) AS m FROM lineitem GROUP BY l_suppkey))"


def _cost_sql() -> str:
    """The two cost tables' rows, from the published orders."""
    lam = "ln(1000.0)"
    return f"""WITH {_SIZES}, g AS (SELECT n, m, {lam} AS l, 123.0 AS d, 20.5 AS q FROM (VALUES (1), (10), (100)) a(n), ms),
  k AS (SELECT *, sqrt(n) * m / sqrt(q * d * l) AS k, pow(q, 1.5) / sqrt(n) AS tau, m * sqrt(d) / sqrt(l) AS root, n * pow(m, 2.0) / (q * l) AS tail, sqrt(q * d * l) / (sqrt(n) * m) AS sq FROM g),
  r AS (SELECT n, m, 'single_random_permutation_sgd' AS method, 'one node' AS setting, sqrt(d * ln(m / 0.001) * l) / m AS acc, NULL::DOUBLE AS comm, false AS derived FROM k
    UNION ALL SELECT n, m, 'single_private_sgd', 'one node', sqrt(d * l) / m, NULL, false FROM k
    UNION ALL SELECT n, m, 'single_recursive_momentum', 'one node', sqrt(d * l) / m, NULL, false FROM k
    UNION ALL SELECT n, m, 'distributed_recursive_momentum', 'uncompressed, central', sqrt(d * l) / (n * m), n * n * root, false FROM k
    UNION ALL SELECT n, m, 'local_svrg_or_recursive_path', 'uncompressed', sqrt(d * l) / (sqrt(n) * m), pow(n, 1.5) * root, false FROM k
    UNION ALL SELECT n, m, 'quantised_private_sgd', 'direct', pow(1.0 / n + 1.0 / m, 2.0 / 3) * pow(d * l, 1.0 / 3) / pow(m, 2.0 / 3), (1 + n / m::DOUBLE) * pow(m, 2.0) / (d * l), false FROM k
    UNION ALL SELECT n, m, 'sparsified_decentralised_sgd', 'direct', sqrt(d * l) / (sqrt(n) * m), pow(n, 3.5) * root / pow(q, 1.5) + tail, false FROM k
    UNION ALL SELECT n, m, 'direct_compression_sgd', 'direct', sq, pow(n, 1.5) * root / pow(q, 1.5) + tail, false FROM k
    UNION ALL SELECT n, m, 'shifted_sgd_or_gd', 'shifted', sq * (1 + sqrt(tau)), n * d * k * (1 + sqrt(tau)) / q, true FROM k
    UNION ALL SELECT n, m, 'shifted_svrg_or_saga', 'shifted', sq, n * d * k * greatest(1.0, tau) / q, true FROM k)
  SELECT n, m, method, setting, round(acc, 5) AS accuracy, round(comm, 5) AS communication, derived FROM r"""


def _spent_sql() -> str:
    """Renyi composition of 400 Gaussian rounds at the best of the orders."""
    return f"""WITH {_SIZES}, o AS (SELECT 1 + x / 100.0::DOUBLE AS a FROM (SELECT unnest(range(1, 400)) AS x) UNION ALL SELECT 5 + x / 4.0::DOUBLE FROM (SELECT unnest(range(0, 240)) AS x) UNION ALL SELECT unnest(range(65, 512, 8))::DOUBLE),
  k AS (SELECT kind, eps, CASE kind WHEN 'sgd' THEN 0.5 ELSE 1.0 END::DOUBLE AS ga, CASE kind WHEN 'sgd' THEN 0.0 ELSE 0.5 END::DOUBLE AS gb
    FROM (VALUES ('sgd'), ('svrg'), ('saga')) t(kind), (VALUES (1.0::DOUBLE), (5.0::DOUBLE), (10.0::DOUBLE)) e(eps)),
  s AS (SELECT kind, m, eps, (ga * ga / 4 + gb * gb) * 400 * ln(1000.0) / (m * m * eps * eps) AS var, 2 * (ga / 128 + gb / m) AS sens FROM k, ms)
  SELECT kind, m, eps, round(sqrt(any_value(var)), 9) AS sigma, round(min(a * 400 * sens * sens / (2 * var) + ln(1000.0) / (a - 1)), 6) AS spent FROM s, o GROUP BY kind, m, eps"""


SQL = {
    "constants_table": """WITH m AS (SELECT CAST(floor(count(*) / 10) AS BIGINT) AS m FROM lineitem),
      k AS (SELECT kind, m, CASE kind WHEN 'sgd' THEN 128.0 WHEN 'gd' THEN m WHEN 'svrg' THEN floor(pow(m, 0.6666666666666666) / 4) ELSE least(floor(3 * pow(m, 0.6666666666666666)), m) END::DOUBLE AS b
        FROM (VALUES ('sgd'), ('gd'), ('svrg'), ('saga')) t(kind), m)
      SELECT kind, m, b, (CASE WHEN kind IN ('svrg', 'saga') THEN 1.0 ELSE 0.5 END)::DOUBLE AS ga, (CASE WHEN kind IN ('svrg', 'saga') THEN 0.5 ELSE 0.0 END)::DOUBLE AS gb,
        round(CASE WHEN kind IN ('svrg', 'saga') THEN 1.0 / b ELSE 0.0 END, 9) AS c1, round(CASE WHEN kind IN ('svrg', 'saga') THEN 0.0 ELSE (m - b) * 0.25 / (m * b) END, 9) AS c2,
        round(CASE kind WHEN 'svrg' THEN 2 * (1 - b / m) / (b / m) WHEN 'saga' THEN 2 * (m - b) / b ELSE 0.0 END, 6) AS c3_per_eta2,
        (CASE WHEN kind IN ('svrg', 'saga') THEN 1.0 ELSE 0.0 END)::DOUBLE AS c4, round(CASE kind WHEN 'svrg' THEN b / m / 2 WHEN 'saga' THEN b / (2 * m) ELSE 1.0 END, 9) AS theta FROM k""",
    "noise_variance_table": f"""WITH {_SIZES} SELECT kind, m, eps, rounds, round((CASE kind WHEN 'sgd' THEN 0.25 / 4 ELSE 1.0 / 4 + 0.25 END) * rounds * ln(1000.0) / (m * m * eps * eps), 9) AS variance
      FROM (VALUES ('sgd'), ('svrg'), ('saga')) k(kind), (VALUES (1.0::DOUBLE), (5.0::DOUBLE), (10.0::DOUBLE)) e(eps), (VALUES (100), (400)) r(rounds), ms""",
    "gradient_cost_table": f"""WITH {_SIZES}, g AS (SELECT n, m, sqrt(n) * m / (0.5 * sqrt(20.5 * 123 * ln(1000.0))) AS k, pow(20.5, 1.5) / sqrt(n) AS tau FROM (VALUES (1), (10), (100)) a(n), ms)
      SELECT n, m, 'gd' AS method, round(k * (1 + sqrt(tau)) * m, 3) AS gradients FROM g UNION ALL SELECT n, m, 'sgd', round(k * (1 + sqrt(tau)) * 128, 3) FROM g
      UNION ALL SELECT n, m, 'svrg_saga', round(k * (1 + tau) * pow(m, 2.0 / 3), 3) FROM g""",
    "preset_table": f"""WITH {_SIZES}, g AS (SELECT n, m, sqrt(n) * m / (0.5 * sqrt(20.5 * 123 * ln(1000.0))) AS k, pow(20.5, 1.5) / sqrt(n) AS tau, 0.5 * sqrt(20.5 * 123 * ln(1000.0)) / (sqrt(n) * m) AS plain,
        least(1.0, sqrt(n / pow(20.5, 3))) AS mu, sqrt(40.0 / (2 * pow(20.5, 3))) AS gamma FROM (VALUES (1), (10), (100)) a(n), ms),
      s AS (SELECT *, tau / 41.0 AS beta FROM g), v AS (SELECT *, greatest(1, floor(pow(m, 2.0 / 3) / 4)) AS b FROM g)
      SELECT kind, n, m, round(1 / (1 + 2 * tau), 9) AS eta, round(beta, 9) AS beta, round(gamma, 9) AS gamma,
        CAST(CASE kind WHEN 'gd' THEN m ELSE greatest(1, least(m, floor(m * 0.5 * sqrt(beta) / sqrt(20.5 * 123 * ln(1000.0))))) END AS INTEGER) AS b,
        round(k * (1 + sqrt(tau)), 5) AS rounds, round(plain * (1 + sqrt(tau)), 7) AS accuracy FROM s, (VALUES ('gd'), ('sgd')) t(kind)
      UNION ALL SELECT 'svrg', n, m, round(pow(b / m, 2.0 / 3) * pow(b, 1.0 / 3) * mu / 2, 9), round(pow(b / m, 4.0 / 3) * pow(b, 2.0 / 3) * 20.5 * 20.5 * mu * mu / n, 9), round(gamma, 9), CAST(b AS INTEGER), round(k * greatest(1.0, tau), 5), round(plain, 7) FROM v
      UNION ALL SELECT 'saga', n, m, round(mu / 3, 9), round(20.5 * 20.5 * mu * mu / (3 * n), 9), round(gamma, 9), CAST(greatest(1, least(m, floor(3 * pow(m, 2.0 / 3)))) AS INTEGER), round(k * greatest(1.0, tau), 5), round(plain, 7) FROM g""",
    "m_dependence": f"""WITH {_SIZES} SELECT k AS m, round(sqrt(10.0) * m / (0.5 * sqrt(20.5 * 123 * ln(1000.0))) + m * m / (123 * ln(1000.0)), 3) AS direct_rounds,
      round(sqrt(10.0) * m / (0.5 * sqrt(20.5 * 123 * ln(1000.0))) * greatest(1.0, pow(20.5, 1.5) / sqrt(10.0)), 3) AS shifted_rounds
      FROM (SELECT CAST(m * f AS INTEGER) AS k FROM ms, (VALUES (1), (10), (100), (1000)) x(f)), LATERAL (SELECT k::DOUBLE AS m)""",
    "net_forward": _net_sql() + " SELECT vec_id, round(-lp, 6) AS loss FROM lp WHERE o = label",
    "net_accuracy": _net_sql() + " SELECT count(*) FILTER (best = label) AS right, count(*) AS n FROM (SELECT vec_id, label, arg_max(o, z) AS best FROM lp GROUP BY 1, 2)",
    "net_gradient": _net_gradient_sql(None),
    "net_clipped_gradient": _net_gradient_sql(1.0),
    "cost_table": _cost_sql(),
    "privacy_spent": _spent_sql(),
}
