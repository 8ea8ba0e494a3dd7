"""The training loop on Spark against a plain loop, and its invariances."""

import numpy as np
import pytest

from hushgrad.fl import compress, losses, theory, train
from hushgrad.functions import digest

M, D, N = 24, 8, 3
LOSS = losses.LogisticNonconvex(0.05)


@pytest.fixture(scope="module")
def data():
    rng = np.random.default_rng(0)
    w = rng.normal(size=D)
    a = rng.normal(size=(N, M, D))
    a /= np.linalg.norm(a, axis=2, keepdims=True)
    return a, np.where(a @ w > 0, 1.0, -1.0)


@pytest.fixture(scope="module")
def samples(spark, data):
    a, y = data
    rows = [(c, s, a[c, s].tolist(), float(y[c, s])) for c in range(N) for s in range(M)]
    return spark.createDataFrame(rows, "client_id long, seq long, features array<double>, label double")


def runs():
    spec = theory.PrivacySpec(2.0, 1e-3)
    out = [train.Run(k, k, 7, 0.5, 0.5, M, D, spec, compress.RandomK(k=2), b=6) for k in train.METHODS]
    return [*out, train.Run("quantised", "direct_sgd", 7, 0.5, 0.5, M, D, spec, compress.RandomQuantizer(4), b=6)]


def sample_gradient(a, y, x, clip):
    """One sample's gradient, clipped, from the loss's definition: d/dx of log(1 + exp(-y a.x)) + lam * sum x^2 / (1 + x^2)."""
    g = -y * a / (1 + np.exp(y * (a @ x))) + LOSS.lam * 2 * x / (1 + x**2) ** 2
    size = np.sqrt(g @ g)
    return g * min(1, clip / size) if clip and size > 0 else g


def plain(run, a, y):
    """The same run, one sample after the other, from the methods' description; only draws are the library's."""
    kind, squeezed, shifted = train.METHODS[run.method]
    b = M if kind == "gd" else run.b
    p = b / M
    xs = [np.zeros(D)]
    w = xs[0]
    points = np.zeros((N, M, D))  # of each sample, at the first model
    s, s_all = np.zeros((N, D)), np.zeros(D)
    log_term, eps = np.log(1 / run.privacy.delta), run.privacy.eps
    ga, gb = (2 * run.clip, run.clip) if kind in ("svrg", "saga") else (run.clip, 0.0)
    sigma = np.sqrt((ga**2 / 4 + gb**2) * run.rounds * log_term) / (M * eps)
    omega = run.compressor.omega(D) if squeezed else 0.0
    gamma = np.sqrt((1 + 2 * omega) / (2 * (1 + omega) ** 3)) if shifted else 0.0
    for t in range(run.rounds):
        x, sent = xs[-1], np.zeros(D)
        grad = lambda i, j, z: sample_gradient(a[i, j], y[i, j], z, run.clip)
        for i in range(N):
            batch = [j for j in range(M) if b == M or digest.shuffled(np.array([j]), M, run.seed, i, t)[0] < b]
            assert len(batch) == b
            if kind in ("sgd", "gd"):
                v = sum(grad(i, j, x) for j in batch) / b
            elif kind == "svrg":
                v = sum(grad(i, j, x) - grad(i, j, w) for j in batch) / b + sum(grad(i, j, w) for j in range(M)) / M
            else:
                v = sum(grad(i, j, x) - grad(i, j, points[i, j]) for j in batch) / b + sum(grad(i, j, points[i, j]) for j in range(M)) / M
                for j in batch:
                    points[i, j] = x
            v = v + sigma * digest.philox(run.seed, i, t, 1).standard_normal(D)
            diff = v - s[i]
            rng = digest.philox(run.seed, i, t, 2)
            if not squeezed:
                out = diff
            elif isinstance(run.compressor, compress.RandomK):
                out = np.zeros(D)
                for c in rng.choice(D, run.compressor.k, replace=False):
                    out[c] = diff[c] * D / run.compressor.k
            else:
                size, levels = np.sqrt(diff @ diff), run.compressor.levels
                steps = np.abs(diff) / size * levels
                out = np.sign(diff) * (np.floor(steps) + (rng.random(D) < steps - np.floor(steps))) * size / levels
            s[i] = s[i] + gamma * out
            sent += out / N
        if kind == "svrg" and digest.uniform_value("coin", run.seed, t) < p:
            w = x
        xs.append(x - run.eta * (s_all + sent))
        s_all = s_all + gamma * sent
        assert np.allclose(s_all, s.mean(axis=0)) or not shifted
    return xs[-1]


def test_against_a_plain_loop_whatever_the_partitions(samples, data):
    want = {r.name: plain(r, *data) for r in runs()}
    for parts in (1, 5):
        x, trace = train.train(samples.repartition(parts).persist(), runs(), LOSS, eval_every=2)
        for k, v in want.items():
            assert x[k] == pytest.approx(v, abs=1e-9), k
    last = {r[0]: r for r in trace if r[3] == 7}
    assert last["direct_sgd"][4] == 7 * N * 2 and last["ldp_sgd"][4] == 7 * N * D
    assert last["direct_sgd"][7] == 7 * N * 6 and last["ldp_gd"][7] == 7 * N * M
    # snapshot: two batches a round, and all samples in the first round and after every coin that fell
    coins = 1 + sum(digest.uniform_value("coin", 1, t) < 6 / M for t in range(6))
    assert last["ldp_svrg"][7] == N * (7 * 2 * 6 + coins * M) and last["ldp_saga"][7] == N * (7 * 2 * 6 + M)
    names = [c.split()[0] for c in train.TRACE.split(", ")]
    drift = {r[0]: r[names.index("drift")] for r in trace if r[3] == 7}
    assert drift["shifted_svrg"] >= 0 and drift["shifted_saga"] > 0 and drift["direct_sgd"] is None
    assert all(r[names.index("payload")] > 0 for r in trace if r[3] == 7)


def test_a_run_alone_is_the_run_among_others(samples, data):
    """Batches fetched beforehand, full scans and shared jobs change nothing."""
    both = {r.name: r for r in runs()}
    x, _ = train.train(samples, [both["shifted_saga"]], LOSS, eval_every=3)
    assert x["shifted_saga"] == pytest.approx(plain(both["shifted_saga"], *data), abs=1e-9)
    one = train.Run("far", "shifted_svrg", 9, 0.5, 0.5, M, D, theory.PrivacySpec(2.0), compress.RandomK(k=2), b=1)
    x, _ = train.train(samples, [one], LOSS, eval_every=3)
    assert x["far"] == pytest.approx(plain(one, *data), abs=1e-9)


def test_saga_drift_is_the_mean_distance_to_the_points(samples, data):
    run = train.Run("s", "ldp_saga", 5, 0.5, None, M, D, b=6)
    x, trace = train.train(samples, [run], LOSS, eval_every=1)
    a, y = data
    points, now = np.zeros((N, M, D)), np.zeros(D)
    names = [c.split()[0] for c in train.TRACE.split(", ")]
    for t in range(5):
        assert trace[t][names.index("drift")] == pytest.approx(((now - points) ** 2).sum() / (N * M), abs=1e-12)
        picked = [[j for j in range(M) if run.sampled(i, np.array([j]), t)[0]] for i in range(N)]
        grad = lambda i, j, z: sample_gradient(a[i, j], y[i, j], z, None)
        v = sum(sum(grad(i, j, now) - grad(i, j, points[i, j]) for j in picked[i]) / 6 + sum(grad(i, j, points[i, j]) for j in range(M)) / M for i in range(N)) / N
        for i in range(N):
            points[i, picked[i]] = now
        now = now - 0.5 * v
    assert x["s"] == pytest.approx(now, abs=1e-10)


def test_schedules_and_first_references(spark, samples, data):
    a, y = data
    first = np.arange(N * D, dtype=float).reshape(N, D) / 50
    refs = spark.createDataFrame([(i, first[i].tolist()) for i in range(N)], "client_id long, values array<double>")
    eta, gamma = lambda t: 0.5 / (t + 1), lambda t: 0.3 + 0.1 * t
    run = train.Run("r", "shifted_gd", 3, eta, None, M, D, compressor=compress.RandomK(k=2), gamma=gamma)
    x, _ = train.train(samples, [run], LOSS, eval_every=1, references=refs)
    now, s = np.zeros(D), first.copy()
    for t in range(3):
        v, ref = np.zeros(D), s.mean(axis=0)
        for i in range(N):
            g = sum(sample_gradient(a[i, j], y[i, j], now, None) for j in range(M)) / M - s[i]
            out = np.zeros(D)
            for c in digest.philox(1, i, t, 2).choice(D, 2, replace=False):
                out[c] = g[c] * D / 2
            s[i] += gamma(t) * out
            v += out / N
        now = now - eta(t) * (ref + v)
    assert x["r"] == pytest.approx(now, abs=1e-10)


def test_order_of_a_runs_stages(samples):
    spec = theory.PrivacySpec(2.0)
    wrong = dict(order=("estimate", "compress", "perturb"))
    base = ("direct_sgd", 2, 0.5, 0.5, M, D, spec, compress.RandomK(k=2))
    with pytest.raises(compress.OrderError):
        train.train(samples, [train.Run("w", *base, b=6, **wrong)], LOSS, eval_every=1)
    x, trace = train.train(samples, [train.Run("w", *base, b=6, unsafe_order=True, **wrong), train.Run("ok", *base, b=6)], LOSS, eval_every=1)
    assert {r[0]: r[2] for r in trace} == {"w": None, "ok": 2.0}  # the wrong order isn't called private
    # noise after compression isn't scaled by d/k
    run = train.Run("w", *base, b=6, unsafe_order=True, **wrong)
    from hushgrad.fl import estimators

    sums = estimators.Sums(np.zeros(D))
    at, late, _, _ = train.client_step(run, 0, 0, sums, np.zeros(D), None)
    same, early, _, _ = train.client_step(train.Run("ok", *base, b=6), 0, 0, sums, np.zeros(D), None)
    assert (at == same).all() and early == pytest.approx(late * D / 2)


def test_eps_beyond_the_formula_warns(samples):
    with pytest.warns(UserWarning, match="beyond the condition"):
        train.train(samples, [train.Run("x", "direct_sgd", 2, 0.5, 0.5, M, D, theory.PrivacySpec(50.0), b=2)], LOSS, eval_every=1)


def test_sums_of_clipped_gradients_from_norms():
    """Clip factors from norms give what clipped gradients of rows give, for both losses, and measures of several models agree."""
    rng = np.random.default_rng(7)
    for loss, y in ((losses.LogisticNonconvex(0.2), np.sign(rng.normal(size=50))), (losses.ShallowNet(5, 4, 3), rng.integers(0, 3, 50).astype(float))):
        a = rng.normal(size=(50, 5))
        models = rng.normal(size=(3, loss.dimension(5)))
        for clip in (None, 0.5, 3.0):
            got = loss.measured(a, y, models, clip)
            for k, x in enumerate(models):
                g = loss.gradients(a, y, x)
                f = losses.clip_factors(np.sqrt((g * g).sum(axis=1)), clip)
                total, cut = loss.summed(a, y, x, clip)
                assert total == pytest.approx(f @ g) and cut == (f < 1).sum()
                assert got[0][k] == pytest.approx(loss.values(a, y, x).sum()) and got[1][k] == loss.correct(a, y, x).sum()
                assert got[2][k] == pytest.approx(g.sum(axis=0)) and got[3][k] == cut and got[4][k] == pytest.approx(f @ g)


def test_full_batch_sgd_is_gd_and_no_compression_is_plain(samples, data):
    a, y = data
    none = dict(clip=None, m=M, d=D, privacy=None)
    one = [
        train.Run("a", "shifted_sgd", 4, 0.5, compressor=compress.Identity(), b=M, gamma=0.7, **none),
        train.Run("b", "ldp_gd", 4, 0.5, **none),
        train.Run("c", "shifted_sgd", 4, 0.5, compressor=compress.RandomK(k=2), gamma=0.0, b=6, **none),
        train.Run("d", "direct_sgd", 4, 0.5, compressor=compress.RandomK(k=2), b=6, **none),
    ]
    x, _ = train.train(samples, one, LOSS, eval_every=2)
    assert x["a"] == pytest.approx(x["b"], abs=1e-12) and x["c"] == pytest.approx(x["d"], abs=1e-12)


def test_more_noise_for_less_eps(samples):
    r = [train.Run(str(e), "direct_sgd", 4, 0.5, 0.5, M, D, theory.PrivacySpec(e), b=6) for e in (1.0, 2.0)]
    assert r[0].sigma == pytest.approx(2 * r[1].sigma)


def test_unequal_clients_weigh_by_their_samples(spark, data):
    """Full gradients of clients of 24, 12 and 6 samples give the gradient of all their samples."""
    a, y = data
    sizes = {0: 24, 1: 12, 2: 6}
    rows = [(c, s, a[c, s].tolist(), float(y[c, s])) for c, m in sizes.items() for s in range(m)]
    df = spark.createDataFrame(rows, "client_id long, seq long, features array<double>, label double")
    x, _ = train.train(df, [train.Run("u", "ldp_gd", 2, 0.5, None, M, D, sizes=sizes)], LOSS, eval_every=1)
    want = LOSS.start(D)
    fa, fy = np.concatenate([a[c, :m] for c, m in sizes.items()]), np.concatenate([y[c, :m] for c, m in sizes.items()])
    for _ in range(2):
        want = want - 0.5 * losses.summed(LOSS, fa, fy, want, None)[0] / len(fy)
    assert x["u"] == pytest.approx(want, abs=1e-12)
    small = train.Run("v", "direct_sgd", 2, 0.5, 0.5, M, D, theory.PrivacySpec(1.0), b=6, sizes=sizes)
    assert small.sigma_of(2) == pytest.approx(4 * small.sigma_of(0))


def test_a_small_round_takes_few_tasks(spark, monkeypatch):
    """The messages of a small round are made in one task, whatever the session's partitions; many vectors take all of them."""
    made = []
    settle = train.storage.settle
    monkeypatch.setattr(train.storage, "settle", lambda df, name: made.append(df.rdd.getNumPartitions()) or settle(df, name))
    samples = spark.createDataFrame([(c, i, [1.0, float(i % 3)], 1.0) for c in range(2) for i in range(8)], "client_id long, seq long, features array<double>, label double")
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "7")
    try:
        train.train(samples, [train.Run("r", "shifted_sgd", 2, 0.1, 0.5, 8, 2, b=2)], LOSS, eval_every=1)
        assert made == [1, 1] and train._parts(spark, 10**6, 123) == 7
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
