"""Formulas, compressors, losses and draws against worked values, enumeration and identities."""

import itertools
import math
import warnings

import numpy as np
import pytest

from hushgrad.fl import accountant, compress, estimators, losses, theory, train
from hushgrad.functions import digest

SPEC = theory.PrivacySpec(1.0, 1e-3)


@pytest.mark.parametrize(("omega", "gamma"), [(0, 0.707107), (19.5, 0.0481819), (19.041667, 0.0492697)])
def test_shift_step(omega, gamma):
    assert theory.shift_step(omega) == pytest.approx(gamma, rel=1e-5)


def test_dimensions_and_kept_coordinates():
    for n_in, d, k in ((784, 50890, 2544), (64, 4810, 240)):
        assert losses.ShallowNet(n_in).dimension() == d and compress.RandomK().kept(d) == k
    assert compress.RandomK().kept(123) == 6


def test_noise_scales():
    one = lambda kind, T=100, m=1000, e=1.0: theory.noise_variance(theory.constants(kind, 1.0, 1.0, m, 50, 0.05), T, m, theory.PrivacySpec(e))
    assert one("svrg") == pytest.approx(8 * one("sgd")) and one("saga") == pytest.approx(8 * one("sgd"))
    assert one("sgd", e=0.5) == pytest.approx(4 * one("sgd"))
    assert one("sgd", T=400) == pytest.approx(4 * one("sgd"))
    assert one("sgd", m=2000) == pytest.approx(one("sgd") / 4)


def test_regime_warns_or_raises():
    with warnings.catch_warnings():
        warnings.simplefilter("error")
        assert theory.in_regime(SPEC, 500, 100, 1000)
    with pytest.warns(UserWarning):
        assert not theory.in_regime(SPEC, 5, 1, 1000)
    with pytest.raises(ValueError):
        theory.in_regime(SPEC, 5, 1, 1000, strict=True)


def test_presets_obey_the_general_step_condition():
    broken = set()
    for kind in ("sgd", "svrg", "saga"):
        for n, omega in itertools.product((1, 2, 3, 5, 10, 100), (0.0, 1.0, 4.0, 19.5)):
            p = theory.preset(kind, n, 4800, 123, 1.0, 0.5, omega, SPEC)
            k = theory.constants(kind, 0.5, 1.0, 4800, p.b, p.p)
            if p.eta > theory.max_step(k, omega, n, 1.0, p.beta) * (1 + 1e-9):
                broken.add((kind, n, omega))
            safe = theory.preset(kind, n, 4800, 123, 1.0, 0.5, omega, SPEC, mode="safe")
            assert safe.eta <= theory.max_step(k, omega, n, 1.0, safe.beta) * (1 + 1e-9)
    assert {b[0] for b in broken} <= {"svrg"} and ("svrg", 10, 19.5) not in broken


def test_direct_rounds_grow_with_the_square_and_shifted_ones_linearly():
    far = [theory.direct_bounds(10, m, 123, 1.0, 0.5, 19.5, SPEC)[0] for m in (10**6, 10**7)]
    assert far[1] / far[0] == pytest.approx(100, rel=0.05)
    t = [theory.preset("svrg", 10, m, 123, 1.0, 0.5, 19.5, SPEC).rounds for m in (10**6, 10**7)]
    assert t[1] / t[0] == pytest.approx(10)


def test_direct_communication_row_is_rounds_times_round_cost():
    n, m, d, w = 10, 1000, 123, 19.5
    rows = {r[0]: r for r in theory.cost_rows(n, m, d, w, SPEC)}
    rounds = theory.direct_bounds(n, m, d, 1.0, 1.0, w, SPEC)[0]
    assert rows["direct_compression_sgd"][3] == pytest.approx(theory.communication(n, d, rounds, w))


def test_random_k_over_all_masks():
    v = np.array([1.0, 2.0, 3.0, 4.0])
    sent = [np.where(np.arange(4) == i, v * 4, 0.0) for i in range(4)]
    assert np.mean(sent, axis=0) == pytest.approx(v)
    assert np.mean([((s - v) ** 2).sum() for s in sent]) / (v @ v) == pytest.approx(compress.RandomK(k=1).omega(4)) == pytest.approx(3)


def test_random_k_draws_every_mask_alike():
    c, seen = compress.RandomK(k=2), {}
    for i in range(3000):
        at, v = c.apply(np.ones(4), digest.philox(1, i))
        assert len(at) == 2 and (v == 2).all()
        seen[tuple(at)] = seen.get(tuple(at), 0) + 1
    assert len(seen) == 6 and min(seen.values()) > 400


def test_quantizer_over_all_roundings():
    c, v = compress.RandomQuantizer(2), np.array([0.3, -0.5, 0.1])
    norm = np.linalg.norm(v)
    x = np.abs(v) / norm * 2
    low, up = np.floor(x), x - np.floor(x)
    mean, err = np.zeros(3), 0.0
    for bits in itertools.product((0, 1), repeat=3):
        p = np.prod([u if b else 1 - u for b, u in zip(bits, up, strict=True)])
        q = np.sign(v) * (low + bits) * norm / 2
        mean += p * q
        err += p * ((q - v) ** 2).sum()
    assert mean == pytest.approx(v) and err / norm**2 <= c.omega(3) + 1e-12
    assert c.apply(np.zeros(3), digest.philox(1))[1].tolist() == [0, 0, 0]


def test_order_of_stages():
    compress.check_order(("estimate", "perturb", "compress"))
    with pytest.raises(compress.OrderError):
        compress.check_order(("estimate", "compress", "perturb"))
    compress.check_order(("estimate", "compress", "perturb"), unsafe=True)


def test_permuted_batches():
    for m, b in ((5, 2), (37, 10), (1000, 128)):
        seq = np.arange(m)
        assert sorted(digest.shuffled(seq, m, 1, 2, 3)) == list(range(m))
        hits = np.zeros(m)
        for t in range(600):
            got = digest.shuffled(seq, m, 1, 2, t) < b
            assert got.sum() == b
            hits += got
        assert abs(hits / 600 - b / m).max() < 0.12


@pytest.mark.parametrize("loss", [losses.LogisticNonconvex(0.2), losses.ShallowNet(5, 4, 3)])
def test_gradients_against_differences(loss):
    rng = np.random.default_rng(0)
    net = isinstance(loss, losses.ShallowNet)
    a = rng.normal(size=(6, 5))
    y = rng.integers(0, 3, 6).astype(float) if net else np.sign(rng.normal(size=6))
    d = loss.dimension(5)
    x = rng.normal(size=d) * 0.5
    g = loss.gradients(a, y, x)
    for j in range(d):
        e = np.zeros(d)
        e[j] = 1e-6
        assert (loss.values(a, y, x + e) - loss.values(a, y, x - e)) / 2e-6 == pytest.approx(g[:, j], abs=1e-6)


def test_logistic_at_the_origin_and_far_away():
    loss = losses.LogisticNonconvex(0.2)
    a, y = np.array([[1.0, 2.0]]), np.array([-1.0])
    assert loss.values(a, y, np.zeros(2)) == pytest.approx(math.log(2))
    assert loss.gradients(a, y, np.zeros(2))[0] == pytest.approx(-y[0] * a[0] / 2)
    assert np.isfinite(loss.gradients(a * 1e4, y, np.ones(2))).all() and np.isfinite(loss.values(a * 1e4, y, np.ones(2))).all()


def test_clip():
    n = np.array([0.0, 0.25, 0.5, 1.0])
    assert losses.clip_factors(n, 0.5).tolist() == [1, 1, 1, 0.5]


def test_accountant_moves_the_right_way():
    s = accountant.spent
    assert s(1.0, 10, 0.1, 1e-3) < s(1.0, 20, 0.1, 1e-3) and s(2.0, 10, 0.1, 1e-3) < s(1.0, 10, 0.1, 1e-3)
    assert s(0.0, 1, 0.1, 1e-3) == math.inf and s(1e6, 10, 0.1, 1e-3) < 0.05


def small_problem():
    rng = np.random.default_rng(4)
    return losses.LogisticNonconvex(0.2), rng.normal(size=(5, 3)), np.sign(rng.normal(size=5)), [rng.normal(size=3) for _ in range(3)]


def gradients_of(loss, a, y, x):
    return np.stack([loss.gradients(a[j : j + 1], y[j : j + 1], x)[0] for j in range(len(y))])


@pytest.mark.parametrize("kind", ["sgd", "gd", "svrg", "saga"])
def test_estimators_over_all_batches(kind):
    """Unbiased, and the variance is below c1 * drift + c2 of the constants with G and L of this problem."""
    loss, a, y, (w, other, x) = small_problem()
    m, b = 5, 5 if kind == "gd" else 2
    full = gradients_of(loss, a, y, x).mean(axis=0)
    last = np.array([0, 1, 0, 1, 0])
    points = {"snapshot": w, 0: w, 1: other}
    memory = None
    if kind == "saga":
        memory = np.mean([gradients_of(loss, a, y, points[r])[j] for j, r in enumerate(last)], axis=0)
    mean, var = estimators.check_unbiased(estimators.ESTIMATORS[kind], loss, a, y, x, b, points, last, memory)
    assert mean == pytest.approx(full)
    L = loss.smoothness((a * a).sum(axis=1).max())
    # the bound holds for any G above the gradients met
    G = max(np.sqrt((gradients_of(loss, a, y, z) ** 2).sum(axis=1).max()) for z in (w, other, x))
    k = theory.constants(kind, G, L, m, b, b / m)
    drift = {"svrg": ((x - w) ** 2).sum(), "saga": np.mean([((x - points[r]) ** 2).sum() for r in last])}.get(kind, 0.0)
    assert var <= k.c1 * drift + k.c2 + 1e-12
    assert (var > 1e-6) == (kind != "gd")


def test_minibatch_variance_is_that_of_drawing_without_replacement():
    """(m - b) / (b (m - 1)) times the samples' variance, exactly, over all batches."""
    loss, a, y, (_, _, x) = small_problem()
    g = gradients_of(loss, a, y, x)
    _, var = estimators.check_unbiased(estimators.ESTIMATORS["sgd"], loss, a, y, x, 2, {})
    spread = ((g - g.mean(axis=0)) ** 2).sum(axis=1).mean()
    assert var == pytest.approx((5 - 2) / (2 * (5 - 1)) * spread)


def test_reduced_estimators_are_exact_where_their_points_are_the_model():
    loss, a, y, (_, _, x) = small_problem()
    full = gradients_of(loss, a, y, x).mean(axis=0)
    for kind in ("svrg", "saga"):
        mean, var = estimators.check_unbiased(estimators.ESTIMATORS[kind], loss, a, y, x, 2, {"snapshot": x, 0: x})
        assert mean == pytest.approx(full) and var == pytest.approx(0, abs=1e-20)


def test_scalar_table_of_the_logistic_loss():
    """With numbers instead of points the data part is SAGA's; without penalty the two storages agree."""
    loss, a, y, (w, _, x) = small_problem()
    loss = losses.LogisticNonconvex(0.0)
    t = estimators.ScalarTable(loss, a, y, w)
    points = np.tile(w, (5, 1))
    for batch, z in ((np.array([0, 3]), x), (np.array([3, 4]), x * 0.5), (np.array([1, 3]), -x)):
        g = lambda j, v: loss.gradients(a[j : j + 1], y[j : j + 1], v)[0]
        want = sum(g(j, z) - g(j, points[j]) for j in batch) / 2 + sum(g(j, points[j]) for j in range(5)) / 5
        assert t.estimate(z, batch) == pytest.approx(want)
        points[batch] = z


def test_a_new_estimator_needs_no_change_elsewhere(monkeypatch):
    class Heavy(estimators.Estimator):
        kind = "heavy"

        def batch(self, m):
            return m // 2

        def constants(self, G, L, m, b, p):
            return theory.Constants(G, 0.0, 0.0, (m - b) * G * G / (m * b), 0.0, 0.0, 1.0)

    monkeypatch.setitem(estimators.ESTIMATORS, "heavy", Heavy())
    monkeypatch.setitem(train.METHODS, "shifted_heavy", ("heavy", True, True))
    run = train.Run("h", "shifted_heavy", 5, 0.1, 0.5, 40, 3, SPEC)
    assert run.batch == 20 and run.sigma == pytest.approx(train.Run("s", "shifted_sgd", 5, 0.1, 0.5, 40, 3, SPEC, b=20).sigma)


def test_step_potential_bound_rounds_and_accuracy_by_worked_values():
    """n 4, m 100, d 10, omega 3, L 2, G 1, eps 1, delta e^-2 (log term 2), snapshot with b 10 and p 0.1, beta 0.5."""
    spec = theory.PrivacySpec(1.0, math.exp(-2))
    k = theory.constants("svrg", 1.0, 2.0, 100, 10, 0.1)
    assert (k.ga, k.gb, k.c1, k.c2, k.c4) == (2.0, 1.0, 0.4, 0.0, 1.0)
    assert k.c3_per_eta2 == pytest.approx(18) and k.theta == pytest.approx(0.05)
    # alpha: 3 * 0.5 * 0.4 / (2 * 4 * 0.05 * 4)
    assert theory.alpha(k, 0.5, 3.0, 2.0) == pytest.approx(0.375)
    # first bound: 1 + 2 * .375 + 4 * .5 * 4 = 9.75, with 2 * .375 * 18 = 13.5: 1 / (23.25 * 2); second: sqrt(2) / (sqrt(9.75) * 4 * 2)
    assert theory.max_step(k, 3.0, 4, 2.0, 0.5) == pytest.approx(min(1 / 46.5, math.sqrt(2) / (math.sqrt(9.75) * 8)))
    phi = theory.potential(0.7, 0.375, 2.0, 0.2, 0.5, 1.2)
    assert phi == pytest.approx(0.7 + 0.375 * 2 * 0.2 + 0.25 * 1.2) == pytest.approx(1.15)
    # noise term: 2 (= 4/4 + 1) * 10 * 50 * 2 / 10^4 = 0.2
    assert theory.bound_at(50, k, phi, 0.02, 0.5, 3.0, 2.0, 100, 10, spec) == pytest.approx(2 * 1.15 / (0.02 * 50) + 1.5 / (4 * 2 * 0.02) * 0.2)
    # rounds: 100 * sqrt(2 * 4 * 2 * 1.15) / sqrt(3 * .5 * 40)
    assert theory.rounds(k, phi, 0.5, 3.0, 2.0, 100, 10, spec) == pytest.approx(100 * math.sqrt(18.4) / math.sqrt(60))
    assert theory.accuracy(k, 0.02, 0.5, 3.0, 2.0, 100, 10, spec) == pytest.approx(math.sqrt(0.5 * 40) / (0.02 * 100 * math.sqrt(8)))
    sgd = theory.constants("sgd", 1.0, 2.0, 100, 10)
    # c2 = 90 / 1000; the second term of each maximum
    assert sgd.c2 == pytest.approx(0.09)
    assert theory.rounds(sgd, 1e-9, 0.5, 3.0, 2.0, 100, 10, spec) == pytest.approx(0.09 * 10**4 / (0.25 * 20))
    assert theory.accuracy(sgd, 0.02, 50.0, 3.0, 2.0, 100, 10, spec) == pytest.approx(max(math.sqrt(50 * 0.25 * 20) / (2 * math.sqrt(8)), 50 * 0.09 / (4 * 2 * 0.02)))


def test_the_bound_is_least_near_the_stated_rounds():
    """Where the first term of the maximum rules, the stated rounds balance the bound's two parts in T."""
    k = theory.constants("svrg", 0.5, 1.0, 1000, 25, 0.025)
    args = (0.001, 0.5, 3.0, 1.0, 1000, 123, SPEC)
    T = theory.rounds(k, 1.0, 0.5, 3.0, 1.0, 1000, 123, SPEC)
    at = [theory.bound_at(int(T * f), k, 1.0, *args) for f in (0.5, 1.0, 2.0)]
    assert at[1] < at[0] and at[1] < at[2]


def test_preset_probabilities():
    """p and p^(2/3) b^(1/3) of the snapshot preset are at most a quarter."""
    for m in (2, 8, 100, 4800, 10**6):
        p = theory.preset("svrg", 10, m, 123, 1.0, 0.5, 19.5, SPEC)
        assert p.p <= 0.5 and (m < 8 or (p.p <= 0.25 and p.p ** (2 / 3) * p.b ** (1 / 3) <= 0.25 + 1e-12))


def test_private_runs_need_a_clip_bound():
    with pytest.raises(ValueError):
        train.Run("x", "direct_sgd", 5, 0.1, None, 10, 3, SPEC)
