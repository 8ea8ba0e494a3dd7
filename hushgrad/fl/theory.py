"""Costs, presets and guarantees as plain functions.

Symbols: n clients with m samples each, dimension d, minibatch b, compressor
variance omega, T rounds, privacy (eps, delta), gradient bound G, smoothness L.
Values under an order symbol take their hidden constant as an argument, 1 by
default; they are orders of magnitude, not predictions.
"""

from __future__ import annotations

import math
import warnings
from dataclasses import dataclass


@dataclass(frozen=True)
class PrivacySpec:
    eps: float
    delta: float = 1e-3

    def __post_init__(self) -> None:
        if not (self.eps > 0 and 0 < self.delta < 1):
            raise ValueError("eps must be positive and delta between 0 and 1")

    @property
    def log_term(self) -> float:
        return math.log(1 / self.delta)


@dataclass(frozen=True)
class Constants:
    """Bounds of an estimator's two parts (ga, gb), its variance (c1, c2), and the recursion of its drift.

    c3_per_eta2 is the third constant over the squared stepsize, so that the
    step condition needs no stepsize.
    """

    ga: float
    gb: float
    c1: float
    c2: float
    c3_per_eta2: float
    c4: float
    theta: float

    @property
    def noise_bound(self) -> float:
        return self.ga**2 / 4 + self.gb**2


def constants(kind: str, G: float, L: float, m: int, b: int, p: float | None = None) -> Constants:
    """Constants of the local estimators gd, sgd, svrg and saga."""
    if kind == "gd":
        b = m
    if kind in ("gd", "sgd"):
        return Constants(G, 0.0, 0.0, (m - b) * G * G / (m * b), 0.0, 0.0, 1.0)
    if kind == "svrg":
        return Constants(2 * G, G, L * L / b, 0.0, 2 * (1 - p) / p, 1.0, p / 2)
    if kind == "saga":
        return Constants(2 * G, G, L * L / b, 0.0, 2 * (m - b) / b, 1.0, b / (2 * m))
    raise ValueError(kind)


def noise_variance(k: Constants, T: int, m: int, spec: PrivacySpec, c: float = 1.0) -> float:
    """Variance of the Gaussian perturbation for T rounds.  c is unknown in theory; see accountant.spent."""
    return c * k.noise_bound * T * spec.log_term / (m * m * spec.eps**2)


def in_regime(spec: PrivacySpec, b: int, T: int, m: int, c2: float = 1.0, strict: bool = False) -> bool:
    """Whether eps is small enough for the noise formula to hold; warns (or raises) if not."""
    ok = spec.eps < c2 * b * b * T / (m * m)
    if not ok:
        text = f"eps {spec.eps} is not below {c2 * b * b * T / (m * m):.4g}; the noise formula's condition fails"
        if strict:
            raise ValueError(text)
        warnings.warn(text, stacklevel=2)
    return ok


def shift_step(omega: float) -> float:
    return math.sqrt((1 + 2 * omega) / (2 * (1 + omega) ** 3))


def tau(omega: float, n: int) -> float:
    return (1 + omega) ** 1.5 / math.sqrt(n)


def rounds_unit(n: int, m: int, d: int, L: float, G: float, omega: float, spec: PrivacySpec) -> float:
    """The unit in which all round counts of the shifted methods are stated."""
    return math.sqrt(n * L) * m * spec.eps / (G * math.sqrt((1 + omega) * d * spec.log_term))


def alpha(k: Constants, beta: float, omega: float, L: float) -> float:
    return 3 * beta * k.c1 / (2 * (1 + omega) * k.theta * L * L)


def max_step(k: Constants, omega: float, n: int, L: float, beta: float) -> float:
    """The largest stepsize of the general condition."""
    al = alpha(k, beta, omega, L)
    a = 1 + 2 * al * k.c4 + 4 * beta * (1 + omega)
    return min(1 / ((a + 2 * al * k.c3_per_eta2) * L), math.sqrt(beta * n) / (math.sqrt(a) * (1 + omega) * L))


def potential(gap: float, al: float, L: float, drift: float, beta: float, mismatch: float) -> float:
    """Initial potential: function gap, scaled drift, and mean squared distance of gradients to references."""
    return gap + al * L * drift + beta / L * mismatch


def bound_at(T: int, k: Constants, phi0: float, eta: float, beta: float, omega: float, L: float, m: int, d: int, spec: PrivacySpec, c: float = 1.0) -> float:
    """Mean squared gradient norm guaranteed after T rounds."""
    noise = c * k.noise_bound * d * T * spec.log_term / (m * m * spec.eps**2)
    return 2 * phi0 / (eta * T) + 3 * beta / ((1 + omega) * L * eta) * (k.c2 + noise)


def rounds(k: Constants, phi0: float, beta: float, omega: float, L: float, m: int, d: int, spec: PrivacySpec, c: float = 1.0) -> float:
    """The number of rounds that balances the bound."""
    unit = c * d * k.noise_bound * spec.log_term
    return max(m * spec.eps * math.sqrt(2 * (1 + omega) * L * phi0) / math.sqrt(3 * beta * unit), k.c2 * m * m * spec.eps**2 / unit)


def accuracy(k: Constants, eta: float, beta: float, omega: float, L: float, m: int, d: int, spec: PrivacySpec, order: float = 1.0) -> float:
    first = math.sqrt(beta * d * k.noise_bound * spec.log_term) / (eta * m * spec.eps * math.sqrt((1 + omega) * L))
    return order * max(first, beta * k.c2 / ((1 + omega) * L * eta))


def direct_bounds(n: int, m: int, d: int, L: float, G: float, omega: float, spec: PrivacySpec, order: float = 1.0) -> tuple[float, float]:
    """(rounds, accuracy) of direct compression."""
    t = rounds_unit(n, m, d, L, G, omega, spec) + m * m * spec.eps**2 / (d * spec.log_term)
    u = G * math.sqrt((1 + omega) * L * d * spec.log_term) / (math.sqrt(n) * m * spec.eps)
    return order * t, order * u


@dataclass(frozen=True)
class Preset:
    kind: str
    eta: float
    beta: float
    gamma: float
    b: int
    p: float | None
    rounds: float
    accuracy: float


def preset(kind: str, n: int, m: int, d: int, L: float, G: float, omega: float, spec: PrivacySpec, mode: str = "corollary", order: float = 1.0) -> Preset:
    """Parameters of a shifted method.  mode 'safe' also obeys the general step condition."""
    t = tau(omega, n)
    unit = rounds_unit(n, m, d, L, G, omega, spec)
    _, plain = direct_bounds(n, m, d, L, G, omega, spec)
    mu = min(1.0, math.sqrt(n / (1 + omega) ** 3))
    p = None
    if kind in ("gd", "sgd"):
        beta = t / (2 * (1 + omega))
        eta = 1 / ((1 + 2 * t) * L)
        b = m if kind == "gd" else max(1, min(m, math.floor(m * spec.eps * G * math.sqrt(beta) / math.sqrt((1 + omega) * L * d * spec.log_term))))
        T, u = unit * (1 + math.sqrt(t)), plain * (1 + math.sqrt(t))
    elif kind == "svrg":
        b = max(1, math.floor(m ** (2 / 3) / 4))
        p = b / m
        beta = p ** (4 / 3) * b ** (2 / 3) * (1 + omega) ** 2 * mu * mu / n
        eta = p ** (2 / 3) * b ** (1 / 3) * mu / (2 * L)
        T, u = unit * max(1.0, t), plain
    elif kind == "saga":
        b = max(1, min(m, math.floor(3 * m ** (2 / 3))))
        beta = (1 + omega) ** 2 * mu * mu / (3 * n)
        eta = mu / (3 * L)
        T, u = unit * max(1.0, t), plain
    else:
        raise ValueError(kind)
    if mode == "safe":
        eta = min(eta, max_step(constants(kind, G, L, m, b, p), omega, n, L, beta))
    return Preset(kind, eta, beta, shift_step(omega), b, p, order * T, order * u)


def communication(n: int, d: int, T: float, omega: float) -> float:
    """Coordinates sent in T rounds."""
    return n * d * T / (1 + omega)


def cost_rows(n: int, m: int, d: int, omega: float, spec: PrivacySpec, sigma2: float = 1.0) -> list[tuple]:
    """(method, setting, accuracy, communication, derived) of the published methods and of the shifted ones.

    Rows marked derived multiply the stated rounds by the stated cost of a round.
    """
    lam, e = spec.log_term, spec.eps
    single = math.sqrt(d * lam) / (m * e)
    nodes = math.sqrt(d * lam) / (math.sqrt(n) * m * e)
    squeezed = math.sqrt((1 + omega) * d * lam) / (math.sqrt(n) * m * e)
    k = rounds_unit(n, m, d, 1.0, 1.0, omega, spec)
    t = tau(omega, n)
    tail = n * m * m * e * e / ((1 + omega) * lam)
    root = m * e * math.sqrt(d) / math.sqrt(lam)
    rows = [
        ("single_random_permutation_sgd", "one node", math.sqrt(d * math.log(m / spec.delta) * lam) / (m * e), None, False),
        ("single_private_sgd", "one node", single, None, False),
        ("single_recursive_momentum", "one node", single, None, False),
        ("distributed_recursive_momentum", "uncompressed, central", math.sqrt(d * lam) / (n * m * e), n * n * root, False),
        ("local_svrg_or_recursive_path", "uncompressed", nodes, n**1.5 * root, False),
        ("quantised_private_sgd", "direct", (sigma2 / n + 1 / m) ** (2 / 3) * (d * lam) ** (1 / 3) / (m * e) ** (2 / 3), (1 + n / (m * sigma2)) * m * m * e * e / (d * lam), False),
        ("sparsified_decentralised_sgd", "direct", nodes, n**3.5 * root / (1 + omega) ** 1.5 + tail, False),
        ("direct_compression_sgd", "direct", squeezed, n**1.5 * root / (1 + omega) ** 1.5 + tail, False),
        ("shifted_sgd_or_gd", "shifted", squeezed * (1 + math.sqrt(t)), communication(n, d, k * (1 + math.sqrt(t)), omega), True),
        ("shifted_svrg_or_saga", "shifted", squeezed, communication(n, d, k * max(1.0, t), omega), True),
    ]
    return rows


def gradient_cost_rows(n: int, m: int, d: int, L: float, G: float, omega: float, b: int, spec: PrivacySpec) -> list[tuple[str, float]]:
    k, t = rounds_unit(n, m, d, L, G, omega, spec), tau(omega, n)
    return [("gd", k * (1 + math.sqrt(t)) * m), ("sgd", k * (1 + math.sqrt(t)) * b), ("svrg_saga", k * (1 + t) * m ** (2 / 3))]
