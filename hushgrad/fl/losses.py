"""The two sample losses, over batches of rows.

`gradients` gives one gradient for each row, for tests and small batches.
`summed` gives the sum of clipped gradients without them: clip factors come from
norms (of rows and margins, or of layers), and one matrix product adds up what
is left.  `measured` gives all measures of several models over the same rows.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


def clip_factors(norms: np.ndarray, bound: float | None) -> np.ndarray:
    if bound is None:
        return np.ones_like(norms)
    return np.minimum(1.0, bound / np.maximum(norms, 1e-300))


@dataclass(frozen=True)
class LogisticNonconvex:
    """log(1 + exp(-label * <features, x>)) plus a bounded non-convex penalty of each coordinate."""

    lam: float = 0.2

    def dimension(self, n_features: int) -> int:
        return n_features

    def start(self, d: int) -> np.ndarray:
        return np.zeros(d)

    def values(self, a: np.ndarray, y: np.ndarray, x: np.ndarray) -> np.ndarray:
        return np.logaddexp(0.0, -y * (a @ x)) + self.lam * float(np.sum(x * x / (1 + x * x)))

    def gradients(self, a: np.ndarray, y: np.ndarray, x: np.ndarray) -> np.ndarray:
        """(rows, d)."""
        z = np.clip(-y * (a @ x), -700, 700)
        w = -y / (1 + np.exp(-z))
        return w[:, None] * a + 2 * self.lam * x / (1 + x * x) ** 2

    def correct(self, a: np.ndarray, y: np.ndarray, x: np.ndarray) -> np.ndarray:
        return np.where(a @ x >= 0, 1.0, -1.0) == y

    def smoothness(self, max_sq_norm: float) -> float:
        return max_sq_norm / 4 + 2 * self.lam

    def _slope(self, x: np.ndarray) -> np.ndarray:
        return 2 * self.lam * x / (1 + x * x) ** 2

    def summed(self, a: np.ndarray, y: np.ndarray, x: np.ndarray, clip: float | None) -> tuple[np.ndarray, int]:
        """(sum of clipped gradients, number clipped).  A gradient is w*a + s, with s the same for all rows."""
        s = self._slope(x)
        w = -y / (1 + np.exp(np.clip(y * (a @ x), -700, 700)))
        if clip is None:
            return w @ a + len(y) * s, 0
        sq = w * w * np.einsum("ij,ij->i", a, a) + 2 * w * (a @ s) + s @ s
        f = clip_factors(np.sqrt(np.maximum(sq, 0.0)), clip)
        return (f * w) @ a + f.sum() * s, int((f < 1).sum())

    def measured(self, a: np.ndarray, y: np.ndarray, models: np.ndarray, clip: float | None) -> list[np.ndarray]:
        """Sums over the rows for each of the models (R, d): loss, correct rows, gradient, clipped rows, clipped gradient."""
        x, s = models, self._slope(models)
        margin = a @ x.T
        t = y[:, None] * margin
        loss = np.logaddexp(0.0, -t).sum(axis=0) + len(y) * self.lam * (x * x / (1 + x * x)).sum(axis=1)
        right = (np.where(margin >= 0, 1.0, -1.0) == y[:, None]).sum(axis=0)
        w = -y[:, None] / (1 + np.exp(np.clip(t, -700, 700)))
        g = w.T @ a + len(y) * s
        if clip is None:
            return [loss, right, g, np.zeros(len(x), np.int64), g]
        sq = w * w * np.einsum("ij,ij->i", a, a)[:, None] + 2 * w * (a @ s.T) + (s * s).sum(axis=1)
        f = clip_factors(np.sqrt(np.maximum(sq, 0.0)), clip)
        return [loss, right, g, (f < 1).sum(axis=0), (f * w).T @ a + f.sum(axis=0)[:, None] * s]


@dataclass(frozen=True)
class ShallowNet:
    """One hidden sigmoid layer, softmax, cross-entropy; the vector is W1, c1, W2, c2 in rows."""

    n_in: int = 64
    hidden: int = 64
    n_out: int = 10
    seed: int = 3

    def dimension(self, n_features: int | None = None) -> int:
        return self.hidden * self.n_in + self.hidden + self.n_out * self.hidden + self.n_out

    def start(self, d: int) -> np.ndarray:
        rng = np.random.default_rng(self.seed)
        x = np.zeros(d)
        w1, _, w2, _ = self.parts(x)
        w1[...] = rng.normal(0, 1 / np.sqrt(self.n_in), w1.shape)
        w2[...] = rng.normal(0, 1 / np.sqrt(self.hidden), w2.shape)
        return x

    def parts(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        i, h, o = self.n_in, self.hidden, self.n_out
        a, b, c = h * i, h * i + h, h * i + h + o * h
        return x[:a].reshape(h, i), x[a:b], x[b:c].reshape(o, h), x[c:]

    def _forward(self, a: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        w1, c1, w2, c2 = self.parts(x)
        hid = 1 / (1 + np.exp(-np.clip(a @ w1.T + c1, -60, 60)))
        out = hid @ w2.T + c2
        out -= out.max(axis=1, keepdims=True)
        return hid, out - np.log(np.exp(out).sum(axis=1, keepdims=True))

    def values(self, a: np.ndarray, y: np.ndarray, x: np.ndarray) -> np.ndarray:
        _, logp = self._forward(a, x)
        return -logp[np.arange(len(y)), y.astype(int)]

    def gradients(self, a: np.ndarray, y: np.ndarray, x: np.ndarray) -> np.ndarray:
        _, _, w2, _ = self.parts(x)
        hid, logp = self._forward(a, x)
        delta = np.exp(logp)
        delta[np.arange(len(y)), y.astype(int)] -= 1
        back = (delta @ w2) * hid * (1 - hid)
        n = len(y)
        return np.concatenate(
            [(back[:, :, None] * a[:, None, :]).reshape(n, -1), back, (delta[:, :, None] * hid[:, None, :]).reshape(n, -1), delta], axis=1
        )

    def correct(self, a: np.ndarray, y: np.ndarray, x: np.ndarray) -> np.ndarray:
        return self._forward(a, x)[1].argmax(axis=1) == y.astype(int)

    def _back(self, a: np.ndarray, y: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, ...]:
        """Hidden values, log probabilities, and what comes back at the two layers."""
        hid, logp = self._forward(a, x)
        delta = np.exp(logp)
        delta[np.arange(len(y)), y.astype(int)] -= 1
        return hid, logp, delta, (delta @ self.parts(x)[2]) * hid * (1 - hid)

    @staticmethod
    def _clipped(a: np.ndarray, hid: np.ndarray, delta: np.ndarray, back: np.ndarray, clip: float | None) -> np.ndarray:
        """Clip factors; a layer's gradient is an outer product, so its norm is a product of norms."""
        sq = lambda v: np.einsum("ij,ij->i", v, v)
        return clip_factors(np.sqrt(sq(back) * (sq(a) + 1) + sq(delta) * (sq(hid) + 1)), clip)

    @staticmethod
    def _collect(f: np.ndarray, a: np.ndarray, hid: np.ndarray, delta: np.ndarray, back: np.ndarray) -> np.ndarray:
        b, d = f[:, None] * back, f[:, None] * delta
        return np.concatenate([(b.T @ a).reshape(-1), b.sum(axis=0), (d.T @ hid).reshape(-1), d.sum(axis=0)])

    def summed(self, a: np.ndarray, y: np.ndarray, x: np.ndarray, clip: float | None) -> tuple[np.ndarray, int]:
        """(sum of clipped gradients, number clipped)."""
        hid, _, delta, back = self._back(a, y, x)
        f = self._clipped(a, hid, delta, back, clip)
        return self._collect(f, a, hid, delta, back), int((f < 1).sum())

    def measured(self, a: np.ndarray, y: np.ndarray, models: np.ndarray, clip: float | None) -> list[np.ndarray]:
        """Sums over the rows for each of the models (R, d): loss, correct rows, gradient, clipped rows, clipped gradient."""
        each = []
        for x in models:
            hid, logp, delta, back = self._back(a, y, x)
            f = self._clipped(a, hid, delta, back, clip)
            rows = np.arange(len(y)), y.astype(int)
            parts = (a, hid, delta, back)
            each.append((-logp[rows].sum(), (logp.argmax(axis=1) == rows[1]).sum(), self._collect(np.ones(len(y)), *parts), (f < 1).sum(), self._collect(f, *parts)))
        return [np.array(c) for c in zip(*each, strict=True)]


ROWS = 8192


def summed(loss, a: np.ndarray, y: np.ndarray, x: np.ndarray, clip: float | None) -> tuple[np.ndarray, int]:  # noqa: ANN001
    """(sum of clipped gradients, number clipped), some thousand rows at a time."""
    total, cut = np.zeros(len(x)), 0
    for i in range(0, len(y), ROWS):
        g, c = loss.summed(a[i : i + ROWS], y[i : i + ROWS], x, clip)
        total += g
        cut += c
    return total, cut


def max_sq_norm(samples):  # noqa: ANN001, ANN201
    """The largest squared norm of a row's features: what the smoothness of the logistic loss follows from.  One scan."""
    from pyspark.sql import functions as F

    sq = F.aggregate("features", F.lit(0.0), lambda s, v: s + v * v)
    return samples.agg(F.max(sq)).first()[0]
