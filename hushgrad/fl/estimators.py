"""Local gradient estimators: a mean over the batch plus, for some, a mean over all of a client's samples.

An estimator says how large its batch is, its constants for the noise and the
theory, what a task adds up over the rows it holds (`local`), and what a client
makes of the sums (`finish`).  To add one, derive from Estimator, put an instance
into ESTIMATORS under a name, and name it in `train.METHODS`; `check_unbiased`
holds it against the full gradient over all batches.
"""

from __future__ import annotations

import itertools
import math
from dataclasses import dataclass, field

import numpy as np

from hushgrad.fl import losses, theory


@dataclass
class Ask:
    """A client's rows in one task and round.  pick: rows in the batch; points: earlier models by round; last: rounds
    whose models the table may still hold, newest first; full: whether the sum over all samples is asked for."""

    loss: object
    clip: float | None
    x: np.ndarray
    seq: np.ndarray
    a: np.ndarray
    y: np.ndarray
    pick: np.ndarray
    full: bool
    points: object
    last: object


@dataclass
class Sums:
    batch: np.ndarray
    full: np.ndarray | None = None
    used: int = 0
    cut: int = 0
    #: of each earlier round, how many picked samples had its model in their table entry
    left: dict[int, int] = field(default_factory=dict)

    def add(self, o: Sums) -> None:
        self.batch = self.batch + o.batch
        if o.full is not None:
            self.full = o.full if self.full is None else self.full + o.full
        self.used += o.used
        self.cut += o.cut
        for r, n in o.left.items():
            self.left[r] = self.left.get(r, 0) + n


class Estimator:
    kind = ""
    #: refreshes a snapshot / keeps a point for each sample
    snapshot = table = False

    def batch(self, m: int) -> int:
        raise NotImplementedError

    def constants(self, G: float, L: float, m: int, b: int, p: float) -> theory.Constants:
        return theory.constants(self.kind, G, L, m, b, p)

    def local(self, q: Ask) -> Sums:
        """The sum of clipped gradients over the batch; by default that is all."""
        g, cut = losses.summed(q.loss, q.a[q.pick], q.y[q.pick], q.x, q.clip)
        n = int(q.pick.sum())
        return Sums(g, None, n, cut)

    def finish(self, s: Sums, m: int, b: int, memory: np.ndarray | None) -> tuple[np.ndarray, np.ndarray | None]:
        """(estimate, what the client remembers) from the sums of all tasks."""
        return s.batch / b, memory


class Minibatch(Estimator):
    kind = "sgd"

    def batch(self, m: int) -> int:
        return min(m, 128)


class FullGradient(Estimator):
    kind = "gd"

    def batch(self, m: int) -> int:
        return m


class Snapshot(Estimator):
    """SVRG: gradients' differences to a snapshot, plus the snapshot's full gradient, which the client remembers."""

    kind = "svrg"
    snapshot = True

    def batch(self, m: int) -> int:
        return math.floor(m ** (2 / 3) / 4)

    def local(self, q: Ask) -> Sums:
        s = super().local(q)
        w = q.points("snapshot")
        s.batch = s.batch - losses.summed(q.loss, q.a[q.pick], q.y[q.pick], w, q.clip)[0]
        s.used *= 2
        if q.full:
            s.full = losses.summed(q.loss, q.a, q.y, w, q.clip)[0]
            s.used += len(q.y)
        return s

    def finish(self, s: Sums, m: int, b: int, memory: np.ndarray | None) -> tuple[np.ndarray, np.ndarray | None]:
        if s.full is not None:
            memory = s.full / m
        return s.batch / b + memory, memory


class Table(Estimator):
    """SAGA: differences to each sample's own past point, plus the mean gradient over all past points.

    storage 'round' keeps no gradient: a sample's entry is the round that drew it
    last, and the gradient there is worked out again.  The client remembers the
    table's mean."""

    kind = "saga"
    table = True

    def batch(self, m: int) -> int:
        return min(m, math.floor(3 * m ** (2 / 3)))

    def local(self, q: Ask) -> Sums:
        s = super().local(q)
        if q.full:
            s.full = losses.summed(q.loss, q.a, q.y, q.x, q.clip)[0]
            s.used += len(q.y)
        at = np.flatnonzero(q.pick)
        last = q.last(q.seq[at])
        for r in np.unique(last):
            some = at[last == r]
            s.batch = s.batch - losses.summed(q.loss, q.a[some], q.y[some], q.points(int(r)), q.clip)[0]
            s.left[int(r)] = len(some)
        s.used += len(at)
        return s

    def finish(self, s: Sums, m: int, b: int, memory: np.ndarray | None) -> tuple[np.ndarray, np.ndarray | None]:
        if s.full is not None:
            memory = s.full / m
        return s.batch / b + memory, memory + s.batch / m


ESTIMATORS: dict[str, Estimator] = {e.kind: e for e in (Minibatch(), FullGradient(), Snapshot(), Table())}


class ScalarTable:
    """SAGA with storage 'scalar', for losses whose gradient is a number times the features plus a term without data.

    A sample's entry is that one number, so no earlier model is needed; the
    penalty's slope is taken at the present model.  Rows of one client, in memory."""

    def __init__(self, loss: losses.LogisticNonconvex, a: np.ndarray, y: np.ndarray, x: np.ndarray) -> None:
        self.loss, self.a, self.y = loss, a, y
        self.w = self._number(np.arange(len(y)), x)
        self.mean = self.w @ a / len(y)

    def _number(self, at: np.ndarray, x: np.ndarray) -> np.ndarray:
        y = self.y[at]
        return -y / (1 + np.exp(np.clip(y * (self.a[at] @ x), -700, 700)))

    def estimate(self, x: np.ndarray, batch: np.ndarray) -> np.ndarray:
        """The estimate at x with this batch, whose entries are then renewed."""
        new = self._number(batch, x)
        diff = (new - self.w[batch]) @ self.a[batch]
        out = diff / len(batch) + self.mean + self.loss._slope(x)
        self.mean = self.mean + diff / len(self.y)
        self.w[batch] = new
        return out


def check_unbiased(e: Estimator, loss, a: np.ndarray, y: np.ndarray, x: np.ndarray, b: int, points: dict, last: np.ndarray | None = None, memory: np.ndarray | None = None) -> tuple[np.ndarray, float]:  # noqa: ANN001
    """(mean of the estimate, mean squared distance to the full gradient) over all batches of b samples, without clipping."""
    m = len(y)
    full = losses.summed(loss, a, y, x, None)[0] / m
    mean, var, n = np.zeros(len(x)), 0.0, 0
    for batch in itertools.combinations(range(m), b):
        pick = np.isin(np.arange(m), batch)
        q = Ask(loss, None, x, np.arange(m), a, y, pick, memory is None, points.__getitem__, lambda seq: np.zeros(len(seq), np.int64) if last is None else last[seq])
        v, _ = e.finish(e.local(q), m, b, memory)
        mean, var, n = mean + v, var + float(((v - full) ** 2).sum()), n + 1
    return mean / n, var / n
