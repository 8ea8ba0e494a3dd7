"""Training: direct and shifted compression, and their uncompressed counterparts.

All runs of a comparison advance together, one Spark job a round.  A round is

  map     each task adds up, for each run and client it holds, the clipped
          gradients its estimator asks for;
  reduce  partial sums meet by (run, client);
  client  noise, compression and the client's reference, in one task, so what a
          retried task sends is what it sent before;
  server  the sum of messages by run, n*k numbers instead of n*d.

Samples carry (client_id, seq, features, label), seq counting a client's samples
from 0; a client's samples may lie in any number of tasks.  Minibatches are keyed
permutations of seq (`digest.shuffled`), so they need no ranking and are the same
wherever a sample lies.  They are also known beforehand: one scan fetches the
batches of the next rounds, and a round that needs no full gradient reads only
its own.

SAGA's table of past points is not stored: a sample's entry is the last round
that drew it, found by the same permutations among the rounds still in use.  The
tasks report which entries they renewed, so the driver knows when no sample holds
a round any more and lets its model go; every model is sent once.

A client's state (its reference and its table or snapshot mean) is a row of the
round's written table; the server holds only vectors of length d for each run.
A client here is a task, and the driver knows every seed: this simulates local
privacy and does not provide it.
"""

from __future__ import annotations

import math
import time
import warnings
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hushgrad.fl import compress, estimators, losses, storage, theory
from hushgrad.functions import digest

#: name -> (estimator, compressed, shifted)
METHODS = {
    "direct_sgd": ("sgd", True, False),
    "direct_gd": ("gd", True, False),
    "shifted_sgd": ("sgd", True, True),
    "shifted_gd": ("gd", True, True),
    "shifted_svrg": ("svrg", True, True),
    "shifted_saga": ("saga", True, True),
    "ldp_sgd": ("sgd", False, False),
    "ldp_gd": ("gd", False, False),
    "ldp_svrg": ("svrg", False, False),
    "ldp_saga": ("saga", False, False),
}



@dataclass(frozen=True)
class Run:
    """One training run.  privacy None means no noise at all: a control that is not private.

    eta and gamma are numbers or functions of the round.  order is that of a
    client's stages; compressing before the noise is refused unless unsafe_order,
    and the trace then doesn't call the run private."""

    name: str
    method: str
    rounds: int
    eta: float | Callable[[int], float]
    clip: float | None
    m: int
    d: int
    privacy: theory.PrivacySpec | None = None
    compressor: object = field(default_factory=compress.RandomK)
    gamma: float | Callable[[int], float] | None = None
    b: int | None = None
    p: float | None = None
    c: float = 1.0
    seed: int = 1
    #: samples of each client, where they differ; a client then weighs n * m_i / sum of m
    sizes: dict[int, int] | None = None
    order: tuple[str, ...] = ("estimate", "perturb", "compress")
    unsafe_order: bool = False

    def __post_init__(self) -> None:
        if self.privacy is not None and self.clip is None:
            raise ValueError("a private run needs a clip bound")

    @property
    def how(self) -> estimators.Estimator:
        return estimators.ESTIMATORS[METHODS[self.method][0]]

    @property
    def estimator(self) -> str:
        return self.how.kind

    @property
    def shifted(self) -> bool:
        return METHODS[self.method][2]

    @property
    def squeeze(self):  # noqa: ANN201
        return self.compressor if METHODS[self.method][1] else compress.Identity()

    @property
    def batch(self) -> int:
        if self.estimator == "gd":
            return self.m
        return max(1, min(self.m, self.b if self.b is not None else self.how.batch(self.m)))

    @property
    def refresh(self) -> float:
        return self.p if self.p is not None else min(1.0, self.batch / self.m)

    @property
    def shift(self) -> float:
        return self.shift_at(0)

    def shift_at(self, t: int) -> float:
        if not self.shifted:
            return 0.0
        if self.gamma is None:
            return theory.shift_step(self.squeeze.omega(self.d))
        return self.gamma(t) if callable(self.gamma) else self.gamma

    def eta_at(self, t: int) -> float:
        return self.eta(t) if callable(self.eta) else self.eta

    @property
    def sigma(self) -> float:
        return self.sigma_of(None)

    @property
    def private(self) -> bool:
        return self.privacy is not None and self.order.index("perturb") < self.order.index("compress")

    def m_of(self, client: int | None) -> int:
        return self.sizes[client] if self.sizes and client is not None else self.m

    def batch_of(self, client: int | None) -> int:
        m = self.m_of(client)
        return m if self.estimator == "gd" else min(m, self.batch)

    def weight_of(self, client: int) -> float:
        return len(self.sizes) * self.sizes[client] / self._samples if self.sizes else 1.0

    @cached_property
    def _samples(self) -> int:
        return sum(self.sizes.values())

    def sigma_of(self, client: int | None) -> float:
        """The noise of a client, for its own number of samples.  The weight comes after the noise,
        so it doesn't touch the sensitivity."""
        if self.privacy is None:
            return 0.0
        m = self.m_of(client)
        k = self.how.constants(self.clip, 1.0, m, self.batch_of(client), self.refresh)
        return math.sqrt(theory.noise_variance(k, self.rounds, m, self.privacy, self.c))

    def draw(self, client: int) -> tuple[int, int, int]:
        """What a batch depends on besides client and round: runs that agree in it share their batches."""
        return self.seed, self.m_of(client), self.batch_of(client)

    def sampled(self, client: int, seq: np.ndarray, t: int) -> np.ndarray:
        return drawn(self.draw(client), client, seq, t)

    def coin(self, t: int) -> bool:
        """Whether the snapshot moves to the model of round t (one coin for all clients)."""
        return digest.uniform_value("coin", self.seed, t) < self.refresh


def drawn(draw: tuple[int, int, int], client: int, seq: np.ndarray, t: int) -> np.ndarray:
    seed, m, b = draw
    if b >= m:
        return np.ones(len(seq), dtype=bool)
    return digest.shuffled(seq, m, seed, client, t) < b


@dataclass
class View:
    """What the tasks of a round read: the models, snapshots, runs that sum over all samples, and rounds in use."""

    t: int
    x: dict[str, np.ndarray]
    snapshot: dict[str, np.ndarray] = field(default_factory=dict)
    full: set[str] = field(default_factory=set)
    live: dict[str, list[int]] = field(default_factory=dict)


def last_rounds(run: Run, client: int, seq: np.ndarray, live: list[int]) -> np.ndarray:
    """For each sample the round whose model its table entry holds: the last of the rounds in use that drew it, else 0."""
    out = np.zeros(len(seq), dtype=np.int64)
    open_ = np.arange(len(seq))
    for u in sorted(live, reverse=True):
        if not len(open_) or u == 0:
            break
        hit = run.sampled(client, seq[open_], u)
        out[open_[hit]] = u
        open_ = open_[~hit]
    return out


def local_sums(loss, run: Run, view: View, past: dict, client: int, seq: np.ndarray, a: np.ndarray, y: np.ndarray, pick: np.ndarray | None = None) -> estimators.Sums:  # noqa: ANN001
    """What a task adds up for a run over a client's rows.  past: models of earlier rounds, as broadcasts."""

    def point(r: int | str) -> np.ndarray:
        return view.snapshot[run.name] if r == "snapshot" else past[r].value[run.name]

    pick = run.sampled(client, seq, view.t) if pick is None else pick
    live = view.live.get(run.name, [])
    ask = estimators.Ask(loss, run.clip, view.x[run.name], seq, a, y, pick, run.name in view.full, point, lambda s: last_rounds(run, client, s, live))
    return run.how.local(ask)


def _slim(samples: DataFrame) -> DataFrame:
    """The columns that tasks read: `hot`, positions of equal entries of unit vectors (a byte each, 255: none), instead of vectors where it is there."""
    features = F.col("hot" if "hot" in samples.columns else "features")
    return samples.select(F.col("client_id").cast("long").alias("client_id"), F.col("seq").cast("long").alias("seq"), features.alias("features"), F.col("label").cast("double").alias("label"))


def _features(batch: pa.RecordBatch, d: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    col = batch.column(batch.schema.get_field_index("features"))
    if pa.types.is_binary(col.type):
        n, off = batch.num_rows, np.frombuffer(col.buffers()[1], "<i4")[col.offset : col.offset + batch.num_rows + 1]
        at = np.frombuffer(col.buffers()[2], np.uint8)[off[0] : off[-1]]
        row = np.repeat(np.arange(n), np.diff(off))
        if (at == 255).any():
            row, at = row[at < 255], at[at < 255]
        a = np.zeros(n * d)
        a[row * d + at] = (1.0 / np.sqrt(np.bincount(row, minlength=n)))[row]
        a = a.reshape(n, d)
    else:
        a = col.flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
    a = a.astype(np.float64, copy=False)
    get = lambda n: batch.column(batch.schema.get_field_index(n)).to_numpy(zero_copy_only=False)
    return get("client_id").astype(np.int64), get("seq").astype(np.int64), a, get("label").astype(np.float64)


_SUMS = "run string, client_id long, g binary, full binary, used long, cut long, left binary"
_STATE = "run string, client_id long, shift binary, memory binary"


def _bytes(values: list, kind: str = "<f8") -> pa.Array:
    return pa.array([None if v is None else np.asarray(v, dtype=kind).tobytes() for v in values], pa.binary())


def _partial(loss, runs: list[Run], view, past: dict):  # noqa: ANN001
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[tuple[str, int], estimators.Sums] = {}
        for batch in batches:
            if not batch.num_rows:
                continue
            who, seq, a, y = _features(batch, runs[0].d)
            for client in np.unique(who).tolist():
                at = np.flatnonzero(who == client)
                rows = (seq[at], a[at], y[at])
                picks: dict[tuple, np.ndarray] = {}
                for run in runs:
                    draw = run.draw(client)
                    if draw not in picks:
                        picks[draw] = drawn(draw, client, rows[0], view.value.t)
                    got = local_sums(loss, run, view.value, past, client, *rows, picks[draw])
                    have = total.get((run.name, client))
                    if have is None:
                        total[run.name, client] = got
                    else:
                        have.add(got)
        sums = [total[k] for k in sorted(total)]
        keys = sorted(total)
        yield pa.RecordBatch.from_arrays(
            [
                pa.array([k[0] for k in keys], pa.string()),
                pa.array([k[1] for k in keys], pa.int64()),
                _bytes([s.batch for s in sums]),
                _bytes([s.full for s in sums]),
                pa.array([s.used for s in sums], pa.int64()),
                pa.array([s.cut for s in sums], pa.int64()),
                _bytes([[x for p in sorted(s.left.items()) for x in p] if s.left else None for s in sums], "<i8"),
            ],
            ["run", "client_id", "g", "full", "used", "cut", "left"],
        )

    return go


def client_step(run: Run, t: int, client: int, sums: estimators.Sums, shift: np.ndarray, memory: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray | None]:
    """The stages of a client after its sums have met: returns (coords, values, new reference, new memory)."""
    v, memory = run.how.finish(sums, run.m_of(client), run.batch_of(client), memory)
    at = np.arange(run.d)
    reference = shift
    for stage in run.order[1:]:
        if stage == "perturb":
            # noise once for a client and round, whatever tasks its samples came from
            v = v + run.sigma_of(client) * digest.philox(run.seed, client, t, 1).standard_normal(run.d)[at]
        else:
            at, v = run.squeeze.apply(v - reference, digest.philox(run.seed, client, t, 2))
    if run.shifted:
        shift = shift.copy()
        shift[at] += run.shift_at(t) * v
    return at, v, shift, memory


_CLIENT = "run string, client_id long, shift binary, memory binary, coords binary, values binary, used long, cut long, left binary, payload long"


def _clients(runs: dict[str, Run], t: int):
    """Rows of sums and of state in order of (run, client); one message for each."""
    get = lambda x: None if x is None else np.frombuffer(x)

    def one(name: str, client: int, parts: list, state: tuple | None) -> tuple:
        run = runs[name]
        total, payload = None, 0
        # partials in a fixed order, so the sum doesn't depend on how the samples lay
        for g, full, used, cut, left in sorted(parts, key=lambda z: (z[2], z[0])):
            pairs = np.frombuffer(left, "<i8").reshape(-1, 2).tolist() if left else []
            s = estimators.Sums(get(g), get(full), used, cut, dict(map(tuple, pairs)))
            payload += len(g) + (len(full) if full else 0)
            if total is None:
                total = s
            else:
                total.add(s)
        shift, memory = (np.zeros(run.d), None) if state is None else (get(state[0]), get(state[1]))
        coords, v, shift, memory = client_step(run, t, client, total, shift, memory)
        left = [x for p in sorted(total.left.items()) for x in p] if total.left else None
        return name, client, shift if run.shifted else None, memory, coords, run.weight_of(client) * v, total.used, total.cut, left, payload + 12 * len(v)

    def batch_of(rows: list[tuple]) -> pa.RecordBatch:
        name, client, shift, memory, coords, v, used, cut, left, payload = map(list, zip(*rows, strict=True))
        long = lambda x: pa.array(x, pa.int64())
        cols = [pa.array(name), long(client), _bytes(shift), _bytes(memory), _bytes(coords, "<i4"), _bytes(v), long(used), long(cut), _bytes(left, "<i8"), long(payload)]
        return pa.RecordBatch.from_arrays(cols, [c.split()[0] for c in _CLIENT.split(", ")])

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, parts, state = None, [], None
        rows: list[tuple] = []
        for batch in batches:
            for name, client, g, full, used, cut, left, shift, memory in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if (name, client) != at:
                    if parts:
                        rows.append(one(*at, parts, state))
                    at, parts, state = (name, client), [], None
                if g is None:
                    state = (shift if shift is not None else np.zeros(runs[name].d).tobytes(), memory) if name in runs else None
                else:
                    parts.append((g, full, used, cut, left))
                if len(rows) >= 256:
                    yield batch_of(rows)
                    rows = []
        if parts:
            rows.append(one(*at, parts, state))
        if rows:
            yield batch_of(rows)

    return go


def _added(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(run, vector) in order of run: one vector for each run."""
    total: dict[str, np.ndarray] = {}
    for batch in batches:
        for name, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            x = np.frombuffer(v)
            total[name] = total[name] + x if name in total else x
    yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.string()), _bytes(list(total.values()))], ["run", "v"])


def _parts(spark: SparkSession, vectors: float, d: int) -> int:
    """Tasks for so many vectors of d numbers: 8 MB each, as many as the session has partitions at most.  A task costs
    more than a small round's arithmetic."""
    return max(1, min(int(spark.conf.get("spark.sql.shuffle.partitions")), math.ceil(vectors * d * 8 / 2**23)))


def totals(vectors: DataFrame, runs: int, d: int) -> dict[str, np.ndarray]:
    """(run, v) rows, at most one for each task and run, as the sum of each run.  Only the sums reach the driver."""
    n = _parts(vectors.sparkSession, 16 * runs, d)
    # in a fixed order, so the sum doesn't depend on which task came first
    met = vectors.repartition(n, "run").sortWithinPartitions("run", "v").mapInArrow(_added, "run string, v binary")
    return {r["run"]: np.frombuffer(r["v"]) for r in met.collect()}


def _messages(runs: dict[str, Run], live: dict[str, list[int]]):
    """Messages of a task as one vector for each run: gradients computed, clipped, payload, renewed entries by round, sum of values."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for batch in batches:
            for name, at, v, used, cut, left, payload in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                rounds = live.get(name, [])
                have = total.setdefault(name, np.zeros(3 + len(rounds) + runs[name].d))
                have[:3] += (used, cut, payload)
                for r, k in np.frombuffer(left, "<i8").reshape(-1, 2).tolist() if left else []:
                    have[3 + rounds.index(r)] += k
                have[3 + len(rounds) + np.frombuffer(at, "<i4")] += np.frombuffer(v)
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.string()), _bytes(list(total.values()))], ["run", "v"])

    return go


def evaluate(loss, data: DataFrame, models: dict[str, np.ndarray], clip: float | None = None) -> dict[str, dict[str, float]]:  # noqa: ANN001
    """Loss, share of correct rows, squared norms of the unclipped and of the clipped full gradient, and the
    clipped share, for each model."""
    names = list(models)
    shared = data.sparkSession.sparkContext.broadcast(np.stack([models[k] for k in names]))

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tot, n = None, 0
        for batch in batches:
            if batch.num_rows:
                _, _, a, y = _features(batch, shared.value.shape[1])
                n += len(y)
                for i in range(0, len(y), losses.ROWS):
                    got = loss.measured(a[i : i + losses.ROWS], y[i : i + losses.ROWS], shared.value, clip)
                    tot = got if tot is None else [p + q for p, q in zip(tot, got, strict=True)]
        if tot is not None:
            rows = [np.concatenate([[n, tot[0][k], tot[1][k], tot[3][k]], tot[2][k], tot[4][k]]) for k in range(len(names))]
            yield pa.RecordBatch.from_arrays([pa.array(names), _bytes(rows)], ["run", "v"])

    got = totals(_slim(data).mapInArrow(go, "run string, v binary"), len(names), shared.value.shape[1])
    shared.destroy()
    out = {}
    for k, v in got.items():
        n, (g, c) = v[0], np.split(v[4:], 2)
        out[k] = {"loss": v[1] / n, "accuracy": v[2] / n, "grad_sq": float(((g / n) ** 2).sum()), "clipped_share": v[3] / n, "clipped_grad_sq": float(((c / n) ** 2).sum())}
    return out


TRACE = (
    "run string, method string, eps double, round int, coords_sent long, value_bits long, index_bits long, grads long, clipped long, "
    "grad_sq double, mean_grad_sq double, loss double, accuracy double, clipped_share double, clipped_grad_sq double, drift double, "
    "seconds double, payload long"
)

#: Rounds whose batches one scan fetches, at most.
AHEAD = 50


def _ahead(samples: DataFrame, runs: list[Run], clients: list[int], t0: int, t1: int) -> DataFrame:
    """(round, client_id, seq, features, label) of the samples that the runs' batches of rounds t0 to t1 - 1 draw."""
    draws = {c: sorted({r.draw(c) for r in runs}) for c in clients}

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            who, seq = (batch.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in (0, 1))
            at, when = [], []
            for c in np.unique(who).tolist():
                mine = np.flatnonzero(who == c)
                for u in range(t0, t1):
                    hit = np.zeros(len(mine), dtype=bool)
                    for draw in draws[c]:
                        hit |= drawn(draw, c, seq[mine], u)
                    at.append(mine[hit])
                    when.append(np.full(int(hit.sum()), u, dtype=np.int32))
            if at:
                got = batch.take(pa.array(np.concatenate(at)))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(when)), *got.columns], ["round", *got.schema.names])

    return samples.mapInArrow(go, f"round int, client_id long, seq long, features {samples.schema['features'].dataType.simpleString()}, label double")


@dataclass
class _Progress:
    """The server's side of a run."""

    x: np.ndarray
    reference: np.ndarray
    snapshot: np.ndarray
    moved: bool
    #: of each round in use, how many samples' table entries hold its model, and that model
    held: dict[int, int] = field(default_factory=dict)
    points: dict[int, np.ndarray] = field(default_factory=dict)
    sent: np.ndarray = field(default_factory=lambda: np.zeros(5, dtype=np.int64))
    payload: int = 0
    means: list[float] = field(default_factory=list)

    def drift(self, run: Run) -> float | None:
        """The estimator's drift: squared distance to the snapshot, or the mean one to the samples' points."""
        if run.how.snapshot:
            return float(((self.x - self.snapshot) ** 2).sum())
        if run.how.table:
            return sum(n * float(((self.x - self.points[r]) ** 2).sum()) for r, n in self.held.items()) / sum(self.held.values())
        return None


def _check(runs: list[Run], eval_every: int) -> None:
    outside = []
    for run in runs:
        compress.check_order(run.order, run.unsafe_order)
        if run.rounds / eval_every < 1:
            raise ValueError("eval_every must be below the number of rounds")
        if run.privacy is not None:
            with warnings.catch_warnings():
                warnings.simplefilter("ignore")
                if not theory.in_regime(run.privacy, run.batch, run.rounds, run.m):
                    outside.append(run.name)
    if outside:
        warnings.warn(f"eps of {len(outside)} runs, such as {outside[0]}, is beyond the condition of the noise formula", stacklevel=3)


def train(samples: DataFrame, runs: list[Run], loss, eval_every: int = 5, test: DataFrame | None = None, references: DataFrame | None = None) -> tuple[dict[str, np.ndarray], list[tuple]]:  # noqa: ANN001
    """Advance all runs together; returns their final models and rows of TRACE.

    Each run makes exactly run.rounds updates; measures are taken before the
    update of every eval_every-th round and after the last, and the running mean
    is over those.  references: (client_id, values), the clients' first reference
    vectors for shifted runs, zero where absent.  samples should be persisted.
    """
    spark: SparkSession = samples.sparkSession
    sc = spark.sparkContext
    _check(runs, eval_every)
    samples = _slim(samples)
    sizes = {r["client_id"]: r["count"] for r in samples.groupBy("client_id").count().collect()}  # one row for each client
    clients, n = sorted(sizes), len(sizes)
    at = {}
    for r in runs:
        x = loss.start(r.d)
        at[r.name] = _Progress(x, np.zeros(r.d), x, r.how.snapshot, {0: sum(sizes.values())} if r.how.table else {}, {0: x} if r.how.table else {})
    state, old = spark.createDataFrame([], _STATE), None
    if references is not None:
        state = _first_state(references, runs)
        for r in runs:
            if r.shifted:
                mean = references.select("client_id", F.posexplode("values").alias("i", "v")).collect()
                for row in mean:
                    at[r.name].reference[row["i"]] += r.weight_of(row["client_id"]) * row["v"] / n
    trace: list[tuple] = []
    began = time.monotonic()

    def measure(t: int, live: list[Run]) -> None:
        models = {r.name: at[r.name].x for r in live}
        got: dict = {}
        for clip in {r.clip for r in live}:
            got |= evaluate(loss, samples, {r.name: models[r.name] for r in live if r.clip == clip}, clip)
        held = evaluate(loss, test, models) if test is not None else got
        for r in live:
            q, p = got[r.name], at[r.name]
            p.means.append(q["grad_sq"])
            trace.append(
                (
                    r.name, r.method, r.privacy.eps if r.private else None, t, *map(int, p.sent), q["grad_sq"], float(np.mean(p.means)), float(q["loss"]),
                    float(held[r.name]["accuracy"]), float(q["clipped_share"]), q["clipped_grad_sq"], p.drift(r), time.monotonic() - began, p.payload,
                )
            )

    past: dict[int, object] = {}
    near, near_end = None, 0
    for t in range(max(r.rounds for r in runs)):
        live = [r for r in runs if t < r.rounds]
        if t % eval_every == 0:
            measure(t, live)
        tables = [r for r in live if r.how.table]
        if tables:
            past[t] = sc.broadcast({r.name: at[r.name].x for r in tables})
        full = {r.name for r in live if (r.how.snapshot and at[r.name].moved) or (r.how.table and t == 0)}
        in_use = {r.name: sorted(at[r.name].held) for r in tables}
        view = View(t, {r.name: at[r.name].x for r in live}, {r.name: at[r.name].snapshot for r in live if r.how.snapshot}, full, in_use)
        shared = sc.broadcast(view)
        # runs whose round needs only a batch read the rows fetched beforehand
        whole = [r for r in live if r.name in full or r.batch >= r.m]
        part = [r for r in live if r not in whole]
        if part and t >= near_end:
            small = [r for r in live if r.batch < r.m]
            share = sum(b / m for _, m, b in {r.draw(clients[0]) for r in small})
            span = min(AHEAD, int(0.25 / share))
            if near is not None:
                near.unpersist()
                near = None
            near_end = t + max(1, span)
            if span > 1:
                near = _ahead(samples, small, clients, t, near_end)
                # a small number of rows meets in few tasks; many stay where they lie
                if (few := _parts(spark, share * span * sum(sizes.values()), live[0].d)) < int(spark.conf.get("spark.sql.shuffle.partitions")):
                    near = near.repartition(few, "round", "client_id").sortWithinPartitions("round", "client_id", "seq")
                near = near.persist()
        if near is None:
            whole, part = live, []
        sums = samples.mapInArrow(_partial(loss, whole, shared, past), _SUMS) if whole else None
        if part:
            rows = near.filter(F.col("round") == t).drop("round").mapInArrow(_partial(loss, part, shared, past), _SUMS)
            sums = rows if sums is None else sums.unionByName(rows)
        by_name = {r.name: r for r in live}
        both = sums.unionByName(state, allowMissingColumns=True)
        # a row brings a few vectors: a partial sum or two, the reference and the memory
        parts = _parts(spark, 4 * len(live) * n, live[0].d)
        made = both.repartition(parts, "run", "client_id").sortWithinPartitions("run", "client_id").mapInArrow(_clients(by_name, t), _CLIENT)
        made = storage.settle(made, f"round-{t}")
        got = totals(made.select("run", "coords", "values", "used", "cut", "left", "payload").mapInArrow(_messages(by_name, in_use), "run string, v binary"), len(live), live[0].d)
        for r in live:
            p, v = at[r.name], got[r.name]
            rounds = in_use.get(r.name, [])
            mean = v[3 + len(rounds) :] / n
            if rounds:
                for u, k in zip(rounds, v[3 : 3 + len(rounds)].tolist(), strict=True):
                    p.held[u] -= int(k)
                    p.held[t] = p.held.get(t, 0) + int(k)
                p.points[t] = p.x
                for u in [u for u, k in p.held.items() if k == 0]:
                    del p.held[u], p.points[u]
            value_bits, index_bits = r.squeeze.bits(r.d)
            p.sent += np.array([n * r.squeeze.kept(r.d), n * value_bits, n * index_bits, int(v[0]), int(v[1])])
            p.payload += int(v[2])
            p.moved = r.how.snapshot and r.coin(t)
            if p.moved:
                p.snapshot = p.x  # the snapshot takes the model before this round's update
            p.x = p.x - r.eta_at(t) * (p.reference + mean)
            p.reference = p.reference + r.shift_at(t) * mean
        shared.destroy()
        used = {u for r in tables if r.rounds > t + 1 for u in at[r.name].held}
        for u in [u for u in past if u not in used]:
            past.pop(u).destroy()
        state = made.select("run", "client_id", "shift", "memory")
        if old is not None:
            storage.drop(old)
        old = made
        ended = [r for r in live if r.rounds == t + 1]
        if ended:
            measure(t + 1, ended)
    if near is not None:
        near.unpersist()
    return {k: p.x for k, p in at.items()}, trace


def _first_state(references: DataFrame, runs: list[Run]) -> DataFrame:
    """Rows of _STATE with the clients' first references for every shifted run."""
    names = [r.name for r in runs if r.shifted]

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for client, values in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                k = len(names)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(names, pa.string()), pa.array([client] * k, pa.int64()), _bytes([values] * k), pa.array([None] * k, pa.binary())], ["run", "client_id", "shift", "memory"]
                )

    return references.select(F.col("client_id").cast("long"), F.col("values").cast("array<double>")).mapInArrow(go, _STATE)
