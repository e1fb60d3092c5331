"""Chains that draw coefficients from the bounded-loss posterior.

The target density is exp((epsilon / 2v) U(f)), U = minus prior minus sum of bounded losses.  One chain is one group of a
grouped map: its state stays in one process for all its steps, and many chains (budgets, seeds, variants) run side by
side.  Minibatch rows never depend on the state, so they can be chosen and fetched by one join for a block of steps
(``prefetch``); small pools (whose size is checked) are broadcast instead, larger ones sent to the chains' tasks.  ``sample`` chooses;
all ways run the same step code.

``temperature="calibrated"`` adds noise of twice the step's variance, which makes the target the stationary law;
``"printed"`` adds it once, which samples the squared density: such runs charge twice the budget.  Chains end
after a fixed number of steps, and only the last state is a release; traces are for diagnosis.
"""

from __future__ import annotations

import math
import pickle
from collections.abc import Callable, Iterator
from dataclasses import asdict, dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import rng
from ..functions.loss import SumOfLogistic
from ..functions.moments import Moments
from .ledger import Ledger
from .objective import Data
from .prep import row_ids
from .private import Release, default_bound, default_prior, require_ball, run_name
from .sensitivity import ball_bound, require_bounded_gradient

POOL = 5_000_000  # most numbers of a pool that is broadcast
SHIPPED = 5  # pools of up to as many times that are sent to the chains' tasks, not through the driver
PIECE = 10_000  # states that a chain hands on at once
TRACE = "chain_id string, step long, last boolean, f array<double>"


@dataclass(frozen=True)
class Config:
    epsilon: float
    v: float
    sigma: float
    steps: int
    k: int | None = 200  # records per step; None: all
    tau: float = 0.51
    floor: float = 1e-5
    mu: float = 0.99
    precondition: bool = True
    temperature: str = "calibrated"
    drift_correction: bool = False
    with_replacement: bool = False
    bound: str = "tanh"
    radius: float | None = None  # projection to a ball
    sampler: str = "preconditioned"  # or plain, thermostat, metropolis
    step_scale: float = 1.0
    burn_in: int = 0
    every: int = 1
    seed: int = 0
    replay: bool = False  # digest noise, full batch: replayable in SQL

    def __post_init__(self) -> None:
        if not 0.5 < self.tau <= 1:
            raise ValueError("the step exponent is above one half and at most one")
        if self.temperature not in ("calibrated", "printed"):
            raise ValueError("temperature is calibrated or printed")

    @property
    def charged(self) -> float:
        return self.epsilon * (2 if self.temperature == "printed" else 1)


def stable_scale(n: float, epsilon: float, v: float, k: int | None = 200, ratio: float = 11.0) -> float:
    """Factor of the published step lengths at which a preconditioned chain reaches its target; of public quantities only.

    Minibatch noise moves a coefficient by about h n in a step of length h, injected noise by sqrt(2 h / rms gradient).  Their
    squared ratio starts at ``ratio`` and falls as h does: below a tenth after ten thousand steps.  Published lengths have a ratio
    that grows with the square of the records; such chains are driven by minibatch noise.
    """
    return 2 * ratio * math.sqrt(k or max(n, 1)) / (max(n, 1) ** 2 * epsilon / (2 * v))


def bounded_gradient(kernel: SumOfLogistic, f: np.ndarray, x: np.ndarray, t: np.ndarray, y: np.ndarray, v: float, bound: str, w: np.ndarray | float = 1.0) -> tuple[np.ndarray, float]:
    """Mean gradient of bounded losses, and their sum; ``w`` counts equal records."""
    loss, grad = kernel.weighted(f, x, t, y, bounded_slope(v, bound, w))
    bounded = v * np.tanh(loss / v) if bound == "tanh" else np.minimum(loss, v) if bound == "clip" else loss
    return grad / max(1, len(t) if np.isscalar(w) else w.sum()), float((w * bounded).sum())


def bounded_slope(v: float, bound: str, w: np.ndarray | float = 1.0) -> Callable[[np.ndarray], np.ndarray]:
    """By what a bounded loss grows with its loss, times the weight."""
    if bound == "tanh":
        return lambda own: w * (1 - np.tanh(own / v) ** 2)
    return (lambda own: w * (own < v)) if bound == "clip" else (lambda own: w * np.ones_like(own))


@dataclass
class State:
    """All that a chain carries from step to step."""

    f: np.ndarray
    second: np.ndarray
    momentum: np.ndarray
    g: np.random.Generator
    friction: float = 1.0
    here: float | None = None  # energy, of Metropolis chains


def begin(d: int, seed: int) -> State:
    return State(np.zeros(d), np.zeros(d), np.zeros(d), np.random.default_rng(seed))


class Held:
    """Records in this process: the pool of a chain (of one whose steps take all of it, equal records once with a weight), or (with
    ``batches``) the fetched records of each step."""

    def __init__(self, a: np.ndarray, link: str, x: np.ndarray, t: np.ndarray, y: np.ndarray, c: Config, batches: Callable[[int], np.ndarray] | None = None, w: np.ndarray | None = None):
        self.kernel, self.x, self.t, self.y, self.c, self.batches = SumOfLogistic(a, link), x, t, y, c, batches
        self.w = 1.0 if w is None else w.astype(float)
        self.moments: Moments | None = None
        self.slope, self.many = bounded_slope(c.v, c.bound, self.w), None if w is None else max(1.0, float(self.w.sum()))
        self.flat = np.ascontiguousarray(np.column_stack((x, t, y))) if batches is None and w is None and c.sampler != "metropolis" else None  # minibatches are one look-up

    def batch(self, step: int, g: np.random.Generator):
        n, c = len(self.t), self.c
        if not np.isscalar(self.w):
            return slice(None)
        if self.batches is not None:
            return self.batches(step)
        if c.k is None or c.k >= n:
            return slice(None)
        return g.integers(0, n, c.k) if c.with_replacement else g.choice(n, c.k, replace=False)

    def mean(self, p: np.ndarray, own) -> np.ndarray:
        if self.flat is None or isinstance(own, slice):
            x, t, y = self.x[own], self.t[own], self.y[own]
        else:
            rows, e = self.flat.take(own, axis=0), self.x.shape[1]
            x, t, y = rows[:, :e], rows[:, e].astype(np.int64), rows[:, e + 1]
        return self.kernel.weighted(p, x, t, y, self.slope)[1] / (self.many or max(1, len(t)))

    def total(self, p: np.ndarray) -> float:
        c = self.c
        if self.moments is None and Moments.pays(self.kernel.link, self.x.shape[1], len(self.t), c.bound):
            self.moments = Moments(self.kernel.a, np.abs(self.x).max(axis=0)).take(self.x, self.t, self.y, self.w)
        value = None if self.moments is None else self.moments.total(p, c.v, c.bound)
        return bounded_gradient(self.kernel, p, self.x, self.t, self.y, c.v, c.bound, self.w)[1] if value is None else value


class Spread:
    """Records that stay distributed: full-batch steps are one pass each, Metropolis steps are from sums that one pass takes, or where
    these give no value (``Moments``) a pass each too."""

    def __init__(self, d: Data, c: Config):
        self.d, self.c, self.moments = d, c, None

    def batch(self, step: int, g: np.random.Generator) -> None:
        return None

    def _sums(self, p: np.ndarray) -> np.ndarray:
        kernel, x, c, size = SumOfLogistic(self.d.a, self.d.link), list(self.d.x), self.c, len(p) + 1

        def run(frames):
            out = np.zeros(size)
            for f in frames:
                for lo in range(0, len(f), kernel.chunk):
                    own = f.iloc[lo : lo + kernel.chunk]
                    w = own["w"].to_numpy(float)
                    loss, grad = kernel.gradients(p, own[x].to_numpy(float), own["t"].to_numpy(), own["y"].to_numpy())
                    th = np.tanh(loss / c.v)
                    value, slope = {"tanh": (c.v * th, 1 - th * th), "clip": (np.minimum(loss, c.v), (loss < c.v) * 1.0)}.get(c.bound, (loss, np.ones(len(loss))))
                    out += np.concatenate(([w @ value], (w * slope) @ grad))
            yield pd.DataFrame({"i": np.arange(size), "v": out})

        out = np.zeros(size)
        for i, v in self.d.df.mapInPandas(run, "i int, v double").groupBy("i").agg(F.sum("v")).collect():  # coefficients
            out[i] = v
        return out

    def mean(self, p: np.ndarray, own: None) -> np.ndarray:
        return self._sums(p)[1:] / self.d.n

    def _moments(self) -> Moments:
        x, empty = list(self.d.x), Moments(self.d.a, np.full(len(self.d.x), self.d.radius))

        def run(frames):
            out = np.zeros((2 * len(empty.a) + 2, 1 + len(empty.powers)))  # of the partition, by key
            for f in frames:
                if len(f):
                    m = empty.take(f[x].to_numpy(float), f["t"].to_numpy(), f["y"].to_numpy(), f["w"].to_numpy(float))
                    out[m.keys] += np.column_stack((m.mass, m.sums))
            keys = np.flatnonzero(out[:, 0])
            yield pd.DataFrame({"key": keys, "sums": [out[k].tobytes() for k in keys]})

        def add(frame):
            return pd.DataFrame({"key": frame["key"].iloc[:1], "sums": [sum(np.frombuffer(b) for b in frame["sums"]).tobytes()]})

        schema = "key long, sums binary"
        few = self.d.df.coalesce(self.d.df.sparkSession.sparkContext.defaultParallelism)  # one table of sums a core
        rows = few.mapInPandas(run, schema).groupBy("key").applyInPandas(add, schema).collect()  # a row per interval and flag
        sums = np.array([np.frombuffer(r["sums"]) for r in rows])
        return empty.set(np.array([r["key"] for r in rows]), sums[:, 0], sums[:, 1:])

    def total(self, p: np.ndarray) -> float:
        c = self.c
        if self.moments is None and Moments.pays(self.d.link, len(self.d.x), self.d.n, c.bound):
            self.moments = self._moments()
        value = None if self.moments is None else self.moments.total(p, c.v, c.bound)
        return float(self._sums(p)[0]) if value is None else value


def advance(s: State, c: Config, n: int, source: Held | Spread, first: int, last: int) -> list[tuple[int, np.ndarray]]:
    """Steps first..last of a chain over n records; the thinned trace."""
    d, scale, trace = len(s.f), c.epsilon / (2 * c.v), []

    def noise(step: int) -> np.ndarray:
        return np.array([rng.normal_value(c.seed, step, i) for i in range(d)]) if c.replay else s.g.standard_normal(d)

    def energy(p: np.ndarray) -> float:
        return -scale * (0.5 * c.sigma * float(p @ p) + source.total(p))

    for step in range(first, last + 1):
        h = c.step_scale * step**-c.tau
        if c.sampler == "metropolis":
            if s.here is None:
                s.here = energy(s.f)
            tried = s.f + h * noise(step)
            there = energy(tried)
            if np.log(s.g.random()) < there - s.here:
                s.f, s.here = tried, there
        else:
            own = source.batch(step, s.g)
            slope_at = lambda p, own=own: scale * (c.sigma * p / n + source.mean(p, own))
            grad = slope_at(s.f)
            if c.sampler == "thermostat":
                s.momentum = s.momentum - h * s.friction * s.momentum - h * n * grad + np.sqrt(2 * h) * noise(step)
                s.f = s.f + h * s.momentum
                s.friction += h * (float(s.momentum @ s.momentum) / d - 1)
            else:
                s.second = c.mu * s.second + (1 - c.mu) * grad * grad
                scales = 1 / (c.floor + np.sqrt(s.second)) if c.precondition and c.sampler != "plain" else np.ones(d)
                move = scales * n * grad
                if c.drift_correction and c.precondition:
                    # Divergence of the preconditioner, with the curvature taken from the ridge part and a secant of the gradient.
                    slope = np.array([(slope_at(s.f + z) - grad)[i] / 1e-4 for i, z in enumerate(1e-4 * np.eye(d))])
                    move += (1 - c.mu) * scales**2 * grad * slope / np.maximum(np.sqrt(s.second), 1e-12)
                s.f = s.f - h * move + np.sqrt(h * scales * (2 if c.temperature == "calibrated" else 1)) * noise(step)
        if c.radius is not None and np.linalg.norm(s.f) > c.radius:
            s.f = s.f * c.radius / np.linalg.norm(s.f)
        if step > c.burn_in and (step - c.burn_in) % c.every == 0:
            trace.append((step, s.f.copy()))
    return trace


def run_chain(a: np.ndarray, link: str, x: np.ndarray, t: np.ndarray, y: np.ndarray, c: Config, batches: Callable[[int], np.ndarray] | None = None, w: np.ndarray | None = None) -> tuple[np.ndarray, list[tuple[int, np.ndarray]]]:
    """Last state and thinned trace (step, state)."""
    s = begin(a.shape[1] + x.shape[1], c.seed)
    trace = advance(s, c, len(t) if w is None else int(w.sum()), Held(a, link, x, t, y, c, batches, w), 1, c.steps)
    return s.f, trace


def _rows(d: Data, most: int = POOL) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    if d.n * (2 + len(d.x)) > most:
        raise ValueError(f"{d.n:.0f} records are too many to broadcast; prefetch minibatches instead")
    rows = d.df.orderBy("t", "y", *d.x).toPandas()
    return rows[d.x].to_numpy(dtype=float), rows["t"].to_numpy(), rows["y"].to_numpy(), rows["w"].to_numpy()


def pool(d: Data, most: int = POOL) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All records on the driver, behind a check of their size; beyond it ``sample`` feeds chains by joins."""
    *own, w = _rows(d, most)
    return tuple(np.repeat(v, w, axis=0) for v in own)


def _traced(name: str, c: Config, a: np.ndarray, link: str, x: np.ndarray, t: np.ndarray, y: np.ndarray, w: np.ndarray) -> Iterator[pd.DataFrame]:
    """A chain over all records, here; its trace in pieces, so a chain of any length holds few states."""
    if (w == 1).all():
        w = None
    elif c.sampler != "metropolis" and c.k is not None and c.k < w.sum():  # minibatches are of single records
        x, t, y, w = *(np.repeat(v, w, axis=0) for v in (x, t, y)), None
    s, held, n = begin(a.shape[1] + x.shape[1], c.seed), Held(a, link, x, t, y, c, w=w), len(t) if w is None else int(w.sum())
    block = PIECE * max(1, c.every)
    for first in range(1, max(c.steps, 1) + 1, block):
        last = min(first + block - 1, c.steps)
        trace = advance(s, c, n, held, first, last)
        if last == c.steps and (not trace or trace[-1][0] != last):
            trace.append((last, s.f))
        if trace:
            yield pd.DataFrame({"chain_id": name, "step": [i for i, _ in trace], "last": [i == c.steps for i, _ in trace], "f": [v.tolist() for _, v in trace]})


def sample(d: Data, configs: dict[str, Config]) -> DataFrame:
    """chain_id, step, last, f: traces of several chains, each in one task; of pools too large for that, from prefetched blocks."""
    spark = d.df.sparkSession
    if d.n * (2 + len(d.x)) > POOL:
        return _sample_large(d, configs)
    held = spark.sparkContext.broadcast((_rows(d), d.a, d.link, [(k, asdict(c)) for k, c in configs.items()]))

    def run(frames):
        (x, t, y, w), a, link, all_ = held.value
        for frame in frames:
            for i in frame["id"]:
                yield from _traced(all_[i][0], Config(**all_[i][1]), a, link, x, t, y, w)

    return spark.range(0, len(configs), 1, max(1, len(configs))).mapInPandas(run, TRACE)  # hashed names may share a task


def _sample_shipped(d: Data, configs: dict[str, Config]) -> DataFrame:
    """The same of pools that are not broadcast: a chain's task gets all records by a shuffle and keeps them as arrays."""
    x, a, link, all_ = list(d.x), d.a, d.link, [(k, asdict(c)) for k, c in configs.items()]

    def run(frames):
        parts = {}
        for frame in frames:
            for i, own in frame.groupby("chain"):
                parts.setdefault(i, []).append((own[x].to_numpy(float), *(own[c].to_numpy(np.int32) for c in ("t", "y", "w"))))
        for i in sorted(parts):
            own = [np.concatenate(v) for v in zip(*parts.pop(i), strict=True)]
            order = np.lexsort((*own[0].T[::-1], own[2], own[1]))  # whatever order the shuffle left
            yield from _traced(all_[i][0], Config(**all_[i][1]), a, link, *(v[order] for v in own))

    each = d.df.where("w > 0").select("t", "y", "w", *x, F.explode(F.array(*[F.lit(i) for i in range(len(all_))])).alias("chain"))
    return each.repartitionById(len(all_), "chain").mapInPandas(run, TRACE)


def _ball(d: Data, radius: float | None, v: float | None) -> float:
    """The bound of losses in a ball; refuses what it does not hold for."""
    if radius is None:
        raise ValueError("an unbounded loss has no privacy guarantee; give a radius, or run it by sample() as a comparator")
    require_bounded_gradient(d.link)
    require_ball(d)
    least = ball_bound(d.a, radius)
    if v is not None and v < least:
        raise ValueError(f"losses in the ball reach {least:.6g}, above the bound {v:g}")
    return least if v is None else v


def bounded_sampler_fit(d: Data, epsilon: float, v: float | None = None, sigma: float | None = None, steps: int = 20_000, ledger: Ledger | None = None, unit: str = "data", seed: int | None = None, step_scale: float | None = None, **more) -> Release:
    """One draw from the bounded-loss posterior: the last state of a chain of fixed length.  Never exact, since chains only converge.

    ``step_scale`` one gives the published step lengths; by default ``stable_scale`` shortens them.  With bound="none" and a
    ``radius`` states stay in that ball, which bounds losses by itself (``sensitivity.ball_bound``, the default of ``v`` then): the
    older mechanism, whose noise grows with the ball.
    """
    if more.get("bound") == "none":
        v = _ball(d, more.get("radius"), v)
    v = default_bound(d.n) if v is None else v
    scale = stable_scale(d.n, epsilon, v, more.get("k", 200)) if step_scale is None else step_scale
    prior = default_prior(v, epsilon) if sigma is None else sigma
    entropy = np.random.SeedSequence().entropy if seed is None else seed
    c = Config(epsilon, v, prior, steps, burn_in=steps - 1, seed=entropy, step_scale=scale, **more)
    run = run_name("sampler", seed)
    if ledger:
        ledger.charge(run, unit, c.charged, exact=False)
    f = sample(d, {"run": c}).where("last").first()["f"]
    params = {"v": v, "sigma": c.sigma, "steps": float(steps), "step_scale": scale}
    return Release("bounded_sampler", c.charged, list(f), *d.a.shape, link=d.link, params=params, exact=False, run_id=run)


def minibatch_ids(spark, chain_id: str, seed: int, first: int, steps: int, k: int, n: int, replacement: bool = False) -> DataFrame:
    """chain_id, step, slot, row_id of a block of steps: k distinct rows of n per step, by digests.

    Slots draw by counter and keep the first k distinct values, which is uniform without replacement; work is k per step, not n.
    """
    if replacement:
        draws = spark.range(first, first + steps).select(F.col("id").alias("step"), F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("slot"))
        return draws.select(F.lit(chain_id).alias("chain_id"), "step", "slot", F.floor(rng.uniform(chain_id, str(seed), F.col("step"), F.col("slot")) * n).cast("long").alias("row_id"))
    spare = k + 8 + int(k * k / max(n - k, 1)) + (4 * k if 2 * k > n else 0)
    if 4 * k > n:  # a large part of the pool: order all rows by digest
        rows = spark.range(first, first + steps).select(F.col("id").alias("step")).crossJoin(spark.range(n).select(F.col("id").alias("row_id")))
        key = rng.uniform(chain_id, str(seed), F.col("step"), F.col("row_id"))
        listed = rows.groupBy("step").agg(F.slice(F.sort_array(F.collect_list(F.struct(key.alias("u"), "row_id"))), 1, k).alias("r"))
        return listed.select(F.lit(chain_id).alias("chain_id"), "step", F.posexplode("r").alias("slot", "v")).select("chain_id", "step", "slot", "v.row_id")
    draws = spark.range(first, first + steps).select(F.col("id").alias("step"), F.explode(F.sequence(F.lit(0), F.lit(spare - 1))).alias("draw"))
    draws = draws.withColumn("row_id", F.floor(rng.uniform(chain_id, str(seed), F.col("step"), F.col("draw")) * n).cast("long"))
    firsts = draws.groupBy("step", "row_id").agg(F.min("draw").alias("draw"))
    listed = firsts.groupBy("step").agg(F.slice(F.sort_array(F.collect_list(F.struct("draw", "row_id"))), 1, k).alias("r"))
    return listed.select(F.lit(chain_id).alias("chain_id"), "step", F.posexplode("r").alias("slot", "v")).select("chain_id", "step", "slot", "v.row_id")


def prefetch(ids: DataFrame, rows: DataFrame) -> DataFrame:
    """The records of a block of minibatches: one join on row_id, then by chain in step order."""
    return ids.join(rows, "row_id").repartition("chain_id").sortWithinPartitions("chain_id", "step", "slot")


def _advanced(fetched: DataFrame, d: Data, active: dict[str, tuple[Config, State, int, int]]) -> dict[str, tuple[State, list]]:
    """Runs the fetched steps (first..last) of each chain from its state, a chain a task; the new states and their traces."""
    x, a, link, n = list(d.x), d.a, d.link, int(d.n)

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        name = frame["chain_id"].iloc[0]
        c, s, first, last = active[name]
        frame = frame.sort_values(["step", "slot"])
        at = np.searchsorted(frame["step"].to_numpy(), np.arange(first, last + 2))
        held = Held(a, link, frame[x].to_numpy(float), frame["t"].to_numpy(), frame["y"].to_numpy(), c, lambda step: slice(at[step - first], at[step - first + 1]))
        trace = advance(s, c, n, held, first, last)
        return pd.DataFrame({"chain_id": [name], "state": [pickle.dumps((s, trace))]})

    rows = fetched.groupBy("chain_id").applyInPandas(run, "chain_id string, state binary").collect()  # one row a chain
    return {r["chain_id"]: pickle.loads(bytes(r["state"])) for r in rows}


def _run_large(d: Data, rows: DataFrame, configs: dict[str, Config], block: int = 500) -> dict[str, tuple[State, list]]:
    """Chains over records of any number: minibatches of a block of steps of all chains by one join; steps over all records as passes."""
    n, out = int(d.n), {k: (begin(d.d, c.seed), []) for k, c in configs.items()}
    joined = {k: c for k, c in configs.items() if c.sampler != "metropolis" and c.k is not None and c.k < n}
    for name in configs.keys() - joined.keys():
        s, trace = out[name]
        trace += advance(s, configs[name], n, Spread(d, configs[name]), 1, configs[name].steps)
    block = max(1, min([block, *[1_000_000 // c.k for c in joined.values()]]))
    for first in range(1, max([c.steps for c in joined.values()], default=0) + 1, block):
        active = {k: (c, out[k][0], first, min(first + block - 1, c.steps)) for k, c in joined.items() if c.steps >= first}
        ids = None
        for k, (c, _, _, last) in active.items():
            own = minibatch_ids(d.df.sparkSession, k, c.seed, first, last - first + 1, c.k, n, c.with_replacement)
            ids = own if ids is None else ids.unionByName(own)
        for k, (s, trace) in _advanced(prefetch(ids, rows.select("row_id", "t", "y", *d.x)), d, active).items():
            out[k] = (s, out[k][1] + trace)
    return out


def _sample_large(d: Data, configs: dict[str, Config]) -> DataFrame:
    """What ``sample`` gives, for pools that are not broadcast."""
    out = []
    if d.n * (2 + len(d.x)) <= SHIPPED * POOL:
        sent = {k: c for k, c in configs.items() if c.sampler != "metropolis" and c.k is not None and c.k < int(d.n)}
        configs = {k: c for k, c in configs.items() if k not in sent}
        out += [_sample_shipped(d, sent)] if sent else []
    out += [_sample_joined(d, configs)] if configs else []
    return out[0] if len(out) == 1 else out[0].unionByName(out[1])


def _sample_joined(d: Data, configs: dict[str, Config]) -> DataFrame:
    """By joins of minibatches, and passes."""
    flat = d.df.groupBy("t", "y", *d.x).agg(F.sum("w").cast("long").alias("w")).where("w > 0").withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("w"))))
    rows = row_ids(flat.withColumn("key", F.struct("t", "y", *d.x, "copy")), "key").select("row_id", "t", "y", *d.x).persist()
    done, out = _run_large(d, rows, configs), []
    rows.unpersist()
    for name, (s, trace) in done.items():
        last = configs[name].steps
        if not trace or trace[-1][0] != last:
            trace = [*trace, (last, s.f)]
        out += [(name, step, step == last, f.tolist()) for step, f in trace]
    return d.df.sparkSession.createDataFrame(out, TRACE)


def sample_prefetched(d: Data, rows: DataFrame, name: str, c: Config, block: int = 500) -> np.ndarray:
    """Last state of a chain over records of any number (``rows`` has row_id)."""
    return _run_large(d, rows, {name: c}, block)[name][0].f


def grid_posterior(df: DataFrame, grid: DataFrame, score, epsilon: float, v: float, sigma: float) -> DataFrame:
    """Exact probabilities on a small public grid (columns f1, f2): every record against every point, summed before anything moves."""
    pairs = df.crossJoin(F.broadcast(grid))  # the grid is public and bounded
    sums = pairs.groupBy("f1", "f2").agg(F.sum(F.col("w") * score).alias("loss"))
    logp = (epsilon / (2 * v)) * (-0.5 * sigma * (F.col("f1") ** 2 + F.col("f2") ** 2) - F.col("loss"))
    from pyspark.sql import Window

    all_ = Window.partitionBy(F.lit(0))
    rel = sums.withColumn("logp", logp).withColumn("rel", F.exp(F.col("logp") - F.max("logp").over(all_)))
    return rel.withColumn("p", F.col("rel") / F.sum("rel").over(all_)).select("f1", "f2", "p")


def variants(base: Config, **changes) -> Config:
    return replace(base, **changes)


def gaussian_chain(h: float, steps: int, temperature: str, seed: int = 0, precision: float = 1.0) -> float:
    """Variance of a chain with fixed step on a normal target of variance 1 / ``precision``: a check of the noise scale."""
    g, f, out = np.random.default_rng(seed), 0.0, []
    for _ in range(steps):
        f = f - h * precision * f + math.sqrt(h * (2 if temperature == "calibrated" else 1)) * g.standard_normal()
        out.append(f)
    return float(np.var(out[steps // 10 :]))
