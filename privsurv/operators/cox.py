"""Cox partial likelihood, non-private: the continuous-time model the discrete one is compared with.

Records are first summed per distinct time (weights, weighted covariates, their products); risk sets are running totals of those
sums from the last time back.  With discretised times the sums are q rows, made by a numpy kernel per partition; raw times keep one
row per distinct time, in columns.  Tied events under Efron's rule are summed in closed form, whatever their number.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import gammas
from ..functions.loss import dot
from .prep import covariates


def _sums(df: DataFrame, x: Sequence[str], beta: Sequence[float], time: str) -> DataFrame:
    """Per distinct time: sums over the records that end there (r_) and over the events there (e_)."""
    z = F.exp(dot([F.col(c) for c in x], beta))
    w, event = F.col("w").cast("double"), F.col("y") == 1
    terms: list[Column] = []
    for tag, keep in (("r", F.lit(True)), ("e", event)):
        own = lambda c, keep=keep: F.sum(F.when(keep, w * c).otherwise(0.0))
        terms.append(own(z).alias(f"{tag}0"))
        terms += [own(z * F.col(c)).alias(f"{tag}1_{i}") for i, c in enumerate(x)]
        terms += [own(z * F.col(a) * F.col(b)).alias(f"{tag}2_{i}_{j}") for i, a in enumerate(x) for j, b in enumerate(x) if j >= i]
    terms.append(F.sum(F.when(event, w).otherwise(0.0)).alias("m"))
    terms.append(F.sum(F.when(event, w * dot([F.col(c) for c in x], beta)).otherwise(0.0)).alias("bx"))
    terms += [F.sum(F.when(event, w * F.col(c)).otherwise(0.0)).alias(f"x_{i}") for i, c in enumerate(x)]
    return df.groupBy(F.col(time).alias("time")).agg(*terms)


def cell_edges(df: DataFrame, time: str, cells: int = 256) -> list[float]:
    """Bounds of ranges that hold about as many records each, however the times are spread."""
    found = df.approxQuantile(time, [i / cells for i in range(1, cells)], 0.25 / cells)
    return sorted({float(v) for v in found})


def _cell(time: Column, edges: Sequence[float]) -> Column:
    """How many edges are at most ``time``: binary search."""
    if not edges:
        return F.lit(0)
    held = F.array(*[F.lit(v) for v in edges])
    steps = F.array(*[F.lit(1 << k) for k in range(len(edges).bit_length() - 1, -1, -1)])
    return F.aggregate(steps, F.lit(0), lambda at, s: F.when((at + s <= len(edges)) & (F.get(held, at + s - 1) <= time), at + s).otherwise(at))


def _running(df: DataFrame, names: Sequence[str], edges: Sequence[float], backwards: bool) -> DataFrame:
    """Totals of columns over ``time`` up to each row, in two levels: cells, then inside them; no single task sorts all times."""
    way = (lambda c: F.col(c).desc()) if backwards else F.col
    held = df.withColumn("cell", _cell(F.col("time").cast("double"), edges))
    before = Window.partitionBy(F.lit(0)).orderBy(way("cell")).rowsBetween(Window.unboundedPreceding, -1)
    whole = held.groupBy("cell").agg(*[F.sum(c).alias(c) for c in names])  # one row per cell
    whole = whole.select("cell", *[F.coalesce(F.sum(c).over(before), F.lit(0.0)).alias(f"before_{c}") for c in names])
    inside = Window.partitionBy("cell").orderBy(way("time")).rowsBetween(Window.unboundedPreceding, 0)
    rest = [c for c in df.columns if c not in names]
    out = held.select("cell", *rest, *[F.sum(c).over(inside).alias(f"in_{c}") for c in names]).join(F.broadcast(whole), "cell")
    return out.select(*rest, *[(F.col(f"in_{c}") + F.col(f"before_{c}")).alias(c) for c in names])


def risk_sets(df: DataFrame, x: Sequence[str], beta: Sequence[float], time: str = "t", edges: Sequence[float] | None = None) -> DataFrame:
    """Running totals from the last time back."""
    sums = _sums(df, x, beta, time)
    return _running(sums, [c for c in sums.columns if c[0] == "r"], cell_edges(df, time) if edges is None else edges, True)


def _efron(m, r0, e0, log, power_sums):
    """Over the m tied events at a time, whose risk total falls from r0 in m equal parts of e0: sums of the log, the inverse and the squared inverse."""
    c = e0 / m
    top = r0 / c
    few, many = power_sums
    exact = (
        m * log(c) + gammas.log_gamma(top + 1, log) - gammas.log_gamma(top - m + 1, log),
        (gammas.digamma(top + 1, log) - gammas.digamma(top - m + 1, log)) / c,
        (gammas.trigamma(top - m + 1) - gammas.trigamma(top + 1)) / (c * c),
    )
    return tuple(many(a, b) for a, b in zip(few(m, r0, c), exact, strict=True))


FEW = 32  # ties up to this many are summed one by one, more in closed form


def _column_sums(m: Column, r0: Column, c: Column) -> tuple[Column, ...]:
    """Sums over few ties inside a row; rows with more get a null."""
    k = F.when(m <= FEW, F.sequence(F.lit(0), F.greatest(F.lit(0), m.cast("int") - 1)))
    total = lambda f: F.aggregate(F.transform(k, f), F.lit(0.0), lambda a, v: a + v)
    return total(lambda i: F.log(r0 - i * c)), total(lambda i: 1 / (r0 - i * c)), total(lambda i: 1 / ((r0 - i * c) * (r0 - i * c)))


def _array_sums(m: np.ndarray, r0: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, ...]:
    out = np.full((3, len(m)), np.nan)
    for i in np.flatnonzero(m <= FEW).tolist():
        left = r0[i] - np.arange(int(m[i])) * c[i]
        out[:, i] = np.log(left).sum(), (1 / left).sum(), (1 / left**2).sum()
    return tuple(out)


def _grid_sums(df: DataFrame, x: Sequence[str], beta: Sequence[float]) -> dict[str, np.ndarray]:
    """The sums of ``_sums`` per interval, from numpy sums of each partition: q rows of them reach the driver."""
    p, names, b = len(x), list(x), np.asarray(beta, dtype=float)
    up = np.triu_indices(p)
    size = 2 * (1 + p + len(up[0])) + 2 + p

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        out: dict[int, np.ndarray] = {}
        for f in frames:
            cols, w, event = f[names].to_numpy(dtype=float), f["w"].to_numpy(dtype=float), (f["y"] == 1).to_numpy()
            z = cols @ b
            risk = w * np.exp(z)
            own = np.concatenate((risk[:, None], risk[:, None] * cols, (risk[:, None] * cols[:, up[0]] * cols[:, up[1]])), axis=1)
            rows = np.concatenate((own, own * event[:, None], (w * event)[:, None], (w * event * z)[:, None], (w * event)[:, None] * cols), axis=1)
            t, at = np.unique(f["t"].to_numpy(), return_inverse=True)
            sums = np.zeros((len(t), size))
            np.add.at(sums, at, rows)
            for k, v in zip(t.tolist(), sums, strict=True):
                out[k] = out[k] + v if k in out else v
        for k, v in out.items():
            yield pd.DataFrame({"t": k, "i": np.arange(size), "v": v})

    rows = df.select("t", "y", "w", *names).mapInPandas(run, "t int, i int, v double").groupBy("t", "i").agg(F.sum("v").alias("v")).collect()  # q rows of sums
    times = sorted({r["t"] for r in rows})
    at = {t: k for k, t in enumerate(times)}
    m = np.zeros((len(times), size))
    for r in rows:
        m[at[r["t"]], r["i"]] = r["v"]
    wide = 1 + p + len(up[0])
    risk = np.cumsum(m[::-1, :wide], axis=0)[::-1]
    return {"r": risk, "e": m[:, wide : 2 * wide], "m": m[:, 2 * wide], "bx": m[:, 2 * wide + 1], "x": m[:, 2 * wide + 2 :]}


def _on_grid(df: DataFrame, x: Sequence[str], beta: Sequence[float], ties: str) -> tuple[float, np.ndarray, np.ndarray]:
    p, s = len(x), _grid_sums(df, x, beta)
    keep = s["m"] > 0
    r, e, m = s["r"][keep], s["e"][keep], s["m"][keep]
    r0, e0 = r[:, 0], e[:, 0]
    if ties == "breslow":
        l0, s1, s2 = m * np.log(r0), m / r0, m / r0**2
        t1 = t2 = u2 = np.zeros(len(m))
    else:
        l0, s1, s2 = _efron(m, r0, e0, np.log, (_array_sums, lambda few, many: np.where(np.isnan(few), many, few)))
        t1 = (r0 * s1 - m) / e0
        t2 = (r0 * s2 - s1) / e0
        u2 = (r0 * t2 - t1) / e0
    value = float(s["bx"][keep].sum() - l0.sum())
    r1, e1 = r[:, 1 : p + 1], e[:, 1 : p + 1]
    g = s["x"][keep].sum(axis=0) - s1 @ r1 + t1 @ e1
    h, up = np.zeros((p, p)), np.triu_indices(p)
    h[up] = -(s1 @ r[:, p + 1 :] - t1 @ e[:, p + 1 :])
    h = h + h.T - np.diag(np.diag(h))
    cross = (r1 * t2[:, None]).T @ e1
    return value, g, h + (r1 * s2[:, None]).T @ r1 - cross - cross.T + (e1 * u2[:, None]).T @ e1


def partial_likelihood(df: DataFrame, x: Sequence[str], beta: Sequence[float], ties: str = "breslow", time: str = "t", edges: Sequence[float] | None = None) -> tuple[float, np.ndarray, np.ndarray]:
    """Log partial likelihood, gradient and Hessian at beta, as sums over event times."""
    if ties not in ("breslow", "efron"):
        raise ValueError("ties are breslow or efron")
    if time == "t":
        return _on_grid(df, x, beta, ties)
    p = len(x)
    rows = risk_sets(df, x, beta, time, edges).where("m > 0")
    m, r0, e0 = F.col("m"), F.col("r0"), F.col("e0")
    if ties == "breslow":
        l0, s1, s2, t1, t2, u2 = m * F.log(r0), m / r0, m / (r0 * r0), F.lit(0.0), F.lit(0.0), F.lit(0.0)
    else:
        l0, s1, s2 = _efron(m, r0, e0, F.log, (_column_sums, lambda few, many: F.coalesce(few, many)))
        t1 = (r0 * F.col("s1") - m) / e0
        t2 = (r0 * F.col("s2") - F.col("s1")) / e0
        u2 = (r0 * F.col("t2") - F.col("t1")) / e0
    rows = rows.withColumns({"l0": l0, "s1": s1, "s2": s2}).withColumns({"t1": t1, "t2": t2}).withColumn("u2", u2)
    pair = [(i, j) for i in range(p) for j in range(i, p)]
    c = F.col
    terms = [F.sum(c("bx") - c("l0")).alias("v")]
    terms += [F.sum(c(f"x_{i}") - c("s1") * c(f"r1_{i}") + c("t1") * c(f"e1_{i}")).alias(f"g{i}") for i in range(p)]
    for i, j in pair:
        square = c("s2") * c(f"r1_{i}") * c(f"r1_{j}") - c("t2") * (c(f"r1_{i}") * c(f"e1_{j}") + c(f"e1_{i}") * c(f"r1_{j}")) + c("u2") * c(f"e1_{i}") * c(f"e1_{j}")
        terms.append(F.sum(-(c("s1") * c(f"r2_{i}_{j}") - c("t1") * c(f"e2_{i}_{j}") - square)).alias(f"h{i}_{j}"))
    row = rows.agg(*terms).first()
    g, h = np.array([row[f"g{i}"] or 0.0 for i in range(p)]), np.zeros((p, p))
    for i, j in pair:
        h[i, j] = h[j, i] = row[f"h{i}_{j}"] or 0.0
    return row["v"] or 0.0, g, h


def fit(df: DataFrame, ties: str = "breslow", time: str = "t", most: int = 30, tolerance: float = 1e-9) -> np.ndarray:
    """Newton steps with halving."""
    x = covariates(df)
    edges = None if time == "t" else cell_edges(df, time)
    at = lambda b: partial_likelihood(df, x, b, ties, time, edges)
    beta = np.zeros(len(x))
    value, g, h = at(beta)
    for _ in range(most):
        step = np.linalg.solve(h - 1e-12 * np.eye(len(x)), g)
        scale = 1.0
        while True:
            new = beta - scale * step
            v, g2, h2 = at(new)
            if v >= value - 1e-12 * abs(value) or scale < 1e-4:
                break
            scale /= 2
        done = np.abs(new - beta).max() < tolerance
        beta, value, g, h = new, v, g2, h2
        if done:
            break
    return beta


def baseline(df: DataFrame, beta: Sequence[float], time: str = "t") -> DataFrame:
    """Cumulative baseline hazard: events over risk-set weight, added up over event times."""
    edges = cell_edges(df, time)
    rows = risk_sets(df, covariates(df), beta, time, edges).where("m > 0").select("time", (F.col("m") / F.col("r0")).alias("cumulative"))
    return _running(rows, ["cumulative"], edges, False)


def projected(df: DataFrame, r: int, seed: int = 0) -> DataFrame:
    """Covariates times a seeded random matrix: fewer of them, but no formal privacy."""
    x = covariates(df)
    from ..functions import rng

    m = np.array([[rng.normal_value(seed, "project", i, j) for j in range(r)] for i in range(len(x))]) / r**0.5
    return df.select("subject_id", "unit_id", "t", "y", *[dot([F.col(c) for c in x], m[:, j]).alias(f"x{j + 1}") for j in range(r)], "w")
