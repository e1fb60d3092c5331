"""Soft-membership mixing of documents to target domain weights.

A softmax classifier on hashed words, fitted on labelled rows, gives each document a posterior over domains.  Documents
get rates (how often to draw them) that minimise a squared distance (weighted by the posteriors' inverse Gram matrix) of expected domain token totals from the targets,
subject to rates of at least ``least`` (nonnegative by default), starting from one.  The solver is accelerated
projected gradient descent.  A document's rate follows from its posterior and the few residual vectors of earlier
steps, so a step is one pass over a narrow table that returns one sum per domain; no rates are stored or collected.

Domains are pairs of quality and toxicity of ``labels`` (any table with doc_id, domain works in ``fit_classifier``).
Bound: at most ``per_domain`` labelled rows of each domain and ``most_chars`` characters are collected for training, chosen by a hash of
their ids.

Defined results: null and empty texts count one token (their end) and get the posterior of no evidence; documents without labels are treated as all
others; with one domain or none, all posteriors are one for it and rates scale to the budget; repeated rows get equal rates; an empty table gives no rows.
"""

from __future__ import annotations

import warnings
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import shingles as S
from .common import cut, lean, sample_texts

BITS = 15


@dataclass
class Classifier:
    names: list[str]
    weights: np.ndarray  # 2^BITS x domains
    bias: np.ndarray


def _slots(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    hashes, first = S.word_hashes(texts)
    return (hashes >> S.U(64 - BITS)).astype(np.int64), first


def posteriors(c: Classifier, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Token counts (words and the end) and posteriors."""
    tokens, out = np.ones(len(texts), dtype=np.int64), np.zeros((len(texts), len(c.names)))
    for a, b in S.batches([len(t) for t in texts]):
        slot, first = _slots(texts[a:b])
        n = np.diff(first)
        z = np.zeros((b - a, len(c.names)))
        full = np.flatnonzero(n)
        if len(full):
            for k in range(len(c.names)):
                z[full, k] = np.add.reduceat(c.weights[slot, k], first[full]) / n[full]
        z += c.bias
        z = np.exp(z - z.max(axis=1, keepdims=True))
        out[a:b] = z / z.sum(axis=1, keepdims=True)
        tokens[a:b] += n
    return tokens, out


def fit(texts: list[str], domain: np.ndarray, names: list[str], steps: int = 60) -> Classifier:
    """Adaptive full-batch steps on the mean log loss."""
    c = Classifier(names, np.zeros((1 << BITS, len(names))), np.zeros(len(names)))
    if len(names) < 2:
        return c
    slot, first = _slots(texts)
    n = np.diff(first)
    full = np.flatnonzero(n)
    y = np.eye(len(names))[domain]
    share = y.mean(axis=0)
    c.bias = np.log(np.maximum(share, 1e-6))
    seen, seen_b = np.full_like(c.weights, 1e-8), np.full(len(names), 1e-8)
    for _ in range(steps):
        z = np.zeros((len(texts), len(names)))
        for k in range(len(names)):
            z[full, k] = np.add.reduceat(c.weights[slot, k], first[full]) / n[full]
        z += c.bias
        z = np.exp(z - z.max(axis=1, keepdims=True))
        g = (z / z.sum(axis=1, keepdims=True) - y) / len(texts)
        per = np.repeat(g / np.maximum(n, 1)[:, None], n, axis=0)
        for k in range(len(names)):
            step = np.bincount(slot, weights=per[:, k], minlength=1 << BITS) + 1e-7 * c.weights[:, k]
            seen[:, k] += step * step
            c.weights[:, k] -= 3.0 * step / np.sqrt(seen[:, k])
        step = g.sum(axis=0)
        seen_b += step * step
        c.bias -= 0.1 * step / np.sqrt(seen_b)
    return c


def domains(labels: DataFrame) -> DataFrame:
    """doc_id, domain from quality and toxicity; rows with nulls have no domain."""
    return labels.where("doc_id is not null and quality is not null and toxic is not null").select("doc_id", F.concat(F.lit("q"), F.col("quality"), F.lit("t"), F.col("toxic")).alias("domain"))


def fit_classifier(docs: DataFrame, labelled: DataFrame, per_domain: int = 1000, most_chars: int = 10_000_000, seed: int = 4) -> Classifier:
    """``labelled``: doc_id, domain (few distinct values).  Collects at most ``per_domain`` texts of each, ``most_chars`` characters in all."""
    held = labelled.join(docs.select("doc_id").distinct(), "doc_id", "left_semi")
    many = {r[0]: r[1] for r in held.groupBy("domain").count().collect()}  # the domains
    names = sorted(many)
    picked = []
    for name in names:
        picked += [(r[0], name) for r in held.where(F.col("domain") == name).select("doc_id").orderBy(F.xxhash64(F.lit(seed), "doc_id"), "doc_id").limit(per_domain).collect()]
    if len(names) < 2:
        return fit([], np.zeros(0, dtype=int), names or ["all"])
    rows = sample_texts(docs, picked, "string", most_chars)
    taken = Counter(r[2] for r in rows)
    c = fit([r[1] for r in rows], np.array([names.index(r[2]) for r in rows], dtype=int), names)
    # Sampling by domain changed the priors; put them back.
    c.bias += np.log([many[n] / max(1, taken[n]) for n in names])
    return c


def judged(docs: DataFrame, c: Classifier) -> Column:
    """Struct of n (tokens) and p (posteriors) of ``text``, as a column."""
    held = docs.sparkSession.sparkContext.broadcast(c)

    @F.pandas_udf("n long, p array<double>")
    def run(text: pd.Series) -> pd.DataFrame:
        n, p = posteriors(held.value, text.fillna("").tolist())
        return pd.DataFrame({"n": n, "p": list(p)})

    return run(F.col("text").cast("string"))


def rates(p: np.ndarray, history: list[np.ndarray], size: float, least: float) -> np.ndarray:
    """The rates that accelerated projected steps give: one residual vector per step made.

    The first value is the point where the next residual is taken.
    """
    r = y = np.ones(len(p))
    t = 1.0
    for e in history:
        r2 = np.maximum(least, y - size * (p @ e))
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        y, r, t = r2 + (t - 1) / t2 * (r2 - r), r2, t2
    return np.stack((y, r))


@dataclass
class Mix:
    classifier: Classifier
    history: list[np.ndarray]
    size: float
    least: float
    targets: np.ndarray
    totals: np.ndarray

    @property
    def gap(self) -> float:
        """Largest distance of a domain's expected tokens from its target, as a share of all target tokens."""
        return float(np.abs(self.totals - self.targets).max(initial=0.0) / max(1e-300, self.targets.sum()))


def solve(table: DataFrame, k: int, targets, least: float = 0.0, steps: int = 60, tolerance: float = 1e-5, stall: float = 1e-4) -> tuple[list[np.ndarray], float, np.ndarray, np.ndarray]:
    """``table``: n, p.  ``targets`` makes token totals into target totals.  Returns residuals, step size, targets, totals reached."""
    pairs = [F.sum(F.col("n") * F.get("p", i) * F.get("p", j)) for i in range(k) for j in range(i, k)]
    first = table.agg(F.sum("n"), *[F.sum(F.col("n") * F.get("p", i)) for i in range(k)], *pairs).first()
    total = float(first[0] or 0)
    have = np.array([float(x or 0) for x in first[1 : k + 1]])
    want = targets(have)
    if not total:
        return [], 1.0, want, have
    gram, at = np.zeros((k, k)), k + 1
    for i in range(k):
        for j in range(i, k):
            gram[i, j] = gram[j, i] = float(first[at]) / total
            at += 1
    # Distances are measured in the inverse Gram metric of the posteriors, each document's step is scaled by the inverse
    # of its tokens: then the unconstrained problem has condition number one, and a unit step is safe.
    metric, size = np.linalg.inv(gram + 1e-6 * np.trace(gram) * np.eye(k)), 1.0
    history: list[np.ndarray] = []
    sums = have

    def totals(which: int) -> np.ndarray:
        past = list(history)

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            out = np.zeros(k)
            for x in frames:
                p = np.stack(x["p"].to_numpy()) if len(x) else np.zeros((0, k))
                out += (rates(p, past, size, least)[which] * x["n"].to_numpy(dtype=float)) @ p
            yield pd.DataFrame({f"s{i}": [out[i]] for i in range(k)})

        row = table.select("n", "p").mapInPandas(lean(run), ", ".join(f"s{i} double" for i in range(k))).agg(*[F.sum(f"s{i}") for i in range(k)]).first()
        return np.array([float(x or 0) for x in row])

    for _ in range(steps):
        residual = (sums - want) / total
        history.append(metric @ residual)
        before, sums = sums, totals(0)
        # Targets are met, or (where no rates meet them) steps change next to nothing any more.
        if np.abs(sums - want).max() <= tolerance * want.sum() or np.abs(sums - before).max() <= stall * want.sum():
            break
    reached = totals(1)
    if np.abs(reached - want).max() > 0.01 * want.sum():
        # Said, since a caller may want other targets; the rates are the nearest that were found.
        warnings.warn(f"no rates of at least {least:g} were found that meet the targets: reached {reached.round()}, wanted {want.round()}", stacklevel=2)
    return history, size, want, reached


def fit_mix(docs: DataFrame, labelled: DataFrame, weights: dict[str, float], budget: float | str | None = None, least: float = 0.0, c: Classifier | None = None) -> tuple[Mix, DataFrame]:
    """``weights``: wanted share of tokens per domain (unnamed domains share the rest by size). ``budget``: tokens in all, as
    many as now if None, or ``grow``: the fewest at which no domain must shrink."""
    c = c or fit_classifier(docs, labelled)
    table = cut(docs.select("doc_id", judged(docs, c).alias("j")).select("doc_id", "j.n", "j.p"), "mix-posteriors")

    def targets(have: np.ndarray) -> np.ndarray:
        share = np.array([weights.get(n, np.nan) for n in c.names])
        rest = np.isnan(share)
        left = max(0.0, 1 - np.nansum(share))
        share[rest] = left * have[rest] / max(have[rest].sum(), 1e-12)
        share = share / max(share.sum(), 1e-12)
        if budget == "grow":
            return share * max((h / s for h, s in zip(have, share, strict=True) if s > 0 and h > 0), default=0.0)
        return share * (have.sum() if budget is None else budget)

    history, size, want, reached = solve(table, len(c.names), targets, least)
    return Mix(c, history, size, least, want, reached), table


def rate_column(mix: Mix, name: str = "p") -> Column:
    """Rate of a row from its posterior column."""

    @F.pandas_udf("double")
    def run(p: pd.Series) -> pd.Series:
        return pd.Series(rates(np.stack(p.to_numpy()), mix.history, mix.size, mix.least)[1] if len(p) else np.zeros(0))

    return run(F.col(name))


def rate_of_text(docs: DataFrame, mix: Mix) -> Column:
    """Rate of a row from its whole text, in one pass."""
    held = docs.sparkSession.sparkContext.broadcast(mix)

    @F.pandas_udf("double")
    def run(text: pd.Series) -> pd.Series:
        m = held.value
        return pd.Series(rates(posteriors(m.classifier, text.fillna("").tolist())[1], m.history, m.size, m.least)[1])

    return run(F.col("text").cast("string"))


def copies(rate: Column, seed: int, *names: str) -> Column:
    """Whole number of copies: the rate, rounded up or down by a hash of the row's names, so that its mean is the rate."""
    u = F.pmod(F.xxhash64(F.lit(seed), *[F.col(n) for n in names]), F.lit(1 << 20)) / float(1 << 20)
    return F.floor(rate + u).cast("int")


#: Wanted shares of tokens: mostly good, clean text.
WEIGHTS = {"q1t0": 0.8}


def mix_documents(docs: DataFrame, labels: DataFrame, weights: dict[str, float] | None = None, seed: int = 6) -> DataFrame:
    """doc_id, n_tokens, posteriors (map of domain to probability), rate, copies."""
    mix, table = fit_mix(docs, domains(labels), weights or WEIGHTS)
    named = F.map_from_arrays(F.array(*[F.lit(n) for n in mix.classifier.names]), F.transform("p", lambda x: F.round(x, 6)))
    rated = table.withColumn("rate", rate_column(mix))
    return rated.select("doc_id", F.col("n").alias("n_tokens"), named.alias("posteriors"), F.round("rate", 6).alias("rate"), copies(F.col("rate"), seed, "doc_id").alias("copies"))
