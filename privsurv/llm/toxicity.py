"""Toxic spans by a linear-chain conditional random field; document scores from its marginals.

Labels are per document, so tokens are labelled first: in toxic documents, tokens whose word or word beginning is far
commoner in toxic than in clean documents (at least the most telling one); all tokens of clean documents are clean.
The field has two states, emissions summed over hashed features of a token and its neighbours, and a transition table.
It is trained by adaptive gradient steps on the exact conditional likelihood; tokens are then labelled again by its
marginals and it is trained once more.  A part of the sample is held back to turn marginals into document scores.

Forward and backward messages of two states are Moebius maps of one ratio, so whole batches run as one blocked scan.

Bound: training collects at most ``per_class`` labelled documents of each class, chosen by a hash of their ids, among
rows whose remainder isn't held out, and at most ``most_chars`` characters of whole texts.  Scoring reads every whole text; memory is bounded by the longest text.

Defined results: null and empty texts have no tokens and get the score of a document without evidence; null labels are
not used; if a class is missing, all documents score 0; repeated ids in ``labels`` count once (toxic if any says so);
extra columns pass through.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shingles as S
from .common import lean, sample_texts

BITS = 18
SLOTS = 9
FOLDS = 5


@dataclass
class Model:
    weights: np.ndarray  # kinds of features x table slots
    trans: np.ndarray  # 2 x 2 log potentials
    start: float
    bias: float
    doc: np.ndarray | None  # intercept, slope of the best logit, slope of the log mass


def features(w: S.Words) -> np.ndarray:
    """Table slots of each token: word, beginnings, ending, neighbours; one row per kind."""
    n = w.ends - w.starts
    rows = [w.hashes]
    rows += [w.span(w.starts, w.starts + np.minimum(n, k)) for k in (3, 4, 5, 6)]
    rows.append(w.span(w.ends - np.minimum(n, 3), w.ends))
    before, after = np.roll(w.hashes, 1), np.roll(w.hashes, -1)
    at = w.first[w.first < len(n)]
    before[at] = 1
    last = w.first[1:] - 1
    after[last[last >= 0]] = 2
    rows += [before, after, S.mix(n.astype(np.uint64))]
    return np.stack([(S.mix(r + np.uint64(k + 1)) >> np.uint64(64 - BITS)).astype(np.int32) for k, r in enumerate(rows)])


def emissions(m: Model, f: np.ndarray) -> np.ndarray:
    e = np.full(f.shape[1], m.bias)
    for k in range(SLOTS):
        e += m.weights[k][f[k]]
    return np.clip(e, -30, 30)


def _scan(a: np.ndarray, b: np.ndarray, c: np.ndarray, d: np.ndarray, r0: float) -> np.ndarray:
    """r[t] = (a r[t-1] + b) / (c r[t-1] + d), in blocks: first the blocks' maps, then their starts, then all values."""
    n = len(a)
    long = max(1, int(np.sqrt(n)))
    many = -(-n // long)
    pad = many * long - n
    a, b, c, d = (np.concatenate((x, np.full(pad, v))).reshape(many, long).T.copy() for x, v in ((a, 1.0), (b, 0.0), (c, 0.0), (d, 1.0)))
    pa, pb, pc, pd_ = a[0].copy(), b[0].copy(), c[0].copy(), d[0].copy()
    for t in range(1, long):
        pa, pb, pc, pd_ = a[t] * pa + b[t] * pc, a[t] * pb + b[t] * pd_, c[t] * pa + d[t] * pc, c[t] * pb + d[t] * pd_
        top = np.maximum(np.maximum(pa, pb), np.maximum(pc, pd_))
        pa /= top
        pb /= top
        pc /= top
        pd_ /= top
    begin = np.empty(many)
    r = r0
    for i, (x, y, z, w) in enumerate(zip(pa.tolist(), pb.tolist(), pc.tolist(), pd_.tolist(), strict=True)):
        begin[i] = r
        r = min(1e30, max(1e-30, (x * r + y) / max(z * r + w, 1e-300)))
    out = np.empty((long, many))
    r = begin
    for t in range(long):
        r = np.clip((a[t] * r + b[t]) / np.maximum(c[t] * r + d[t], 1e-300), 1e-30, 1e30)
        out[t] = r
    return out.T.reshape(-1)[:n]


def marginals(m: Model, e: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Probability of the toxic state of each token; forward and backward ratios. ``first``: starts of texts, then the number of tokens."""
    n = len(e)
    if not n:
        return np.zeros(0), np.zeros(0), np.zeros(0)
    ex, t = np.exp(e), np.exp(m.trans)
    heads = np.unique(first[:-1][first[:-1] < n])
    a, b, c, d = ex * t[1, 1], ex * t[0, 1], np.full(n, t[1, 0]), np.full(n, t[0, 0])
    a[heads], b[heads], c[heads], d[heads] = 0, ex[heads] * np.exp(m.start), 0, 1
    forward = _scan(a, b, c, d, 1.0)
    nxt = np.append(ex[1:], 1.0)
    a, b, c, d = nxt * t[1, 1], np.full(n, t[1, 0]), nxt * t[0, 1], np.full(n, t[0, 0])
    tails = np.unique(np.append(heads[1:] - 1, n - 1))
    a[tails], b[tails], c[tails], d[tails] = 0, 1, 0, 1
    backward = _scan(a[::-1], b[::-1], c[::-1], d[::-1], 1.0)[::-1]
    odds = forward * backward
    return odds / (1 + odds), forward, backward


def _probabilities(m: Model, f: np.ndarray, first: np.ndarray) -> np.ndarray:
    out = np.zeros(f.shape[1])
    for a, b in S.batches(np.diff(first).tolist(), 100_000):
        own = slice(first[a], first[b])
        out[own] = marginals(m, emissions(m, f[:, own]), first[a : b + 1] - first[a])[0]
    return out


def _log_odds(f: np.ndarray, first: np.ndarray, toxic: np.ndarray) -> np.ndarray:
    """Best log ratio, over the word and its beginnings, of document frequencies in toxic and clean documents."""
    doc = np.repeat(np.arange(len(first) - 1), np.diff(first))
    best = np.full(f.shape[1], -9.0)
    n1, n0 = max(1, toxic.sum()), max(1, (~toxic).sum())
    for k in (0, 3, 4):
        seen = np.unique(doc.astype(np.int64) << BITS | f[k])
        slot, hit = seen & ((1 << BITS) - 1), toxic[seen >> BITS]
        c1, c0 = np.bincount(slot[hit], minlength=1 << BITS), np.bincount(slot[~hit], minlength=1 << BITS)
        ratio = np.log((c1 + 0.1) / (n1 + 1)) - np.log((c0 + 1.0) / (n0 + 1)) - 2.0 / np.sqrt(c1 + 1.0)
        best = np.maximum(best, ratio[f[k]])
    return best


def _label(signal: np.ndarray, first: np.ndarray, toxic: np.ndarray, above: float) -> np.ndarray:
    y = signal > above
    for i, bad in enumerate(toxic):
        own = slice(first[i], first[i + 1])
        if not bad:
            y[own] = False
        elif first[i + 1] > first[i] and not y[own].any():
            y[first[i] + int(np.argmax(signal[own]))] = True
    return y


def _train(f: np.ndarray, first: np.ndarray, y: np.ndarray, epochs: int, seed: int) -> Model:
    rng = np.random.default_rng(seed)
    m = Model(np.zeros((SLOTS, 1 << BITS)), np.zeros((2, 2)), 0.0, -3.0, None)
    seen, seen_t, seen_b = np.full((SLOTS, 1 << BITS), 1e-3), np.full((2, 2), 1e-3), 1e-3
    order, size = np.arange(len(first) - 1), np.diff(first)
    for _ in range(epochs):
        rng.shuffle(order)
        for lo, hi in S.batches(size[order].tolist(), 20_000):
            docs = order[lo:hi]
            index = np.concatenate([np.arange(first[i], first[i + 1]) for i in docs])
            if not len(index):
                continue
            own, heads = f[:, index], np.concatenate(([0], np.cumsum(size[docs])))
            target = y[index].astype(float)
            e = emissions(m, own)
            p, fw, bw = marginals(m, e, heads)
            g = p - target
            for k in range(SLOTS):
                slot, at = np.unique(own[k], return_inverse=True)
                step = np.bincount(at, weights=g) + 0.02 * m.weights[k][slot]
                seen[k][slot] += step * step
                m.weights[k][slot] -= 0.3 * step / np.sqrt(seen[k][slot])
            inner = np.ones(len(index), dtype=bool)
            inner[heads[:-1][heads[:-1] < len(index)]] = False
            j = np.flatnonzero(inner)
            pair = np.empty((len(j), 2, 2))
            t = np.exp(m.trans)
            for a in (0, 1):
                for b in (0, 1):
                    pair[:, a, b] = (fw[j - 1] if a else 1.0) * t[a, b] * (np.exp(e[j]) * bw[j] if b else 1.0)
            pair /= pair.sum(axis=(1, 2), keepdims=True)
            want = np.zeros((2, 2))
            np.add.at(want, (y[index][j - 1].astype(int), y[index][j].astype(int)), 1)
            step = (pair.sum(axis=0) - want) / 50
            seen_t += step * step
            m.trans -= 0.1 * step / np.sqrt(seen_t)
            step = g.sum() / 50
            seen_b += step * step
            m.bias -= 0.1 * step / np.sqrt(seen_b)
    return m


def summary(p: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Per document: one, the best token's logit, the log of the expected number of toxic tokens."""
    n = len(first) - 1
    out = np.zeros((n, 3))
    out[:, 0], out[:, 1] = 1, -12
    full = np.flatnonzero(np.diff(first) > 0)
    if len(full):
        top = np.clip(np.maximum.reduceat(p, first[full]), 1e-6, 1 - 1e-6)
        out[full, 1] = np.log(top / (1 - top))
        out[full, 2] = np.log1p(np.add.reduceat(np.where(p > 0.05, p, 0), first[full]))
    return out


def _logistic(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Newton steps with a small ridge towards a sensible rule."""
    prior = np.array([0.0, 0.8, 0.5])
    b = prior.copy()
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -30, 30)))
        h = (x * (p * (1 - p))[:, None]).T @ x + 0.5 * np.eye(3)
        b = b - np.linalg.solve(h, x.T @ (p - y) + 0.5 * (b - prior))
    return b


def fit(texts: list[str], toxic: np.ndarray, epochs: int = 4, seed: int = 3) -> Model:
    """Trains on texts with document labels."""
    if not len(texts) or toxic.all() or not toxic.any():
        return Model(np.zeros((SLOTS, 1)), np.zeros((2, 2)), 0.0, -9.0, np.array([-50.0, 0.0, 0.0]))
    held = np.random.default_rng(seed).random(len(texts)) < 0.25
    if not (toxic & held).any() or not (toxic & ~held).any():
        held = np.zeros(len(texts), dtype=bool)
    order = np.argsort(held, kind="stable")  # those held back come last
    texts, toxic, held = [texts[i] for i in order], toxic[order], held[order]
    fs, sizes = [], []
    for t in texts:
        parts = [S.words([p]) for p in S.pieces(S.lower(t).encode("utf-8", "surrogatepass"))]
        fs += [features(p) for p in parts]
        sizes.append(sum(len(p.starts) for p in parts))
    f, first = np.concatenate(fs, axis=1), np.concatenate(([0], np.cumsum(sizes)))
    del fs
    some = int((~held).sum())
    first1, toxic1 = first[: some + 1], toxic[:some]
    f1 = f[:, : first1[-1]]
    y = _label(_log_odds(f1, first1, toxic1), first1, toxic1, 2.0)
    m = _train(f1, first1, y, epochs, seed)
    m = _train(f1, first1, _label(_probabilities(m, f1, first1), first1, toxic1, 0.5), epochs, seed + 1)
    p = _probabilities(m, f, first)
    use = held if held.any() else np.ones(len(texts), dtype=bool)
    m.doc = _logistic(summary(p, first)[use], toxic[use].astype(float))
    m.weights = m.weights.astype(np.float32)
    return m


def score(m: Model, texts: list[str], spans: bool = False) -> tuple[np.ndarray, list[list[tuple[int, int]]]]:
    """Document scores, and if asked for the toxic spans in code points."""
    out, found = np.zeros(len(texts)), [[] for _ in texts]
    if m.weights.shape[1] == 1:
        return out, found
    for a, b in S.batches([len(t) for t in texts], S.BLOCK):
        raws = [S.lower(t).encode("utf-8", "surrogatepass") for t in texts[a:b]]
        split = list(S.pieces(raws[0])) if b - a == 1 else None
        es, places, first, at = [], [], None, 0
        for part in split or [None]:
            w = S.words(raws if part is None else [part])
            es.append(emissions(m, features(w)))
            places.append(np.stack((w.starts, w.ends)) + at)
            first, at = w.first, at + len(part or b"")
        e = np.concatenate(es)
        first = np.array([0, len(e)]) if split else first
        p, *_ = marginals(m, e, first)
        out[a:b] = 1 / (1 + np.exp(-np.clip(summary(p, first) @ m.doc, -30, 30)))
        if spans and len(p):
            _collect(found, a, raws, np.concatenate(places, axis=1), first, p > 0.5)
    return out, found


def _collect(found: list[list[tuple[int, int]]], a: int, raws: list[bytes], places: np.ndarray, first: np.ndarray, toxic: np.ndarray) -> None:
    """Adds the toxic tokens' spans in code points; tokens at most one character apart make one span."""
    begins = np.cumsum([0, *[len(r) + 1 for r in raws]])
    hits = np.flatnonzero(toxic)
    owner = np.searchsorted(first, hits, side="right") - 1
    for d in np.unique(owner).tolist():
        own = places[:, hits[owner == d]] - begins[d]
        chars = np.concatenate(([0], np.cumsum((np.frombuffer(raws[d], dtype=np.uint8) & 0xC0) != 0x80)))  # code points before each byte
        for lo, hi in chars[own].T.tolist():
            if found[a + d] and lo - found[a + d][-1][1] <= 1:
                found[a + d][-1] = (found[a + d][-1][0], hi)
            else:
                found[a + d].append((lo, hi))


def fold(column: str = "doc_id"):
    return F.crc32(F.encode(F.col(column).cast("string"), "UTF-8")) % FOLDS


def train_on(docs: DataFrame, labels: DataFrame, per_class: tuple[int, int] = (1000, 2500), most_chars: int = 10_000_000, seed: int = 3, held_out: bool = True) -> Model:
    """Fits on a bounded sample: at most ``per_class`` toxic and clean labelled documents, none of them held out, and of these as
    many as have ``most_chars`` characters together."""
    known = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    if held_out:
        known = known.where(fold() != 0)
    picked = []
    for value, most in zip((1, 0), per_class, strict=True):
        picked += [(r[0], value) for r in known.where(F.col("toxic") == value).select("doc_id").orderBy(F.xxhash64(F.lit(seed), "doc_id"), "doc_id").limit(most).collect()]
    if not picked:
        return fit([], np.zeros(0, dtype=bool))
    rows = sample_texts(docs, picked, "int", most_chars)
    return fit([r[1] for r in rows], np.array([r[2] for r in rows], dtype=int) == 1, seed=seed)


def score_documents(docs: DataFrame, model: Model, spans: bool = True) -> DataFrame:
    """Adds ``tox_score`` and, if asked for, ``tox_spans`` (code point ranges) to doc_id."""
    held = docs.sparkSession.sparkContext.broadcast(model)  # 10 MB

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in frames:
            value, found = score(held.value, x["text"].fillna("").tolist(), spans)
            out = pd.DataFrame({"doc_id": x["doc_id"], "tox_score": value})
            if spans:
                out["tox_spans"] = [[{"begin": a, "end": b} for a, b in f] for f in found]
            yield out

    kind = "doc_id long, tox_score double" + ", tox_spans array<struct<begin:long,end:long>>" * spans
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInPandas(lean(run), kind)


def toxicity(docs: DataFrame, labels: DataFrame, held_out: bool = True) -> DataFrame:
    """doc_id, held_out, score, predicted, spans (code points of toxic tokens)."""
    scored = score_documents(docs, train_on(docs, labels, held_out=held_out))
    held, predicted = (F.coalesce(fold(), F.lit(1)) == 0).alias("held_out"), (F.col("tox_score") >= 0.5).cast("int").alias("predicted")
    return scored.select("doc_id", held, F.col("tox_score").alias("score"), predicted, F.col("tox_spans").alias("spans"))
