"""Exact Jaccard links inside candidate buckets, and connected components of links.

Both the chosen-path join and the banded fingerprints give each set some bucket numbers.  A pair of sets is the business
of the smallest bucket they share, so each pair is compared once and link counts add up without listing pairs.  Buckets
over ``BLOCK`` members are cut into blocks and compared block by block; no bucket is ever one task's unbounded group.
First signatures are compared, then only sets with a likely partner have their texts fetched and verified exactly.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shingles as S
from .common import cut, lean, ordered, parts, whole

BLOCK = 1024
SLACK = 0.2  # signatures may fall this far below the threshold before a pair is dropped unverified


def passes(count: int, threshold: float) -> float:
    """Probability that a pair at the threshold agrees in enough of ``count`` minima to be verified."""
    least = math.ceil((threshold - SLACK) * count - 1e-9)
    return sum(math.comb(count, k) * threshold**k * (1 - threshold) ** (count - k) for k in range(least, count + 1))


def set_key(values: np.ndarray) -> bytes:
    """128-bit name of a set of distinct shingles."""
    with np.errstate(over="ignore"):
        a, b = S.mix(values).sum(dtype=S.U), S.mix(values ^ S.U(0x5DEECE66D1234567)).sum(dtype=S.U)
    return np.array([a, b + S.U(len(values))], dtype=">u8").tobytes()


def profile(docs: DataFrame, count: int, seed: int, width: int = S.WIDTH) -> DataFrame:
    """doc_id, dh (hash of the text), key (name of the shingle set), n (its size), sig (``count`` 32-bit minima)."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in frames:
            texts = x["text"].fillna("").tolist()
            for a, b in S.batches([len(t) for t in texts]):
                values, starts = S.shingles(texts[a:b], width)
                own = S.sets(values, starts)
                sig = S.minhash(values, starts, count, seed)
                ids = {"doc_id": x["doc_id"].iloc[a:b].to_numpy(), "dh": x["dh"].iloc[a:b].to_numpy()}
                sets_ = {"key": [set_key(v) for v in own], "n": [len(v) for v in own], "sig": [r.tobytes() for r in sig]}
                yield pd.DataFrame(ids | sets_).astype({"doc_id": "Int64"})

    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole().alias("text")).withColumn("dh", F.xxhash64("text"))
    return texts.mapInPandas(lean(run), "doc_id long, dh long, key binary, n long, sig binary")


def shingle_sets(docs: DataFrame, wanted: DataFrame, width: int = S.WIDTH) -> DataFrame:
    """key, set (sorted 64-bit shingles) of the wanted keys; ``wanted`` has key and doc_id of one document each."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in frames:
            texts = x["text"].fillna("").tolist()
            for a, b in S.batches([len(t) for t in texts]):
                own = S.sets(*S.shingles(texts[a:b], width))
                rows = [(k, v.tobytes()) for k, v in zip(x["key"].iloc[a:b], own, strict=True) if set_key(v) == bytes(k)]
                yield pd.DataFrame(rows, columns=["key", "set"])

    few = wanted.withColumnRenamed("doc_id", "__id")
    texts = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    found = texts.join(few, texts["doc_id"].eqNullSafe(few["__id"])).select("key", "text").mapInPandas(lean(run), "key binary, set binary")
    return found.dropDuplicates(["key"])


def _groups(frames: Iterator[pd.DataFrame], by: list[str]) -> Iterator[pd.DataFrame]:
    """Whole groups of a stream that is sorted by ``by``."""
    held: list[pd.DataFrame] = []
    for x in frames:
        if not len(x):
            continue
        code = (x[by] != x[by].shift()).any(axis=1).to_numpy()
        code[0] = False if held and all(held[-1][c].iloc[-1] == x[c].iloc[0] for c in by) else True
        cuts = [*np.flatnonzero(code).tolist(), len(x)]
        if cuts[0] > 0 or not code[0]:
            held.append(x.iloc[: cuts[0]])
        for a, b in zip(cuts, cuts[1:], strict=False):
            if held:
                yield pd.concat(held) if len(held) > 1 else held[0]
            held = [x.iloc[a:b]]
    if held:
        yield pd.concat(held) if len(held) > 1 else held[0]


def _own_pairs(leaf: int, live: list[np.ndarray]) -> np.ndarray | None:
    """For members of a bucket: which pairs share no smaller bucket; None if all pairs do."""
    n = len(live)
    flat = np.concatenate([v[v < leaf] for v in live])
    if not len(flat):
        return np.ones((n, n), dtype=bool)
    member = np.repeat(np.arange(n), [int((v < leaf).sum()) for v in live])
    name, at, many = np.unique(flat, return_inverse=True, return_counts=True)
    keep = many[at] > 1
    if not keep.any():
        return np.ones((n, n), dtype=bool)
    if (many == n).any():
        return None
    cols = np.unique(at[keep], return_inverse=True)[1]
    m = np.zeros((n, int(cols.max()) + 1), dtype=np.float32)
    m[member[keep], cols] = 1
    return (m @ m.T) < 0.5


def _components(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    root = np.arange(n)
    while True:
        low = np.minimum(root[a], root[b])
        new = root.copy()
        np.minimum.at(new, a, low)
        np.minimum.at(new, b, low)
        np.minimum.at(new, root[a], low)
        np.minimum.at(new, root[b], low)
        new = new[new]
        if (new == root).all():
            return root
        root = new


def _sides(x: pd.DataFrame, mask: np.ndarray) -> np.ndarray:
    """Keeps pairs of the block pair only: inside one block, or across the two."""
    if x["i"].iloc[0] == x["j"].iloc[0]:
        return np.triu(mask, 1)
    left = (x["block"] == x["i"]).to_numpy()
    return mask & left[:, None] & ~left[None, :]


def likely(frames: Iterator[pd.DataFrame], count: int, least: float) -> Iterator[pd.DataFrame]:
    """Members of block pairs that have a likely partner there, by signature, with their local group."""
    for x in _groups(frames, ["leaf", "i", "j"]):
        if len(x) < 2:
            continue
        leaf = int(x["leaf"].iloc[0])
        mask = _own_pairs(leaf, [np.asarray(v) for v in x["live"]])
        if mask is None:
            continue
        mask = _sides(x, mask)
        sig = np.stack([np.frombuffer(v, dtype=np.uint32) for v in x["sig"]])
        size = x["n"].to_numpy().astype(float)
        step = max(1, (1 << 22) // (len(x) * count))
        pairs = []
        for a in range(0, len(x), step):
            rows = np.flatnonzero(mask[a : a + step].any(axis=1)) + a
            if len(rows):
                same = (sig[rows][:, None, :] == sig[None, :, :]).sum(axis=2, dtype=np.int32)
                ratio = np.minimum(size[rows][:, None], size[None, :]) / np.maximum(size[rows][:, None], size[None, :])
                r, c = np.nonzero((same >= least * count) & (ratio >= least) & mask[rows])
                pairs.append((rows[r], c))
        a, b = (np.concatenate(v) for v in zip(*pairs, strict=True)) if pairs else (np.zeros(0, int), np.zeros(0, int))
        if len(a):
            root = _components(a, b, len(x))
            own = np.unique(np.concatenate((a, b)))
            out = x.iloc[own][["leaf", "i", "j", "block", "key", "live", "copies"]].copy()
            out["part"] = root[own]
            yield out


def verified(frames: Iterator[pd.DataFrame], threshold: float) -> Iterator[pd.DataFrame]:
    """Exact links of each group: per member its number of linked sets and documents, and the group's smallest linked key."""
    for x in _groups(frames, ["leaf", "i", "j", "part"]):
        mask = _own_pairs(int(x["leaf"].iloc[0]), [np.asarray(v) for v in x["live"]]) if len(x) > 1 else None
        if mask is None:
            continue
        mask = _sides(x, mask)
        own = [np.frombuffer(v, dtype=np.uint64) for v in x["set"]]
        size = np.array([len(v) for v in own], dtype=np.float64)
        common = np.zeros((len(x), len(x)), dtype=np.float32)
        member = np.repeat(np.arange(len(x)), size.astype(int))
        _, at, many = np.unique(np.concatenate(own), return_inverse=True, return_counts=True)
        keep = many[at] > 1
        if keep.any():
            at, member = np.unique(at[keep], return_inverse=True)[1], member[keep]
            order = np.argsort(at, kind="stable")
            at, member = at[order], member[order]
            width = min(int(at[-1]) + 1, max(64, (1 << 23) // len(x)))
            for lo in range(0, int(at[-1]) + 1, width):
                a, b = np.searchsorted(at, (lo, lo + width))
                m = np.zeros((len(x), width), dtype=np.float32)
                m[member[a:b], at[a:b] - lo] = 1
                common += m @ m.T
        linked = mask & (common * (1 + threshold) >= threshold * (size[:, None] + size[None, :]) - 1e-6)
        a, b = np.nonzero(linked)
        if not len(a):
            continue
        copies = x["copies"].to_numpy()
        sets_, docs_ = np.bincount(a, minlength=len(x)) + np.bincount(b, minlength=len(x)), np.bincount(a, copies[b], len(x)) + np.bincount(b, copies[a], len(x))
        root = _components(a, b, len(x))
        keys = x["key"].tolist()
        has = np.flatnonzero(sets_)
        yield pd.DataFrame({"key": [keys[k] for k in has], "sets": sets_[has], "docs": docs_[has].astype(np.int64), "other": [keys[root[k]] for k in has]})


def find_links(docs: DataFrame, rows: DataFrame, leaves: DataFrame, count: int, threshold: float, width: int = S.WIDTH) -> DataFrame:
    """key, sets, docs, other: partial link counts and forest edges, one row per set and bucket with links.

    ``rows``: key, n, sig, copies, doc_id (of one copy), one per distinct set; ``leaves``: key, leaf, in which buckets of one member don't occur.
    """
    live = leaves.groupBy("key").agg(F.sort_array(F.collect_set("leaf")).alias("live"))  # as many as runs and bands, not as partners
    sized = cut(leaves.groupBy("leaf").agg(F.count(F.lit(1)).alias("members")).where("members > 1"), "link-sizes")
    blocks = F.ceil(F.col("members") / BLOCK).cast("int")
    placed = leaves.distinct().join(sized, "leaf").select("key", "leaf", blocks.alias("blocks"), F.pmod(F.xxhash64("key"), blocks).cast("int").alias("block"))
    spread = placed.select("key", "leaf", "block", F.explode(F.expr("transform(sequence(0, blocks - 1), o -> struct(least(block, o) AS i, greatest(block, o) AS j))")).alias("p")).select("key", "leaf", "block", "p.i", "p.j")
    full = spread.join(rows.join(live, "key").select("key", "n", "sig", "copies", "live"), "key")
    by = ["leaf", "i", "j"]
    kind = "leaf long, i int, j int, block int, key binary, live array<long>, copies long, part int"
    near = cut(full.repartition(parts(docs.sparkSession), *by).sortWithinPartitions(*by).mapInPandas(lean(lambda f: likely(f, count, threshold - SLACK)), kind), "link-likely")
    wanted = near.select("key").distinct().join(rows.select("key", "doc_id"), "key")
    sets = shingle_sets(docs, wanted, width)
    by = [*by, "part"]
    return near.join(sets, "key").repartition(parts(docs.sparkSession), *by).sortWithinPartitions(*by).mapInPandas(lean(lambda f: verified(f, threshold)), "key binary, sets long, docs long, other binary")


def components(edges: DataFrame, most: int = 60) -> DataFrame:
    """key, root (smallest key) of each node of the edges key - other; alternates large and small stars until nothing changes."""
    now = cut(edges.select("key", "other").where("key <> other").distinct(), "stars")
    nodes = now.select("key").union(now.select("other")).distinct()
    mark = lambda df: df.agg(F.count(F.lit(1)), F.sum(F.xxhash64("key", "other").cast("decimal(38,0)"))).first()
    before = None
    for _ in range(most):
        # Minima are written before they are joined back: the join stands alone, and a hub's edges can be split over tasks.
        both = now.union(now.select(F.col("other").alias("key"), F.col("key").alias("other")))
        low = cut(both.groupBy("key").agg(F.min("other").alias("low")).select("key", F.least("low", "key").alias("low")), "star-lows")
        large = both.where("other > key").join(low, "key").select(F.col("other").alias("key"), F.col("low").alias("other"))
        down = cut(large.select(F.greatest("key", "other").alias("key"), F.least("key", "other").alias("other")).where("key <> other").distinct(), "star-large")
        low = cut(down.groupBy("key").agg(F.min("other").alias("low")), "star-lows")
        small = down.join(low, "key").select(F.col("other").alias("key"), F.col("low").alias("other"))
        now = cut(small.union(low.select("key", F.col("low").alias("other"))).where("key <> other").distinct(), "stars")
        after = mark(now)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError(f"components did not settle in {most} rounds")
    return nodes.join(now, "key", "left").select("key", F.coalesce("other", "key").alias("root"))


def classes(docs: DataFrame, profiles: DataFrame, leaves_of: Callable[[DataFrame], DataFrame], count: int, threshold: float, width: int = S.WIDTH) -> DataFrame:
    """doc_id, dh, class_id (smallest id of all documents it is linked with, directly or not), class_dh (that document's dh), n_links, n_copies."""
    profiles = cut(profiles, "link-profiles")
    # The signature is a function of the set, so any of the copies' will do.
    sets = profiles.groupBy("key").agg(F.first("n").alias("n"), F.first("sig").alias("sig"), F.count(F.lit(1)).alias("copies"), F.min(ordered("doc_id", "dh")).alias("who"))
    rows = cut(sets.withColumn("doc_id", F.col("who.doc_id")), "link-sets")
    leaves = cut(leaves_of(rows), "link-leaves")
    found = cut(find_links(docs, rows, leaves, count, threshold, width), "links")
    sums = found.groupBy("key").agg(F.sum("docs").alias("linked"))
    roots = components(found.select("key", "other"))
    named = rows.select("key", "who", "copies").join(sums, "key", "left").join(roots, "key", "left").withColumn("root", F.coalesce("root", "key"))
    named = cut(named.withColumn("n_links", F.coalesce("linked", F.lit(0)) + F.col("copies") - 1), "link-named")
    first = cut(named.groupBy("root").agg(F.min("who").alias("first")), "link-classes")  # alone, so that large classes can be split
    per_set = named.join(first, "root").select("key", F.col("first.doc_id").alias("class_id"), F.col("first.dh").alias("class_dh"), "n_links", "copies")
    return profiles.select("doc_id", "dh", "key").join(per_set, "key").select("doc_id", "dh", "class_id", "class_dh", "n_links", F.col("copies").alias("n_copies"))
