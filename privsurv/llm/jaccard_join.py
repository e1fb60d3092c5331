"""Similarity self-join on word shingles by chosen paths.

Each distinct shingle set is embedded in a vector of ``COUNT`` minima, whose positions agree with probability equal to
the Jaccard similarity.  A run starts with all sets at one node.  A node picks each position with probability
1 / (threshold * COUNT), by a hash of its path, and sends its sets to one child per picked position and value there: sets
that share the sampled token stay together.  Nodes with more than ``SMALL`` sets split again, up to ``DEPTH`` times;
others are buckets, compared by brute force with exact verification.  So many runs are made that a pair at the
threshold meets and passes the comparison of signatures, even at the last level, with probability ``recall``.

Results: doc_id, class_id (smallest id among documents linked directly or indirectly), n_links (other documents of
similarity ``threshold`` or more, copies included), n_copies (documents with the same shingle set).

Defined results: null and empty texts are one class of copies; texts without words are equal if their characters are;
rows that repeat an id are documents of their own with one id; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import links
from . import shingles as S
from .common import cut, lean

COUNT = 64
SMALL = 256
DEPTH = 3


def survival(threshold: float, depth: int) -> float:
    """Probability that a pair at the threshold shares a node at the given depth of one run."""
    q = 1.0
    for _ in range(depth):
        q = 1 - (1 - threshold * q / (threshold * COUNT)) ** COUNT
    return q


def runs_for(threshold: float, recall: float, depth: int = DEPTH) -> int:
    """Runs after which a pair at the threshold has met with probability ``recall``, losses of the signature filter included."""
    need = recall / links.passes(COUNT, threshold)
    if need >= 1:
        raise ValueError(f"signatures of {COUNT} minima do not allow a recall of {recall}")
    return math.ceil(math.log(1 - need) / math.log(1 - survival(threshold, depth)))


def picked(paths: np.ndarray, rate: float) -> np.ndarray:
    """Which positions the nodes pick: one row per path."""
    place = S.mix(np.arange(1, COUNT + 1, dtype=S.U))
    return S.mix(paths[:, None] ^ place[None, :]) < S.U(int(rate * 2**64))


def _children(paths: np.ndarray, sig: np.ndarray, rate: float) -> tuple[np.ndarray, np.ndarray]:
    """Rows and their child paths."""
    row, place = np.nonzero(picked(paths, rate))
    value = sig[row, place].astype(S.U) | (place.astype(S.U) << S.U(32))
    return row, S.mix(paths[row] * S.U(0x9E3779B97F4A7C15) + S.mix(value + S.U(1)))


def paths_of(rows: DataFrame, runs: int, threshold: float, seed: int) -> DataFrame:
    """key, leaf: buckets of at least two sets."""
    rate = 1 / (threshold * COUNT)
    roots = S.mix(np.arange(runs, dtype=S.U) + S.U(seed * 1000 + 1))

    def first(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in frames:
            sig = np.stack([np.frombuffer(v, dtype=np.uint32) for v in x["sig"]]) if len(x) else np.zeros((0, COUNT), np.uint32)
            for r in roots:
                row, child = _children(np.full(len(x), r, dtype=S.U), sig, rate)
                yield pd.DataFrame({"key": x["key"].to_numpy()[row], "leaf": child.view(np.int64)})

    def again(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in frames:
            sig = np.stack([np.frombuffer(v, dtype=np.uint32) for v in x["sig"]]) if len(x) else np.zeros((0, COUNT), np.uint32)
            row, child = _children(x["leaf"].to_numpy().astype(np.int64).view(S.U), sig, rate)
            yield pd.DataFrame({"key": x["key"].to_numpy()[row], "leaf": child.view(np.int64)})

    kind, out = "key binary, leaf long", None
    now = rows.select("key", "sig").mapInPandas(lean(first), kind)
    for depth in range(1, DEPTH + 1):
        now = cut(now, "paths")
        # Counts are written before they are joined back, so a leaf of very many sets can be split over tasks.
        sized = cut(now.groupBy("leaf").agg(F.count(F.lit(1)).alias("members")).where("members > 1"), "paths-sized")
        shared = cut(now.join(sized, "leaf"), "paths-shared")
        small = shared if depth == DEPTH else shared.where(F.col("members") <= SMALL)
        out = small.select("key", "leaf") if out is None else out.union(small.select("key", "leaf"))
        large = shared.where(F.col("members") > SMALL)
        if depth == DEPTH or large.isEmpty():
            return out
        now = large.select("key", "leaf").join(rows.select("key", "sig"), "key").select("key", "leaf", "sig").mapInPandas(lean(again), kind)
    return out


def joined(docs: DataFrame, threshold: float = 0.8, recall: float = 0.999, seed: int = 1) -> DataFrame:
    """What ``links.classes`` gives: with hashes that tell rows of one id apart."""
    runs = runs_for(threshold, recall)
    return links.classes(docs, links.profile(docs, COUNT, seed), lambda rows: paths_of(rows, runs, threshold, seed), COUNT, threshold)


def jaccard_join(docs: DataFrame, threshold: float = 0.8, recall: float = 0.999, seed: int = 1) -> DataFrame:
    return joined(docs, threshold, recall, seed).drop("dh", "class_dh")
