"""Removal of long repeated byte strings by hash-compared suffix sorting.

Every byte that a ``WIDTH``-byte string covers which also starts anywhere else goes.  Suffixes are sorted only where it can
matter: each window of WIDTH bytes has an anchor, the place in it whose ``GRAM``-byte string has the least hash (the
first of equals).  Equal windows have equal anchors at equal places, so windows need comparing only among windows whose
anchors' strings are equal.  Consecutive windows with one anchor make a segment.

* Segments that are equal as a whole, which their SHA-256 tells, are counted; all windows of those that occur twice or more are
  repeats.
* Of anchor strings with several different segments, one copy of each segment is fetched.  Suffixes that start at the anchors are
  merge-sorted; two suffixes are compared by finding their common extension with a binary search over prefix polynomial
  hashes.  Neighbours' common extensions are verified byte by byte.  For each distance from the anchor, runs of neighbours that
  agree far enough to the right, and whose bytes to the left have equal hashes, are repeats; what agrees to the left is verified too.
* Anchor strings with more than ``MOST`` different segments (one passage in very many contexts) are split by the content that
  all windows of half of the distances share, again and again, until groups are small or windows equal: no task
  gets an unbounded group, and nothing is left out.

With ``words`` the same anchors, over words in place of bytes, also find every passage of that many successive words which occurs
in another row, whatever white space is between them.  Most such passages are under ``WIDTH`` bytes, so they stay in the text: their words
are counted only.  Segments are equal by 128 bits of SHA-256, windows of small groups by their bytes, of large ones by SHA-256.

Anchors and groups are found by plain 64-bit hashes, which only decide what meets; what is removed rests on SHA-256 of
whole segments or on bytes that were compared.

Defined results: null texts are empty; texts shorter than WIDTH have no windows; rows that repeat an id are texts of their own (and
repeats of each other); a text made of one repeated period is removed as far as its windows recur; an empty table gives
no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import os
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shingles as S
from .common import cut, drop, lean, parts, whole
from .links import _groups

WIDTH = 400
GRAM = 64
WORD_GRAM = 8  # words of an anchor's string
MOST = 4_000  # different segments of one anchor string that are sorted together
STEP = 1 << 18  # windows handled at a time; a place in a step fits 20 bits
BATCH = 1 << 21  # bytes of segments sorted together
FETCH = 1 << 22  # bytes of segments handed on together
PAIRS = 1 << 17  # pairs of suffixes held for verification
ROW = "gram long, doc_id long, dh long, pos long, n_win int, delta int, weight long, single boolean, seg binary, bytes binary"


def _least(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each ``width`` consecutive values."""
    n = len(x)
    pad = -n % width
    held = np.concatenate((x, np.full(pad, np.iinfo(np.uint64).max, dtype=S.U))).reshape(-1, width)
    before = np.minimum.accumulate(held, axis=1).reshape(-1)
    after = np.minimum.accumulate(held[:, ::-1], axis=1)[:, ::-1].reshape(-1)
    return np.minimum(after[: n - width + 1], before[width - 1 : n])


def segments(raws: list[bytes], width: int = WIDTH, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """Owners, anchors' hashes, segments' SHA-256 (four numbers each), first windows, numbers of windows, distances of the anchors from them.

    ``raws``: some texts, in all within a step; longer ones are given in overlapping steps.
    """
    none = (*(np.zeros(n, dtype=k) for n, k in ((0, np.int64), (0, S.U), ((0, 4), S.U), (0, np.int64), (0, np.int64), (0, np.int64))),)
    x = np.frombuffer(b"".join(raws), dtype=np.uint8)
    sizes = np.array([len(r) for r in raws], dtype=np.int64)
    if len(x) < width:
        return none
    first = np.cumsum(sizes) - sizes
    b = S.Prefixes(x)
    place = np.arange(len(x) - gram + 1)
    # Equal in the upper bits: the first place wins, and that is so in every copy.
    key = (b.span(place, place + gram) & S.U(2**64 - 2**20)) | place.astype(S.U)
    anchor = (_least(key, width - gram + 1) & S.U(2**20 - 1)).astype(np.int64)
    many = np.maximum(sizes - width + 1, 0)
    owner = np.repeat(np.arange(len(raws)), many)
    window = np.repeat(first, many) + np.arange(len(owner)) - np.repeat(np.cumsum(many) - many, many)
    if not len(window):
        return none
    a = anchor[window]
    edge = np.flatnonzero(np.concatenate(([True], (a[1:] != a[:-1]) | (owner[1:] != owner[:-1]))))
    n = np.diff(np.append(edge, len(a)))
    a, begin, owner = a[edge], window[edge], owner[edge]
    view = memoryview(x)
    names = [hashlib.sha256(view[i:j]).digest() for i, j in zip(begin.tolist(), (begin + n + width - 1).tolist(), strict=True)]
    return owner, b.span(a, a + gram), np.frombuffer(b"".join(names), dtype=S.U).reshape(-1, 4), begin - first[owner], n, a - begin


def word_segments(raws: list[bytes], words: int, gram: int = WORD_GRAM) -> tuple[np.ndarray, ...]:
    """As ``segments``, for windows of words: places and numbers count words, the distance is -1 to tell them apart, and
    128 bits of SHA-256 are kept."""
    none = (*(np.zeros(n, dtype=k) for n, k in ((0, np.int64), (0, S.U), ((0, 2), S.U), (0, np.int64), (0, np.int64), (0, np.int64))),)
    lists = [r.split() for r in raws]
    sizes = np.array([len(w) for w in lists], dtype=np.int64)
    m = int(sizes.sum()) - words + 1
    if m < 1:
        return none
    x = np.frombuffer(b" ".join(b" ".join(w) for w in lists if w), dtype=np.uint8)
    del lists
    gap = np.flatnonzero(x == 32)
    starts, ends = np.append(0, gap + 1), np.append(gap, len(x))
    hashes = np.empty(len(starts), dtype=S.U)
    i = 0
    while i < len(starts):  # whole words, about a step of bytes at a time
        j = max(i + 1, int(np.searchsorted(ends, starts[i] + STEP, side="right")))
        hashes[i:j] = S.Prefixes(x[starts[i] : ends[j - 1]]).span(starts[i:j] - starts[i], ends[i:j] - starts[i])
        i = j
    key = np.zeros(len(hashes) - gram + 1, dtype=S.U)
    for k in range(gram):
        key += hashes[k : k + len(key)] * S._mul[k]
    key = S.mix(key)
    anchor = np.empty(m, dtype=np.int64)
    for at in range(0, m, STEP):
        own = key[at : at + STEP + words - gram]
        least = _least((own & S.U(2**64 - 2**20)) | np.arange(len(own)).astype(S.U), words - gram + 1)
        anchor[at : at + STEP] = (least[:STEP] & S.U(2**20 - 1)).astype(np.int64) + at
    first = np.cumsum(sizes) - sizes
    owner = np.repeat(np.arange(len(raws)), sizes)
    window = np.flatnonzero(owner[:m] == owner[words - 1 :])
    if not len(window):
        return none
    a, owner = anchor[window], owner[window]
    edge = np.flatnonzero(np.concatenate(([True], (a[1:] != a[:-1]) | (owner[1:] != owner[:-1]))))
    n = np.diff(np.append(edge, len(a)))
    a, begin, owner = a[edge], window[edge], owner[edge]
    view = memoryview(x)
    names = [hashlib.sha256(view[i:j]).digest()[:16] for i, j in zip(starts[begin].tolist(), ends[begin + n + words - 2].tolist(), strict=True)]
    return owner, key[a], np.frombuffer(b"".join(names), dtype=S.U).reshape(-1, 2), begin - first[owner], n, np.full(len(n), -1)


def anchors(docs: DataFrame, width: int, gram: int, words: int = 0) -> DataFrame:
    """gram, seg, doc_id, dh, n_win, delta, at (first windows of equal segments): one row per document and distinct segment.

    With ``words`` segments of words.
    """
    kind = pa.schema([("gram", pa.int64()), ("seg", pa.binary()), ("doc_id", pa.int64()), ("dh", pa.int64()), ("n_win", pa.int32()), ("delta", pa.int32()), ("at", pa.list_(pa.int64()))])

    def rows(batch: pa.RecordBatch, owner, g, s, at, n, d) -> pa.RecordBatch:
        order = np.lexsort((at, s[:, 0], owner))
        owner, g, s, at, n, d = (v[order] for v in (owner, g, s, at, n, d))
        new = np.flatnonzero(np.concatenate(([True], (owner[1:] != owner[:-1]) | (s[1:] != s[:-1]).any(axis=1))))
        lists = pa.ListArray.from_arrays(pa.array(np.append(new, len(at)).astype(np.int32)), pa.array(at))
        ids = batch.column(0).take(pa.array(owner[new])), batch.column(1).take(pa.array(owner[new]))
        names = pa.FixedSizeBinaryArray.from_buffers(pa.binary(8 * s.shape[1]), len(new), [None, pa.py_buffer(s[new].tobytes())]).cast(pa.binary())
        columns = [pa.array(g[new].view(np.int64)), names, *ids, pa.array(n[new].astype(np.int32)), pa.array(d[new].astype(np.int32)), lists]
        return pa.RecordBatch.from_arrays(columns, schema=kind)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(2).cast(pa.binary()).to_pylist()
            for lo, hi in S.batches([len(t) for t in texts], STEP):
                if words:
                    own = word_segments(texts[lo:hi], words)
                    found = [own[0] + lo, *own[1:]]
                elif len(texts[lo]) > STEP:
                    raw = texts[lo]
                    steps = []
                    for at in range(0, len(raw) - width + 1, STEP):
                        part = segments([raw[at : at + STEP + width - 1]], width, gram)
                        steps.append((part[0] + lo, *part[1:3], part[3] + at, *part[4:]))
                    found = [np.concatenate(v) for v in zip(*steps, strict=True)]
                else:
                    own = segments(texts[lo:hi], width, gram)
                    found = [own[0] + lo, *own[1:]]
                if len(found[0]):
                    yield rows(batch, *found)

    return docs.select("doc_id", "dh", "text").mapInArrow(lean(run), "gram long, seg binary, doc_id long, dh long, n_win int, delta int, at array<long>")


def _fetched(docs: DataFrame, wanted: DataFrame, width: int, words: int = 0) -> DataFrame:
    """The bytes of wanted segments; segments of words have one space between words."""
    lists = wanted.groupBy("doc_id", "dh").agg(F.collect_list(F.struct("gram", "pos", "n_win", "delta", "weight", "single", "seg")).alias("want"))
    same = docs["doc_id"].eqNullSafe(lists["doc_id"]) & (docs["dh"] == lists["dh"])

    names = [c.split()[0] for c in ROW.split(", ")]
    frame = lambda rows: pd.DataFrame(rows, columns=names).astype({"doc_id": "Int64"})

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rows, held = [], 0
        for x in frames:
            for doc_id, dh, text, want in zip(x["doc_id"], x["dh"], x["text"], x["want"], strict=True):
                raw, own = text.encode("utf-8", "surrogatepass"), None if pd.isna(doc_id) else int(doc_id)
                split = raw.split() if any(w["delta"] < 0 for w in want) else []
                for w in want:
                    a, n = w["pos"], w["n_win"] - 1
                    part = b" ".join(split[a : a + n + words]) if w["delta"] < 0 else raw[a : a + n + width]
                    rows.append((w["gram"], own, dh, w["pos"], w["n_win"], w["delta"], w["weight"], w["single"], w["seg"], part))
                    held += len(part)
                    if held > FETCH:
                        yield frame(rows)
                        rows, held = [], 0
        if rows:
            yield frame(rows)

    return docs.join(lists, same).select(docs["doc_id"], docs["dh"], "text", "want").mapInPandas(lean(run), ROW)


class Suffixes:
    """Suffixes of some segments that start at their anchors, and prefix polynomial hashes of each segment at a random point."""

    def __init__(self, rows: list[bytes], delta: np.ndarray, group: np.ndarray):
        sizes = np.array([len(r) for r in rows])
        self.wide = int(sizes.max()) + 1
        self.raw = np.zeros((len(rows), self.wide), dtype=np.uint8)
        self.raw[np.arange(self.wide) < sizes[:, None]] = np.frombuffer(b"".join(rows), dtype=np.uint8)
        point = int.from_bytes(os.urandom(8), "little") % (S.PRIME - 1024) + 512
        self.power, base = S.power_table(point, self.wide + 1), np.full(len(rows), point, dtype=S.U)
        self.prefix = np.zeros((self.wide + 1, len(rows)), dtype=S.U)  # one row per length
        for k in range(self.wide):
            self.prefix[k + 1] = S._reduced(S.times(self.prefix[k], base) + self.raw[:, k] + S.U(1))
        self.at, self.room, self.group = delta, sizes - delta, group

    def span(self, i: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Hashes of the bytes a..b of segments i."""
        return S.less(self.prefix[b, i], S.times(self.prefix[a, i], self.power[b - a]))

    def common(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Length of the common extension to the right: binary search over prefix hashes."""
        low, high = np.zeros(len(i), dtype=np.int64), np.minimum(self.room[i], self.room[j])
        a, b = self.at[i], self.at[j]
        while (low < high).any():
            mid = (low + high + 1) // 2
            same = self.span(i, a, a + mid) == self.span(j, b, b + mid)
            low, high = np.where(same, mid, low), np.where(same, high, mid - 1)
        return low

    def less(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        n = self.common(i, j)
        x = np.where(n < self.room[i], self.raw[i, self.at[i] + n].astype(np.int16), -1)
        y = np.where(n < self.room[j], self.raw[j, self.at[j] + n].astype(np.int16), -1)
        return (x < y) | ((x == y) & (i < j))

    def sort(self) -> np.ndarray:
        """Order of the suffixes within their groups: merge sort, all runs of a level merged at once."""
        order = np.argsort(self.group, kind="stable")
        n = len(order)
        _, base, size = np.unique(self.group[order], return_index=True, return_counts=True)
        base, size = np.repeat(base, size), np.repeat(size, size)
        spot = np.arange(n) - base
        run = 1
        while run < (size.max() if n else 0):
            own = spot // run
            begin = (own ^ 1) * run
            end = np.minimum(begin + run, size)
            low, high = np.minimum(begin, end), end.copy()
            while True:
                go = np.flatnonzero(low < high)
                if not len(go):
                    break
                mid = (low[go] + high[go]) // 2
                smaller = self.less(order[base[go] + mid], order[go])
                low[go] = np.where(smaller, mid + 1, low[go])
                high[go] = np.where(smaller, high[go], mid)
            to = base + np.minimum(own, own ^ 1) * run + (spot - own * run) + np.maximum(low - begin, 0)
            new = np.empty_like(order)
            new[to] = order
            order, run = new, run * 2
        return order

    def equal(self, i: np.ndarray, j: np.ndarray, back: np.ndarray, ahead: np.ndarray) -> np.ndarray:
        """Whether the bytes around two anchors are the same, byte by byte."""
        out, n = np.ones(len(i), dtype=bool), back + ahead
        flat = self.raw.reshape(-1)
        for lo, hi in S.batches(n.tolist(), 1 << 17):
            m = n[lo:hi]
            step = np.arange(int(m.sum())) - np.repeat(np.cumsum(m) - m, m)
            x = flat[np.repeat(i[lo:hi] * self.wide + self.at[i[lo:hi]] - back[lo:hi], m) + step]
            y = flat[np.repeat(j[lo:hi] * self.wide + self.at[j[lo:hi]] - back[lo:hi], m) + step]
            wrong = np.repeat(np.arange(lo, hi), m)[x != y]
            out[wrong] = False
        return out


def repeats(rows: list[bytes], n_win: np.ndarray, delta: np.ndarray, group: np.ndarray, width: int = WIDTH) -> np.ndarray:
    """For each segment and distance from its anchor: does that window occur in another segment of the group?"""
    s = Suffixes(rows, delta, group)
    order = s.sort()
    n, far = len(order), int(delta.max()) + 1
    out = np.zeros((n, far), dtype=bool)
    agree = np.zeros(n + 1, dtype=np.int64)
    near = np.flatnonzero(s.group[order[1:]] == s.group[order[:-1]]) + 1
    agree[near] = s.common(order[near - 1], order[near])
    exact = s.equal(order[near - 1], order[near], np.zeros(len(near), dtype=np.int64), agree[near])
    doubt = set(s.group[order[near[~exact]]].tolist())
    pairs: list[np.ndarray] = []

    def verify() -> None:
        """Compares what pairs share to the left of their anchors, each at the farthest distance held."""
        a, b, d = np.concatenate(pairs, axis=1)
        by = np.lexsort((-d, b, a))
        top = by[np.concatenate(([True], (a[by][1:] != a[by][:-1]) | (b[by][1:] != b[by][:-1])))]
        same = s.equal(a[top], b[top], d[top], np.zeros(len(top), dtype=np.int64))
        doubt.update(s.group[a[top[~same]]].tolist())
        pairs.clear()

    low, high = (delta - n_win + 1)[order], delta[order]
    for d in reversed(range(far)):
        long = agree >= width - d
        live = np.flatnonzero((long[:-1] | long[1:]) & (low <= d) & (d <= high))
        if len(live) < 2:
            continue
        run = np.cumsum(~long[:-1])[live]
        own = order[live]
        key = S.mix(s.span(own, s.at[own] - d, s.at[own]) + run.astype(S.U) * S._mul[5])
        by = np.argsort(key)
        same = key[by][1:] == key[by][:-1]
        if same.any():
            a, b = own[by][:-1][same], own[by][1:][same]
            out[a, d] = out[b, d] = True
            pairs.append(np.stack((a, b, np.full(len(a), d))))
            if sum(p.shape[1] for p in pairs) > PAIRS:
                verify()
    if pairs:
        verify()
    for g in doubt:  # a hash told a lie: compare this group's windows themselves
        own = np.flatnonzero(group == g)
        for d in range(far):
            seen: dict[bytes, list[int]] = {}
            for i in own.tolist():
                if delta[i] - n_win[i] < d <= delta[i]:
                    seen.setdefault(rows[i][delta[i] - d : delta[i] - d + width], []).append(i)
            for v in seen.values():
                out[v, d] = len(v) > 1
    return out


def _sorted_groups(frames: Iterator[pd.DataFrame], width: int, batch: int) -> Iterator[pd.DataFrame]:
    """Repeated spans (doc_id, dh, begin, end) of groups of segments; whole groups together, several per batch."""

    def run(held: list[pd.DataFrame]) -> pd.DataFrame:
        x = pd.concat(held)
        delta = x["delta"].to_numpy(dtype=np.int64)
        group = np.repeat(np.arange(len(held)), [len(h) for h in held])
        found = repeats([bytes(v) for v in x["bytes"]], x["n_win"].to_numpy(dtype=np.int64), delta, group, width)
        found[~x["single"].to_numpy(dtype=bool)] = False
        edge = np.diff(np.pad(found, ((0, 0), (1, 1))).astype(np.int8), axis=1)
        row, first = np.nonzero(edge == 1)
        _, last = np.nonzero(edge == -1)
        base = x["pos"].to_numpy(dtype=np.int64) + delta  # the anchor
        spans = {"doc_id": x["doc_id"].iloc[row].astype("Int64").to_numpy(), "dh": x["dh"].to_numpy()[row], "begin": base[row] - last + 1, "end": base[row] - first + width}
        return pd.DataFrame(spans).astype({"doc_id": "Int64"})

    held: list[pd.DataFrame] = []
    size = 0
    for x in _groups(frames, ["gram"]):
        if len(x) > 1:
            held.append(x)
            size += int(x["bytes"].str.len().sum())
        if size >= batch:
            yield run(held)
            held, size = [], 0
    if held:
        yield run(held)


def _halved(rows: DataFrame, width: int) -> DataFrame:
    """Splits the distances of each group in two and renames groups by the content that all windows of a half share."""

    names = [*[c.split()[0] for c in ROW.split(", ")], "d0", "d1"]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in frames:
            out = []
            for r in x.itertuples(index=False):
                raw, low, high = bytes(r.bytes), r.delta - r.n_win + 1, r.delta
                mid = (r.d0 + r.d1) // 2
                for a, b in ((r.d0, mid), (mid + 1, r.d1)):
                    lo, hi = max(a, low), min(b, high)
                    if a > b or lo > hi:
                        continue
                    # Places count from the anchor, which is delta into the bytes.
                    core, own = raw[r.delta - a : r.delta + width - b], raw[r.delta - hi : r.delta + width - lo]
                    name = hashlib.blake2b(core + f"{r.gram},{a},{b}".encode(), digest_size=8).digest()
                    seg = hashlib.sha256(own + f",{lo},{hi}".encode()).digest()
                    name = int.from_bytes(name, "little", signed=True)
                    out.append((name, r.doc_id, r.dh, r.pos + r.delta - hi, hi - lo + 1, hi, r.weight, r.single, seg, own, a, b))
            yield pd.DataFrame(out, columns=names).astype({"doc_id": "Int64"})

    return rows.mapInPandas(lean(run), ROW + ", d0 int, d1 int")


def _met(rows: DataFrame, width: int, words: bool, used: list[DataFrame]) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Spans of segments that occur more than once (of words: in more than one row), one copy of those to compare, and anchor strings with several.

    The table of ``rows`` is given up when those with repeated anchor strings are written; ``used`` gets the tables that spans are read from.
    """
    each, own = F.count(F.lit(1)) if words else F.sum(F.size("at")), F.struct("doc_id", "dh")
    # Written first, so that the join stands alone and an anchor that very many texts share can be split.
    sized = cut(rows.groupBy("gram").agg(each.alias("all")).where("all > 1").select("gram"), "repeat-grams")
    met = cut(rows.join(sized, "gram"), "repeat-anchors")
    drop(rows)
    drop(sized)
    named = met.groupBy("gram", "seg").agg(each.cast("long").alias("weight"), *[F.first(c).alias(c) for c in ("doc_id", "dh", "n_win", "delta")], F.first(F.get("at", 0)).alias("pos"))
    named = cut(named, "repeat-segments")
    used += [met, named]
    several = named.groupBy("gram").agg(F.count(F.lit(1)).alias("segs"), F.min(own).alias("a"), F.max(own).alias("b"), F.max("weight").alias("most")).where("segs > 1")
    several = several.where(~F.col("a").eqNullSafe(F.col("b")) | (F.col("most") > 1) | F.lit(not words)).select("gram", "segs")
    twice = named.where("weight > 1").select("gram", "seg")
    spans = met.join(twice, ["gram", "seg"]).select("doc_id", "dh", F.explode("at").alias("begin"), "n_win").select("doc_id", "dh", "begin", (F.col("begin") + F.col("n_win") + width - 1).alias("end"))
    return spans, cut(named.join(several, "gram").withColumn("single", F.col("weight") == 1), "repeat-wanted"), several


def _windows(raw: bytes, n_win: int, words: int) -> list[bytes]:
    """The windows of a segment of words."""
    gap = np.flatnonzero(np.frombuffer(raw, dtype=np.uint8) == 32)
    starts, ends = [0, *(gap[: n_win - 1] + 1).tolist()], [*gap[words - 1 :].tolist(), len(raw)]
    return [raw[a:b] for a, b in zip(starts, ends, strict=True)]


def _agreeing(group: list[tuple], words: int) -> list[tuple]:
    """Spans (doc_id, dh, pos, begin, end; from pos on) of the windows that another row of a group has too; rows: doc_id, dh, pos, n_win, single, bytes."""
    seen: dict[bytes, list[int]] = {}
    windows = [_windows(r[5], r[3], words) for r in group]
    for i, own in enumerate(windows):
        for w in own:
            seen.setdefault(w, []).append(i)
    good = {w: len(v) > 1 and (len({group[i][:2] for i in v}) > 1 or not all(group[i][4] for i in v)) for w, v in seen.items()}
    out = []
    for (doc_id, dh, pos, _, single, _), own in zip(group, windows, strict=True):
        if single:
            out += [(doc_id, dh, pos, a, b) for a, b in merged([(k, k + words) for k, w in enumerate(own) if good[w]])]
    return out


def _shared(rows: DataFrame, several: DataFrame, words: int, most: int) -> DataFrame:
    """Spans of words (doc_id, dh, pos, begin, end; from pos on) whose windows are in another row too, of segments that are in one row only."""

    names = ["doc_id", "dh", "pos", "begin", "end"]
    frame = lambda out, names: pd.DataFrame(out, columns=names).astype({"doc_id": "Int64"})
    ids = lambda x: [None if pd.isna(d) else d for d in x["doc_id"].tolist()]

    def groups(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        gram, held = None, []
        for x in frames:
            out = []
            columns = [x[c].tolist() for c in ("dh", "pos", "n_win", "single", "bytes")]
            for g, *row in zip(x["gram"].tolist(), ids(x), *columns, strict=True):
                if g != gram:
                    out += _agreeing(held, words) if len(held) > 1 else []
                    gram, held = g, []
                held.append((*row[:5], bytes(row[5])))
            yield frame(out, names)
        if len(held) > 1:
            yield frame(_agreeing(held, words), names)

    def apart(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in frames:
            columns = [x[c].tolist() for c in ("dh", "pos", "n_win", "single", "bytes")]
            out = [(hashlib.sha256(w).digest(), i, h, at, k, one) for i, h, at, n, one, raw in zip(ids(x), *columns, strict=True) for k, w in enumerate(_windows(bytes(raw), n, words))]
            yield frame(out, ["seg", "doc_id", "dh", "pos", "begin", "single"])

    kind = "doc_id long, dh long, pos long, begin long, end long"
    work = lambda few: few.repartition(parts(rows.sparkSession), "gram").sortWithinPartitions("gram").mapInPandas(lean(groups), kind)
    large = several.where(F.col("segs") > most).select("gram")
    if large.isEmpty():
        return work(rows)
    large = cut(large, "passage-large")
    each = cut(rows.join(large, "gram").mapInPandas(lean(apart), "seg binary, doc_id long, dh long, pos long, begin long, single boolean"), "passage-windows")
    own = F.struct("doc_id", "dh")
    met = each.groupBy("seg").agg(F.min(own).alias("a"), F.max(own).alias("b"), F.min("single").alias("single")).where(~F.col("a").eqNullSafe(F.col("b")) | ~F.col("single")).select("seg")
    rest = each.where("single").join(cut(met, "passage-met"), "seg").select("doc_id", "dh", "pos", "begin", (F.col("begin") + words).alias("end"))
    return work(rows.join(large, "gram", "left_anti")).union(rest)


def _spans(rows: DataFrame, docs: DataFrame, width: int, gram: int, most: int, words: int, used: list[DataFrame]) -> DataFrame:
    """All repeated spans: doc_id, dh, begin, end, and whether they count words; ``used`` gets the tables they are read from."""
    spans, wanted, several = _met(rows, width, False, used)
    if not words:
        used.append(fetched := cut(_fetched(docs, wanted, width), "repeat-bytes"))
        drop(wanted)
        return _sorted_spans(fetched, spans, several, width, gram, most).withColumn("words", F.lit(False))
    alike, more, groups = _met(cut(anchors(docs, width, gram, words), "passage-places"), words, True, used)
    used.append(fetched := cut(_fetched(docs, wanted.unionByName(more), width, words), "repeat-bytes"))
    drop(wanted)
    drop(more)
    spans = _sorted_spans(fetched.where("delta >= 0"), spans, several, width, gram, most).withColumn("words", F.lit(False))
    part = _shared(fetched.where("delta < 0"), groups, words, most)
    # A segment that one row has at several places was compared at the first.
    again = used[2].where(F.size("at") > 1).select(F.col("doc_id").alias("i"), F.col("dh").alias("h"), F.get("at", 0).alias("p"), "at")
    part = part.join(again, F.col("doc_id").eqNullSafe(F.col("i")) & (F.col("dh") == F.col("h")) & (F.col("pos") == F.col("p")), "left")
    part = part.select("doc_id", "dh", F.explode(F.coalesce("at", F.array("pos"))).alias("pos"), "begin", "end")
    part = part.select("doc_id", "dh", (F.col("pos") + F.col("begin")).alias("begin"), (F.col("pos") + F.col("end")).alias("end"))
    return spans.union(alike.union(part).withColumn("words", F.lit(True)))


def _sorted_spans(fetched: DataFrame, spans: DataFrame, several: DataFrame, width: int, gram: int, most: int) -> DataFrame:
    """``spans``, and those of windows that only parts of segments share."""
    spark = fetched.sparkSession
    kind = "doc_id long, dh long, begin long, end long"
    work = lambda few: few.repartition(parts(spark), "gram").sortWithinPartitions("gram").mapInPandas(lean(lambda f: _sorted_groups(f, width, BATCH)), kind)
    columns = [c.split()[0] for c in ROW.split(", ")]
    large = several.where(F.col("segs") > most)
    if large.isEmpty():
        return spans.union(work(fetched))
    large = cut(large, "repeat-large")
    spans = spans.union(work(fetched.join(large, "gram", "left_anti")))
    rest = fetched.join(large.select("gram"), "gram").withColumn("d0", F.lit(0)).withColumn("d1", F.lit(width - gram))
    while True:
        rest = cut(_halved(rest, width), "repeat-halves")
        named = cut(rest.groupBy("gram", "seg").agg(F.sum("weight").alias("n")), "repeat-half-names")
        segs = named.groupBy("gram").agg(F.count(F.lit(1)).alias("segs"))
        twice = rest.where("single").join(named.where("n > 1"), ["gram", "seg"])
        spans = spans.union(twice.select("doc_id", "dh", F.col("pos").alias("begin"), (F.col("pos") + F.col("n_win") + width - 1).alias("end")))
        left = rest.join(named, ["gram", "seg"]).withColumn("single", F.col("single") & (F.col("n") == 1)).withColumn("weight", F.col("n")).drop("n").dropDuplicates(["gram", "seg"]).join(segs.where("segs > 1"), "gram")
        left = cut(left, "repeat-left")
        spans = spans.union(work(left.where(F.col("segs") <= most).select(*columns)))
        rest = left.where(F.col("segs") > most).drop("segs")
        if rest.isEmpty():
            return spans


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def remove_repeats(docs: DataFrame, width: int = WIDTH, gram: int = GRAM, most: int = MOST, keep_text: bool = False, words: int = 0) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_removed, n_spans, kept_sha256, and with ``keep_text`` spans and kept bytes.

    With ``words`` (at least ``WORD_GRAM``) also n_shared_words: how many words of the text are in passages of that many words which another row has too.
    """
    if 0 < words < WORD_GRAM:
        raise ValueError(f"words must be 0 or at least {WORD_GRAM}")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole().alias("text"))
    docs = docs.select("doc_id", "text", F.xxhash64("text").alias("dh"))
    used: list[DataFrame] = []
    found = _spans(cut(anchors(docs, width, gram), "repeat-places"), docs, width, gram, most, words, used)
    lists = found.groupBy("doc_id", "dh").agg(F.collect_set(F.struct("begin", "end", "words")).alias("spans"))
    lists = cut(lists, "repeat-spans")
    for table in used:
        drop(table)
    kind = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", spans array<struct<begin:long,end:long>>, kept binary" * keep_text + ", n_shared_words long" * bool(words)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in frames:
            rows = []
            for doc_id, text, spans in zip(x["doc_id"], x["text"], x["spans"], strict=True):
                raw = text.encode("utf-8", "surrogatepass")
                spans = [] if spans is None else spans
                gone = merged([(s["begin"], s["end"]) for s in spans if not s["words"]])
                kept, at = [], 0
                for a, b in gone:
                    kept.append(raw[at:a])
                    at = b
                kept = b"".join([*kept, raw[at:]])
                row = (None if pd.isna(doc_id) else int(doc_id), len(raw), len(raw) - len(kept), len(gone), hashlib.sha256(kept).hexdigest())
                row = (*row, [{"begin": a, "end": b} for a, b in gone], kept) if keep_text else row
                rows.append((*row, sum(b - a for a, b in merged([(s["begin"], s["end"]) for s in spans if s["words"]]))) if words else row)
            names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"] + ["spans", "kept"] * keep_text + ["n_shared_words"] * bool(words)
            yield pd.DataFrame(rows, columns=names).astype({"doc_id": "Int64"})

    same = docs["doc_id"].eqNullSafe(lists["doc_id"]) & (docs["dh"] == lists["dh"])
    return docs.join(lists, same, "left").select(docs["doc_id"], "text", "spans").mapInPandas(lean(run), kind)
