"""Packing token sequences by linear grouping.

Documents become pieces of at most ``LIMIT`` tokens.  Packing works on the histogram of piece lengths (at most ``LIMIT``
entries, whatever the corpus): long pieces are sorted, cut into groups of equal cardinality and rounded up to the
longest of their group; a linear programme over configurations of these few sizes (columns made by a knapsack, simplex
on the driver) says how often each configuration is used, rounded down, with the rest packed best-fit.  Actual pieces
replace the rounded ones, so every configuration stays within the limit.  Small pieces then go best-fit into what
is left, longest first, on the histogram of remainders, and what does not fit opens new sequences.

The plan is a list of intervals of ranks; ranks of equal lengths are counted in salted cells, so a length that a third
of all pieces has is spread over many tasks.  Neither texts nor pieces reach the driver.

Defined results: null texts are empty and have the end token alone; repeated ids are packed once per row; an empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import bisect
import unicodedata
import zlib
from collections import defaultdict
from collections.abc import Iterator
from functools import cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import shingles as S
from .common import cells, cut, lean

LIMIT = 4096
END = 1
GROUPS = 96  # sizes that the linear programme sees
LONG = LIMIT // 4  # pieces above are long
Interval = tuple[int, int, int, int, int, int]  # length, first rank, number, bundle, first sequence of it, offset


@cache
def _tokenizer(path: str):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


#: What a byte is to the tokenizer's pre-tokenizer: 0 white space, 1 letter (also all above 127), 2 digit, 3 other.
KINDS = np.full(256, 3, dtype=np.int8)
KINDS[[9, 10, 11, 12, 13, 32]] = 0
KINDS[[*range(65, 91), *range(97, 123), *range(128, 256)]] = 1
KINDS[48:58] = 2


@cache
def _plain(char: str) -> bool:
    """A letter that normalisation leaves alone, or ASCII: only such texts are split by bytes."""
    return char < "\x80" or unicodedata.category(char)[0] == "L" and not unicodedata.combining(char) and unicodedata.normalize("NFC", char) == char


LANES = 3  # of eight bytes: words up to 24 bytes are compared as numbers


class Encoder:
    """Ids of texts, each distinct word encoded once by the tokenizer and then found by its bytes.

    Words are the pre-tokenizer's: runs of letters, single digits, runs of other signs.  Chunks with an apostrophe or a bar
    (contractions, special tokens) stay whole, and texts with characters that aren't plain go to the tokenizer as they are.
    Words of up to eight bytes per lane are looked up by a hash and then compared byte by byte (as numbers); longer ones, and
    those whose hash a different word has, are looked up in a dictionary.  Forgets everything when it holds more than ``most`` words.
    """

    def __init__(self, path: str, most: int = 1_500_000):
        self.path, self.most = path, most
        self.forget()

    def forget(self) -> None:
        self.runs: list[tuple[np.ndarray, ...]] = []  # sorted hashes, bytes in lanes, places in the pool, numbers of ids; sizes halve
        self.long: dict[bytes, tuple[int, int]] = {}
        self.pool = np.zeros(1 << 16, dtype=np.uint32)
        self.used = 0

    def find(self, keys: np.ndarray, lanes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Places and numbers of ids (-1: new), and which words have the hash of another one."""
        at, many = np.full(len(keys), -1, dtype=np.int64), np.zeros(len(keys), dtype=np.int64)
        clash = np.zeros(len(keys), dtype=bool)
        left = np.arange(len(keys))
        for own, bytes_, places, numbers in self.runs:
            spot = np.minimum(np.searchsorted(own, keys[left]), len(own) - 1)
            hit = own[spot] == keys[left]
            same = hit & (bytes_[spot] == lanes[left]).all(axis=1)
            clash[left[hit & ~same]] = True
            at[left[same]], many[left[same]] = places[spot[same]], numbers[spot[same]]
            left = left[~hit]
            if not len(left):
                break
        return at, many, clash

    def put(self, names: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Encodes words, joined by blanks, in a few calls; tokens are told apart by their places.  Places and numbers of ids."""
        numbers, begin = [np.zeros(0, dtype=np.int64)], self.used
        for a in range(0, len(names), 20_000):
            some = names[a : a + 20_000]
            e = _tokenizer(self.path).encode(" ".join(some), add_special_tokens=False)
            starts = np.cumsum([0, *[len(n) + 1 for n in some]])
            owner = np.searchsorted(starts, np.fromiter((o[0] for o in e.offsets), dtype=np.int64, count=len(e)), side="right") - 1
            while self.used + len(e) > len(self.pool):
                self.pool = np.concatenate((self.pool, np.zeros(len(self.pool), dtype=np.uint32)))
            self.pool[self.used : self.used + len(e)] = e.ids
            numbers.append(np.bincount(owner, minlength=len(some)))
            self.used += len(e)
        many = np.concatenate(numbers).astype(np.int32)
        return (begin + np.cumsum(many) - many).astype(np.int32), many

    def learn(self, keys: np.ndarray, lanes: np.ndarray, names: list[str]) -> None:
        """Adds words to the table; ``keys`` ascend."""
        self.runs.append((keys, lanes, *self.put(names)))
        while len(self.runs) > 1 and len(self.runs[-2][0]) < 2 * len(self.runs[-1][0]):
            both = [np.concatenate(v) for v in zip(self.runs[-2], self.runs[-1], strict=True)]
            order = np.argsort(both[0], kind="stable")  # two sorted runs: a merge
            self.runs[-2:] = [tuple(v[order] for v in both)]

    def block(self, raws: list[bytes]) -> list[np.ndarray]:
        """Ids of each of some short texts."""
        raw, starts, ends, bounds = split(raws)
        if not len(starts):
            return [np.zeros(0, dtype=np.uint32) for _ in raws]
        lanes, fits = lanes_of(raw, starts, ends)
        short, other = np.flatnonzero(fits), [np.flatnonzero(~fits)]
        lanes = lanes[short]
        keys = np.zeros(len(short), dtype=S.U)
        for k in range(LANES):
            keys = S.mix(keys * S.U(0x9E3779B97F4A7C15) + lanes[:, k] + S.U(k + 1))
        order = np.argsort(keys)
        fresh = np.ones(len(order), dtype=bool)
        fresh[1:] = (lanes[order[1:]] != lanes[order[:-1]]).any(axis=1)
        back = np.empty(len(order), dtype=np.int64)
        back[order] = np.cumsum(fresh) - 1
        first = order[fresh]
        keys, lanes = keys[first], lanes[first]
        if len(self.long) + sum(len(r[0]) for r in self.runs) + len(keys) > self.most:
            self.forget()
        text = raw.tobytes()
        word = lambda i: text[starts[i] : ends[i]]
        at, many, clash = self.find(keys, lanes)
        clash[1:] |= (keys[1:] == keys[:-1]) & (at[1:] < 0)
        new = (at < 0) & ~clash
        if new.any():
            self.learn(keys[new], lanes[new], [word(i).decode("utf-8") for i in short[first[new]].tolist()])
            at[new], many[new], _ = self.find(keys[new], lanes[new])
        begin, count = np.zeros(len(starts), dtype=np.int64), np.zeros(len(starts), dtype=np.int64)
        begin[short], count[short] = at[back], many[back]
        if clash.any():
            other.append(short[clash[back]])
        for i in np.concatenate(other).tolist():
            name = word(i)
            if name not in self.long:
                (own,), (n,) = self.put([name.decode("utf-8")])
                self.long[name] = (int(own), int(n))
            begin[i], count[i] = self.long[name]
        upto = np.cumsum(count)
        out = self.pool[np.repeat(begin - (upto - count), count) + np.arange(int(upto[-1]))]
        cuts = np.concatenate(([0], upto))[bounds]
        return [out[a:b] for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)]

    def encode(self, texts: list[str]) -> list[bytes]:
        """Packed unsigned 32-bit ids with the end token."""
        end = np.asarray([END], dtype="<u4")
        out: list[bytes] = [b""] * len(texts)
        plain = []
        for i, t in enumerate(texts):
            if t.isascii() or all(map(_plain, set(t))):
                plain.append(i)
            else:
                ids = _tokenizer(self.path).encode(t, add_special_tokens=False).ids
                out[i] = np.asarray([*ids, END], dtype="<u4").tobytes()
        raws = [texts[i].encode("utf-8") for i in plain]
        for a, b in S.batches([len(r) for r in raws]):
            if b - a == 1 and len(raws[a]) > S.BLOCK:
                ids = [np.concatenate([self.block([p])[0] for p in at_blanks(raws[a])])]
            else:
                ids = self.block(raws[a:b])
            for i, x in zip(plain[a:b], ids, strict=True):
                out[i] = np.concatenate((x, end)).astype("<u4").tobytes()
        return out


def at_blanks(raw: bytes) -> Iterator[bytes]:
    """Cuts a long text at white space into parts of about a block."""
    at = 0
    while len(raw) - at > S.BLOCK:
        end = at + S.BLOCK
        while end < len(raw) and KINDS[raw[end]]:
            end += 1
        yield raw[at:end]
        at = end
    yield raw[at:]


def split(raws: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """All bytes, starts and ends of words, and where each text's words begin."""
    joined = np.frombuffer(b"\n".join(raws) + b"\n", dtype=np.uint8)
    kind = KINDS[joined]
    whole = np.flatnonzero((joined == 39) | (joined == 124))
    if len(whole):
        chunk = np.cumsum(kind == 0)
        kind[np.isin(chunk, np.unique(chunk[whole])) & (kind != 0)] = 4
    edge = np.ones(len(joined) + 1, dtype=bool)
    edge[1:-1] = (kind[1:] != kind[:-1]) | (kind[1:] == 2)
    at = np.flatnonzero(edge)
    keep = kind[at[:-1]] != 0
    starts, ends = at[:-1][keep], at[1:][keep]
    return joined, starts, ends, np.searchsorted(starts, np.cumsum([0, *[len(r) + 1 for r in raws]]))


def lanes_of(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Words as rows of numbers, eight bytes each and zeros after the end, and which words fit them.  No word has a zero
    byte at its end but runs of other signs; those that have one don't fit."""
    eight = np.lib.stride_tricks.sliding_window_view(np.concatenate((raw, np.zeros(8 * LANES, dtype=np.uint8))), 8)
    size = ends - starts
    out = np.zeros((len(starts), LANES), dtype=S.U)
    for k in range(LANES):
        live = np.flatnonzero(size > 8 * k)
        number = np.ascontiguousarray(eight[starts[live] + 8 * k]).view("<u8").ravel()
        spare = 8 * np.maximum(0, 8 * (k + 1) - size[live])
        out[live, k] = (number << spare.astype(S.U)) >> spare.astype(S.U)
    return out, (size <= 8 * LANES) & (raw[ends - 1] != 0)


@cache
def _encoder(path: str) -> Encoder:
    return Encoder(path)


def encode(texts: list[str], path: str) -> list[bytes]:
    return _encoder(path).encode(texts)


def pieces(docs: DataFrame, path: str, limit: int = LIMIT) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in frames:
            rows = []
            texts = x["text"].fillna("").tolist()
            for key, raw in zip(x["doc_id"], (r for a, b in S.batches([len(t) for t in texts]) for r in encode(texts[a:b], path)), strict=True):
                key = None if pd.isna(key) else int(key)
                for k, a in enumerate(range(0, len(raw), 4 * limit)):
                    part = raw[a : a + 4 * limit]
                    rows.append((key, k, k * limit, len(part) // 4, zlib.crc32(part)))
            yield pd.DataFrame(rows, columns=["doc_id", "piece", "start", "length", "ids_crc32"]).astype({"doc_id": "Int64"})

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInPandas(lean(run), "doc_id long, piece int, start long, length long, ids_crc32 long")


def knapsack(sizes: list[int], worth: np.ndarray, limit: int) -> np.ndarray:
    """The most valuable multiset of sizes that fits the limit, on the grid of single tokens."""
    best, took = np.zeros(limit + 1), np.full(limit + 1, -1)
    for i in (i for i in range(len(sizes)) if worth[i] > 1e-12):
        s, v = sizes[i], worth[i]
        for at in range(s, limit + 1, s):  # values a size apart depend on each other, those between don't
            there = best[at : at + s]
            tried = best[at - s : at - s + len(there)] + v
            better = tried > there + 1e-12
            there[better] = tried[better]
            took[at : at + s][better] = i
    out, at = np.zeros(len(sizes), dtype=np.int64), int(np.argmax(best))
    while at > 0 and took[at] >= 0:
        out[took[at]] += 1
        at -= sizes[took[at]]
    return out


def configurations(sizes: list[int], counts: list[int], limit: int, rounds: int = 5000) -> list[tuple[np.ndarray, int]]:
    """Configurations and how often each is used: the linear programme's solution, rounded down.

    Columns are added until none improves the programme.  ``rounds`` only guards against cycling among equal solutions: any basis
    gives a valid plan, and ``plan`` compares it with best fit.
    """
    n = len(sizes)
    need = np.asarray(counts, dtype=float)
    basis = np.diag([float(limit // s) for s in sizes])
    for _ in range(rounds):
        inverse = np.linalg.inv(basis)
        price = np.maximum(np.ones(n) @ inverse, 0)
        column = knapsack(sizes, price, limit).astype(float)
        if price @ column <= 1 + 1e-7:
            break
        level, step = inverse @ need, inverse @ column
        ok = step > 1e-9
        if not ok.any():
            break
        out = int(np.argmin(np.where(ok, level / np.where(ok, step, 1), np.inf)))
        basis[:, out] = column
    level = np.linalg.solve(basis, need)
    return [(basis[:, j].astype(np.int64), int(np.floor(level[j] + 1e-9))) for j in range(n) if level[j] >= 1 - 1e-9]


class _Ranks:
    """Hands out ranks of each length."""

    def __init__(self, counts: dict[int, int]):
        self.left, self.next = dict(counts), defaultdict(int)

    def take(self, length: int, n: int) -> int:
        first = self.next[length]
        self.next[length] += n
        self.left[length] -= n
        return first


def plan(counts: dict[int, int], limit: int = LIMIT, groups: int = GROUPS, long: int = LONG) -> tuple[list[Interval], int]:
    """The better of two plans: with configurations, and by best fit alone (rounding up to group sizes can miss exact fits)."""
    return min(_plan(counts, limit, groups, long), _plan(counts, limit, groups, limit), key=lambda x: x[1])


def _plan(counts: dict[int, int], limit: int, groups: int, long: int) -> tuple[list[Interval], int]:
    """Intervals that place every piece, and the number of sequences.

    A bundle is a run of sequences with the same fill; an interval puts one piece of its length into each of them.
    """
    ranks, out, made = _Ranks(counts), [], 0
    room: dict[int, list[list[int]]] = defaultdict(list)  # remainder: [first sequence, number] runs

    def place(length: int, n: int, first: int, offset: int) -> None:
        out.append((length, ranks.take(length, n), n, first, n, offset))

    # Whole sequences first.
    if counts.get(limit):
        place(limit, counts[limit], 0, 0)
        made = counts[limit]
    big = sorted((x for x in counts if long < x < limit and counts[x]), reverse=True)
    total = sum(counts[x] for x in big)
    if total:
        each = -(-total // groups)
        members: list[list[list[int]]] = []  # per group: [length, number], longest first
        for x in big:
            left = counts[x]
            while left:
                held = sum(m[1] for m in members[-1]) if members else each
                if held == each:
                    members.append([])
                    held = 0
                n = min(left, each - held)
                members[-1].append([x, n])
                left -= n
        sizes = [m[0][0] for m in members]
        numbers = [sum(m[1] for m in g) for g in members]
        # Groups of one size are one size to the programme.
        distinct = sorted(set(sizes), reverse=True)
        at = {s: i for i, s in enumerate(distinct)}
        stock: list[list[list[int]]] = [[] for _ in distinct]
        for s, g in zip(sizes, members, strict=True):
            stock[at[s]] += g
        need = [sum(n for s, n in zip(sizes, numbers, strict=True) if s == d) for d in distinct]
        for column, times in configurations(distinct, need, limit):
            # The actual pieces of a configuration: runs of equal pieces in each place.
            done = 0
            heads = [i for i, k in enumerate(column) for _ in range(int(k))]
            times = min([times, *[sum(m[1] for m in stock[i]) // int(column[i]) for i in set(heads)]])
            while done < times:
                use: dict[int, int] = defaultdict(int)
                for i in heads:
                    use[i] += 1
                n = min([times - done, *[max(1, stock[i][0][1] // use[i]) for i in use]])
                picked, offset = [], 0
                for i in heads:
                    # With fewer pieces left of a length than places want, the next length serves the rest of them.
                    k = next(j for j, m in enumerate(stock[i]) if m[1] >= n)
                    picked.append(stock[i][k][0])
                    stock[i][k][1] -= n
                    stock[i] = [m for m in stock[i] if m[1]]
                for x in picked:
                    place(x, n, made, offset)
                    offset += x
                room[limit - offset].append([made, n])
                made += n
                done += n
    # The rest, longest first, each into the tightest remainder that holds it.
    free = sorted(r for r in room if room[r] and r > 0)
    for x in sorted((x for x in counts if 0 < x < limit), reverse=True):
        while ranks.left[x] > 0:
            k = bisect.bisect_left(free, x)
            if k < len(free):
                r = free[k]
                first, n = room[r][-1]
                m = min(n, ranks.left[x])
                room[r][-1] = [first + m, n - m]
                if n == m:
                    room[r].pop()
                if not room[r]:
                    free.pop(k)
            else:
                r, fit = limit, limit // x
                m = -(-ranks.left[x] // fit)
                first, made = made, made + m
                if m * fit > ranks.left[x]:
                    m = max(1, ranks.left[x] // fit)
                    made = first + m
            place(x, m, first, limit - r)
            if r - x > 0:
                room[r - x].append([first, m])
                if len(room[r - x]) == 1:
                    bisect.insort(free, r - x)
    return out, made


def pack(docs: DataFrame, path: str, limit: int = LIMIT, cell_rows: int = 5_000) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    spark = docs.sparkSession
    cut_up = cut(pieces(docs, path, limit), "pack-pieces")
    many = cells(cut_up.count(), cell_rows, 4096)
    cut_up = cut_up.withColumn("cell", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(many)).cast("int"))
    sized = cut(cut_up.groupBy("length", "cell").agg(F.count(F.lit(1)).alias("n")), "pack-sizes")
    counts = {int(r[0]): int(r[1]) for r in sized.groupBy("length").agg(F.sum("n")).collect()}  # one row per length at most
    placed, _ = plan(counts, limit)
    where = spark.createDataFrame([x[:4] + (x[5],) for x in placed] or [(0, 0, 0, 0, 0)], "length long, first_rank long, n long, first_sequence long, offset long")
    before = Window.partitionBy("length").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    first = sized.select("length", "cell", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("first"))
    own = Window.partitionBy("length", "cell").orderBy("doc_id", "piece", "ids_crc32")
    ranked = cut_up.withColumn("nth", F.row_number().over(own)).join(first, ["length", "cell"]).withColumn("rank", F.col("first") + F.col("nth") - 1)
    # Each length's intervals, sorted by rank, as one row; the interval of a rank is found by binary search.
    listed = where.groupBy("length").agg(F.sort_array(F.collect_list(F.struct("first_rank", "first_sequence", "offset"))).alias("runs"))
    steps = F.array(*[F.lit(1 << k) for k in range(max(1, len(placed)).bit_length(), -1, -1)])
    at = F.aggregate(steps, F.lit(0), lambda i, s: F.when((i + s < F.size("runs")) & (F.get("runs", i + s)["first_rank"] <= F.col("rank")), i + s).otherwise(i))
    found = ranked.join(F.broadcast(listed), "length").withColumn("run", F.get("runs", at))  # bounded by the plan, not by rows
    return found.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("run.first_sequence") + F.col("rank") - F.col("run.first_rank")).alias("sequence_id"), F.col("run.offset").alias("offset"))
