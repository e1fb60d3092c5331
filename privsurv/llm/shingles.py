"""Vectorised word and shingle hashing over whole texts, and MinHash signatures (numpy only).

Words are runs of letters and digits (any byte above 127 counts as a letter) of the lower-cased text.  A word's hash is
a polynomial over its UTF-8 bytes at a random point of the field of 2^61 - 1 elements, then mixed.  A shingle is five words; texts of one to four words have
one shingle, of all their words; texts without words have one shingle, of their trimmed characters.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np

WIDTH = 5
BLOCK = 1 << 18  # bytes hashed at a time: arrays stay small
STEP = 1 << 15  # numbers that one run of numpy calls takes
U = np.uint64
PRIME = 2**61 - 1  # no texts are known whose polynomials agree at a random point, unlike modulo 2^64
_rng = np.random.default_rng(77)
_base = int(_rng.integers(1 << 59, 1 << 60))
_mul = _rng.integers(1, 1 << 63, 64, dtype=U) * U(2) + U(1)
_word = np.zeros(256, dtype=bool)
_word[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True
_powers: dict[str, np.ndarray] = {}
_P, _LOW31, _LOW30 = U(PRIME), U(2**31 - 1), U(2**30 - 1)


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every bit of 64."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U(27))
    x = x * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def _reduced(x: np.ndarray) -> np.ndarray:
    """Any 64-bit numbers modulo the prime."""
    x = (x & _P) + (x >> U(61))
    return np.minimum(x, x - _P)  # below zero wraps to large numbers


def times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Products in the field, by halves of 30 and 31 bits."""
    a1, a0, b1, b0 = a >> U(31), a & _LOW31, b >> U(31), b & _LOW31
    middle = a1 * b0 + a0 * b1
    return _reduced(a1 * b1 * U(2) + (middle >> U(30)) + ((middle & _LOW30) << U(31)) + a0 * b0)


def less(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Differences in the field."""
    d = a - b
    return np.minimum(d, d + _P)


def power_table(value: int, n: int) -> np.ndarray:
    """value^0 .. value^(n-1) in the field."""
    out = np.ones(max(1, n), dtype=U)
    done = 1
    while done < len(out):
        more = min(done, len(out) - done)
        out[done : done + more] = times(out[:more], np.full(more, pow(value, done, PRIME), dtype=U))
        done += more
    return out


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, at least ``n`` of each; what texts longer than a block need isn't kept."""
    if n > BLOCK + 4096:
        return power_table(_base, n), power_table(pow(_base, -1, PRIME), n)
    if not _powers:
        _powers["up"], _powers["down"] = power_table(_base, BLOCK + 4096), power_table(pow(_base, -1, PRIME), BLOCK + 4096)
    return _powers["up"], _powers["down"]


class Prefixes:
    """Prefix polynomial hashes of a byte string: the hash of any span of it in constant time."""

    def __init__(self, raw: np.ndarray):
        self.raw = raw
        up, self._down = powers(len(raw) + 1)
        self._sum = np.zeros(len(raw) + 1, dtype=U)
        for lo in range(0, len(raw), STEP):  # arrays stay in cache, and sums of halves fit 64 bits
            values, own = raw[lo : lo + STEP].astype(U), up[lo : min(lo + STEP, len(raw))]
            values += U(1)
            low = own & _LOW31
            low *= values
            values *= own >> U(31)
            high = np.cumsum(values, out=values)
            low = np.cumsum(low, out=low)
            low += (high & _LOW30) << U(31)
            low += high >> U(30)
            low += self._sum[lo]
            self._sum[lo + 1 : lo + 1 + len(low)] = _reduced(low)

    def span(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        out = np.empty(len(a), dtype=U)
        for lo in range(0, len(a), STEP):
            i = a[lo : lo + STEP]
            out[lo : lo + STEP] = mix(times(less(self._sum[b[lo : lo + STEP]], self._sum[i]), self._down[i]))
        return out


class Words:
    """Words of several texts: hash, start and end in ``raw``, and where each text's words begin (``first``)."""

    def __init__(self, raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, first: np.ndarray):
        self.raw, self.starts, self.ends, self.first = raw, starts, ends, first
        self.span = Prefixes(raw).span
        self.hashes = self.span(starts, ends)


def lower(text: str) -> str:
    """Lower case with the same number of characters."""
    low = text.lower()
    return low if len(low) == len(text) else "".join(c.lower() if len(c.lower()) == 1 else c for c in text)


def words(raws: Sequence[bytes]) -> Words:
    """``raws``: lower-cased texts in UTF-8, in all not much more than ``BLOCK`` bytes."""
    joined = np.frombuffer(b"\n".join(raws) + b"\n", dtype=np.uint8)
    inside = np.concatenate(([False], _word[joined])).astype(np.int8)
    turn = np.diff(inside)
    starts = np.flatnonzero(turn == 1)
    ends = np.flatnonzero(turn == -1)
    begins = np.cumsum([0, *[len(r) + 1 for r in raws]])
    return Words(joined, starts, ends, np.searchsorted(starts, begins))


def pieces(raw: bytes) -> Iterator[bytes]:
    """Cuts a long text between words into pieces of about ``BLOCK`` bytes."""
    at = 0
    while len(raw) - at > BLOCK:
        end = at + BLOCK
        while end < len(raw) and _word[raw[end]]:
            end += 1
        yield raw[at:end]
        at = end
    yield raw[at:]


def batches(sizes: Sequence[int], most: int = BLOCK) -> Iterator[tuple[int, int]]:
    """Ranges of rows whose sizes sum to ``most`` or are one row."""
    begin, total = 0, 0
    for i, n in enumerate(sizes):
        if i > begin and total + n > most:
            yield begin, i
            begin, total = i, 0
        total += n
    if begin < len(sizes):
        yield begin, len(sizes)


def word_hashes(texts: Sequence[str]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of all texts, and each text's first."""
    raws = [lower(t).encode("utf-8", "surrogatepass") for t in texts]
    hashes, counts = [], []
    for a, b in batches([len(r) for r in raws]):
        if b - a == 1 and len(raws[a]) > BLOCK:
            own = np.concatenate([words([p]).hashes for p in pieces(raws[a])])
            hashes.append(own)
            counts.append(len(own))
        else:
            w = words(raws[a:b])
            hashes.append(w.hashes)
            counts.extend(np.diff(w.first).tolist())
    return np.concatenate(hashes) if hashes else np.zeros(0, U), np.concatenate(([0], np.cumsum(np.asarray(counts, dtype=np.int64))))


def shingles(texts: Sequence[str], width: int = WIDTH) -> tuple[np.ndarray, np.ndarray]:
    """Shingle hashes of all texts (repeats kept) and each text's first; every text has at least one."""
    hashes, first = word_hashes(texts)
    n = np.diff(first)
    out = np.zeros(0, dtype=U)
    if len(hashes) >= width:
        out = np.zeros(len(hashes) - width + 1, dtype=U)
        for k in range(width):
            out += hashes[k : k + len(out)] * _mul[k]
        out = mix(out)
    counts = np.maximum(n - width + 1, 1)
    starts = np.concatenate(([0], np.cumsum(counts)))
    full = np.zeros(int(starts[-1]), dtype=U)
    long = np.flatnonzero(n >= width)
    if len(long):
        lengths = counts[long]
        step = np.arange(int(lengths.sum())) - np.repeat(np.cumsum(lengths) - lengths, lengths)
        full[np.repeat(starts[long], lengths) + step] = out[np.repeat(first[long], lengths) + step]
    for i in np.flatnonzero(n < width).tolist():
        if n[i]:
            full[starts[i]] = mix((hashes[first[i] : first[i + 1]] * _mul[8 : 8 + n[i]]).sum(dtype=U, keepdims=True) + U(n[i]))[0]
        else:
            raw = np.frombuffer(" ".join(texts[i].split()).encode("utf-8", "surrogatepass"), dtype=np.uint8)
            full[starts[i]] = mix(Prefixes(raw).span(np.zeros(1, int), np.full(1, len(raw))) + _mul[20])[0]
    return full, starts


def permutations(count: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """Multipliers and offsets of ``count`` multiply-shift hash functions."""
    rng = np.random.default_rng(seed)
    return rng.integers(0, 1 << 63, count, dtype=U) * U(2) + U(1), rng.integers(0, 1 << 63, count, dtype=U) * U(2)


def minhash(values: np.ndarray, starts: np.ndarray, count: int, seed: int = 5) -> np.ndarray:
    """One row of ``count`` 32-bit minima per set; ``starts`` ends with the number of values and sets aren't empty."""
    a, b = permutations(count, seed)
    out = np.zeros((len(starts) - 1, count), dtype=np.uint32)
    for lo, hi in batches(np.diff(starts).tolist(), 1 << 17):
        own = values[starts[lo] : starts[hi]]
        at = starts[lo:hi] - starts[lo]
        held = np.empty_like(own)
        for k in range(count):
            np.multiply(own, a[k], out=held)
            held += b[k]
            out[lo:hi, k] = np.minimum.reduceat(held, at) >> U(32)
    return out


def sets(values: np.ndarray, starts: np.ndarray) -> list[np.ndarray]:
    """Sorted distinct values of each text."""
    return [np.unique(values[starts[i] : starts[i + 1]]) for i in range(len(starts) - 1)]
