"""Whole-batch word splitting and 64-bit word hashing on raw UTF-8 bytes with numpy."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

#: Fixed values of the word rules: white space is x20 and x09-x0D.
SPACES = b"\x20\x09\x0a\x0b\x0c\x0d"
LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))

_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_INV = np.uint64(pow(int(_BASE), -1, 1 << 64))
_SEG = 1 << 20
_is_space = np.zeros(256, dtype=bool)
_is_space[list(SPACES)] = True
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = max(_SEG, 1 << max(0, (n - 1)).bit_length())
    if size not in _powers:
        with np.errstate(over="ignore"):
            both = []
            for base in (_BASE, _INV):
                t = np.full(size, base, dtype=np.uint64)
                t[0] = 1
                both.append(np.multiply.accumulate(t))
        if size > _SEG:
            return both[0], both[1]
        _powers[size] = (both[0], both[1])
    return _powers[size]


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every output bit depends on every input bit."""
    with np.errstate(over="ignore"):
        x = x ^ (x >> np.uint64(30))
        x = x * np.uint64(0xBF58476D1CE4E5B9)
        x = x ^ (x >> np.uint64(27))
        x = x * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


@dataclass
class Words:
    """Hashes and byte spans of all words of a batch; words of row i are ``first[i]:first[i+1]``."""

    h: np.ndarray
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray
    base: np.ndarray  # byte offset of each row in the joined buffer
    buf: bytes


def range_hash(values: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Polynomial hash of ``values[lo:hi]`` for many ranges at once, equal for equal contents."""
    if not len(lo):
        return np.zeros(0, dtype=np.uint64)
    power, inverse = _power_tables(len(values) + 1)
    with np.errstate(over="ignore"):
        sums = np.zeros(len(values) + 1, dtype=np.uint64)
        np.cumsum(values * power[: len(values)], out=sums[1:])
        return mix((sums[hi] - sums[lo]) * inverse[lo] + (hi - lo).astype(np.uint64))


def hash_words(texts: list[bytes], lower: bool = False) -> Words:
    """Words ``[^\\x20\\x09-\\x0D]+`` of every text, hashed by their bytes; empty texts have none."""
    buf = b"\n".join(texts) + b"\n"
    if lower:
        buf = buf.translate(LOWER)
    raw = np.frombuffer(buf, dtype=np.uint8)
    base = np.zeros(len(texts) + 1, dtype=np.int64)
    np.cumsum(np.array([len(t) + 1 for t in texts], dtype=np.int64), out=base[1:])
    gap = _is_space[raw]
    edge = np.flatnonzero(gap[1:] != gap[:-1]) + 1
    if len(raw) and not gap[0]:
        edge = np.concatenate([[0], edge])
    start, end = edge[0::2], edge[1::2]
    h = np.empty(len(start), dtype=np.uint64)
    at = 0
    while at < len(start):  # the power tables stay small whatever the batch holds
        to = max(at + 1, int(np.searchsorted(end, start[at] + _SEG - 8, side="right")))
        lo = int(start[at])
        part = raw[lo : int(end[to - 1])].astype(np.uint64) + np.uint64(1)
        h[at:to] = range_hash(part, start[at:to] - lo, end[at:to] - lo)
        at = to
    return Words(h, start, end, np.searchsorted(start, base), base, buf)


def grams(h: np.ndarray, k: int) -> np.ndarray:
    """Ordered hash of each run of k words, for all positions (runs over row ends included)."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, dtype=np.uint64)
    out = np.zeros(n, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for i in range(k):
            out = out * np.uint64(0xD6E8FEB86659FD93) + h[i : i + n]
    return mix(out + np.uint64(k))


def as_long(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)
