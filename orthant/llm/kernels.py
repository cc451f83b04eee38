"""Vectorised passes over UTF-8 bytes: word spans, span hashes, windows, per-text counts.

A span hash is the difference of two prefix sums of ``byte * P**i`` modulo 2**64, moved back by
``P**-start`` and mixed, so that equal spans hash alike wherever they stand, in every process.
"""

from __future__ import annotations

import numpy as np

U64 = np.uint64
_P = 0x9E3779B97F4A7C15 | 1
_P_INV = pow(_P, -1, 1 << 64)
_powers: dict[str, np.ndarray] = {}


def lut(members: bytes) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(members)] = True
    return out


SPACE = lut(b"\x20\x09\x0a\x0b\x0c\x0d")
CONTINUATION = np.zeros(256, bool)
CONTINUATION[0x80:0xC0] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    have = _powers.get("p")
    if have is None or len(have) < n:
        size = max(n, 1 << 16) + (n >> 1)
        for key, base in (("p", _P), ("q", _P_INV)):
            run = np.full(size, base, U64)
            run[0] = 1
            _powers[key] = np.multiply.accumulate(run)
    return _powers["p"][:n], _powers["q"][:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64 bits."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


def prefix(buf: np.ndarray) -> np.ndarray:
    """Prefix sums for span hashes; one longer than ``buf``."""
    p, _ = powers(len(buf) + 1)
    out = np.zeros(len(buf) + 1, U64)
    np.cumsum((buf.astype(U64) + U64(1)) * p[: len(buf)], out=out[1:])
    return out


def span_hash(pre: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    _, q = powers(len(pre))
    return mix((pre[end] - pre[start]) * q[start] + (end - start).astype(U64) * U64(0xD6E8FEB86659FD93))


def spans(inside: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Maximal runs of true within each text: (starts, ends, index of each text's first run and one more)."""
    n = len(inside)
    before = np.zeros(n + 1, bool)
    before[1:] = inside
    first = off[:-1][off[:-1] < n]
    opens = before[:-1].copy()
    opens[first] = False
    start = np.flatnonzero(inside & ~opens)
    after = np.zeros(n, bool)
    after[:-1] = inside[1:]
    last = off[1:][(off[1:] > 0)] - 1
    after[last] = False
    end = np.flatnonzero(inside & ~after) + 1
    return start, end, np.searchsorted(start, off)


def words(buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return spans(~SPACE[buf], off)


def per_text(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Sums of ``values`` between consecutive bounds."""
    run = np.zeros(len(values) + 1, np.int64)
    np.cumsum(values, out=run[1:])
    return run[bounds[1:]] - run[bounds[:-1]]


def owner(bounds: np.ndarray) -> np.ndarray:
    return np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))


_WINDOW = np.array([pow(0xC2B2AE3D27D4EB4F, i + 1, 1 << 64) | 1 for i in range(16)], dtype=U64)


def windows(hashes: np.ndarray, bounds: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of all runs of ``width`` words inside a text: (hash, first word's index, text's index)."""
    n = len(hashes)
    if n < width:
        return np.zeros(0, U64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    total = hashes[: n - width + 1] * _WINDOW[0]
    for i in range(1, width):
        total = total + hashes[i : n - width + 1 + i] * _WINDOW[i]
    text = owner(bounds)
    keep = np.flatnonzero(text[: n - width + 1] == text[width - 1 :])
    return mix(total[keep]), keep, text[keep]
