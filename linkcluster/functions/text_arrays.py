"""Vectorised text kernels shared by the operators on Arrow batches.

A piece is a list of texts laid end to end with one separator after each.  Words, lines
and n-grams are found with array operations and named by 64-bit polynomial hashes with a
mixing step, so no per-word Python object exists.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np

BASE = 0x9E3779B97F4A7C15
PIECE = 1 << 19
_U = np.uint64


def pieces(lengths: list[int], budget: int = PIECE):
    """Ranges [lo, hi) of consecutive texts of about ``budget`` characters; a longer text stands alone."""
    lo, total = 0, 0
    for i, n in enumerate(lengths):
        if total and total + n > budget:
            yield lo, i
            lo, total = i, 0
        total += n + 1
    if lo < len(lengths):
        yield lo, len(lengths)


@lru_cache(maxsize=2)
def _powers(bits: int) -> tuple[np.ndarray, np.ndarray]:
    n = 1 << bits
    up = np.full(n, BASE, dtype=_U)
    down = np.full(n, pow(BASE, -1, 1 << 64), dtype=_U)
    up[0] = down[0] = 1
    return np.cumprod(up, dtype=_U), np.cumprod(down, dtype=_U)


def mix(h: np.ndarray) -> np.ndarray:
    """A full-avalanche finaliser for 64-bit keys."""
    h = h.astype(_U, copy=True)
    h ^= h >> _U(30)
    h *= _U(0xBF58476D1CE4E5B9)
    h ^= h >> _U(27)
    h *= _U(0x94D049BB133111EB)
    h ^= h >> _U(31)
    return h


def span_hashes(codes: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """One 64-bit hash for each span of ``codes``; equal spans have equal hashes wherever they stand."""
    if not len(starts):
        return np.zeros(0, dtype=_U)
    up, down = _powers(max(20, int(len(codes)).bit_length()))
    total = np.zeros(len(codes) + 1, dtype=_U)
    np.cumsum((codes.astype(_U) + _U(1)) * up[: len(codes)], out=total[1:])
    return mix(((total[ends] - total[starts]) * down[starts]) ^ (ends - starts).astype(_U))


def runs(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of True."""
    edge = np.diff(np.concatenate(([0], mask.view(np.int8), [0])))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def ngram_hashes(words: np.ndarray, n: int) -> np.ndarray:
    """Order-sensitive hashes of all n-word windows (len(words) - n + 1 of them)."""
    m = len(words) - n + 1
    if m <= 0:
        return np.zeros(0, dtype=_U)
    h = np.zeros(m, dtype=_U)
    for i in range(n):
        h = h * _U(BASE) + words[i : i + m]
        h ^= h >> _U(29)
    return mix(h)


@lru_cache(maxsize=1)
def _classes() -> tuple[np.ndarray, np.ndarray]:
    """For each code point: whether it is a letter; whether it is a letter or a digit."""
    size = 0x110000
    alpha, alnum = np.zeros(size, dtype=bool), np.zeros(size, dtype=bool)
    for i in range(size):
        c = chr(i)
        if c.isalnum():
            alnum[i] = True
            alpha[i] = c.isalpha()
    return alpha, alnum


def letters(codes: np.ndarray) -> np.ndarray:
    return _classes()[0][codes]


def letters_or_digits(codes: np.ndarray) -> np.ndarray:
    return _classes()[1][codes]


def code_points(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of the texts with a line feed after each, and where each text starts (one more at the end)."""
    joined = "\n".join(texts) + "\n"
    codes = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    starts = np.zeros(len(texts) + 1, dtype=np.int64)
    np.cumsum([len(t) + 1 for t in texts], out=starts[1:])
    return codes, starts


def utf8_bytes(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """As ``code_points``, for UTF-8 bytes."""
    raw = [t.encode("utf-8", "surrogatepass") for t in texts]
    starts = np.zeros(len(texts) + 1, dtype=np.int64)
    np.cumsum([len(t) + 1 for t in raw], out=starts[1:])
    return np.frombuffer(b"\n".join(raw) + b"\n", dtype=np.uint8), starts
