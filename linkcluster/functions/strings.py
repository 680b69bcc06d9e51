"""String similarities.

Jaro-Winkler is not built in.  ``jaro_winkler`` is an Arrow UDF whose kernel works on whole
batches: both sides become padded code-point matrices and the match loop runs over
positions, not pairs.  ``jaro_winkler_expr`` is the same measure from higher-order functions for
short labels without a Python worker.  The prefix bonus (scale 0.1, at most four letters)
applies above a Jaro similarity of 0.7 only.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T


def _matrix(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    n = np.array([len(t) for t in texts], dtype=np.int64)
    flat = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    out = np.zeros((len(texts), max(1, int(n.max(initial=0)))), dtype=np.uint32)
    out[np.arange(out.shape[1]) < n[:, None]] = flat
    return out, n


def _packed(codes: np.ndarray, hit: np.ndarray) -> np.ndarray:
    """Matched letters moved to the front, order kept."""
    order = np.argsort(~hit, axis=1, kind="stable")
    return np.take_along_axis(np.where(hit, codes, 0), order, axis=1)


def jaro_winkler_batch(left: list[str], right: list[str]) -> np.ndarray:
    if not left:
        return np.zeros(0)
    a, la = _matrix(left)
    b, lb = _matrix(right)
    reach = np.maximum(0, np.maximum(la, lb) // 2 - 1)
    at = np.arange(b.shape[1])
    hit_a, hit_b = np.zeros(a.shape, dtype=bool), np.zeros(b.shape, dtype=bool)
    rows = np.arange(len(left))
    for i in range(a.shape[1]):
        can = (b == a[:, i : i + 1]) & ~hit_b & (np.abs(at - i) <= reach[:, None]) & (at < lb[:, None]) & (i < la)[:, None]
        j = can.argmax(axis=1)
        ok = can[rows, j]
        hit_b[rows[ok], j[ok]] = True
        hit_a[:, i] = ok
    m = hit_a.sum(axis=1)
    x, y = _packed(a, hit_a), _packed(b, hit_b)
    w = min(x.shape[1], y.shape[1])
    swaps = (x[:, :w] != y[:, :w]).sum(axis=1) // 2
    with np.errstate(divide="ignore", invalid="ignore"):
        jaro = np.where(m > 0, (m / la + m / lb + (m - swaps) / m) / 3.0, 0.0)
    w = min(4, a.shape[1], b.shape[1])
    same = (a[:, :w] == b[:, :w]) & (np.arange(w) < np.minimum(la, lb)[:, None])
    prefix = np.cumprod(same, axis=1).sum(axis=1)
    return np.where(jaro > 0.7, jaro + 0.1 * prefix * (1 - jaro), jaro)


@F.pandas_udf(T.DoubleType())
def _jw(a: pd.Series, b: pd.Series) -> pd.Series:
    out = np.full(len(a), np.nan)
    ok = (a.notna() & b.notna()).to_numpy()
    out[ok] = np.concatenate([jaro_winkler_batch(a[ok].tolist()[i : i + 4096], b[ok].tolist()[i : i + 4096]) for i in range(0, int(ok.sum()), 4096)] or [np.zeros(0)])
    return pd.Series(out).where(ok, None).astype("object").where(ok, None)


def jaro_winkler(a: Column, b: Column) -> Column:
    """Jaro-Winkler similarity of two labels; null in, null out."""
    return _jw(a, b)


def jaro_winkler_expr(a: str, b: str) -> Column:
    """The same measure from built-in higher-order functions over two string columns."""
    la, lb = f"char_length({a})", f"char_length({b})"
    reach = f"greatest(0, cast(greatest({la}, {lb}) / 2 as int) - 1)"
    free = f"filter(sequence(greatest(1, i - {reach}), least({lb}, i + {reach})), j -> substring({b}, j, 1) = substring({a}, i, 1) AND NOT array_contains(acc.js, j))"
    init = "named_struct('is', cast(array() as array<int>), 'js', cast(array() as array<int>))"
    step = f"CASE WHEN greatest(1, i - {reach}) > least({lb}, i + {reach}) THEN acc WHEN size({free}) > 0 THEN named_struct('is', array_append(acc.is, i), 'js', array_append(acc.js, ({free})[0])) ELSE acc END"
    found = f"aggregate(sequence(1, {la}), {init}, (acc, i) -> {step})"
    other = f"zip_with(m.is, array_sort(m.js), (i, j) -> IF(substring({a}, i, 1) <> substring({b}, j, 1), 1, 0))"
    swaps = f"cast(aggregate({other}, 0, (s, x) -> s + x) / 2 as int)"
    n = "cast(size(m.is) as double)"
    jaro = f"CASE WHEN size(m.is) = 0 THEN 0D ELSE ({n} / {la} + {n} / {lb} + ({n} - {swaps}) / {n}) / 3D END"
    prefix = f"aggregate(sequence(1, 4), named_struct('n', 0, 'on', true), (p, i) -> IF(p.on AND i <= least({la}, {lb}) AND substring({a}, i, 1) = substring({b}, i, 1), named_struct('n', p.n + 1, 'on', true), named_struct('n', p.n, 'on', false))).n"
    whole = f"element_at(transform(transform(array({found}), m -> {jaro}), q -> IF(q > 0.7D, q + 0.1D * {prefix} * (1D - q), q)), 1)"
    return F.expr(f"CASE WHEN {a} IS NULL OR {b} IS NULL THEN cast(null as double) WHEN {la} = 0 OR {lb} = 0 THEN 0D ELSE {whole} END")


def levenshtein_ratio(a: Column, b: Column) -> Column:
    longest = F.greatest(F.char_length(a), F.char_length(b))
    return F.when(longest == 0, F.lit(1.0)).otherwise(1 - F.levenshtein(a, b) / longest)


def qgrams(c: Column, q: int = 3) -> Column:
    n = F.char_length(c) - q + 1
    return F.when(n < 1, F.array(c)).otherwise(F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.substring(c, i, F.lit(q)))))


def qgram_jaccard(a: Column, b: Column, q: int = 3) -> Column:
    x, y = qgrams(a, q), qgrams(b, q)
    return F.size(F.array_intersect(x, y)) / F.size(F.array_union(x, y))


def qgram_dice(a: Column, b: Column, q: int = 3) -> Column:
    x, y = qgrams(a, q), qgrams(b, q)
    return 2 * F.size(F.array_intersect(x, y)) / (F.size(x) + F.size(y))


def exact(a: Column, b: Column) -> Column:
    return (a == b).cast("double")


def closeness(a: Column, b: Column, scale: float) -> Column:
    """1 at equal numbers, falling to 0 at a difference of ``scale``."""
    return F.greatest(F.lit(0.0), 1 - F.abs(a - b).cast("double") / scale)


def cosine(a: Column, b: Column) -> Column:
    dot = F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
    norm = lambda v: F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))
    return dot / (norm(a) * norm(b))
