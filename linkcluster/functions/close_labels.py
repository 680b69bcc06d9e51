"""All pairs of close labels: a similarity join on Jaro-Winkler without loss.

A bound of t on Jaro-Winkler means Jaro >= (t - 0.1 p) / (1 - 0.1 p) with p common first letters, hence a length ratio of
at least 3 Jaro - 2 and a least number of common letters, for which letter subsets are keys.
"""

from __future__ import annotations

import functools
import itertools
import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from linkcluster.functions.strings import jaro_winkler
from linkcluster.plans.iterate import release, written

SLACK = 1e-9


def least_jaro(bound: float) -> float:
    """Least Jaro similarity of labels whose Jaro-Winkler similarity is at least ``bound``."""
    return max((bound - 0.4) / 0.6, min(0.7, bound))


def close_jaro(bound: float) -> float:
    """The same with at most three equal first letters."""
    return max((bound - 0.3) / 0.7, min(0.7, bound))


#: Letter subsets a label may have for one partner length before the weaker letter filter takes over.
SUBSETS = 400
#: Labels, those of the rarest lengths, that are compared with all labels and have no keys.
RARE = 200


def _overlap(a: int, b: int, jaro: float) -> int:
    """Least number of common letters of labels of these lengths with that Jaro similarity."""
    return max(1, math.ceil((3 * jaro - 1) * a * b / (a + b) - SLACK))


def _covered(a: int, b: int, jaro: float) -> bool:
    m = _overlap(a, b, jaro)
    return m > min(a, b) or max(math.comb(a, m), math.comb(b, m)) <= SUBSETS


def _swaps_from(a: int, b: int, jaro: float) -> int:
    """Least number of matched letters that leaves that Jaro similarity to labels of these lengths in spite of a transposition."""
    return next((m for m in range(1, min(a, b) + 1) if m / a + m / b + (m - 1) / m >= 3 * jaro - SLACK), min(a, b) + 1)


@functools.cache
def _kinds(n: int, bound: float) -> list[tuple[int, int, int | None, int | None]]:
    """(p, other, letters in order, sorted letters): the kinds of keys of a label of n letters.

    A kind of more equal first letters is left out where one of fewer, which these letters have too, asks for no more letters."""
    kinds, least = [], close_jaro(bound)
    ordered, swapped = {}, {}
    for p in range(min(4, n) + 1):
        jaro = max((bound - 0.1 * p) / (1 - 0.1 * p), min(0.7, bound))
        c = 3 * jaro - 2
        for other in range(max(1, p, math.ceil(n * c - SLACK)), (math.floor(n / c + SLACK) if c > 0 else 4 * n) + 1):
            m, swaps = _overlap(n, other, jaro), _swaps_from(n, other, jaro)
            if m > min(n, other) or not _covered(n, other, least):
                continue
            both = max(m, swaps)
            s = both if swaps <= min(n, other) and swapped.get(other, n + 1) > both else None
            o = m if m < swaps and min(ordered.get(other, n + 1), swapped.get(other, n + 1)) > m else None
            if s is not None:
                swapped[other] = s
            if o is not None:
                ordered[other] = o
            if s is not None or o is not None:
                kinds.append((p, other, o, s))
    return kinds


def subset_keys(label: str, bound: float, lengths: frozenset[int] | None = None) -> list[str]:
    """Keys such that two labels of at least that Jaro-Winkler similarity share one, where their lengths are covered.

    For each number of equal first letters and each partner length (of ``lengths``, if given), the Jaro similarity that they need leaves a least overlap.
    Equal first letters match each other, so the key is these and a part of the rest: letters in their order where a
    transposition would cost too much, and sorted ones for overlaps that bear it.  The first sign tells whether the label
    is the shorter (s) or longer (l) one of such a pair, or as long as its partner (e)."""
    n, keys = len(label), set()
    for p, other, o, s in _kinds(n, bound):
        if lengths is not None and other not in lengths:
            continue
        first, rest = label[:p], label[p:]
        head = f"{'e' if n == other else 's' if n < other else 'l'}{p}{first}:{min(n, other)}:{max(n, other)}:"
        if o is not None:
            keys |= {f"{head}o{''.join(x)}" for x in itertools.combinations(rest, max(0, o - p))}
        if s is not None:
            keys |= {f"{head}s{''.join(x)}" for x in itertools.combinations(sorted(rest), max(0, s - p))}
    return sorted(keys)


def _all_covered(n: int, bound: float) -> bool:
    """Whether keys serve every partner that a label of n letters and four equal first letters may have."""
    c, least = 3 * least_jaro(bound) - 2, close_jaro(bound)
    return c > 0 and all(_covered(n, other, least) for other in range(max(1, math.ceil(n * c - SLACK)), math.floor(n / c + SLACK) + 1))


def _letter_pairs(names: DataFrame, jaro: float, long: int) -> DataFrame:
    """Pairs with a label of ``long`` letters or more, by prefix filtering on (letter, occurrence)."""
    ratio = max(0.0, 3 * jaro - 2)
    letters = names.select("label", "n", F.posexplode(F.array_sort(F.split("label", ""))).alias("p", "c"))
    g = letters.withColumn("o", F.col("p") - F.expr("min(p) over (partition by label, c)")).select("label", "n", F.concat("c", F.col("o").cast("string")).alias("g"))
    freq = g.groupBy("g").agg(F.count(F.lit(1)).alias("f"))
    ranked = g.join(freq, "g").withColumn("r", F.expr("row_number() over (partition by label order by f, g)"))
    # m / n + m / n' >= 3 jaro - 1 and n' <= n / ratio: the least overlap a partner of a label of length n has
    share = (3 * jaro - 1) / (1 + max(1.0, 1 / max(ratio, 0.1)))
    need = F.ceil(F.col("n") * share - SLACK)
    probe = ranked.where(F.col("r") <= F.col("n") - need + 1)
    a, b = probe.where(F.col("n") >= long).select("g", F.col("label").alias("x"), F.col("n").alias("nx")), probe.select("g", F.col("label").alias("y"), F.col("n").alias("ny"))
    near = a.join(b, "g").where((F.col("x") != F.col("y")) & (F.least("nx", "ny") >= ratio * F.greatest("nx", "ny") - SLACK))
    return near.select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y"))


def _with_few(few: list[str], bound: float):
    """Batches of labels to their pairs (x, y) with one of a few, x < y, whose letters allow that similarity."""

    def run(batches):
        from linkcluster.functions.near_pairs import at_most, letter_marks

        marks, each = letter_marks(few), np.array(few, dtype=object)
        for batch in batches:
            label = batch.column("label").to_pylist()
            own, label = letter_marks(label), np.array(label, dtype=object)
            for j in range(len(few)):
                i = np.arange(len(label))
                i = i[(at_most(own, marks, i, np.full(len(i), j)) >= bound - SLACK) & (label != each[j])]
                x = [min(a, few[j]) for a in label[i]]
                y = [max(a, few[j]) for a in label[i]]
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.string()), pa.array(y, pa.string())], ["x", "y"])

    return run


def close_labels(labels: DataFrame, bound: float) -> DataFrame:
    """(x, y, sim) of the distinct labels (column ``label``) of at least that similarity, x < y.

    Exact keys: the shorter the common prefix, the smaller its bonus, so the higher must the Jaro part be, and pairs
    share that prefix and a large part of the other letters.
    """
    jaro = close_jaro(bound)
    names = written(labels.select("label").distinct().withColumn("n", F.char_length("label")).where("n > 0"))
    ratio = max(0.0, 3 * least_jaro(bound) - 2)

    sizes = {r.n: r.c for r in names.groupBy("n").agg(F.count(F.lit(1)).alias("c")).collect()}
    # labels of the rarest lengths are few enough to be compared with all; the others need keys among themselves alone
    rare, held = set(), 0
    for n, c in sorted(sizes.items(), key=lambda x: (x[1], x[0])):
        held += c
        if held > RARE:
            break
        rare.add(n)
    lengths = frozenset(sizes) - rare

    @F.pandas_udf(T.ArrayType(T.StringType()))
    def keys_of(label: pd.Series) -> pd.Series:
        return label.map(lambda x: subset_keys(x, bound, lengths))

    most = names
    names = names.where(F.col("n").isin(sorted(lengths)))
    # four equal first letters are a key of their own only where the other keys do not serve all lengths
    start = names.where(F.col("n").isin([n for n in sorted(lengths) if n >= 4 and not _all_covered(n, bound)])).select("label", "n", F.concat(F.lit("e="), F.substring("label", 1, 4)).alias("key"))
    # the written labels are a small file, their keys are the work
    tasks = int(names.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    keyed = start.unionByName(names.repartition(tasks, "label").select("label", "n", F.explode(keys_of("label")).alias("key")))
    keyed = written(keyed.select("label", "n", F.substring("key", 1, 1).alias("role"), F.expr("substring(key, 2)").alias("key")))
    part = lambda role, name, n: keyed.where(F.col("role") == role).select("key", F.col("label").alias(name), F.col("n").alias(n))
    # labels of one length meet each other; of two lengths, only shorter and longer ones meet
    even = part("e", "x", "nx").join(part("e", "y", "ny"), "key").where((F.col("x") < F.col("y")) & (F.least("nx", "ny") >= ratio * F.greatest("nx", "ny") - SLACK)).select("x", "y")
    odd = part("s", "x", "nx").join(part("l", "y", "ny"), "key").select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y"))
    near = even.unionByName(odd)
    longest = max(lengths, default=0)
    long = next((n for n in range(1, longest + 1) if any(not _covered(n, m, jaro) for m in range(1, n + 1) if m >= (3 * jaro - 2) * n)), None)
    if long is not None:
        near = near.unionByName(_letter_pairs(names, jaro, long))
    if rare:
        few = [r.label for r in most.where(F.col("n").isin(sorted(rare))).select("label").collect()]
        near = near.unionByName(most.repartition(tasks, "label").mapInArrow(_with_few(few, bound), "x string, y string"))
    found = written(near.distinct().withColumn("sim", jaro_winkler(F.col("x"), F.col("y"))).where(F.col("sim") >= bound - SLACK))
    release(keyed, most)
    return found
