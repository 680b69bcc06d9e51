"""Soft TF/IDF as joins: tokens that are close count as matches.

Weights are (1 + ln tf) * ln(1 + N / df) over all values of the property, scaled to unit length.
Close tokens are found once on the vocabulary; pairs of values then meet through an inverted
index on close tokens, of which a bound on the similarity leaves each value's heaviest tokens only, so
that frequent tokens bring nobody together.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import ceil, sqrt

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from linkcluster.functions.close_labels import close_labels
from linkcluster.functions.near_pairs import at_most, letter_marks
from linkcluster.functions.strings import jaro_winkler_batch
from linkcluster.plans.iterate import written

SLACK = 1e-9
#: Rows of the right side of a tile of ``all_pairs``, and hits that one step of it holds.
TILE_ROWS, HITS = 8_000, 500_000
#: Pairs that one step of ``of`` holds.
STEP = 20_000


def token_weights(values: DataFrame) -> DataFrame:
    """(vid, token, w) from (vid, value): unit-length weights."""
    toks = values.select("vid", F.explode(F.filter(F.split(F.lower("value"), r"[^\p{L}\p{N}]+"), lambda t: t != "")).alias("token")).groupBy("vid", "token").agg(F.count(F.lit(1)).alias("tf"))
    n = values.where("value is not null").agg(F.count(F.lit(1)).alias("n_values"))
    df = toks.groupBy("token").agg(F.count(F.lit(1)).alias("df"))
    raw = toks.join(df, "token").crossJoin(F.broadcast(n)).withColumn("raw", (1 + F.log("tf")) * F.log(1 + F.col("n_values") / F.col("df")))
    norm = raw.groupBy("vid").agg(F.sqrt(F.sum(F.col("raw") * F.col("raw"))).alias("norm"))
    return raw.join(norm, "vid").select("vid", "token", (F.col("raw") / F.col("norm")).alias("w"))


def close_tokens(vocabulary: DataFrame, theta: float) -> DataFrame:
    """(ta, tb, inner) of all token pairs with inner similarity of at least ``theta``, equal ones too."""
    v = written(vocabulary.select("token").distinct())
    found = close_labels(v.withColumnRenamed("token", "label"), theta).where(F.col("sim") >= theta).select(F.col("x").alias("ta"), F.col("y").alias("tb"), F.col("sim").alias("inner"))
    both = found.unionByName(found.select(F.col("tb").alias("ta"), F.col("ta").alias("tb"), "inner"))
    return both.unionByName(v.select(F.col("token").alias("ta"), F.col("token").alias("tb"), F.lit(1.0).alias("inner")))


def _sums(pair: np.ndarray, token: np.ndarray, inner: np.ndarray, part: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(pair, sum) with each token counted once, by its closest partner and of equally close ones the greatest part."""
    order = np.lexsort((token, pair))
    p, t = pair[order], token[order]
    last = np.append((p[1:] != p[:-1]) | (t[1:] != t[:-1]), True)
    if not last.all():
        order = np.lexsort((part, inner, token, pair))
        order = order[last]
        p = pair[order]
    else:
        order = order[last]
    first = np.flatnonzero(np.append(True, p[1:] != p[:-1]))
    return p[first], np.add.reduceat(part[order], first)


def _packed(side: DataFrame, name: str, parts: int) -> DataFrame:
    """One row for each of the parts that the values ``v`` are dealt out to: its rows as the array ``name``."""
    dealt = side.withColumn("part", F.pmod(F.xxhash64("v"), F.lit(parts))).repartition(parts, "part")
    return written(dealt.groupBy("part").agg(F.collect_list(F.struct(*side.columns)).alias(name)).select(name))


def _tiles(batches):
    for batch in batches:
        for i in range(batch.num_rows):
            yield from _scored(*(batch.column(k).slice(i, 1).flatten() for k in range(2)))


def _scored(left: pa.StructArray, right: pa.StructArray):
    """Batches of the pairs of a tile: rows of the left side (v, token t, close token u, w, inner) against those of the right (v, t, w)."""
    both = {c: pa.concat_arrays([left.field(c), right.field(c)]) for c in ("v", "t", "w")}
    names = pc.unique(both["v"])
    names = names.take(pc.sort_indices(names))
    v = pc.index_in(both["v"], names).to_numpy().astype(np.int64)
    words = pc.unique(pa.concat_arrays([both["t"], left.field("u")]))
    own, near = (pc.index_in(c, words).to_numpy().astype(np.int64) for c in (both["t"], pa.concat_arrays([left.field("u"), right.field("t")])))
    w, inner = both["w"].to_numpy(), left.field("inner").to_numpy()
    a, b = np.arange(len(left)), len(left) + np.arange(len(right))
    a, b = a[np.argsort(v[a], kind="stable")], b[np.argsort(near[b], kind="stable")]
    start, end = (np.searchsorted(near[b], near[a], side=x) for x in ("left", "right"))
    # steps end where a value of the left side ends, so each pair is whole
    ends = np.flatnonzero(np.append(v[a][1:] != v[a][:-1], True)) + 1 if len(a) else np.zeros(0, np.int64)
    met = np.cumsum(end - start)
    s = 0
    while s < len(a):
        k = np.searchsorted(met[ends - 1], (met[s - 1] if s else 0) + HITS, side="right")
        e = max(int(ends[max(0, k - 1)]), int(ends[np.searchsorted(ends, s, side="right")]))
        size = end[s:e] - start[s:e]
        stop = np.cumsum(size)
        x = np.repeat(a[s:e], size)
        y = b[np.arange(stop[-1]) + np.repeat(start[s:e] - (stop - size), size)]
        s = e
        ok = v[x] < v[y]
        x, y = x[ok], y[ok]
        if len(x):
            pair, part = v[x] * len(names) + v[y], w[x] * w[y] * inner[x]
            (p, one), (_, other) = _sums(pair, own[x], inner[x], part), _sums(pair, own[y], inner[x], part)
            va, vb = (names.take(pa.array(x)) for x in (p // len(names), p % len(names)))
            yield pa.RecordBatch.from_arrays([va, vb, pa.array(np.minimum(1.0, np.maximum(one, other)))], ["va", "vb", "sim"])


def _measured(theta: float):
    """Batches of pairs (va, vb) with the tokens and weights of both (ts, ws, us, xs) to the similarities of those with a close token."""

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, STEP):
                c = {n: batch.column(n).slice(at, STEP) for n in batch.schema.names}
                own, near = c["ts"].flatten(), c["us"].flatten()
                words = pc.unique(pa.concat_arrays([own, near]))
                own, near = (pc.index_in(x, words).to_numpy().astype(np.int64) for x in (own, near))
                w, x = c["ws"].flatten().to_numpy(), c["xs"].flatten().to_numpy()
                n, m = (pc.list_value_length(c[k]).to_numpy().astype(np.int64) for k in ("ts", "us"))
                # every token of a pair's left value with each of its right one
                first = np.cumsum(m) - m
                pair = np.repeat(np.arange(len(n)), n)
                i = np.repeat(np.arange(len(own)), m[pair])
                size = m[pair]
                j = np.arange(size.sum()) + np.repeat(first[pair] - (np.cumsum(size) - size), size)
                pair = pair[i]
                names = words.to_pylist()
                marks = letter_marks(names)
                key, back = np.unique(np.minimum(own[i], near[j]) * len(names) + np.maximum(own[i], near[j]), return_inverse=True)
                p, q = np.divmod(key, len(names))
                sim = np.where(p == q, 1.0, 0.0)
                look = np.flatnonzero((p != q) & (at_most(marks, marks, p, q) >= theta - SLACK))
                if len(look):
                    sim[look] = jaro_winkler_batch([min(names[a], names[b]) for a, b in zip(p[look], q[look])], [max(names[a], names[b]) for a, b in zip(p[look], q[look])])
                inner = sim[back]
                ok = inner >= theta
                if not ok.any():
                    continue
                i, j, pair, inner = i[ok], j[ok], pair[ok], inner[ok]
                part = w[i] * x[j] * inner
                (k, one), (_, other) = _sums(pair, own[i], inner, part), _sums(pair, near[j], inner, part)
                k = pa.array(k)
                yield pa.RecordBatch.from_arrays([c["va"].take(k), c["vb"].take(k), pa.array(np.minimum(1.0, np.maximum(one, other)))], ["va", "vb", "sim"])

    return run


@dataclass(frozen=True)
class SoftIndex:
    """Token weights of values (vid, token, w) and the close tokens (ta, tb, inner), both materialised."""

    weights: DataFrame
    close: DataFrame
    theta: float = 0.9

    def _side(self, end: str) -> DataFrame:
        return self.weights.select(F.col("vid").alias(f"v{end}"), F.col("token").alias(f"t{end}"), F.col("w").alias(f"w{end}"))

    def score(self, hits: DataFrame) -> DataFrame:
        """(va, vb, sim) from (va, vb, ta, tb, wa, wb, inner): each token counts with its closest one, in the better direction's sum."""
        hits = hits.withColumn("part", F.col("wa") * F.col("wb") * F.col("inner"))
        one = lambda t: hits.groupBy("va", "vb", t).agg(F.max(F.struct("inner", "part")).alias("b")).groupBy("va", "vb").agg(F.sum("b.part").alias("s"))
        both = one("ta").join(one("tb").withColumnRenamed("s", "t"), ["va", "vb"])
        return both.select("va", "vb", F.least(F.lit(1.0), F.greatest("s", "t")).alias("sim"))

    def all_pairs(self) -> DataFrame:
        """All value pairs with a close token, va < vb: both sides in packed parts, of which each two are scored whole where they meet.

        A part is one row, and a Cartesian product brings parts together by reading them again: nothing is copied for a shuffle.
        """
        tasks = int(self.weights.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        sides = max(ceil(sqrt(2 * tasks)), ceil(self.weights.count() / TILE_ROWS))
        whole = self.weights.where("vid is not null")
        a = whole.withColumnRenamed("token", "ta").join(self.close.select("ta", "tb", "inner"), "ta").select(F.col("vid").alias("v"), F.col("ta").alias("t"), F.col("tb").alias("u"), "w", "inner")
        b = whole.select(F.col("vid").alias("v"), F.col("token").alias("t"), "w")
        left, right = _packed(a, "a", sides), _packed(b, "b", sides)
        kind = dict(self.weights.dtypes)["vid"]
        return left.hint("shuffle_replicate_nl").crossJoin(right).mapInArrow(_tiles, f"va {kind}, vb {kind}, sim double")

    def of(self, pairs: DataFrame) -> DataFrame:
        """The similarities of the given pairs (va, vb), va < vb; pairs without a close token are left out.

        A pair meets the tokens of its values and measures them, so that close tokens are not joined to it.
        """
        whole = self.weights.groupBy("vid").agg(F.collect_list(F.struct("token", "w")).alias("held"))
        side = lambda v, t, w: whole.select(F.col("vid").alias(v), F.col("held.token").alias(t), F.col("held.w").alias(w))
        met = pairs.select("va", "vb").join(side("va", "ts", "ws"), "va").join(side("vb", "us", "xs"), "vb")
        kind = dict(self.weights.dtypes)["vid"]
        return met.mapInArrow(_measured(self.theta), f"va {kind}, vb {kind}, sim double")

    def leads(self, bound: float) -> DataFrame:
        """(vid, token): of each value the tokens of which a pair of at least that similarity needs a close partner of one.

        A token adds at most its weight times the greatest weight that a token close to it has in any value.  Summed up from
        the least, the tokens that stay below the bound together need not be looked up, so frequent ones bring nobody together.
        """
        heaviest = self.weights.groupBy(F.col("token").alias("tb")).agg(F.max("w").alias("m"))
        most = self.close.join(heaviest, "tb").groupBy(F.col("ta").alias("token")).agg(F.max(F.col("inner") * F.col("m")).alias("m"))
        adds = self.weights.join(most, "token").select("vid", "token", (F.col("w") * F.col("m")).alias("u"))
        upto = F.sum("u").over(W.partitionBy("vid").orderBy("u", "token").rowsBetween(W.unboundedPreceding, W.currentRow))
        return adds.withColumn("upto", upto).where(F.col("upto") >= bound - SLACK).select("vid", "token")

    def led(self, bound: float) -> DataFrame:
        """(vid, token, lead): the tokens of all values and whether they lead them (see ``leads``)."""
        return written(self.weights.select("vid", "token").join(self.leads(bound).withColumn("lead", F.lit(True)), ["vid", "token"], "left").fillna(False, ["lead"]))

    def meetings(self, led: DataFrame) -> int:
        """How often a token that leads a value meets a close one in any value."""
        n = led.groupBy("token").agg(F.count(F.lit(1)).alias("c"), F.count_if("lead").alias("l"))
        met = self.close.join(n.select(F.col("token").alias("ta"), "l"), "ta").join(n.select(F.col("token").alias("tb"), "c"), "tb")
        return met.agg(F.coalesce(F.sum(F.col("l") * F.col("c")), F.lit(0))).first()[0]

    def reaching(self, bound: float, led: DataFrame | None = None, turn: int = 0, turns: int = 1) -> DataFrame:
        """All pairs of at least that similarity; with several turns those whose lesser value falls to this turn.

        Such a pair shares a close token that leads one of its values (see ``leads``).
        """
        if bound <= 0:
            return self.all_pairs()
        led = self.led(bound) if led is None else led
        mine = led.where(F.pmod(F.xxhash64("vid", F.lit(29)), F.lit(turns)) == turn).select(F.col("vid").alias("va"), F.col("token").alias("ta"), "lead")
        other = led.select(F.col("vid").alias("vb"), F.col("token").alias("tb"), F.col("lead").alias("leads"))
        close = self.close.select("ta", "tb")
        # two tokens of which none leads do not meet at all: frequent ones would bring everybody together
        met = mine.where("lead").join(close, "ta").join(other, "tb").unionByName(mine.where("not lead").join(close, "ta").join(other.where("leads"), "tb"))
        return self.of(met.where("va < vb").select("va", "vb").distinct()).where(F.col("sim") >= bound - SLACK)


def index(values: DataFrame, theta: float = 0.9) -> SoftIndex:
    w = written(token_weights(values))
    return SoftIndex(w, close_tokens(w, theta), theta)


def soft_tfidf(values: DataFrame, theta: float = 0.9, bound: float = 0.0) -> DataFrame:
    """(va, vb, sim) of the value pairs (vid, value) of at least ``bound``, va < vb."""
    return index(values, theta).reaching(bound)
