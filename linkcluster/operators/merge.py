"""Cluster merge: score compatible representatives of a block, then join the best pairs until none is left.

Triplets keep the total order of their creation (similarity on its grid, then the original
left and right ids); rewriting to survivors never changes it and of duplicates the better
stays.  So the strategies end in the same clusters:

* ``block_best``  each round takes the best triplet of every block;
* ``dominant``    each round takes every triplet that is the best one at both of its ends, whatever its block,
  which needs far fewer rounds;
* ``auto``        ``dominant`` rounds until at most ``FINISH_ROWS`` triplets are left, whose loop one task then ends;
* ``grouped``     one block's whole loop runs in one task (blocks up to ``cap`` triplets; others by ``dominant``).
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkcluster.functions import near_pairs
from linkcluster.functions.compose import PairMeasure
from linkcluster.functions.normalize import grid
from linkcluster.operators import blocking, representative
from linkcluster.operators.components import connected
from linkcluster.operators.preprocess import compatible
from linkcluster.plans.iterate import release, written

#: Triplets that one task may take to the end of the loop, some 100 MB as Python lists.
FINISH_ROWS = 200_000
BOUND_SLACK = 1e-6
#: Representatives for each task of ``likely_pairs``, and pairs that one step of it holds.
TASK_ROWS, PAIRS = 50_000, 500_000


def _rename(d: DataFrame, prefix: str, shared: tuple[str, ...]) -> DataFrame:
    return d.select(*[F.col(c) if c in shared else F.col(c).alias(f"{prefix}{c}") for c in d.columns])


def candidates(blocked: DataFrame, measure: PairMeasure, theta: float, k: int, untyped: str = "wildcard", max_block: int = 20_000, pairs: DataFrame | None = None) -> DataFrame:
    """Work set (block, l, r, g, ol, orr, sl, sr, nl, nr) of compatible pairs with similarity of at least ``theta``.

    ``pairs`` (l_cid, r_cid) may name the pairs to look at, each once; else all pairs of a block are.
    """
    cols = list(dict.fromkeys(("block", "cid", "types", "sources", "n", *measure.columns)))
    if pairs is None:
        left, right = blocking.tile_pairs(blocked.select(*cols), max_block)
        shared = ("block", "i", "j")
        p = _rename(left, "l_", shared).join(_rename(right, "r_", shared), list(shared))
        p = p.where((F.col("i") != F.col("j")) | (F.col("l_cid") < F.col("r_cid"))).where("l_cid <> r_cid")
    else:
        p = pairs.join(_rename(blocked.select(*cols), "l_", ("block",)), "l_cid").join(_rename(blocked.select(*cols).drop("block"), "r_", ()), "r_cid")
    p = p.where(compatible(F.col("l_types"), F.col("r_types"), untyped))
    p = p.where(~F.arrays_overlap("l_sources", "r_sources")).where((F.size("l_sources") + F.size("r_sources") <= k) & (F.col("l_n") + F.col("r_n") <= k))
    p = measure.apply(p).where(F.col("sim") >= theta)
    swap = F.col("l_cid") > F.col("r_cid")
    side = lambda c: (F.when(swap, F.col(f"r_{c}")).otherwise(F.col(f"l_{c}")), F.when(swap, F.col(f"l_{c}")).otherwise(F.col(f"r_{c}")))
    (l, r), (sl, sr), (nl, nr) = side("cid"), side("sources"), side("n")
    out = p.select("block", l.alias("l"), r.alias("r"), grid(F.col("sim")).alias("g"), sl.alias("sl"), sr.alias("sr"), nl.alias("nl"), nr.alias("nr"))
    out = out.withColumn("ol", F.col("l")).withColumn("orr", F.col("r"))
    return _best_of_duplicates(out)


def unblocked_pairs(reps: DataFrame, theta: float, k: int) -> DataFrame:
    """(l_cid, r_cid): without blocks, all pairs that ``LABEL_GEO`` may bring to ``theta`` and that have room for each other.

    With both places known the measure is the mean of the label's and the place's similarity, else the label's alone.
    """
    v = written(reps.where(F.col("n") < k).select(F.col("cid").alias("id"), "label", "lat", "lon"))
    bare = v.where("lat is null")
    parts = max(1, v.count() // near_pairs.TILE_POINTS)
    found = near_pairs.near_pairs(v, theta).unionByName(near_pairs.label_pairs(bare, v, theta, parts))
    return written(found.select(F.col("l_id").alias("l_cid"), F.col("r_id").alias("r_cid")))


def _likely(weights: tuple[tuple[str, float], ...], theta: float, k: int):
    def run(t: pa.Table) -> pa.Table:
        cid, n, probe = t["cid"].to_numpy(), t["n"].to_numpy(), t["probe"].to_numpy(zero_copy_only=False)
        lists = t["sources"].to_pylist()
        names = {s: x for x, s in enumerate(dict.fromkeys(s for few in lists for s in few))}
        # only as a filter, so that more sources than bits are left to the exact condition
        bits = np.array([sum(1 << names[s] for s in set(few)) if len(names) <= 63 else 0 for few in lists], dtype=np.int64)
        marks, there = {}, {}
        for c, _ in weights:
            there[c] = t[c].is_valid().to_numpy()
            marks[c] = near_pairs.letter_marks(t[c].fill_null("").to_pylist())
        # the tiles of the blocks that came here, one after another
        at, to = t["i"].to_numpy().astype(np.int64), t["j"].to_numpy().astype(np.int64)
        key = (t["block"].combine_chunks().dictionary_encode().indices.to_numpy().astype(np.int64) * (at.max() + 1) + at) * (to.max() + 1) + to
        left, right = np.flatnonzero(probe), np.flatnonzero(~probe)
        right = right[np.argsort(key[right], kind="stable")]
        start, end = (np.searchsorted(key[right], key[left], side=x) for x in ("left", "right"))
        met = np.cumsum(end - start)
        s, out = 0, []
        while s < len(left):
            e = max(s + 1, int(np.searchsorted(met, (met[s - 1] if s else 0) + PAIRS, side="right")))
            size = end[s:e] - start[s:e]
            stop = np.cumsum(size)
            i = np.repeat(left[s:e], size)
            j = right[np.arange(stop[-1]) + np.repeat(start[s:e] - (stop - size), size)]
            s = e
            ok = (n[i] + n[j] <= k) & (bits[i] & bits[j] == 0) & np.where(at[i] == to[i], cid[i] < cid[j], cid[i] != cid[j])
            i, j = i[ok], j[ok]
            weight = sum(w * (there[c][i] & there[c][j]) for c, w in weights)
            # each property counts in full until its own bound is known
            most = weight.copy()
            for c, w in weights:
                both = there[c][i] & there[c][j]
                most = most + np.where(both, w * (np.minimum(1.0, near_pairs.at_most(marks[c], marks[c], i, j)) - 1), 0.0)
                keep = most >= theta * weight - BOUND_SLACK
                i, j, weight, most = i[keep], j[keep], weight[keep], most[keep]
            out.append((cid[i], cid[j]))
        l, r = (np.concatenate(x) for x in zip(*out)) if out else (np.zeros(0, np.int64), np.zeros(0, np.int64))
        return pa.table({"l_cid": pa.array(l, pa.int64()), "r_cid": pa.array(r, pa.int64())})

    return run


def likely_pairs(blocked: DataFrame, measure: PairMeasure, theta: float, k: int, max_block: int = 20_000) -> DataFrame:
    """(l_cid, r_cid): of each block, for representatives of one block each, all pairs that have room for each other and whose
    common letters allow a weighted mean of Jaro-Winkler similarities of ``theta``.  The bound loses no pair."""
    left, right = blocking.tile_pairs(blocked.select("block", "cid", "n", "sources", *[c for c, _ in measure.weights]), max_block)
    both = left.withColumn("probe", F.lit(True)).unionByName(right.withColumn("probe", F.lit(False)))
    tasks = max(int(blocked.sparkSession.conf.get("spark.sql.shuffle.partitions")), blocked.count() // TASK_ROWS)
    both = both.withColumn("task", F.pmod(F.xxhash64("block", "i", "j"), F.lit(tasks)))
    return written(both.groupBy("task").applyInArrow(_likely(measure.weights, theta, k), "l_cid bigint, r_cid bigint"))


def _rank():
    """Greater is better: similarity, then the smaller original ids."""
    return F.struct(F.col("g"), (-F.col("ol")).alias("nol"), (-F.col("orr")).alias("nor"))


def _best_of_duplicates(work: DataFrame) -> DataFrame:
    """One triplet for each pair of clusters (several keys or rewriting may repeat it)."""
    b = work.groupBy("l", "r").agg(F.max(F.struct(_rank().alias("k"), "block", "sl", "sr", "nl", "nr")).alias("b"))
    return b.select("b.block", "l", "r", F.col("b.k.g").alias("g"), "b.sl", "b.sr", "b.nl", "b.nr", (-F.col("b.k.nol")).alias("ol"), (-F.col("b.k.nor")).alias("orr"))


def _picks(work: DataFrame, strategy: str) -> DataFrame:
    row = F.struct(_rank().alias("k"), "l", "r", "sl", "sr", "nl", "nr")
    cols = ["p.l", "p.r", F.array_sort(F.array_union("p.sl", "p.sr")).alias("s"), (F.col("p.nl") + F.col("p.nr")).alias("n")]
    if strategy == "block_best":
        return work.groupBy("block").agg(F.max(row).alias("p")).select(*cols)
    ends = work.select(F.col("l").alias("v"), row.alias("p")).unionByName(work.select(F.col("r").alias("v"), row.alias("p")))
    best = ends.groupBy("v").agg(F.max("p").alias("p"))
    twice = best.groupBy(F.col("p.l").alias("l"), F.col("p.r").alias("r")).agg(F.count(F.lit(1)).alias("c"), F.first("p").alias("p"))
    return twice.where("c = 2").select(*cols)


def _rewrite(work: DataFrame, picks: DataFrame, k: int) -> DataFrame:
    """Triplets with merged clusters replaced by their survivor and its new sources and size."""
    moves = picks.select(F.col("l").alias("old"), F.col("l").alias("new"), F.col("s").alias("ns"), F.col("n").alias("nn")).unionByName(picks.select(F.col("r").alias("old"), F.col("l").alias("new"), F.col("s").alias("ns"), F.col("n").alias("nn")))
    d = work
    for end, s, n in (("l", "sl", "nl"), ("r", "sr", "nr")):
        m = moves.withColumnRenamed("old", end)
        d = d.join(m, end, "left").withColumn(s, F.coalesce("ns", s)).withColumn(n, F.coalesce("nn", n)).withColumn(end, F.coalesce("new", end)).drop("new", "ns", "nn")
    d = d.where("l <> r")
    swap = F.col("l") > F.col("r")
    pick = lambda a, b: F.when(swap, F.col(b)).otherwise(F.col(a))
    d = d.select("block", pick("l", "r").alias("l"), pick("r", "l").alias("r"), "g", pick("sl", "sr").alias("sl"), pick("sr", "sl").alias("sr"), pick("nl", "nr").alias("nl"), pick("nr", "nl").alias("nr"), "ol", "orr")
    d = d.where(~F.arrays_overlap("sl", "sr")).where((F.size("sl") + F.size("sr") <= k) & (F.col("nl") + F.col("nr") <= k))
    return _best_of_duplicates(d)


def loop(work: DataFrame, k: int, strategy: str = "dominant", max_rounds: int | None = None, finish_rows: int = FINISH_ROWS) -> tuple[DataFrame, list[dict]]:
    """(loser, winner) moves of all rounds and a log."""
    spark = work.sparkSession
    moves = [spark.createDataFrame([], "loser bigint, winner bigint")]
    log: list[dict] = []
    work = written(work)
    left = work.count()
    while left and (max_rounds is None or len(log) < max_rounds):
        if strategy == "auto" and max_rounds is None and left <= finish_rows:
            rest = written(_finished(work, k))
            moves.append(rest)
            log.append({"round": len(log) + 1, "work": left, "merged": rest.count()})
            break
        picks = written(_picks(work, strategy))
        n = picks.count()
        moves.append(picks.select(F.col("r").alias("loser"), F.col("l").alias("winner")))
        log.append({"round": len(log) + 1, "work": left, "merged": n})
        done, work = work, written(_rewrite(work, picks, k))
        release(done)
        left = work.count()
    # every round's picks are already cut, so their union has a short plan
    return reduce(DataFrame.unionByName, moves), log


def merge_block(l: list, r: list, g: list, sl: list, sr: list, nl: list, nr: list, ol: list, orr: list, k: int) -> list[tuple[int, int]]:
    """The whole loop over triplets of current clusters, in the order of their creation; returns (loser, winner) moves."""
    at: dict[int, int] = {}
    sources: dict[int, frozenset] = {}
    size: dict[int, int] = {}
    for a, b, x, y, p, q in zip(l, r, sl, sr, nl, nr):
        sources[a], sources[b], size[a], size[b] = frozenset(x), frozenset(y), p, q

    def root(x: int) -> int:
        while at.get(x, x) != x:
            x = at[x]
        return x

    out = []
    for *_, a, b in sorted(zip([-v for v in g], ol, orr, l, r)):
        a, b = root(a), root(b)
        if a == b or sources[a] & sources[b] or len(sources[a] | sources[b]) > k or size[a] + size[b] > k:
            continue
        a, b = min(a, b), max(a, b)
        at[b] = a
        sources[a], size[a] = sources[a] | sources[b], size[a] + size[b]
        out.append((b, a))
    return out


def _merge_table(k: int):
    def run(t: pa.Table) -> pa.Table:
        got = merge_block(*[t[c].to_pylist() for c in ("l", "r", "g", "sl", "sr", "nl", "nr", "ol", "orr")], k)
        return pa.table({"loser": pa.array([x for x, _ in got], pa.int64()), "winner": pa.array([y for _, y in got], pa.int64())})

    return run


def _finished(work: DataFrame, k: int) -> DataFrame:
    """Moves of the whole work set from one task; its size has been counted."""
    return work.groupBy(F.lit(0).alias("all")).applyInArrow(_merge_table(k), "loser bigint, winner bigint")


def grouped_moves(work: DataFrame, k: int, cap: int = 200_000) -> tuple[DataFrame, list[dict]]:
    work = written(work)
    big = written(work.groupBy("block").agg(F.count(F.lit(1)).alias("t")).where(F.col("t") > cap).select("block"))

    moves = work.join(big, "block", "left_anti").groupBy("block").applyInArrow(_merge_table(k), "loser bigint, winner bigint")
    log: list[dict] = []
    if big.limit(1).count():
        more, log = loop(work.join(big, "block", "left_semi"), k, "dominant")
        moves = moves.unionByName(more)
    return written(moves), log


def rescored_loop(reps: DataFrame, entities: DataFrame, assign: DataFrame, block_of, measure: PairMeasure, theta: float, k: int, label_policy: str, geo_policy: str, max_rounds: int | None = None) -> tuple[DataFrame, list[dict]]:
    """Block-best merging that measures fused representatives anew in each round; (id, cid) and a log."""
    log: list[dict] = []
    while max_rounds is None or len(log) < max_rounds:
        work = candidates(block_of(reps), measure, theta, k)
        picks = written(_picks(work, "block_best"))
        n = picks.count()
        log.append({"round": len(log) + 1, "merged": n})
        if not n:
            break
        assign = written(_moved(assign, picks.select(F.col("r").alias("loser"), F.col("l").alias("winner"))))
        reps = written(representative.build(assign, entities, label_policy, geo_policy, tuple(c for c in measure.columns if c not in ("label", "lat", "lon"))))
    return assign, log


def _moved(assign: DataFrame, moves: DataFrame) -> DataFrame:
    links = moves.select(F.col("winner").alias("src"), F.col("loser").alias("dst"))
    ids = moves.select(F.col("loser").alias("id")).unionByName(moves.select(F.col("winner").alias("id"))).distinct()
    to = connected(ids, links, "sized").select(F.col("id").alias("cid"), F.col("cid").alias("new"))
    return assign.join(to, "cid", "left").select("id", F.coalesce("new", "cid").alias("cid"))


def run(assign: DataFrame, reps: DataFrame, work: DataFrame, k: int, strategy: str = "dominant", max_rounds: int | None = None) -> tuple[DataFrame, list[dict]]:
    """Final (id, cid) and the round log.  The loop moves only ids; entities are relabelled once at the end."""
    moves, log = grouped_moves(work, k) if strategy == "grouped" else loop(work, k, strategy, max_rounds)
    return _moved(assign, moves), log
