"""Near-duplicate documents by ProbMinHash signatures, banding and exact verification.

Words are runs of letters and digits in lower case.  A text's shingles are its windows of
five words (a shorter text is one shingle).  Sets decide below, so all weigh the same here.  Each
shingle is a Poisson process whose rate is its weight: its arrivals hit signature places
at random, the earliest arrival at a place wins it, and a shingle stops as soon as
its next arrival comes after every place of its text has been won earlier.  The share of
equal places estimates the probability Jaccard similarity, which for equal weights is that of the sets.

Signatures are banded; texts that agree on a band share a bucket.  Inside buckets:
1. equal texts are one node from the start (they are counted, never paired);
2. each bucket is linked as a star to its densest text, and the links are verified by the exact
   Jaccard similarity of shingle sets;
3. in buckets that still hold more than one component the rest is compared, so no link is lost:
   small ones as pairs of different components, large ones in tiles of fixed size in
   which only verified links leave the task.
Classes are the connected components; a class is named by its least document id.

Defined cases: a null text is a class of its own row's id; empty texts and texts without a
word are equal only to equal texts; null ids get the class of their text; repeated rows share a
class; an id may repeat and may be of any type that can be ordered; other columns may have any
type and any name; a very long text is worked on alone, whole; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkcluster.functions import text_arrays as _text
from linkcluster.llm._frame import HOT_ROWS, cut, join_hot, packed, small, unpacked
from linkcluster.operators.components import connected


@dataclass(frozen=True)
class NearConfig:
    words: int = 5
    similarity: float = 0.8
    bands: int = 25
    rows: int = 5
    seed: int = 11
    #: Buckets up to this size are paired; larger ones are compared in tiles of ``tile`` texts.
    pair_bucket: int = 24
    tile: int = 128
    #: Characters that are worked on at once; bounds a worker's memory.
    piece: int = 900_000


def shingle_sets(texts: list[str], n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(owner, shingle, count) of the distinct shingles of each text, sorted by owner."""
    codes, at = _text.code_points([t.lower() for t in texts])
    s, e = _text.runs(_text.letters_or_digits(codes))
    h = _text.span_hashes(codes, s, e)
    owner = np.searchsorted(at, s, side="right") - 1
    lead = np.searchsorted(owner, np.arange(len(texts) + 1))
    size = np.diff(lead)
    grams = _text.ngram_hashes(h, n)
    ok = np.flatnonzero(owner[: len(grams)] == owner[n - 1 :]) if len(grams) else np.zeros(0, np.int64)
    who, what = owner[ok], grams[ok]
    short = np.flatnonzero((size > 0) & (size < n))
    if len(short):
        whole = np.array([_text.ngram_hashes(h[lead[i] : lead[i + 1]], int(size[i]))[0] for i in short], dtype=np.uint64)
        who, what = np.concatenate([who, short]), np.concatenate([what, whole])
    order = np.lexsort((what, who))
    who, what = who[order], what[order]
    new = np.ones(len(who), dtype=bool)
    new[1:] = (who[1:] != who[:-1]) | (what[1:] != what[:-1])
    first = np.flatnonzero(new)
    return who[first], what[first], np.diff(np.append(first, len(who)))


def prob_minhash(owner: np.ndarray, item: np.ndarray, weight: np.ndarray, n: int, places: int, seed: int) -> np.ndarray:
    """n by ``places`` signatures; rows without items stay 0."""
    best = np.full(n * places, np.inf)
    sig = np.zeros(n * places, dtype=np.uint64)
    time, base, item_key = np.zeros(len(item)), owner.astype(np.int64) * places, _text.mix(item ^ np.uint64(seed))
    alive, r = np.arange(len(item)), 0
    while len(alive):
        r += 1
        x = _text.mix(item_key[alive] + np.uint64((r * _text.BASE) & 0xFFFFFFFFFFFFFFFF))
        time[alive] -= np.log(((x >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53) / weight[alive]
        cell = base[alive] + (_text.mix(x ^ np.uint64(0xA5A5A5A5A5A5A5A5)) % np.uint64(places)).astype(np.int64)
        t = time[alive]
        np.minimum.at(best, cell, t)
        won = best[cell] == t
        sig[cell[won]] = item[alive[won]]
        if r < 8 or r % 4 == 0:  # the bound only falls, so a stale one is safe
            last = best.reshape(n, places).max(axis=1)
        alive = alive[t < last[owner[alive]]]
    return sig.reshape(n, places)


def signatures(texts: list[str], cfg: NearConfig) -> tuple[np.ndarray, np.ndarray]:
    """(number of distinct shingles, band keys) of each text."""
    owner, item, _ = shingle_sets(texts, cfg.words)
    sig = prob_minhash(owner, item, np.ones(len(item)), len(texts), cfg.bands * cfg.rows, cfg.seed)
    keys = np.empty((len(texts), cfg.bands), dtype=np.uint64)
    for b in range(cfg.bands):
        h = np.full(len(texts), b + 1, dtype=np.uint64)
        for k in range(cfg.rows):
            h = _text.mix(h * np.uint64(_text.BASE) + sig[:, b * cfg.rows + k])
        keys[:, b] = h
    return np.bincount(owner, minlength=len(texts)), keys.view(np.int64)


def _signed(docs: DataFrame, cfg: NearConfig) -> DataFrame:
    """(node, n, bands, id) from (node, text, id)."""
    kind = dict(docs.dtypes)["id"]

    def run(batches):
        for b in batches:
            texts, n, keys = b.column(1), [], []
            sizes = [len(t.as_buffer()) for t in texts]
            for lo, hi in _text.pieces(sizes, cfg.piece):
                x, y = signatures(texts.slice(lo, hi - lo).to_pylist(), cfg)
                n.append(x), keys.append(y)
            n = np.concatenate(n) if n else np.zeros(0, np.int64)
            flat = np.concatenate(keys).ravel() if keys else np.zeros(0, np.int64)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(n) + 1, dtype=np.int32) * cfg.bands), pa.array(flat))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n), lists, b.column(2)], ["node", "n", "bands", "id"])

    return docs.mapInArrow(run, f"node bigint, n bigint, bands array<bigint>, id {kind}")


def _sets(docs: DataFrame, cfg: NearConfig) -> DataFrame:
    """(node, sh) from (node, text): the sorted distinct shingles."""

    def run(batches):
        for b in batches:
            texts = b.column(1)
            sizes = [len(t.as_buffer()) for t in texts]
            for lo, hi in _text.pieces(sizes, cfg.piece):
                owner, item, _ = shingle_sets(texts.slice(lo, hi - lo).to_pylist(), cfg.words)
                at = np.searchsorted(owner, np.arange(hi - lo + 1)).astype(np.int32)
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), pa.ListArray.from_arrays(pa.array(at), pa.array(item.view(np.int64)))], ["node", "sh"])

    return docs.mapInArrow(run, "node bigint, sh array<bigint>")


def _verify(pairs: DataFrame, sets: DataFrame, cfg: NearConfig) -> DataFrame:
    """The pairs (a, b) whose exact Jaccard similarity reaches the bound."""
    left, right = sets.select(F.col("node").alias("a"), F.col("sh").alias("x")), sets.select(F.col("node").alias("b"), F.col("sh").alias("y"))
    same = F.size(F.array_intersect("x", "y"))
    return pairs.join(left, "a").join(right, "b").where(same >= cfg.similarity * (F.size("x") + F.size("y") - same) - 1e-9).select("a", "b")


def tile_links(nodes: list[int], cids: list[int], sets: list[np.ndarray], first: np.ndarray, second: np.ndarray, similarity: float) -> list[tuple[int, int]]:
    """One verified link for each pair of components that touch between two tiles (or inside one)."""
    size = np.array([len(s) for s in sets], dtype=np.float64)
    row = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    _, col, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    shared = np.cumsum(times > 1) - 1
    keep = times[col] > 1
    row, col = row[keep], shared[col[keep]]
    order = np.argsort(col, kind="stable")
    row, col = row[order], col[order]
    inter = np.zeros((len(sets), len(sets)), dtype=np.float32)
    width = 4096
    for lo in range(0, int(col[-1]) + 1 if len(col) else 0, width):
        a, b = np.searchsorted(col, [lo, lo + width])
        m = np.zeros((len(sets), width), dtype=np.float32)
        m[row[a:b], col[a:b] - lo] = 1
        inter += m @ m.T
    cid = np.array(cids)
    hit = inter >= similarity * (size[:, None] + size[None, :] - inter) - 1e-6
    hit &= (cid[:, None] != cid[None, :]) & (first[:, None] & second[None, :])
    found = {}
    for i, j in zip(*np.nonzero(hit)):
        found.setdefault((min(cids[i], cids[j]), max(cids[i], cids[j])), (min(nodes[i], nodes[j]), max(nodes[i], nodes[j])))
    return sorted(found.values())


def _tiled(rest: DataFrame, sets: DataFrame, cfg: NearConfig) -> DataFrame:
    """Verified links inside large buckets, from (key, node, cid, size)."""
    tiles = F.ceil(F.col("size") / cfg.tile).cast("int")
    own = F.pmod(F.xxhash64("node", F.lit(cfg.seed)), F.col("tiles")).cast("int")
    d = rest.withColumn("tiles", tiles).withColumn("own", own)
    d = d.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    d = d.select("key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "node", "cid")

    def run(table: pa.Table) -> pa.Table:
        own, i, j = (np.asarray(table.column(c)) for c in ("own", "i", "j"))
        sets_ = [np.asarray(x.values) for x in table.column("sh").combine_chunks()]
        got = tile_links(table.column("node").to_pylist(), table.column("cid").to_pylist(), sets_, own == i, own == j, cfg.similarity)
        return pa.table({"a": pa.array([x for x, _ in got], pa.int64()), "b": pa.array([y for _, y in got], pa.int64())})

    return d.join(sets, "node").groupBy("key", "i", "j").applyInArrow(run, "a bigint, b bigint")


def _nodes(docs: DataFrame, cfg: NearConfig, key: str, text: str) -> DataFrame:
    """(node, n, rows, low, top) of every distinct text: its shingles, rows, least id and class."""
    texts = docs.where(F.col(text).isNotNull()).select(F.xxhash64(text).alias("node"), F.col(text).alias("text"), F.col(key).alias("id"))
    signed = _signed(texts, cfg).groupBy("node").agg(F.first("n").alias("n"), F.first("bands").alias("bands"), F.count(F.lit(1)).alias("rows"), F.min("id").alias("low"))
    signed = cut(signed)
    slots = signed.where("n > 0").select("node", "n", F.explode("bands").alias("key"))
    # a large group of near copies shares its buckets: their keys are dealt out in every join on them
    full = F.col("size") > HOT_ROWS
    shared = cut(slots.groupBy("key").agg(F.count(F.lit(1)).alias("size")).where("size > 1"))
    slots = cut(join_hot(slots, shared, ["key"], full, "node", may_broadcast=False))
    # the densest text of a bucket is the likeliest original of a group of copies
    density = slots.groupBy("node").agg(F.sum("size").alias("density"))
    centre = slots.join(density, "node").groupBy("key").agg(F.max_by("node", F.struct("density", "node")).alias("centre"), F.max_by("n", F.struct("density", "node")).alias("m"), F.first("size").alias("size"))
    centred = join_hot(slots.drop("size"), cut(centre), ["key"], full, "node", may_broadcast=False)
    pairs = centred.where((F.col("node") != F.col("centre")) & (F.least("n", "m") >= cfg.similarity * F.greatest("n", "m") - 1e-9))
    pairs = pairs.select(F.least("node", "centre").alias("a"), F.greatest("node", "centre").alias("b")).distinct()
    members = cut(density.select("node"))
    sets = cut(_sets(texts.join(small(members), "node").select("node", "text"), cfg).groupBy("node").agg(F.first("sh").alias("sh")))
    ends = lambda d: d.select(F.col("a").alias("src"), F.col("b").alias("dst"))
    first = cut(ends(_verify(pairs, sets, cfg)))
    part = cut(connected(members.withColumnRenamed("node", "id"), first, "auto").withColumnRenamed("id", "node"))
    # buckets that still hold several components
    mixed = slots.select("key", "node", "n").join(part, "node")
    parts = mixed.groupBy("key").agg(F.count(F.lit(1)).alias("size"), F.min("cid").alias("lo"), F.max("cid").alias("hi")).where("lo <> hi").select("key", "size")
    mixed = cut(join_hot(mixed, cut(parts), ["key"], full, "node", may_broadcast=False))
    few = mixed.where(F.col("size") <= cfg.pair_bucket)
    x, y = few.select("key", F.col("node").alias("a"), F.col("n").alias("p"), F.col("cid").alias("c")), few.select("key", F.col("node").alias("b"), F.col("n").alias("q"), F.col("cid").alias("d"))
    apart = x.join(y, "key").where((F.col("a") < F.col("b")) & (F.col("c") != F.col("d")) & (F.least("p", "q") >= cfg.similarity * F.greatest("p", "q") - 1e-9)).select("a", "b").distinct()
    second = _verify(apart, sets, cfg).unionByName(_tiled(mixed.where(F.col("size") > cfg.pair_bucket), sets, cfg))
    second = cut(ends(second).distinct())
    # components of components: few links, each end looked up in the node table, whose rows are unique
    to = lambda c: part.select(F.col("node").alias(c), F.col("cid").alias(f"{c}_cid"))
    joined = second.join(to("src"), "src").join(to("dst"), "dst").select(F.col("src_cid").alias("src"), F.col("dst_cid").alias("dst")).where("src <> dst").distinct()
    top = connected(joined.select(F.col("src").alias("id")).unionByName(joined.select(F.col("dst").alias("id"))).distinct(), joined, "auto")
    top = cut(top.select(F.col("id").alias("cid"), F.col("cid").alias("top")))
    width = part.groupBy("cid").agg(F.count(F.lit(1)).alias("width"))
    top = cut(top.join(width, "cid"))
    final = join_hot(part, top, ["cid"], F.col("width") > HOT_ROWS, "node", "left").select("node", F.coalesce("top", "cid").alias("top"))
    # a text outside every shared bucket is its own class
    return cut(signed.drop("bands").join(final, "node", "left").withColumn("top", F.coalesce("top", "node")))


def classes(docs: DataFrame, cfg: NearConfig = NearConfig(), key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, class_id, class_size, n_shingles) of every row."""
    nodes = _nodes(docs, cfg, key, text)
    # classes of one text need no join; of the others the name goes back to each text, and then to each row
    names = nodes.groupBy("top").agg(F.min("low").alias("class_id"), F.sum("rows").alias("class_size"), F.count(F.lit(1)).alias("width"))
    names = cut(names.where("width > 1"))
    named = join_hot(nodes, names, ["top"], F.col("width") > HOT_ROWS, "node", "left")
    named = cut(named.select("node", "n", "rows", F.when(F.col("width").isNull(), F.col("low")).otherwise(F.col("class_id")).alias("class_id"), F.coalesce("class_size", "rows").alias("class_size")))
    rows = docs.select(F.col(key).alias("id"), F.when(F.col(text).isNotNull(), F.xxhash64(text)).alias("node"))
    out = join_hot(rows, named, ["node"], F.col("rows") > HOT_ROWS, "id", "left")
    own = F.col("node").isNull()
    return out.select(
        F.col("id").alias(key), F.when(own, F.col("id")).otherwise(F.col("class_id")).alias("class_id"), F.when(own, F.lit(1)).otherwise(F.col("class_size")).cast("bigint").alias("class_size"), F.coalesce("n", F.lit(0)).cast("bigint").alias("n_shingles")
    )


def one_of_each(docs: DataFrame, cfg: NearConfig = NearConfig(), key: str = "doc_id", text: str = "text") -> DataFrame:
    """All columns of one row of each class, whatever its id: the row with the least id, nulls last.

    Null texts are classes by id.  Of rows alike in id and text the first by the other columns, as JSON, stays.
    """
    nodes = _nodes(docs, cfg, key, text)
    keep = nodes.groupBy("top").agg(F.min(F.struct(F.col("low").isNull(), "low", "node")).alias("s")).select(F.col("s.low").alias("keep_id__"), F.col("s.node").alias("node"))
    keep = cut(keep)
    d = packed(docs, id=F.col(key), node=F.when(F.col(text).isNotNull(), F.xxhash64(text)))
    # one text in many rows: its heaviest keys are dealt out, and all rows but those of the kept id fall
    heavy = cut(keep.join(nodes.select("node", "rows"), "node"))
    kept = join_hot(d.where("node is not null"), heavy, ["node"], F.col("rows") > HOT_ROWS, "id").where(F.col("id").eqNullSafe(F.col("keep_id__")))
    kept = kept.select("doc__", "id", "node").unionByName(d.where("node is null").select("doc__", "id", "node"))
    again = cut(kept.groupBy("id", "node").agg(F.count(F.lit(1)).alias("times")).where("times > 1").select(F.col("id").alias("i__"), F.col("node").alias("n__")))
    if again.limit(1).count() == 0:
        return unpacked(kept, docs)
    same = F.col("id").eqNullSafe(F.col("i__")) & F.col("node").eqNullSafe(F.col("n__"))
    once = kept.join(small(again), same, "left_anti")
    twice = kept.join(small(again), same, "left_semi").groupBy("id", "node").agg(F.min_by("doc__", F.to_json("doc__")).alias("doc__"))
    return unpacked(once.select("doc__"), docs).unionByName(unpacked(twice.select("doc__"), docs))
