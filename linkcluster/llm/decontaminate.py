"""Benchmark decontamination by SimHash windows and multi-index Hamming search.

Words are runs of letters and digits in lower case; shingles are five words long.
1. Anchors.  A window can only resemble an item if it shares a shingle with one, so the
   shingles of all documents are matched with those of all items.  Each match proposes
   the item-sized window that puts the shared shingle where the item has it (moved
   inward at the ends of a text).  Matches of one passage agree on one window.  A window at
   another offset holds its shared shingles shifted, so moving it to the offset on which most of
   them agree takes shingles out of the overlap only at its ends, and brings as many in.
2. Search.  Windows and items get 64-bit SimHash fingerprints over their shingles, each
   as often as it occurs.  Fingerprints are cut into blocks; by the pigeonhole principle two
   fingerprints within ``radius`` differ in some block by at most radius // blocks bits.  Items
   are indexed under all block values within part of these flips and windows probe with the rest,
   so every pair within the radius meets, whichever items it concerns.
3. Verification.  Exact weighted Jaccard similarity of shingle counts, at least ``similarity``.

Defined cases: null and empty texts, and texts or items under five words, have no shingle
and never match; null ids and repeated rows are judged like any other row; an empty table gives
an empty result; one passage in very many documents is one broadcast or sorted join
row for each document; very long texts are searched whole; other columns may have any name.
"""

from __future__ import annotations

import itertools
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkcluster.llm._frame import cut, packed, small, unpacked


@dataclass(frozen=True)
class LeakConfig:
    words: int = 5
    similarity: float = 0.8
    radius: int = 19
    blocks: int = 5
    #: Flips within a block that the index covers; windows probe with the rest.
    index_flips: int = 2


def word_hashes(text: Column) -> Column:
    words = F.array_remove(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), "")
    return F.transform(words, lambda w: F.xxhash64(w))


def shingles(hashes: str, n: int) -> Column:
    """Array of shingle hashes over the column of word hashes; empty if there are fewer words."""
    parts = ", ".join(f"{hashes}[i + {k}]" for k in range(n))
    return F.expr(f"CASE WHEN size({hashes}) >= {n} THEN transform(sequence(0, size({hashes}) - {n}), i -> xxhash64({parts})) ELSE cast(array() AS array<bigint>) END")


def with_shingles(df: DataFrame, text: str, n: int, name: str = "sh") -> DataFrame:
    return df.withColumn("__w", word_hashes(F.col(text))).withColumn(name, shingles("__w", n)).drop("__w")


def simhash(column: str) -> Column:
    """64-bit SimHash of an array of hashes; an element that occurs twice weighs twice."""
    vote = f"aggregate({column}, 0, (n, h) -> n + IF((shiftright(h, b) & 1) = 1, 1, -1))"
    return F.expr(f"aggregate(sequence(0, 63), cast(0 AS bigint), (acc, b) -> acc | IF({vote} > 0, shiftleft(cast(1 AS bigint), b), cast(0 AS bigint)))")


def block_keys(fingerprint: str, cfg: LeakConfig, flips: int) -> Column:
    """(block, value) keys of all values within ``flips`` bits of each block's value."""
    edges = [64 * i // cfg.blocks for i in range(cfg.blocks + 1)]
    keys = []
    for b, (lo, hi) in enumerate(zip(edges, edges[1:])):
        width = hi - lo
        masks = sorted(sum(1 << i for i in c) for k in range(flips + 1) for c in itertools.combinations(range(width), k))
        value = f"(shiftrightunsigned({fingerprint}, {lo}) & {(1 << width) - 1}L)"
        keys.append(F.expr(f"transform(array({', '.join(f'{m}L' for m in masks)}), m -> ({value} ^ m) + {b}L * 4294967296L)"))
    return F.concat(*keys)


def weighted_jaccard(a: str, b: str) -> Column:
    """Sum of least over sum of greatest shingle counts."""
    common = F.expr(f"aggregate(array_intersect({a}, {b}), 0, (n, s) -> n + least(size(filter({a}, x -> x = s)), size(filter({b}, x -> x = s))))")
    return common / (F.size(a) + F.size(b) - common)


def items_of(benchmark: DataFrame, cfg: LeakConfig, item: str = "item_id", text: str = "text") -> DataFrame:
    rows = with_shingles(benchmark.select(F.col(item).alias("item"), F.col(text).alias("text")), "text", cfg.words, "item_sh")
    # cut before the filter: pushed below, it would hash all words again for each shingle
    return cut(rows.select("item", "item_sh", simhash("item_sh").alias("item_fp"))).where("size(item_sh) > 0")


def row_key(key: str, text: str) -> Column:
    return F.xxhash64(F.coalesce(F.col(key).cast("string"), F.lit("")), F.coalesce(F.col(text), F.lit("")))


def windows(docs: DataFrame, items: DataFrame, cfg: LeakConfig, key: str, text: str) -> DataFrame:
    """(row, id, start, len, win): the proposed windows with their shingles."""
    anchors = cut(items.select(F.posexplode("item_sh").alias("offset", "s"), F.size("item_sh").alias("len")).distinct())
    slim = docs.select(row_key(key, text).alias("row"), word_hashes(F.col(text)).alias("w"))
    # the generator takes the expression itself, so no filter on its size is inferred and pushed down
    seen = slim.select("row", (F.size("w") - cfg.words + 1).alias("n"), F.posexplode(shingles("w", cfg.words)).alias("pos", "s"))
    hits = seen.join(small(anchors), "s")
    start = F.greatest(F.lit(0), F.least(F.col("pos") - F.col("offset"), F.col("n") - F.col("len")))
    places = hits.select("row", start.alias("start"), "len").groupBy("row").agg(F.collect_set(F.struct("start", "len")).alias("places"))
    places = cut(places)  # rows with a hit only, each with the few windows of its passages
    texts = docs.select(row_key(key, text).alias("row"), F.col(key).alias("id"), F.col(text).alias("text")).join(small(places), "row")
    cutout = with_shingles(texts, "text", cfg.words).select("row", "id", "sh", F.explode("places").alias("p"))
    return cutout.select("row", "id", F.col("p.start").alias("start"), F.col("p.len").alias("len"), F.expr("slice(sh, p.start + 1, p.len)").alias("win"))


def leaks(docs: DataFrame, benchmark: DataFrame, cfg: LeakConfig = LeakConfig(), key: str = "doc_id", text: str = "text", item: str = "item_id") -> DataFrame:
    """(key, item, similarity, start_word, n_words, hamming, row): the best window of each document and item."""
    items = items_of(benchmark, cfg, item)
    found = cut(windows(docs, items, cfg, key, text).withColumn("fp", simhash("win")))
    flips = cfg.radius // cfg.blocks
    index = items.select("item", "item_fp", F.explode(block_keys("item_fp", cfg, min(flips, cfg.index_flips))).alias("block"))
    probe = found.select("row", "start", "len", "fp", F.explode(block_keys("fp", cfg, max(0, flips - cfg.index_flips))).alias("block"))
    near = probe.join(small(cut(index)), "block").withColumn("hamming", F.bit_count(F.col("fp").bitwiseXOR(F.col("item_fp")))).where(F.col("hamming") <= cfg.radius)
    pairs = near.select("row", "start", "len", "item", "hamming").distinct()
    judged = pairs.join(small(items.select("item", "item_sh")), "item").join(found.select("row", "id", "start", "len", "win"), ["row", "start", "len"])
    judged = judged.withColumn("similarity", weighted_jaccard("win", "item_sh")).where(F.col("similarity") >= cfg.similarity)
    best = judged.groupBy("row", "id", "item").agg(F.max(F.struct("similarity", (-F.col("start")).alias("s"), "len", "hamming")).alias("b"))
    return best.select(
        F.col("id").alias(key), F.col("item").alias(item), F.col("b.similarity").alias("similarity"), (-F.col("b.s")).cast("bigint").alias("start_word"), (F.col("b.len") + cfg.words - 1).cast("bigint").alias("n_words"), F.col("b.hamming").alias("hamming"), "row"
    )


def clean_documents(docs: DataFrame, benchmark: DataFrame, cfg: LeakConfig = LeakConfig(), key: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents without a leaked item, with all their columns."""
    bad = cut(leaks(docs, benchmark, cfg, key, text).select("row").distinct())
    d = packed(docs, row=row_key(key, text))
    return unpacked(d.join(small(bad), "row", "left_anti"), docs)
