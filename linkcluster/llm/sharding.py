"""Sharding by a consistent-hash ring with virtual nodes and bounded loads.

A key's hash names a slot of the ring and the next virtual node clockwise its shard.  Shards
have bounds that add up to the number of rows (they differ by one at most, so the bound
is also the balance); keys that meet a full shard continue clockwise to the next shard.
Rows that are alike in id, size and checksum are counted before the shuffle, ranks are
taken inside a slot, and only slot counts, a table of fixed size, reach the driver, where
the walk around the ring becomes a table of (slot, rank range, shard, first place).

Law: ``rows``.  Counts of the shards are at most one apart, whatever the keys.

Defined cases: null texts have size 1 and the checksum of the empty text; null ids share a
slot; repeated rows take ranks of their own; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from linkcluster.llm._frame import cut

BLOCK = 10_000


@dataclass(frozen=True)
class RingConfig:
    shards: int = 16
    virtual_nodes: int = 64
    slots: int = 1 << 14
    seed: int = 5


def walk(counts: dict[int, int], cfg: RingConfig) -> list[tuple[int, int, int, int, int]]:
    """(slot, lo, hi, shard, first place): who takes the keys of rank lo to hi of a slot.

    In round t the keys of a slot that are still without a place ask the t-th shard clockwise;
    a shard takes them in slot order up to its bound.
    """
    ring = sorted((int.from_bytes(hashlib.blake2b(f"{cfg.seed}:{s}:{v}".encode(), digest_size=8).digest(), "big") % cfg.slots, s, v) for s in range(cfg.shards) for v in range(cfg.virtual_nodes))
    total = sum(counts.values())
    bound = [total // cfg.shards + (s < total % cfg.shards) for s in range(cfg.shards)]
    held = [0] * cfg.shards
    done = dict.fromkeys(counts, 0)
    order = sorted(counts)
    start, i = {}, 0
    for slot in order:
        while i < len(ring) and ring[i][0] < slot:
            i += 1
        start[slot] = i % len(ring)
    turn: dict[int, list[int]] = {}

    def clockwise(at: int) -> list[int]:
        if at not in turn:
            turn[at] = list(dict.fromkeys(ring[(at + j) % len(ring)][1] for j in range(len(ring))))
        return turn[at]

    plan = []
    waiting = order
    for t in range(cfg.shards):
        still = []
        for slot in waiting:
            shard = clockwise(start[slot])[t]
            n = min(counts[slot] - done[slot], bound[shard] - held[shard])
            if n > 0:
                plan.append((slot, done[slot], done[slot] + n, shard, held[shard]))
                held[shard] += n
                done[slot] += n
            if done[slot] < counts[slot]:
                still.append(slot)
        waiting = still
    return plan


def assign(docs: DataFrame, cfg: RingConfig = RingConfig(), key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, size, text_crc32, law, shard, slot, grown_shard) of every row."""
    body = F.coalesce(F.col(text), F.lit(""))
    like = docs.select(F.col(key).alias("id"), (F.octet_length(body).cast("bigint") + 1).alias("size"), F.crc32(body).alias("crc")).groupBy("id", "size", "crc").agg(F.count(F.lit(1)).alias("m"))
    point = F.xxhash64(F.coalesce(F.col("id").cast("string"), F.lit("")), F.lit(cfg.seed))
    like = cut(like.withColumn("slot", F.pmod(point, F.lit(cfg.slots)).cast("int")))
    counts = {r[0]: r[1] for r in like.groupBy("slot").agg(F.sum("m")).collect()}  # at most cfg.slots rows
    spark = docs.sparkSession
    plan = spark.createDataFrame(walk(counts, cfg) or [(None,) * 5], "slot int, lo bigint, hi bigint, shard int, place bigint").where("slot is not null")
    upto = F.sum("m").over(W.partitionBy("slot").orderBy("id", "size", "crc").rowsBetween(W.unboundedPreceding, W.currentRow))
    ranked = like.withColumn("end", upto).withColumn("block", F.explode(F.sequence(F.lit(0).cast("bigint"), F.floor((F.col("m") - 1) / BLOCK))))
    first = F.col("end") - F.col("m") + F.col("block") * BLOCK
    ranked = ranked.withColumn("rank", F.explode(F.sequence(first, F.least(F.col("end"), first + BLOCK) - 1)))
    # the plan has at most slots + shards * shards rows of one shape, whatever the corpus
    placed = ranked.join(F.broadcast(plan), "slot").where("rank >= lo and rank < hi")
    return placed.select(
        F.col("id").alias(key), "size", F.col("crc").alias("text_crc32"), F.lit("rows").alias("law"), "shard", (F.col("place") + F.col("rank") - F.col("lo")).alias("slot"), F.lit(None).cast("int").alias("grown_shard")
    )
