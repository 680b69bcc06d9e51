"""Blocking of representatives before they are compared."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def prefix(reps: DataFrame, n: int = 3, col: str = "label") -> DataFrame:
    """Adds ``block``: the first letters of a property; null properties get the empty block."""
    return reps.withColumn("block", F.substring(F.coalesce(F.lower(col), F.lit("")), 1, n))


def keys(reps: DataFrame, exprs: list[Column]) -> DataFrame:
    """One row for each distinct key of a representative (several keys: several blocks)."""
    named = [F.concat(F.lit(f"{i}:"), e.cast("string")) for i, e in enumerate(exprs)]
    return reps.withColumn("block", F.explode(F.array_distinct(F.filter(F.array(*named), lambda k: k.isNotNull()))))


def none(reps: DataFrame) -> DataFrame:
    """A single block; ``tile_pairs`` deals its pairs out to tasks."""
    return reps.withColumn("block", F.lit(""))


def sizes(blocked: DataFrame) -> DataFrame:
    return blocked.groupBy("block").agg(F.count(F.lit(1)).alias("b"))


def tile_pairs(blocked: DataFrame, max_block: int, key: str = "cid", salt: int = 17) -> tuple[DataFrame, DataFrame]:
    """Left and right sides with (block, i, j): each pair of a block meets in exactly one tile of at most
    about ``max_block`` rows a side, so a large block becomes many tasks."""
    parts = F.ceil(F.col("b") / max_block).cast("int")
    d = blocked.join(sizes(blocked), "block").withColumn("parts", parts)
    d = d.withColumn("own", F.pmod(F.xxhash64(key, F.lit(salt)), F.col("parts")).cast("int")).drop("b")
    left = d.withColumn("j", F.explode(F.sequence(F.col("own"), F.col("parts") - 1))).withColumnRenamed("own", "i").drop("parts")
    right = d.withColumn("i", F.explode(F.sequence(F.lit(0), F.col("own")))).withColumnRenamed("own", "j").drop("parts")
    return left, right


def balance(blocked: DataFrame) -> DataFrame:
    """(block, b, pairs, pairs_before): running comparison counts by falling block size, for planning tiles.

    Sizes, of which there are few, are summed up in order; blocks are ranked among those of their size.
    """
    s = sizes(blocked).withColumn("pairs", (F.col("b") * (F.col("b") - 1) / 2).cast("bigint"))
    per = s.groupBy("pairs").agg(F.sum("pairs").alias("held"))
    per = per.withColumn("larger", F.coalesce(F.sum("held").over(W.orderBy(F.desc("pairs")).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).drop("held")
    ranked = s.withColumn("nth", F.row_number().over(W.partitionBy("pairs").orderBy("block")) - 1)
    return ranked.join(per, "pairs").select("block", "b", "pairs", (F.col("larger") + F.col("nth") * F.col("pairs")).alias("pairs_before"))
