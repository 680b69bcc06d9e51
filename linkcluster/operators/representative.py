"""Cluster representatives: united sources, types and members, and the best label and position."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def build(assign: DataFrame, vertices: DataFrame, label_policy: str = "frequent_longest", geo_policy: str = "of_label_owner", extra: tuple[str, ...] = (), edges: DataFrame | None = None) -> DataFrame:
    """One row for each cluster.

    Label policies: ``frequent_longest`` (most frequent, then longest, then least), ``longest``,
    ``source_priority`` (first source by name), ``medoid`` (highest average similarity; needs ``edges``).
    Position policies: ``of_label_owner``, ``source_priority``, ``mean``.  ``extra`` columns follow the label's owner.
    """
    v = vertices.join(assign, "id")
    if label_policy == "medoid":
        from linkcluster.operators.refine import average_similarity

        v = v.join(average_similarity(edges).select("id", "asim"), "id", "left")
        rank = F.struct(F.coalesce("asim", F.lit(-1.0)), (-F.col("id")))
    elif label_policy == "frequent_longest":
        # dealt out by cluster once: labels are counted and clusters put together where the rows are then
        v = v.repartition("cid").withColumn("often", F.when(F.col("label").isNotNull(), F.count(F.lit(1)).over(W.partitionBy("cid", "label"))).otherwise(F.lit(0)))
        rank = F.struct("often", F.char_length(F.coalesce("label", F.lit(""))), (-F.col("id")))
    elif label_policy == "longest":
        rank = F.struct(F.char_length(F.coalesce("label", F.lit(""))), (-F.col("id")))
    else:
        rank = None
    pick = (lambda c: F.min_by(c, F.struct("source", "id"))) if rank is None else (lambda c: F.max_by(c, rank))
    if rank is not None:
        v = v.withColumn("__rank", rank)
        pick = lambda c: F.max_by(c, F.col("__rank"))
    place = F.struct("lat", "lon")
    here = F.col("lat").isNotNull() & F.col("lon").isNotNull()
    if geo_policy == "mean":
        spot = F.when(F.count(F.when(here, 1)) > 0, F.struct(F.avg(F.when(here, F.col("lat"))).alias("lat"), F.avg(F.when(here, F.col("lon"))).alias("lon")))
    elif geo_policy == "source_priority" or rank is None:
        spot = F.min_by(F.when(here, place), F.when(here, F.struct("source", "id")))
    else:
        spot = F.max_by(F.when(here, place), F.when(here, F.col("__rank")))
    kinds = dict(vertices.dtypes)
    out = v.groupBy("cid").agg(
        pick("label").alias("label"),
        F.array_sort(F.array_distinct(F.flatten(F.collect_set(F.coalesce("types", F.array().cast("array<string>")))))).alias("types"),
        F.array_sort(F.collect_set("source")).alias("sources"),
        F.array_sort(F.collect_list("id")).alias("members"),
        spot.alias("spot"),
        F.count(F.lit(1)).cast("int").alias("n"),
        *([pick("props").alias("props")] if "props" in kinds else []),
        *[pick(c).alias(c) for c in extra],
    )
    return out.select("cid", "label", "types", "sources", "members", F.col("spot.lat").alias("lat"), F.col("spot.lon").alias("lon"), "n", *(["props"] if "props" in kinds else []), *extra)
