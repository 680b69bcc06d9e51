"""Type-based grouping: split components by compatible types."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkcluster.functions.normalize import grid
from linkcluster.operators.components import connected
from linkcluster.plans.iterate import written


def typed_groups(assign: DataFrame, vertices: DataFrame, overlap: str = "transitive") -> DataFrame:
    """(id, cid, tcid) of typed vertices: one sub-cluster for each (transitively overlapping) type of a component."""
    v = assign.join(vertices.select("id", "types"), "id").where(F.size("types") > 0)
    if overlap == "exact":
        return v.withColumn("tcid", F.expr("min(id) over (partition by cid, array_join(array_sort(types), '|'))")).select("id", "cid", "tcid")
    if v.where(F.size("types") > 1).limit(1).count() == 0:
        return v.withColumn("tcid", F.expr("min(id) over (partition by cid, types[0])")).select("id", "cid", "tcid")
    # vertices that share a type in a component hang on its least vertex; overlaps join these stars
    hung = v.select("id", "cid", F.explode("types").alias("type")).withColumn("least", F.expr("min(id) over (partition by cid, type)"))
    links = hung.where("id <> least").select(F.col("least").alias("src"), F.col("id").alias("dst")).distinct()
    groups = connected(v.select("id"), written(links), "sized").withColumnRenamed("cid", "tcid")
    return v.select("id", "cid").join(groups, "id")


def split(assign: DataFrame, intra: DataFrame, vertices: DataFrame, overlap: str = "transitive") -> tuple[DataFrame, DataFrame]:
    """New (id, cid) and the intra-cluster edges inside the new clusters.

    An untyped vertex takes the cluster of its most similar typed neighbour (ties: the smaller
    cluster id); untyped vertices of a component without types stay together.
    """
    typed = typed_groups(assign, vertices, overlap)
    all_ = assign.join(typed.select("id", "tcid"), "id", "left")
    ends = intra.select(F.col("src").alias("u"), F.col("dst").alias("v"), "sim").unionByName(intra.select(F.col("dst").alias("u"), F.col("src").alias("v"), "sim"))
    free = all_.where("tcid is null").select(F.col("id").alias("u"))
    offers = ends.join(free, "u").join(typed.select(F.col("id").alias("v"), F.col("tcid").alias("offer")), "v")
    best = offers.groupBy("u").agg(F.max_by("offer", F.struct(grid(F.col("sim")), -F.col("offer"))).alias("offer"))
    out = all_.join(best.withColumnRenamed("u", "id"), "id", "left").withColumn("new", F.coalesce("tcid", "offer"))
    out = out.withColumn("new", F.coalesce("new", F.expr("min(IF(new IS NULL, id, NULL)) over (partition by cid)")))
    # a cluster is named by its least member, untyped ones included
    new = out.withColumn("cid", F.expr("min(id) over (partition by new)")).select("id", "cid")
    return new, edges_inside(intra, new)


def edges_inside(intra: DataFrame, assign: DataFrame) -> DataFrame:
    e = intra.drop("cid").join(assign.select(F.col("id").alias("src"), "cid"), "src").join(assign.select(F.col("id").alias("dst"), F.col("cid").alias("c2")), "dst")
    return e.where("cid = c2").select("cid", "src", "dst", "sim")
