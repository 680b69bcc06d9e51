"""Intra-cluster pairs: every pair of a component, scored by one measure."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkcluster.functions.compose import PairMeasure
from linkcluster.operators import blocking
from linkcluster.plans.iterate import written


def pairs(assign: DataFrame, scope: str = "all", vertices: DataFrame | None = None) -> DataFrame:
    """(cid, src, dst) of all pairs inside a component; ``cross_source`` leaves out pairs within a source."""
    d = assign if scope == "all" else assign.join(vertices.select("id", "source"), "id")
    extra = [] if scope == "all" else ["source"]
    a = d.select("cid", F.col("id").alias("src"), *[F.col(c).alias("s1") for c in extra])
    b = d.select("cid", F.col("id").alias("dst"), *[F.col(c).alias("s2") for c in extra])
    out = a.join(b, "cid").where("src < dst")
    return (out if scope == "all" else out.where("s1 <> s2")).select("cid", "src", "dst")


def scored_pairs(assign: DataFrame, vertices: DataFrame, measure: PairMeasure, scope: str = "all", cap: int = 2_000) -> DataFrame:
    """(cid, src, dst, sim): the measure's columns travel with the component id, so one shuffle serves both sides.

    Components of more than ``cap`` members are dealt out as tiles, so that no task holds all pairs of a giant.
    """
    v = vertices.join(assign, "id")
    size = assign.groupBy("cid").agg(F.count(F.lit(1)).alias("members"))
    giants = written(size.where(F.col("members") > cap).select("cid"))
    parts = []
    if giants.limit(1).count():
        left, right = blocking.tile_pairs(v.join(giants, "cid", "left_semi").withColumn("block", F.col("cid")), cap, key="id")
        parts.append((left, right, ["block", "i", "j"]))
        v = v.join(giants, "cid", "left_anti")
    parts.insert(0, (v.withColumn("block", F.col("cid")), v.withColumn("block", F.col("cid")), ["block"]))
    out = []
    for a, b, on in parts:
        keep = ("cid", *(("source",) if scope != "all" else ()), *on)
        left, right = measure.side(a, "l_", *keep), measure.side(b, "r_", *keep)
        met = left.join(right, [F.col(f"l_{c}") == F.col(f"r_{c}") for c in on])
        # inside one tile, or one untiled component, each pair meets twice; between two tiles once, in either order
        met = met.where("l_id < r_id") if len(on) == 1 else met.where("l_id <> r_id AND (l_i <> l_j OR l_id < r_id)")
        if len(on) > 1:
            swap = F.col("l_id") > F.col("r_id")
            met = met.select(*[F.when(swap, F.col(f"{'r' if c[0] == 'l' else 'l'}{c[1:]}")).otherwise(F.col(c)).alias(c) for c in met.columns])
        if scope != "all":
            met = met.where("l_source <> r_source")
        out.append(met.drop(*[f"{p}_{c}" for c in on for p in "lr"]))
    return measure.apply(reduce(DataFrame.unionByName, out)).select(F.col("l_cid").alias("cid"), F.col("l_id").alias("src"), F.col("r_id").alias("dst"), "sim")


def pairs_lateral(assign: DataFrame) -> DataFrame:
    """The same pairs from a table function over member lists; for small components, as a cross-check."""
    from pyspark.sql.functions import udtf

    class Pairs:
        def eval(self, members: list):
            for i, a in enumerate(members):
                for b in members[i + 1 :]:
                    yield a, b

    spark = assign.sparkSession
    spark.udtf.register("linkcluster_pairs", udtf(Pairs, returnType="src bigint, dst bigint"))
    lists = assign.groupBy("cid").agg(F.array_sort(F.collect_list("id")).alias("members"))
    return spark.sql("SELECT cid, src, dst FROM {lists}, LATERAL linkcluster_pairs(members)", lists=lists)
