"""Similarity-based refinement: remove, one at a time, the least similar member of a cluster.

A member's average similarity is over the members still in its cluster.  In each round every
cluster removes its lowest member if that lies under the bound (ties: the larger id goes), and it
becomes a cluster of its own.  ``rounds`` runs DataFrame supersteps in which only clusters that changed
stay; ``grouped`` runs a cluster's whole loop in one task after one shuffle; ``auto`` takes
``grouped`` up to ``cap`` members and ``rounds`` beyond.  Results are equal.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkcluster.functions.normalize import grid
from linkcluster.operators.typegroup import edges_inside
from linkcluster.plans.iterate import written


def _ends(edges: DataFrame) -> DataFrame:
    s = edges.select("cid", F.col("src").alias("id"), F.col("dst").alias("other"), grid(F.col("sim")).alias("g"))
    return s.unionByName(s.select("cid", F.col("other").alias("id"), F.col("id").alias("other"), "g"))


def average_similarity(edges: DataFrame) -> DataFrame:
    """(cid, id, asim) of all members with an edge."""
    return _ends(edges).groupBy("cid", "id").agg((F.sum("g") / F.count("g") / 1e9).alias("asim"))


def _lowest(ends: DataFrame) -> DataFrame:
    a = ends.groupBy("cid", "id").agg((F.sum("g").cast("double") / F.count("g")).alias("asim"))
    return a.groupBy("cid").agg(F.min(F.struct("asim", (-F.col("id")).alias("neg"))).alias("low")).select("cid", F.col("low.asim").alias("asim"), (-F.col("low.neg")).alias("id"))


def _rounds(edges: DataFrame, theta: float, max_rounds: int | None, bulk: bool) -> tuple[DataFrame, list[dict]]:
    """(id) of removed members and a log."""
    spark = edges.sparkSession
    removed = spark.createDataFrame([], "id bigint")
    work, log = written(_ends(edges)), []
    while max_rounds is None or len(log) < max_rounds:
        if bulk:
            low = work.groupBy("cid", "id").agg((F.sum("g").cast("double") / F.count("g")).alias("asim"))
        else:
            low = _lowest(work)
        out = written(low.where(F.col("asim") < F.lit(theta * 1e9)).select("cid", "id"))
        n = out.count()
        log.append({"round": len(log) + 1, "removed": n})
        if not n:
            break
        removed = written(removed.unionByName(out.select("id")))
        # clusters that removed nobody are done; the rest goes on without its removed members
        left = work.join(out.select("cid").distinct(), "cid", "left_semi")
        left = left.join(out.select("id"), "id", "left_anti").join(out.select(F.col("id").alias("other")), "other", "left_anti")
        work = written(left.select("cid", "id", "other", "g"))
        if bulk:
            break
    return removed, log


def refine_cluster(src: np.ndarray, dst: np.ndarray, g: np.ndarray, theta: float, max_rounds: int | None = None) -> list[int]:
    """Removed ids of one cluster in order."""
    ids = np.unique(np.concatenate([src, dst]))
    a, b = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    total = np.bincount(a, g, len(ids)) + np.bincount(b, g, len(ids))
    count = np.bincount(a, minlength=len(ids)) + np.bincount(b, minlength=len(ids))
    sims = np.zeros((len(ids), len(ids)))
    has = np.zeros((len(ids), len(ids)), dtype=bool)
    sims[a, b] = sims[b, a] = g
    has[a, b] = has[b, a] = True
    active, out = count > 0, []
    while active.any() and (max_rounds is None or len(out) < max_rounds):
        asim = np.where(active & (count > 0), total / np.maximum(count, 1), np.inf)
        low = len(asim) - 1 - int(np.argmin(asim[::-1]))
        if not asim[low] < theta * 1e9:
            break
        out.append(int(ids[low]))
        active[low] = False
        total -= np.where(has[low], sims[low], 0)
        count -= has[low]
        count[low] = 0
    return out


def _grouped(edges: DataFrame, theta: float, max_rounds: int | None) -> DataFrame:
    def run(t: pa.Table) -> pa.Table:
        gone = refine_cluster(np.asarray(t["src"]), np.asarray(t["dst"]), np.asarray(t["g"]).astype(float), theta, max_rounds)
        return pa.table({"id": pa.array(gone, pa.int64())})

    # a cluster whose least similar member reaches the bound is done; only the others go to Python
    below = _lowest(_ends(edges)).where(F.col("asim") < F.lit(theta * 1e9)).select("cid")
    return edges.join(below, "cid", "left_semi").select("cid", "src", "dst", grid(F.col("sim")).alias("g")).groupBy("cid").applyInArrow(run, "id bigint")


def run(assign: DataFrame, edges: DataFrame, theta: float, max_rounds: int | None = None, strategy: str = "auto", cap: int = 2_000, variant: str = "lowest") -> tuple[DataFrame, DataFrame, list[dict]]:
    """(assignment, edges inside it, round log)."""
    log: list[dict] = []
    if variant == "bulk":
        removed, log = _rounds(edges, theta, max_rounds, True)
    elif strategy == "rounds":
        removed, log = _rounds(edges, theta, max_rounds, False)
    elif strategy == "grouped":
        removed = _grouped(edges, theta, max_rounds)
    else:
        size = assign.groupBy("cid").agg(F.count(F.lit(1)).alias("n"))
        giants = written(size.where(F.col("n") > cap).select("cid"))
        removed = _grouped(edges.join(giants, "cid", "left_anti"), theta, max_rounds)
        if giants.limit(1).count():
            big, log = _rounds(edges.join(giants, "cid", "left_semi"), theta, max_rounds, False)
            removed = removed.unionByName(big)
    gone = removed.distinct().withColumn("gone", F.lit(True))
    new = assign.join(gone, "id", "left").withColumn("key", F.when(F.col("gone"), F.struct(F.col("id").alias("c"), F.lit(1).alias("x"))).otherwise(F.struct(F.col("cid").alias("c"), F.lit(0).alias("x"))))
    new = written(new.withColumn("new", F.expr("min(id) over (partition by key)")).select("id", F.col("new").alias("cid")))
    return new, edges_inside(edges, new), log
