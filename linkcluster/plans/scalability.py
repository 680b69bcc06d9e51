"""Phase timing and speedup."""

from __future__ import annotations

from statistics import mean

from pyspark.sql import DataFrame, SparkSession

from linkcluster.operators.measures import speedup
from linkcluster.plans.config import ClusterConfig
from linkcluster.plans.workflow import cluster


def run(vertices: DataFrame, links: DataFrame, cfg: ClusterConfig, workers: list[int], repeats: int = 3) -> list[dict]:
    """Mean seconds of each phase with as many partitions as workers.

    On a cluster, run once for each number of executors; inside one session, the number of
    partitions bounds how many slots work at once.
    """
    spark = vertices.sparkSession
    before = spark.conf.get("spark.sql.shuffle.partitions")
    out = []
    try:
        for w in workers:
            spark.conf.set("spark.sql.shuffle.partitions", str(w))
            runs = [cluster(vertices.repartition(w, "id"), links.repartition(w, "src"), cfg).seconds for _ in range(repeats)]
            row = {"workers": w} | {p: mean(r[p] for r in runs) for p in runs[0]}
            out.append(row | {"seconds": sum(row[p] for p in runs[0])})
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    return out


def speedups(spark: SparkSession, times: list[dict]) -> DataFrame:
    return speedup(spark.createDataFrame([(t["workers"], float(t["seconds"])) for t in times], "workers int, seconds double"))
