"""Quality, structure and cost measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkcluster.operators import blocking


def pairs_of(assign: DataFrame) -> DataFrame:
    """All links of a clustering (small results; counts need no pairs, see ``cluster_quality``)."""
    a, b = assign.select("cid", F.col("id").alias("src")), assign.select("cid", F.col("id").alias("dst"))
    return a.join(b, "cid").where("src < dst").select("src", "dst")


def _scores(counts: DataFrame) -> DataFrame:
    ratio = lambda a, b: F.when(F.col(b) > 0, F.floor(F.col(a).cast("double") / F.col(b).cast("double") * 1e6 + 0.5) / 1e6)
    d = counts.withColumn("precision", ratio("n_true", "n_pred")).withColumn("recall", ratio("n_true", "n_gold"))
    d = d.withColumn("twice", 2 * F.col("n_true")).withColumn("both", F.col("n_pred") + F.col("n_gold"))
    return d.withColumn("f1", ratio("twice", "both")).select("n_true", "n_pred", "n_gold", "precision", "recall", "f1")


def link_quality(pred: DataFrame, gold: DataFrame) -> DataFrame:
    """Precision, recall and F1 over distinct links (src < dst)."""
    p, g = pred.select("src", "dst").distinct(), gold.select("src", "dst").distinct()
    n = lambda d, name: d.agg(F.count(F.lit(1)).alias(name))
    return _scores(n(p.join(g, ["src", "dst"]), "n_true").crossJoin(n(p, "n_pred")).crossJoin(n(g, "n_gold")))


def cluster_quality(assign: DataFrame, gold: DataFrame) -> DataFrame:
    """As ``link_quality`` for two disjoint clusterings, from overlap counts; no pair is made."""
    pairs = lambda c: F.coalesce(F.sum(F.col(c) * (F.col(c) - 1) / 2), F.lit(0)).cast("bigint")
    both = assign.join(gold.select("id", "gold"), "id")
    cell = both.groupBy("cid", "gold").agg(F.count(F.lit(1)).alias("c"))
    n = lambda d, by, name: d.groupBy(by).agg(F.count(F.lit(1)).alias("c")).agg(pairs("c").alias(name))
    return _scores(cell.agg(pairs("c").alias("n_true")).crossJoin(n(assign, "cid", "n_pred")).crossJoin(n(gold, "gold", "n_gold")))


def overview(vertices: DataFrame, gold: DataFrame) -> DataFrame:
    """Entities, sources, correct links and clusters of a data set."""
    links = gold.groupBy("gold").agg(F.count(F.lit(1)).alias("c")).agg(F.coalesce(F.sum(F.col("c") * (F.col("c") - 1) / 2), F.lit(0)).cast("bigint").alias("links"), F.count(F.lit(1)).alias("clusters"))
    return vertices.agg(F.count(F.lit(1)).alias("entities"), F.countDistinct("source").alias("sources")).crossJoin(links)


def structure(gold: DataFrame) -> DataFrame:
    """Entities of each source (s1 = s2) and correct links of each source pair."""
    n = gold.groupBy("source").agg(F.count(F.lit(1)).alias("n")).select(F.col("source").alias("s1"), F.col("source").alias("s2"), "n")
    a, b = gold.select("gold", F.col("source").alias("x"), F.col("id").alias("i")), gold.select("gold", F.col("source").alias("y"), F.col("id").alias("j"))
    p = a.join(b, "gold").where("i < j").groupBy(F.least("x", "y").alias("s1"), F.greatest("x", "y").alias("s2")).agg(F.count(F.lit(1)).alias("n"))
    return n.unionByName(p.where("s1 <> s2"))


def link_delta(given: DataFrame, pred: DataFrame, gold: DataFrame) -> DataFrame:
    """New correct links, wrong links removed, correct links lost, wrong links added."""
    flag = lambda d, name: d.select("src", "dst", F.lit(1).alias(name)).distinct()
    d = flag(given, "i").join(flag(pred, "p"), ["src", "dst"], "full").join(flag(gold, "g"), ["src", "dst"], "full")
    i, p, g = (F.col(c).isNotNull() for c in "ipg")
    n = lambda c, name: F.count_if(c).alias(name)
    return d.agg(n(~i & p & g, "new_correct"), n(i & ~p & ~g, "wrong_removed"), n(i & ~p & g, "correct_lost"), n(~i & p & ~g, "new_wrong"))


def cluster_profile(assign: DataFrame, vertices: DataFrame) -> DataFrame:
    """(size, clusters, entities, repeated_sources): the size histogram and how many clusters repeat a source."""
    c = assign.join(vertices.select("id", "source"), "id").groupBy("cid").agg(F.count(F.lit(1)).alias("size"), F.countDistinct("source").alias("k"))
    return c.groupBy("size").agg(F.count(F.lit(1)).alias("clusters"), F.sum("size").alias("entities"), F.count_if(F.col("k") < F.col("size")).alias("repeated_sources"))


def exact_match_rate(assign: DataFrame, gold: DataFrame) -> DataFrame:
    """Share of gold clusters that came out whole and pure."""
    d = assign.join(gold.select("id", "gold"), "id")
    size = d.groupBy("cid").agg(F.count(F.lit(1)).alias("cn"))
    g = d.join(size, "cid").groupBy("gold").agg(F.countDistinct("cid").alias("k"), F.max("cn").alias("cn"), F.count(F.lit(1)).alias("n"))
    return g.agg(F.count_if((F.col("k") == 1) & (F.col("cn") == F.col("n"))).alias("whole"), F.count(F.lit(1)).alias("clusters"))


def blocking_cost(blocked: DataFrame) -> DataFrame:
    """Blocks, comparisons, largest block, and the share of all comparisons that blocking saves."""
    s = blocking.sizes(blocked)
    d = s.agg(F.count(F.lit(1)).alias("blocks"), F.sum(F.col("b") * (F.col("b") - 1) / 2).cast("bigint").alias("comparisons"), F.max("b").alias("largest"), F.sum("b").alias("n"))
    every = F.col("n") * (F.col("n") - 1) / 2
    return d.select("blocks", "comparisons", "largest", F.when(every > 0, F.floor((1 - F.col("comparisons") / every) * 1e6 + 0.5) / 1e6).alias("reduction"))


def pair_completeness(blocked: DataFrame, gold_pairs: DataFrame) -> DataFrame:
    """Share of the wanted pairs (src, dst) whose ends share a block."""
    b = blocked.select(F.col("cid"), "block")
    d = gold_pairs.select("src", "dst").join(b.select(F.col("cid").alias("src"), F.col("block").alias("b1")), "src").join(b.select(F.col("cid").alias("dst"), F.col("block").alias("b2")), "dst")
    return d.groupBy("src", "dst").agg(F.max((F.col("b1") == F.col("b2")).cast("int")).alias("met")).agg(F.sum("met").cast("bigint").alias("met"), F.count(F.lit(1)).alias("wanted"))


def compactness(assign: DataFrame) -> DataFrame:
    """Links that the clusters stand for against the number of clusters and members."""
    s = assign.groupBy("cid").agg(F.count(F.lit(1)).alias("c"))
    return s.agg(F.count(F.lit(1)).alias("clusters"), F.sum("c").alias("members"), F.sum(F.col("c") * (F.col("c") - 1) / 2).cast("bigint").alias("links"))


def speedup(times: DataFrame) -> DataFrame:
    """(workers, seconds) -> speedup against the least number of workers, and the linear one."""
    first = times.agg(F.min_by("seconds", "workers").alias("t1"), F.min("workers").alias("w1"))
    s: Column = F.floor(F.col("t1") / F.col("seconds") * 1e6 + 0.5) / 1e6
    return times.crossJoin(first).select("workers", "seconds", s.alias("speedup"), (F.col("workers") / F.col("w1")).alias("linear"))
