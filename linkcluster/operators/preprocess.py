"""Preprocessing: normalise, harmonise types, validate, score links, keep the best links."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from linkcluster.functions import normalize
from linkcluster.functions.compose import PairMeasure
from linkcluster.functions.normalize import grid
from linkcluster.plans.config import ClusterConfig, LinkGraph


def harmonize_types(v: DataFrame, equivalence: dict[str, str] | DataFrame, unknown: str = "keep") -> DataFrame:
    """Map raw types to general ones; unmapped types are kept or, with ``unknown='drop'``, removed.

    A dictionary becomes a literal map inside the projection (no shuffle); a table is joined to the
    exploded types and regrouped.
    """
    if isinstance(equivalence, dict):
        if not equivalence:
            return v if unknown == "keep" else v.withColumn("types", F.array().cast("array<string>"))
        table = F.create_map(*[F.lit(x) for kv in sorted(equivalence.items()) for x in kv])
        to = lambda t: F.coalesce(table[t], t) if unknown == "keep" else table[t]
        mapped = F.array_sort(F.array_distinct(F.filter(F.transform("types", to), lambda t: t.isNotNull())))
        return v.withColumn("types", F.coalesce(mapped, F.array().cast("array<string>")))
    one = v.select("id", F.explode("types").alias("raw_type")).join(equivalence.select("raw_type", "harmonised_type"), "raw_type", "left" if unknown == "keep" else "inner")
    new = one.groupBy("id").agg(F.array_sort(F.collect_set(F.coalesce("harmonised_type", "raw_type"))).alias("types"))
    return v.drop("types").join(new, "id", "left").withColumn("types", F.coalesce("types", F.array().cast("array<string>"))).select(*v.columns)


def compatible(a: Column, b: Column, null: str = "wildcard") -> Column:
    """Types agree when they overlap; an untyped side agrees with all (``wildcard``) or with untyped ones only."""
    empty = (F.coalesce(F.size(a), F.lit(0)) <= 0, F.coalesce(F.size(b), F.lit(0)) <= 0)
    open_ = (empty[0] | empty[1]) if null == "wildcard" else (empty[0] & empty[1])
    return open_ | F.coalesce(F.arrays_overlap(a, b), F.lit(False))


def validate_graph(g: LinkGraph, require_type: str | None = None) -> tuple[LinkGraph, DataFrame]:
    """Drop bad vertices (no id, no label, wrong type) and links (dangling, loops, within a source, repeated).

    Returns the graph and one row of counts.
    """
    good = F.col("id").isNotNull() & F.col("label").isNotNull() & (F.trim("label") != "")
    if require_type:
        good &= F.array_contains("types", require_type)
    v = g.vertices.where(good)
    e = g.edges.where("src is not null and dst is not null")
    e = e.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), *[c for c in e.columns if c not in ("src", "dst")]).where("src <> dst").dropDuplicates(["src", "dst"])
    s = v.select("id", "source")
    e = e.join(s.select(F.col("id").alias("src"), F.col("source").alias("s1")), "src").join(s.select(F.col("id").alias("dst"), F.col("source").alias("s2")), "dst")
    e = e.where(~F.col("s1").eqNullSafe(F.col("s2"))).drop("s1", "s2").select("src", "dst", *[c for c in g.edges.columns if c not in ("src", "dst")])
    n = lambda d, name: d.agg(F.count(F.lit(1)).alias(name))
    counts = n(g.vertices, "vertices_in").crossJoin(n(v, "vertices_out")).crossJoin(n(g.edges, "links_in")).crossJoin(n(e, "links_out"))
    return LinkGraph(v, e), counts


def score_links(g: LinkGraph, measure: PairMeasure) -> LinkGraph:
    """Similarities of the given links only, from the properties; earlier scores are dropped."""
    left, right = measure.side(g.vertices, "l_"), measure.side(g.vertices, "r_")
    pairs = g.edges.select("src", "dst").join(left, F.col("src") == F.col("l_id")).join(right, F.col("dst") == F.col("r_id"))
    return LinkGraph(g.vertices, measure.apply(pairs).select("src", "dst", "sim"))


def best_links(g: LinkGraph, mode: str = "mutual") -> DataFrame:
    """For each entity and other source the best link; ``mutual`` keeps links that are best at both ends,
    ``either`` at one end, ``one_sided`` at the smaller id's end."""
    s = g.vertices.select("id", "source")
    e = g.edges.join(s.select(F.col("id").alias("src"), F.col("source").alias("s_src")), "src").join(s.select(F.col("id").alias("dst"), F.col("source").alias("s_dst")), "dst")
    top = lambda me, other, src: F.row_number().over(W.partitionBy(me, src).orderBy(grid(F.col("sim")).desc(), F.col(other))) == 1
    e = e.withColumn("a", top("src", "dst", "s_dst")).withColumn("b", top("dst", "src", "s_src"))
    keep = {"mutual": F.col("a") & F.col("b"), "either": F.col("a") | F.col("b"), "one_sided": F.col("a")}[mode]
    return e.where(keep).select("src", "dst", "sim")


def run(vertices: DataFrame, links: DataFrame, cfg: ClusterConfig) -> LinkGraph:
    v = harmonize_types(normalize.labels(vertices), cfg.type_map)
    g, _ = validate_graph(LinkGraph(v, links))
    g = score_links(g, cfg.measure)
    return LinkGraph(g.vertices, best_links(g, cfg.link_mode))
