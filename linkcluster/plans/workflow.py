"""The clustering workflow: preprocess, initial clusters, decomposition, merge."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkcluster.functions.compose import LABEL_GEO
from linkcluster.operators import blocking, components, intra, merge, preprocess, refine, representative, typegroup
from linkcluster.plans.config import ClusterConfig, LinkGraph
from linkcluster.plans.iterate import release, written


@dataclass
class ClusterResult:
    assign: DataFrame
    reps: DataFrame
    edges: DataFrame
    graph: LinkGraph
    #: Seconds of each phase and the round logs of the loops.
    seconds: dict[str, float] = field(default_factory=dict)
    rounds: dict[str, list[dict]] = field(default_factory=dict)


def _extra(cfg: ClusterConfig) -> tuple[str, ...]:
    return tuple(c for c in cfg.measure.columns if c not in ("label", "lat", "lon"))


def initial_clusters(g: LinkGraph, cfg: ClusterConfig) -> DataFrame:
    assign = components.connected(g.vertices, g.edges, cfg.component_method)
    if cfg.require_unique_sources:
        # an entity beyond the first of its source in a component leaves it
        d = assign.join(g.vertices.select("id", "source"), "id").withColumn("nth", F.expr("row_number() over (partition by cid, source order by id)"))
        assign = d.select("id", F.when(F.col("nth") > 1, F.col("id")).otherwise(F.col("cid")).alias("cid"))
    return assign


def decompose(assign: DataFrame, g: LinkGraph, cfg: ClusterConfig) -> tuple[DataFrame, DataFrame, list[dict]]:
    """(assignment, intra-cluster edges, refinement log)."""
    every = written(intra.scored_pairs(assign, g.vertices, cfg.measure, cfg.pair_scope))
    edges, log = every, []
    if cfg.use_types:
        typed = written(typegroup.split(assign, edges, g.vertices, cfg.type_overlap)[0])
        # from the written clusters: refinement reads these edges more than once
        edges = written(typegroup.edges_inside(edges, typed))
        release(every)
        assign = typed
    if cfg.use_refine:
        assign, edges, log = refine.run(assign, edges, cfg.theta_refine, cfg.max_rounds, cfg.refine_strategy, cfg.giant_cap)
    return assign, edges, log


def blocked(reps: DataFrame, cfg: ClusterConfig) -> DataFrame:
    if not cfg.use_blocking:
        return blocking.none(reps)
    if len(cfg.block_on) > 1 and cfg.merge_strategy in ("block_best", "grouped"):
        raise ValueError("with several keys a cluster is in several blocks: use the strategies auto or dominant")
    return blocking.keys(reps, [F.expr(e) for e in cfg.block_on]) if cfg.block_on else blocking.prefix(reps, cfg.block_prefix)


def cluster(vertices: DataFrame, links: DataFrame, cfg: ClusterConfig = ClusterConfig()) -> ClusterResult:
    seconds: dict[str, float] = {}
    rounds: dict[str, list[dict]] = {}
    at = time.monotonic()

    def lap(name: str) -> None:
        nonlocal at
        now = time.monotonic()
        seconds[name], at = now - at, now

    g = preprocess.run(vertices, links, cfg)
    # the phases read these columns alone; the result keeps the entities whole, as they were given
    needed = {"id", "source", "label", "types", "lat", "lon", "props", *cfg.measure.columns}
    whole = g.vertices
    g = LinkGraph(written(whole.select(*[c for c in whole.columns if c in needed])), written(g.edges))
    k = cfg.k or g.vertices.select(F.countDistinct("source")).first()[0]
    lap("pre")
    initial = written(initial_clusters(g, cfg))
    lap("components")
    assign, edges, rounds["refine"] = decompose(initial, g, cfg)
    if cfg.use_types:
        release(initial)
    reps = written(representative.build(assign, g.vertices, cfg.label_policy, cfg.geo_policy, _extra(cfg), edges))
    lap("decomposition")
    if cfg.use_merge:
        # the bound on distances needs a theta that the label alone does not reach
        by_bound = not cfg.use_blocking and cfg.measure is LABEL_GEO and cfg.theta_merge > 0.5
        blocks = blocked(reps, cfg)
        pairs = merge.unblocked_pairs(reps, cfg.theta_merge, k) if by_bound else None
        if cfg.measure.weights and cfg.use_blocking and len(cfg.block_on) < 2 and cfg.theta_merge > 0:
            pairs = merge.likely_pairs(blocks, cfg.measure, cfg.theta_merge, k, cfg.block_cap)
        work = merge.candidates(blocks, cfg.measure, cfg.theta_merge, k, cfg.untyped, cfg.block_cap, pairs)
        merged, rounds["merge"] = merge.run(assign, reps, work, k, cfg.merge_strategy, cfg.max_rounds)
        merged = written(merged)
        release(reps, *([pairs] if pairs is not None else []))
        assign = merged
        reps = written(representative.build(assign, g.vertices, cfg.label_policy if cfg.label_policy != "medoid" else "frequent_longest", cfg.geo_policy, _extra(cfg)))
    lap("merge")
    g = LinkGraph(whole, g.edges)
    if cfg.dump_dir:
        from linkcluster.sources import sinks

        for name, df in (("vertices", g.vertices), ("links", g.edges), ("assign", assign), ("representatives", reps)):
            sinks.write(df, f"{cfg.dump_dir}/{name}", cfg.dump_format)
    return ClusterResult(assign, reps, edges, g, seconds, rounds)


def register_views(result: ClusterResult) -> None:
    """Temporary views for follow-up SQL: entities, links, clusters, assignments."""
    result.graph.vertices.createOrReplaceTempView("entities")
    result.graph.edges.createOrReplaceTempView("links")
    result.reps.createOrReplaceTempView("clusters")
    result.assign.createOrReplaceTempView("assignments")
