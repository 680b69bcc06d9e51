"""Parameters and the graph pair of the clustering workflow."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import types as T

from linkcluster.functions.compose import LABEL_GEO, PairMeasure

ENTITY = T.StructType(
    [
        T.StructField("id", T.LongType()),
        T.StructField("source", T.StringType()),
        T.StructField("label", T.StringType()),
        T.StructField("types", T.ArrayType(T.StringType())),
        T.StructField("lat", T.DoubleType()),
        T.StructField("lon", T.DoubleType()),
        T.StructField("props", T.MapType(T.StringType(), T.StringType())),
    ]
)
LINK = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType()), T.StructField("sim", T.DoubleType())])
#: Raw type names and the general type they stand for.
TYPE_EQUIVALENCE = {"city": "settlement", "town": "settlement", "suburb": "settlement"}


@dataclass(frozen=True)
class LinkGraph:
    """Entities and links; links are canonical (src < dst) after preprocessing."""

    vertices: DataFrame
    edges: DataFrame


@dataclass(frozen=True)
class ClusterConfig:
    #: Greatest number of members and sources of a merged cluster; None: the number of distinct sources.
    k: int | None = None
    measure: PairMeasure = LABEL_GEO
    link_mode: str = "mutual"
    type_map: dict[str, str] = field(default_factory=lambda: dict(TYPE_EQUIVALENCE))
    type_overlap: str = "transitive"
    untyped: str = "wildcard"
    theta_refine: float = 0.7
    theta_merge: float = 0.8
    block_prefix: int = 3
    #: SQL expressions over a representative's columns whose values are the blocking keys; none: the first letters of the label.
    block_on: tuple[str, ...] = ()
    max_rounds: int | None = None
    label_policy: str = "frequent_longest"
    geo_policy: str = "of_label_owner"
    merge_strategy: str = "auto"
    refine_strategy: str = "auto"
    component_method: str = "sized"
    pair_scope: str = "all"
    #: Component size above which refinement runs in rounds instead of one task; block size above which blocks are tiled.
    giant_cap: int = 2_000
    block_cap: int = 20_000
    dump_dir: str | None = None
    dump_format: str = "json"
    # ablations
    use_types: bool = True
    use_refine: bool = True
    use_merge: bool = True
    use_blocking: bool = True
    require_unique_sources: bool = False
