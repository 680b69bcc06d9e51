"""Writers: Parquet, bucketed tables, JSON and GeoJSON."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def write(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite", by: list[str] | None = None) -> None:
    w = df.write.mode(mode)
    (w.partitionBy(*by) if by else w).format(fmt).save(path)


def bucketed(df: DataFrame, table: str, key: str = "cid", buckets: int = 64, mode: str = "overwrite") -> None:
    """A table bucketed and sorted by ``key``: later joins and aggregations on it need no shuffle."""
    df.write.mode(mode).bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(table)


def links_by_source_pair(links: DataFrame, path: str) -> None:
    """One directory a mapping, so a source pair is read by partition pruning."""
    write(links.withColumn("mapping", F.concat_ws("-", F.least("s1", "s2"), F.greatest("s1", "s2"))), path, by=["mapping"])


def _feature(geometry, **properties) -> F.Column:
    return F.to_json(F.struct(F.lit("Feature").alias("type"), geometry.alias("geometry"), F.struct(*[c.alias(n) for n, c in properties.items()]).alias("properties")))


def geojson_points(df: DataFrame, *properties: str) -> DataFrame:
    """One GeoJSON feature a line (``value``); rows without a position have a null geometry."""
    point = F.when(F.col("lat").isNotNull() & F.col("lon").isNotNull(), F.struct(F.lit("Point").alias("type"), F.array("lon", "lat").alias("coordinates")))
    return df.select(_feature(point, **{p: F.col(p) for p in properties}).alias("value"))


def geojson_links(links: DataFrame, vertices: DataFrame) -> DataFrame:
    p = vertices.where("lat is not null and lon is not null").select("id", F.array("lon", "lat").alias("at"))
    d = links.join(p.select(F.col("id").alias("src"), F.col("at").alias("a")), "src").join(p.select(F.col("id").alias("dst"), F.col("at").alias("b")), "dst")
    line = F.struct(F.lit("LineString").alias("type"), F.array("a", "b").alias("coordinates"))
    return d.select(_feature(line, src=F.col("src"), dst=F.col("dst"), sim=F.col("sim")).alias("value"))


def round_log(spark, rounds: dict[str, list[dict]], path: str) -> None:
    rows = [(phase, r.get("round"), r.get("work"), r.get("merged", r.get("removed"))) for phase, log in rounds.items() for r in log]
    write(spark.createDataFrame(rows, "phase string, round int, work bigint, changed bigint"), path, "json")
