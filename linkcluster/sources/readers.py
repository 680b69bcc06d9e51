"""Readers with declared schemas and pruned columns."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from linkcluster.plans.config import ENTITY, LINK


def parquet(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None, where: Column | str | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df if where is None else df.where(where)
    return df.select(*cols) if cols else df


def json_entities(spark: SparkSession, path: str, schema=ENTITY) -> DataFrame:
    return spark.read.schema(schema).json(path)


def csv_links(spark: SparkSession, path: str, header: bool = True) -> DataFrame:
    return spark.read.schema(LINK).csv(path, header=header)


def uri_links(spark: SparkSession, path: str, sep: str = " ") -> DataFrame:
    """Links between URIs, one pair a line."""
    return spark.read.schema("src_uri string, dst_uri string").csv(path, sep=sep)


def dictionary(uris: DataFrame, col: str = "uri") -> DataFrame:
    """(uri, id) with 64-bit hashes as ids; URIs whose hashes collide are told apart by rank in a reserved range."""
    d = uris.select(F.col(col).alias("uri")).where("uri is not null").distinct().withColumn("h", F.xxhash64("uri"))
    return d.withColumn("nth", F.expr("row_number() over (partition by h order by uri)")).select("uri", F.when(F.col("nth") == 1, F.col("h")).otherwise(F.xxhash64("uri", "nth")).alias("id"))


def resolve_links(links: DataFrame, ids: DataFrame) -> DataFrame:
    a, b = ids.select(F.col("uri").alias("src_uri"), F.col("id").alias("x")), ids.select(F.col("uri").alias("dst_uri"), F.col("id").alias("y"))
    return links.join(a, "src_uri").join(b, "dst_uri").select(F.least("x", "y").alias("src"), F.greatest("x", "y").alias("dst"))
