"""Entity tables derived from the given tables by integer arithmetic and md5.

The column expressions are plain SQL that Spark and other engines read alike, so the same
recipe builds the entities and the checks against them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

# How hexadecimal digits become letters.
DIGITS, LETTERS = "0123456789abcdef", "bdfgklmnprstvzae"
SIZES = 820


def _name(k: str) -> str:
    return f"translate(substr(md5(cast({k} AS STRING)), 1, 8), '{DIGITS}', '{LETTERS}')"


GEO_NAME = f"CASE WHEN k % 41 = 40 THEN {_name('k - 1')} WHEN k % 23 = 22 THEN substr({_name('k - 1')}, 1, 6) || substr({_name('k')}, 1, 2) ELSE {_name('k')} END"
GEO_HOME = "CASE WHEN k % 41 = 40 OR k % 23 = 22 THEN k - 1 ELSE k END"
GEO_SIZE = f"CASE WHEN (37 * (k % {SIZES})) % {SIZES} < 706 THEN 4 WHEN (37 * (k % {SIZES})) % {SIZES} < 745 THEN 3 WHEN (37 * (k % {SIZES})) % {SIZES} < 783 THEN 2 ELSE 1 END"
GEO_LABEL = (
    "CASE WHEN s = 1 AND k % 29 = 0 THEN reverse(name) WHEN s = 1 THEN name || ' (nation ' || cast(nation AS STRING) || ')' "
    "WHEN s = 2 AND k % 3 = 0 THEN substr(name, 1, 2) || substr(name, 4, 1) || substr(name, 3, 1) || substr(name, 5) "
    "WHEN s = 3 AND k % 5 = 0 THEN substr(name, 1, 6) ELSE name END"
)
GEO_LAT = (
    "CASE WHEN s = 2 AND k % 17 = 0 THEN cast(NULL AS DOUBLE) ELSE cast((7919 * home) % 14000 AS DOUBLE) / 100 - 70 + cast((31 * k + 17 * s) % 10 AS DOUBLE) / 1000 "
    "+ (CASE WHEN home <> k THEN cast(0.3 AS DOUBLE) ELSE cast(0 AS DOUBLE) END) + (CASE WHEN s = 3 AND k % 11 = 0 THEN cast(2.5 AS DOUBLE) ELSE cast(0 AS DOUBLE) END) END"
)
GEO_LON = "CASE WHEN s = 2 AND k % 17 = 0 THEN cast(NULL AS DOUBLE) ELSE cast((104729 * home) % 36000 AS DOUBLE) / 100 - 180 + cast((13 * k + 7 * s) % 10 AS DOUBLE) / 1000 END"
GEO_TYPE = "CASE WHEN (k + s) % 7 = 0 THEN NULL WHEN k % 97 = 5 AND s = 0 THEN 'island' WHEN k % 13 = 0 THEN 'settlement|harbour' WHEN s = 0 THEN 'city' WHEN s = 1 THEN 'town' WHEN s = 2 THEN 'suburb' ELSE 'settlement' END"


#: Entities of a fifth source, one for each supplier and equal to the customer of that key, are numbered from here.
FIFTH = 1 << 40
GEO_ID = f"CASE WHEN s = 4 THEN {FIFTH} + k ELSE k * 4 + s END"
GEO_SOURCE = "ABCDE"


def geo_rows(customer: DataFrame, limit_key: int | None = None, supplier: DataFrame | None = None) -> DataFrame:
    """Flat geographic entities; ``limit_key`` None takes every customer, SIZES is the published small size; ``supplier`` adds a fifth source."""
    c = customer.select(F.col("c_custkey").cast("bigint").alias("k"), F.col("c_nationkey").alias("nation"))
    c = c if limit_key is None else c.where(F.col("k") < limit_key)
    d = c.withColumn("s", F.explode(F.sequence(F.lit(0), F.lit(3))))
    if supplier is not None:
        d = d.unionByName(supplier.select(F.col("s_suppkey").cast("bigint").alias("k"), F.col("s_nationkey").alias("nation"), F.lit(4).alias("s")))
    d = d.withColumn("name", F.expr(GEO_NAME)).withColumn("home", F.expr(GEO_HOME)).withColumn("size", F.expr(GEO_SIZE)).where("s = 4 OR (s + k) % 4 < size")
    return d.select(
        F.expr(GEO_ID).alias("id"), F.col("k").alias("gold"), F.substring(F.lit(GEO_SOURCE), F.col("s") + 1, F.lit(1)).alias("source"), F.expr(GEO_LABEL).alias("label"), F.expr(GEO_TYPE).alias("raw_type"), F.expr(GEO_LAT).alias("lat"), F.expr(GEO_LON).alias("lon")
    )


def geo_entities(spark: SparkSession, sf_dir: str, limit_key: int | None = None, fifth: bool = False) -> DataFrame:
    d = geo_rows(spark.read.parquet(f"{sf_dir}/customer.parquet"), limit_key, spark.read.parquet(f"{sf_dir}/supplier.parquet") if fifth else None)
    types = F.coalesce(F.split("raw_type", r"\|"), F.array().cast("array<string>"))
    return d.withColumn("types", types).withColumn("props", F.create_map(F.lit("raw_type"), F.col("raw_type"))).select("id", "gold", "source", "label", "types", "lat", "lon", "props")


def geo_sql(limit_key: int | None = None, fifth: bool = False) -> str:
    """The same rows as a query for another engine: id, gold, source, label (normalised), raw_type, lat, lon."""
    only = "" if limit_key is None else f"WHERE c_custkey < {limit_key}"
    more = " UNION ALL SELECT s_suppkey::BIGINT, s_nationkey, 4 FROM supplier" if fifth else ""
    return (
        f"SELECT {GEO_ID} AS id, k AS gold, substr('{GEO_SOURCE}', (s + 1)::INT, 1) AS source, trim(regexp_replace(regexp_replace(lower({GEO_LABEL}), '[\\(\\[\\{{][^\\)\\]\\}}]*[\\)\\]\\}}]', ' ', 'g'), '\\s+', ' ', 'g')) AS label, "
        f"{GEO_TYPE} AS raw_type, {GEO_LAT} AS lat, {GEO_LON} AS lon FROM (SELECT *, {GEO_NAME} AS name, {GEO_HOME} AS home, {GEO_SIZE} AS size "
        f"FROM (SELECT c_custkey::BIGINT AS k, c_nationkey AS nation, unnest([0, 1, 2, 3]) AS s FROM customer {only}{more})) WHERE s = 4 OR (s + k) % 4 < size"
    )


def _word(k: str, at: int) -> str:
    return f"translate(substr(md5(cast({k} AS STRING)), {at}, 6), '{DIGITS}', '{LETTERS}')"


def _two(k: str) -> str:
    """An artist of two words."""
    return f"{_word(k, 7)} || ' ' || {_word(k, 20)}"


#: For each table: its key, and the texts behind title, artist and album as SQL over the table.  Five songs in a row
#: share an artist and every eighth song the album of the song before; no word is common to all.
MUSIC_TABLES = {
    "part": ("cast(p_partkey AS BIGINT)", "p_name", _two("p_partkey - p_partkey % 5"), f"p_type || ' ' || {_word('CASE WHEN p_partkey % 8 = 7 THEN p_partkey - 1 ELSE p_partkey END', 13)}"),
    "orders": ("cast(o_orderkey AS BIGINT)", _word("o_custkey", 1), _two("o_orderkey - o_orderkey % 5"), _word("CASE WHEN o_orderkey % 8 = 7 THEN o_orderkey - 1 ELSE o_orderkey END", 13)),
    "lineitem": ("((8 * cast(l_orderkey AS BIGINT) + l_linenumber) * 262144 + l_partkey) * 4096 + l_suppkey", _word("l_partkey", 1), _two("l_suppkey"), _word("l_orderkey", 13)),
}
MUSIC_SIZE = "CASE WHEN q < 8 THEN 1 WHEN q < 12 THEN 2 WHEN q < 14 THEN 3 WHEN q < 15 THEN 4 ELSE 5 END"
MUSIC_TITLE = (
    f"CASE WHEN c = 1 AND k % 5 = 0 THEN reverse(full) WHEN c = 2 THEN substr(full, 1, 2) || substr(full, 4, 1) || substr(full, 3, 1) || substr(full, 5) WHEN c = 3 THEN base || ' ' || {_word('k', 9)} ELSE full END"
)
MUSIC_ARTIST = "CASE WHEN c = 1 AND k % 5 = 0 THEN reverse(artist0) WHEN c = 4 THEN substr(artist0, 1, 7) ELSE artist0 END"
MUSIC_ALBUM = "CASE WHEN (k + c) % 7 = 0 THEN NULL ELSE album0 END"
MUSIC_YEAR = "CASE c % 3 WHEN 0 THEN '''' || substr(cast(1990 + k % 30 AS STRING), 3, 2) WHEN 1 THEN substr(cast(1990 + k % 30 AS STRING), 3, 2) ELSE cast(1990 + k % 30 AS STRING) END"
MUSIC_LENGTH = (
    "CASE c % 4 WHEN 0 THEN cast(cast(floor((120 + k % 200) / 60) AS INT) AS STRING) || 'm ' || cast((120 + k % 200) % 60 AS STRING) || 'sec' "
    "WHEN 1 THEN lpad(cast(cast(floor((120 + k % 200) / 60) AS INT) AS STRING), 2, '0') || ':' || lpad(cast((120 + k % 200) % 60 AS STRING), 2, '0') "
    "WHEN 2 THEN cast((120 + k % 200) * 1000 AS STRING) ELSE cast(cast(floor((120 + k % 200) * 10000 / 60) AS INT) / 10000 AS STRING) END"
)


def music_rows(table: DataFrame, name: str) -> DataFrame:
    key, title, artist, album = MUSIC_TABLES[name]
    q = "k % 16" if name != "lineitem" else f"instr('{DIGITS}', substr(md5(cast(k AS STRING)), 1, 1)) - 1"
    d = table.select(F.expr(key).alias("k"), F.expr(title).alias("base"), F.expr(artist).alias("artist0"), F.expr(album).alias("album0"))
    d = d.withColumn("q", F.expr(q)).withColumn("full", F.expr(f"base || ' ' || {_word('k', 1)} || ' ' || {_word('k', 9)}"))
    d = d.withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(4)))).where(f"c < ({MUSIC_SIZE})")
    return d.select(
        (F.col("k") * 5 + F.col("c")).alias("id"), F.col("k").alias("gold"), F.substring(F.lit("ABCDE"), ((F.col("k") + F.col("c")) % 5 + 1).cast("int"), F.lit(1)).alias("source"),
        F.expr(MUSIC_TITLE).alias("title"), F.expr(MUSIC_ARTIST).alias("artist"), F.expr(MUSIC_ALBUM).alias("album"), F.expr(MUSIC_YEAR).alias("year"), F.expr(MUSIC_LENGTH).alias("length"),
        F.element_at(F.array(F.lit("english"), F.lit("french"), F.lit("german")), (F.col("k") % 3 + 1).cast("int")).alias("language"), F.concat(F.lit("no "), (F.col("k") % 12 + 1).cast("string")).alias("number"),
    )


def music_entities(spark: SparkSession, sf_dir: str, name: str = "part") -> DataFrame:
    """Music entities with the label set to the title, so every operator applies."""
    d = music_rows(spark.read.parquet(f"{sf_dir}/{name}.parquet"), name)
    return d.withColumn("label", F.col("title")).withColumn("types", F.array().cast("array<string>")).withColumn("lat", F.lit(None).cast("double")).withColumn("lon", F.lit(None).cast("double"))


def music_sql(name: str) -> str:
    key, title, artist, album = MUSIC_TABLES[name]
    q = "k % 16" if name != "lineitem" else f"instr('{DIGITS}', substr(md5(cast(k AS STRING)), 1, 1)) - 1"
    return (
        f"SELECT k * 5 + c AS id, k AS gold, substr('ABCDE', ((k + c) % 5 + 1)::INT, 1) AS source, {MUSIC_TITLE} AS title, {MUSIC_ARTIST} AS artist, {MUSIC_ALBUM} AS album, {MUSIC_YEAR} AS year, {MUSIC_LENGTH} AS length "
        f"FROM (SELECT *, unnest([0, 1, 2, 3, 4]) AS c FROM (SELECT *, {q} AS q, base || ' ' || {_word('k', 1)} || ' ' || {_word('k', 9)} AS \"full\" FROM (SELECT {key} AS k, {title} AS base, {artist} AS artist0, {album} AS album0 FROM {name}))) WHERE c < ({MUSIC_SIZE})"
    ).replace("substr(full", 'substr("full"').replace("reverse(full)", 'reverse("full")').replace("ELSE full END", 'ELSE "full" END')


def doc_entities(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = spark.read.parquet(f"{sf_dir}/documents.parquet")
    words = F.slice(F.split(F.trim(F.regexp_replace(F.lower(F.coalesce("text", F.lit(""))), r"[^\p{L}\p{N}]+", " ")), " "), 1, 8)
    return d.select(F.col("doc_id").alias("id"), "source", F.array_join(words, " ").alias("label"), F.array("lang").alias("types"), F.lit(None).cast("double").alias("lat"), F.lit(None).cast("double").alias("lon"), F.create_map(F.lit("n_chars"), F.col("n_chars").cast("string")).alias("props"))


def page_entities(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = spark.read.parquet(f"{sf_dir}/pages.parquet")
    return p.select(F.col("page_id").alias("id"), F.regexp_extract("url", r"://([^/]+)", 1).alias("source"), F.regexp_extract("html", r"<title>([^<]*)</title>", 1).alias("label"), F.array(F.regexp_extract("url", r"://[^/]+/([a-z]{2})/", 1)).alias("types"), "url")


def running_example(spark: SparkSession) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(vertices, links, intra-cluster similarities) of the seven-entity example."""
    v = [(1, "A", "l1", []), (2, "B", "l1", ["t1"]), (3, "C", "l3", ["t2"]), (4, "D", "l3", ["t2"]), (5, "C", "l1", ["t1"]), (6, "D", "l1", ["t1"]), (7, "A", "z7", ["t1"])]
    links = [(1, 2), (1, 3), (1, 4), (3, 4), (5, 6), (5, 7)]
    sims = [(1, 1, 2, 1.0), (1, 1, 3, 0.8), (1, 1, 4, 0.8), (1, 3, 4, 0.9), (1, 2, 3, 0.5), (1, 2, 4, 0.5), (5, 5, 6, 0.9), (5, 5, 7, 0.4), (5, 6, 7, 0.3)]
    vertices = spark.createDataFrame([(i, s, x, t, None, None) for i, s, x, t in v], "id bigint, source string, label string, types array<string>, lat double, lon double")
    return vertices, spark.createDataFrame(links, "src bigint, dst bigint"), spark.createDataFrame(sims, "cid bigint, src bigint, dst bigint, sim double")
