"""Link discovery: the configurations that give the workflow its input links.

Candidates come from equi-joins on keys that follow exactly from the thresholds, so a
configuration gives the same links as comparing all cross-source pairs:

* a label bound is a similarity join on Jaro-Winkler (``functions/close_labels.py``);
* a mean bound of t with labels of 1 at most means a distance bound, hence tiles, and leaves a label bound to each
  pair in reach (``functions/near_pairs.py``).
"""

from __future__ import annotations

from functools import reduce
from math import ceil

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkcluster.functions import geo, tfidf
from linkcluster.functions.close_labels import SLACK, close_labels
from linkcluster.functions.near_pairs import near_pairs
from linkcluster.functions.strings import jaro_winkler
from linkcluster.plans.iterate import release, written

def label_candidates(v: DataFrame, bound: float) -> DataFrame:
    """(src, dst, label_sim) cross-source pairs of at least that Jaro-Winkler similarity.

    Distinct labels are compared once; pairs of labels are widened to entities at the end.
    """
    scored = close_labels(v, bound).withColumnRenamed("sim", "label_sim")
    same = v.select("label").distinct().where(F.char_length("label") > 0).select(F.col("label").alias("x"), F.col("label").alias("y"), F.lit(1.0).alias("label_sim"))
    both = scored.unionByName(scored.select(F.col("y").alias("x"), F.col("x").alias("y"), "label_sim")).unionByName(same)
    e = v.select("id", "source", "label")
    left = e.select(F.col("id").alias("src"), F.col("source").alias("s1"), F.col("label").alias("x"))
    right = e.select(F.col("id").alias("dst"), F.col("source").alias("s2"), F.col("label").alias("y"))
    return left.join(written(both), "x").join(right, "y").where("src < dst and s1 <> s2").select("src", "dst", "label_sim")


def geo_candidates(v: DataFrame, km: float) -> DataFrame:
    """Cross-source pairs within ``km``, with both labels and the distance similarity."""
    p = v.where("lat is not null and lon is not null").select("id", "source", "label", "lat", "lon")
    row, col, _ = geo.cell(F.col("lat"), F.col("lon"), km)
    home = p.select(row.alias("row"), col.alias("col"), *[F.col(c).alias(f"r_{c}") for c in p.columns])
    spread = p.select(F.explode(geo.neighbour_cells(F.col("lat"), F.col("lon"), km)).alias("cell"), *[F.col(c).alias(f"l_{c}") for c in p.columns]).select("cell.row", "cell.col", *[f"l_{c}" for c in p.columns])
    near = spread.join(home, ["row", "col"]).where("l_id < r_id and l_source <> r_source")
    near = near.withColumn("geo_sim", geo.geo_similarity(F.col("l_lat"), F.col("l_lon"), F.col("r_lat"), F.col("r_lon"))).where(F.col("geo_sim") >= 1 - km / geo.MAX_KM - SLACK)
    return near.dropDuplicates(["l_id", "r_id"])


def discover(v: DataFrame, config: str) -> DataFrame:
    """(src, dst, sim) links of ``config1``, ``config2``, ``config3`` or ``music``."""
    if config == "config1":
        return label_candidates(v, 0.9).where(F.col("label_sim") >= 0.9).select("src", "dst", F.col("label_sim").alias("sim"))
    if config in ("config2", "config3"):
        bound = 0.85 if config == "config2" else 0.9
        at = v.select("id", "lat", "lon")
        near = near_pairs(v, bound, "source").join(at.select(F.col("id").alias("l_id"), F.col("lat").alias("l_lat"), F.col("lon").alias("l_lon")), "l_id").join(at.select(F.col("id").alias("r_id"), F.col("lat").alias("r_lat"), F.col("lon").alias("r_lon")), "r_id")
        near = near.withColumn("sim", (F.col("label_sim") + geo.geo_similarity(F.col("l_lat"), F.col("l_lon"), F.col("r_lat"), F.col("r_lon"))) / 2)
        return near.where(F.col("sim") >= bound).select(F.col("l_id").alias("src"), F.col("r_id").alias("dst"), "sim")
    if config == "music":
        return music_links(v)
    raise ValueError(config)


#: Entity pairs, as many as the meetings of leading tokens with close ones bring at most, that one turn of ``music_links`` takes up.
TURN = 12_000_000


def music_links(v: DataFrame, weights=(("title", 0.6), ("artist", 0.3), ("album", 0.1)), bound: float = 0.35, theta: float = 0.9, apart: float = 0.05) -> DataFrame:
    """Weighted soft TF/IDF over three properties; distinct values are compared once.

    A pair reaches the bound with a second property of at least ``apart``, or else with a first one of at least
    (bound - third weight - apart * second weight) / first weight.  Both kinds of pairs come from the properties' indexes; the
    missing similarities are then measured for these pairs alone, in turns that keep what is held at once small.
    """
    (first, w1), (second, w2), (third, w3) = weights

    def values(col: str) -> DataFrame:
        return v.where(F.col(col).isNotNull()).select(F.col(col).alias("value")).distinct().withColumn("vid", F.xxhash64("value"))

    ids = written(v.select("id", "source", *[F.when(F.col(c).isNotNull(), F.xxhash64(c)).alias(c) for c, _ in weights]))
    left, right = (ids.select(*[F.col(c).alias(f"{p}_{c}") for c in ids.columns]) for p in "lr")
    indexes = {c: tfidf.index(values(c), theta) for c, _ in weights}
    least = {first: (bound - w3 - apart * w2) / w1, second: apart}
    led = {c: indexes[c].led(x) for c, x in least.items()}
    often = ids.agg(*[(F.count(c) / F.greatest(F.lit(1), F.countDistinct(c))).alias(c) for c in led]).first()
    turns = max(1, *(ceil(indexes[c].meetings(x) * often[c] ** 2 / TURN) for c, x in led.items()))

    def seeds(col: str, turn: int) -> DataFrame:
        """Entity pairs of the turn, with the similarity of that property."""
        s = indexes[col].reaching(least[col], led[col], turn, turns).withColumnRenamed("sim", f"s_{col}")
        mine = ids.select(F.col(col).alias("va")).where(F.pmod(F.xxhash64(col, F.lit(29)), F.lit(turns)) == turn).distinct()
        same = mine.select("va", F.col("va").alias("vb"), F.lit(1.0).alias(f"s_{col}"))
        p = s.select("va", "vb", f"s_{col}").unionByName(s.select(F.col("vb").alias("va"), F.col("va").alias("vb"), f"s_{col}")).unionByName(same)
        p = p.join(left, F.col("va") == F.col(f"l_{col}")).join(right, F.col("vb") == F.col(f"r_{col}"))
        return p.where("l_id < r_id and l_source <> r_source").drop("va", "vb")

    def measured(pairs: DataFrame, col: str) -> DataFrame:
        a, b = F.col(f"l_{col}"), F.col(f"r_{col}")
        named = pairs.withColumn("va", F.least(a, b)).withColumn("vb", F.greatest(a, b))
        known = indexes[col].of(named.where(a != b).select("va", "vb").distinct()).withColumnRenamed("sim", f"s_{col}")
        return named.join(known, ["va", "vb"], "left").withColumn(f"s_{col}", F.when(a == b, F.lit(1.0)).when(a.isNull() | b.isNull(), F.lit(0.0)).otherwise(F.coalesce(f"s_{col}", F.lit(0.0)))).drop("va", "vb")

    total = lambda *known: sum((F.col(f"s_{c}") * w if c in known else F.lit(w) for c, w in weights), F.lit(0.0))
    out = []
    for turn in range(turns):
        for col, rest in ((first, (second, third)), (second, (first, third))):
            pairs = written(seeds(col, turn))
            known = [col]
            for c in rest:
                known.append(c)
                more = written(measured(pairs, c).where(total(*known) >= bound - tfidf.SLACK))
                release(pairs)
                pairs = more
            out.append(written(pairs.withColumn("sim", total(*known)).where(F.col("sim") >= bound).select(F.col("l_id").alias("src"), F.col("r_id").alias("dst"), "sim")))
            release(pairs)
    # a pair may come from both properties
    return reduce(DataFrame.unionByName, out).groupBy("src", "dst").agg(F.max("sim").alias("sim"))


def star_from_gold(gold: DataFrame) -> DataFrame:
    """The first entity of each gold cluster linked to all its others."""
    first = gold.withColumn("src", F.expr("min(id) over (partition by gold)"))
    return first.where("id <> src").select("src", F.col("id").alias("dst"), F.lit(None).cast("double").alias("sim"))


def gold_links(gold: DataFrame) -> DataFrame:
    a, b = gold.select(F.col("id").alias("src"), "gold", F.col("source").alias("s1")), gold.select(F.col("id").alias("dst"), "gold", F.col("source").alias("s2"))
    return a.join(b, "gold").where("src < dst").select("src", "dst", "s1", "s2")


def restrict_source_pairs(links: DataFrame, pairs: list[tuple[str, str]]) -> DataFrame:
    """Links (with s1, s2) between the given source pairs only."""
    p = links.sparkSession.createDataFrame([tuple(sorted(x)) for x in pairs], "p string, q string")
    keyed = links.withColumn("p", F.least("s1", "s2")).withColumn("q", F.greatest("s1", "s2"))
    return keyed.join(F.broadcast(p), ["p", "q"], "left_semi").drop("p", "q")


def exhaustive(v: DataFrame, config: str, row_cap: int = 20_000) -> DataFrame:
    """All cross-source pairs compared: the baseline and the oracle; above ``row_cap`` entities the joins of ``discover`` find the same links."""
    if v.limit(row_cap + 1).count() > row_cap:
        return discover(v, config)
    cols = ("id", "source", "label", "lat", "lon")
    p = v.select(*[F.col(c).alias(f"l_{c}") for c in cols]).crossJoin(v.select(*[F.col(c).alias(f"r_{c}") for c in cols])).where("l_id < r_id and l_source <> r_source")
    s = jaro_winkler(F.col("l_label"), F.col("r_label"))
    if config != "config1":
        s = (s + geo.geo_similarity(F.col("l_lat"), F.col("l_lon"), F.col("r_lat"), F.col("r_lon"))) / 2
    bound = {"config1": 0.9, "config2": 0.85, "config3": 0.9}[config]
    return p.withColumn("sim", s).where(F.col("sim") >= bound).select(F.col("l_id").alias("src"), F.col("r_id").alias("dst"), "sim")
