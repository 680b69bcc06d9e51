import os
import random
import time
import urllib.parse

from pyspark.sql import functions as F

from linkcluster import queries as q
from linkcluster.functions import close_labels, tfidf
from linkcluster.functions.strings import jaro_winkler_batch
from linkcluster.operators import linking, representative
from linkcluster.plans import iterate


def test_all_pairs_of_values_shuffle_no_copies(spark, monkeypatch):
    """With no bound parts of both sides meet by being read again, so what is shuffled grows with the values and not with the tiles."""
    monkeypatch.setattr(tfidf, "TILE_ROWS", 20)
    monkeypatch.setattr(tfidf, "HITS", 40)
    rng = random.Random(5)
    words = ["promo", "promos", "steel", "steal", "brushed", "tin", "copper", "coper"]
    values = sorted({" ".join(rng.choice(words) for _ in range(rng.randrange(1, 5))) for _ in range(60)})
    found = tfidf.index(spark.createDataFrame([(x, x) for x in values], "vid string, value string"), 0.85)
    got = found.all_pairs()
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" in plan and "Exchange" not in plan
    plain = found.score(found._side("a").join(found.close, "ta").join(found._side("b"), "tb").where("va < vb"))
    rows = lambda d: {(r.va, r.vb): round(r.sim, 9) for r in d.collect()}
    assert rows(got) == rows(plain) and len(rows(got)) == got.agg(F.count(F.lit(1))).first()[0] > 300


def _shuffle_files(spark):
    dirs = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirs()
    return {f for d in dirs for _, _, names in os.walk(d.getPath()) for f in names if f.startswith("shuffle_")}


def test_shuffle_files_end_with_a_written_state_and_states_can_be_released(spark):
    before = _shuffle_files(spark)
    v = iterate.written(spark.range(1000).withColumn("k", F.col("id") % 7).repartition(8, "k"))
    for _ in range(50):
        if _shuffle_files(spark) <= before:
            break
        time.sleep(0.1)
    assert _shuffle_files(spark) <= before and spark.conf.get(iterate.CLEANUP) == "false" and v.count() == 1000
    folder = urllib.parse.urlparse(v.inputFiles()[0].rsplit("/", 1)[0]).path
    assert os.path.isdir(folder)
    iterate.release(spark.range(3), v)
    assert not os.path.exists(folder)


def test_labels_have_few_keys_and_rare_lengths_none(spark, monkeypatch):
    """A word of six letters has half the keys it had; words of rare lengths are compared with all, and no close pair is lost."""
    rng = random.Random(3)
    words = {"".join(rng.choice("abcd") for _ in range(n)) for n in (5, 6, 7) for _ in range(60)} | {"abc", "abcdabcd", "abcdabcdabcd"}
    words = sorted(words | {w[:2] + w[3:] + w[2] for w in words})
    pairs = [(a, b) for a in words for b in words if a < b]
    sims = jaro_winkler_batch([a for a, _ in pairs], [b for _, b in pairs])
    want = {p for p, s in zip(pairs, sims) if s >= 0.9}
    for rare in (0, 8, 200):
        monkeypatch.setattr(close_labels, "RARE", rare)
        got = close_labels.close_labels(spark.createDataFrame([(w,) for w in words], "label string"), 0.9).where("sim >= 0.9")
        assert {(r.x, r.y) for r in got.collect()} == want and len(want) > 100
    assert len(close_labels.subset_keys("bdfgkl", 0.9)) < 40 and len(close_labels.subset_keys("bdfgkl", 0.9, frozenset([6]))) < 10


def test_music_links_in_turns(spark, sf, monkeypatch):
    """Several turns give the links of one, and given pairs are measured without a join to close tokens."""
    v = q.music_vertices(spark, sf).where("gold < 80")
    rows = lambda d: {(r.src, r.dst): round(r.sim, 9) for r in d.collect()}
    one = rows(linking.music_links(v))
    monkeypatch.setattr(linking, "TURN", 400)
    states = []
    monkeypatch.setattr(linking, "release", lambda *d: states.extend(d))
    assert rows(linking.music_links(v)) == one and len(one) > 60 and len(states) > 12
    values = v.select(F.col("title").alias("value")).distinct().withColumn("vid", F.col("value"))
    found = tfidf.index(values)
    pairs = values.select(F.col("vid").alias("va")).crossJoin(values.select(F.col("vid").alias("vb"))).where("va < vb")
    plain = found.score(pairs.join(found._side("a"), "va").join(found.close, "ta").join(found._side("b"), ["vb", "tb"]))
    sims = lambda d: {(r.va, r.vb): round(r.sim, 9) for r in d.collect()}
    assert sims(found.of(pairs)) == sims(plain) and len(sims(plain)) > 100


def test_representatives_deal_entities_out_once(spark):
    """Labels are counted where a cluster's rows are: the entities are shuffled to their ids and to their clusters, and no more."""
    v = spark.createDataFrame([(1, "A", "x", [], 1.0, 2.0), (2, "B", "yy", [], None, None), (3, "C", "x", [], 3.0, 4.0), (4, "D", None, [], None, None), (5, "E", None, [], None, None), (6, "F", None, [], None, None)], "id bigint, source string, label string, types array<string>, lat double, lon double")
    a = spark.createDataFrame([(i, 1) for i in range(1, 7)], "id bigint, cid bigint")
    got = representative.build(a, v)
    assert got._jdf.queryExecution().optimizedPlan().toString().count("Join") == 1
    r = got.first()
    assert (r.label, r.members, r.n, r.lat) == ("x", [1, 2, 3, 4, 5, 6], 6, 1.0)
