"""Readers, writers, switches and helpers that no other test reaches."""

import json
import random

import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import reference_impl as ref
from linkcluster import queries
from linkcluster.functions import compose
from linkcluster.operators import blocking, components, intra, linking, merge, preprocess, relational, typegroup
from linkcluster.plans import iterate, workflow
from linkcluster.plans.config import ClusterConfig
from linkcluster.sources import fixtures, readers, sinks
from linkcluster.streaming import incremental


@pytest.fixture(scope="module")
def geo(spark, sf):
    v = iterate.written(fixtures.geo_entities(spark, sf, 60))
    return v, iterate.written(linking.restrict_source_pairs(linking.gold_links(v), [("A", "B"), ("A", "C"), ("A", "D")]).select("src", "dst"))


def clusters(result):
    return {r.id: r.cid for r in result.assign.collect()}


def test_distributed_sides_give_the_same_clusters(geo, monkeypatch):
    v, links = geo
    want = clusters(workflow.cluster(v, links))
    monkeypatch.setattr(components, "ONE_TASK_LINKS", 0)
    monkeypatch.setattr(merge.loop, "__defaults__", (*merge.loop.__defaults__[:2], 0))
    r = workflow.cluster(v, links, ClusterConfig(giant_cap=2, block_cap=3))
    assert clusters(r) == want and "work" in r.rounds["merge"][0]


def test_blocking_on_expressions_and_rounds(geo, tmp_path):
    v, links = geo
    keyed = workflow.cluster(v, links, ClusterConfig(block_on=("substring(label, 1, 3)",), dump_dir=str(tmp_path / "dump")))
    assert clusters(keyed) == clusters(workflow.cluster(v, links))
    assert json.loads(next((tmp_path / "dump" / "representatives").glob("part-*.json")).read_text().splitlines()[0])["members"]
    with pytest.raises(ValueError):
        workflow.blocked(v, ClusterConfig(block_on=("label", "source"), merge_strategy="grouped"))
    spark = v.sparkSession
    sinks.round_log(spark, keyed.rounds, str(tmp_path / "log"))
    assert spark.read.json(str(tmp_path / "log")).where("phase = 'merge'").count() == len(keyed.rounds["merge"])
    workflow.register_views(keyed)
    assert spark.sql("SELECT count(*) AS n FROM assignments JOIN clusters USING (cid)").first().n == v.count()
    assert len(workflow.cluster(v, links, ClusterConfig(max_rounds=1, merge_strategy="dominant")).rounds["merge"]) <= 1
    unique = workflow.cluster(v, links.unionByName(spark.createDataFrame([(0, 4), (4, 9)], "src bigint, dst bigint")), ClusterConfig(require_unique_sources=True, use_merge=False, use_types=False))
    assert unique.assign.join(v, "id").groupBy("cid", "source").count().where("count > 1").count() == 0


def test_merge_stops_after_max_rounds(spark):
    rows = [("b", 1, 2, 900000000, ["A"], ["B"], 1, 1, 1, 2), ("b", 2, 3, 800000000, ["B"], ["C"], 1, 1, 2, 3), ("b", 1, 3, 700000000, ["A"], ["C"], 1, 1, 1, 3)]
    work = spark.createDataFrame(rows, "block string, l bigint, r bigint, g bigint, sl array<string>, sr array<string>, nl int, nr int, ol bigint, orr bigint")
    a = spark.createDataFrame([(i, i) for i in (1, 2, 3)], "id bigint, cid bigint")
    for strategy in ("block_best", "dominant", "auto"):
        got, log = merge.run(a, None, work, 3, strategy, max_rounds=1)
        assert {r.id: r.cid for r in got.collect()} == {1: 1, 2: 1, 3: 3} and len(log) == 1, strategy
    assert {r.cid for r in merge.run(a, None, work, 3, "dominant")[0].collect()} == {1}


def test_giant_components_are_tiled(spark):
    rng = random.Random(3)
    v = spark.createDataFrame([(i, "ABC"[i % 3], "".join(rng.choice("ab") for _ in range(6))) for i in range(70)], "id bigint, source string, label string")
    a = spark.createDataFrame([(i, 0 if i < 60 else 60) for i in range(70)], "id bigint, cid bigint")
    for scope in ("all", "cross_source"):
        want = sorted(intra.scored_pairs(a, v, compose.LABEL_LEVENSHTEIN, scope).collect())
        assert want == sorted(intra.scored_pairs(a, v, compose.LABEL_LEVENSHTEIN, scope, cap=7).collect()) and len(want) > 1000


def test_type_switches(spark):
    c = lambda a, b, null: spark.createDataFrame([(a, b)], "a array<string>, b array<string>").select(preprocess.compatible(F.col("a"), F.col("b"), null).alias("x")).first().x
    assert c([], ["t"], "wildcard") and not c([], ["t"], "distinct") and c([], [], "distinct") and not c(["s"], ["t"], "wildcard")
    v = spark.createDataFrame([(1, ["s", "h"]), (2, ["s"]), (3, ["h", "s"]), (4, ["h"])], "id bigint, types array<string>")
    a = v.select("id", F.lit(1).cast("bigint").alias("cid"))
    assert {r.id: r.tcid for r in typegroup.typed_groups(a, v, "exact").collect()} == {1: 1, 2: 2, 3: 1, 4: 4}
    assert {r.tcid for r in typegroup.typed_groups(a, v).collect()} == {1}


def test_homonym_with_a_wrong_link(spark, sf):
    """Two towns of one name, one of them under an alias: the wrong link falls, and they stay apart."""
    v = fixtures.geo_entities(spark, sf, 90).where("gold in (39, 40, 80, 81)")
    gold = linking.gold_links(v).select("src", "dst")
    wrong = spark.createDataFrame([(39 * 4, 40 * 4 + 1)], "src bigint, dst bigint")
    r = workflow.cluster(v, gold.unionByName(wrong)).assign.join(v.select("id", "gold"), "id")
    assert r.groupBy("cid").agg(F.countDistinct("gold").alias("k")).where("k > 1").count() == 0


def test_five_sources_and_incomplete_links(spark, sf):
    """Every customer's and supplier's entity is in the run, ids are unique, and a share of the links is known."""
    v, links, _ = queries.WORKLOADS["workflow_geo_five"](spark, sf)
    _, every, _ = queries._geo_large(spark, sf, fifth=True)
    four = fixtures.geo_entities(spark, sf)
    assert v.where("source <> 'E'").select("id", "label").exceptAll(four.select("id", "label")).count() == 0
    assert v.where("source = 'E'").count() == spark.read.parquet(f"{sf}/supplier.parquet").count()
    n = v.count()
    assert n == four.count() + v.where("source = 'E'").count() == v.select("id").distinct().count()
    assert links.exceptAll(every).count() == 0 and 0.3 < links.count() / every.count() < 0.5


def test_rescored_merge_matches_sequential(spark):
    """Fused representatives are measured anew: the longest label of a cluster stands for it."""
    rng = random.Random(5)
    rows = [(i, rng.choice("ABCDE"), "abc" + "".join(rng.choice("xy") for _ in range(rng.randint(2, 5)))) for i in range(14)]
    v = spark.createDataFrame([(i, s, x, [], None, None) for i, s, x in rows], "id bigint, source string, label string, types array<string>, lat double, lon double")
    a = v.select("id", F.col("id").alias("cid"))
    from linkcluster.operators import representative

    got, _ = merge.rescored_loop(representative.build(a, v, "longest"), v, a, lambda r: blocking.prefix(r, 3), compose.LABEL_LEVENSHTEIN, 0.7, 4, "longest", "of_label_owner")

    def distance(x, y):
        d = list(range(len(y) + 1))
        for i, p in enumerate(x, 1):
            last, d[0] = d[0], i
            for j, q in enumerate(y, 1):
                last, d[j] = d[j], min(d[j] + 1, d[j - 1] + 1, last + (p != q))
        return 1 - d[-1] / max(len(x), len(y))

    state = {i: (frozenset(s), (x, i), (i,)) for i, s, x in rows}
    while True:
        best = None
        for p in state:
            for q in state:
                (s, (x, _), m), (t, (y, _), n) = state[p], state[q]
                if p < q and not s & t and len(m) + len(n) <= 4 and distance(x, y) >= 0.7 - 1e-12:
                    best = max(best or (0,), (round(distance(x, y) * 1e9), -p, -q))
        if not best:
            break
        _, p, q = best[0], -best[1], -best[2]
        (s, x, m), (t, y, n) = state[p], state.pop(q)
        state[p] = (s | t, max(x, y, key=lambda z: (len(z[0]), -z[1])), m + n)
    assert {r.id: r.cid for r in got.collect()} == {i: c for c, (_, _, m) in state.items() for i in m}


def test_readers_and_writers(spark, sf, tmp_path):
    v = fixtures.geo_entities(spark, sf, 20)
    sinks.write(v.drop("gold"), str(tmp_path / "v"), "json")
    back = readers.json_entities(spark, str(tmp_path / "v"))
    assert sorted((r.id, r.label, r.types) for r in back.collect()) == sorted((r.id, r.label, r.types) for r in v.collect())
    (tmp_path / "links.csv").write_text("src,dst,sim\n1,2,0.5\n3,4,\n")
    assert [tuple(r) for r in readers.csv_links(spark, str(tmp_path / "links.csv")).collect()] == [(1, 2, 0.5), (3, 4, None)]
    (tmp_path / "uris").write_text("http://a/1 http://b/1\nhttp://b/1 http://c/1\n")
    u = readers.uri_links(spark, str(tmp_path / "uris"))
    ids = readers.dictionary(u.select(F.col("src_uri").alias("uri")).unionByName(u.select(F.col("dst_uri").alias("uri"))))
    assert readers.resolve_links(u, ids).where("src < dst").count() == 2
    links = linking.gold_links(v)
    sinks.links_by_source_pair(links, str(tmp_path / "m"))
    one = spark.read.parquet(str(tmp_path / "m")).where("mapping = 'A-B'")
    assert one.count() == links.where("s1 = 'A' and s2 = 'B'").count() and "PartitionFilters: [isnotnull(mapping" in one._jdf.queryExecution().toString()
    lines = [json.loads(r.value) for r in sinks.geojson_links(links.withColumn("sim", F.lit(1.0)), v).collect()]
    assert lines and all(x["geometry"]["type"] == "LineString" and len(x["geometry"]["coordinates"]) == 2 for x in lines)
    spark.sql("DROP TABLE IF EXISTS bucketed_clusters")
    sinks.bucketed(v.select("id", F.col("gold").alias("cid")), "bucketed_clusters", buckets=4)
    t = spark.table("bucketed_clusters")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = t.groupBy("cid").count()._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("DROP TABLE bucketed_clusters")
    assert "Exchange" not in plan


def test_relational_helpers(spark):
    left, right = spark.createDataFrame([(1, 2), (1, 3), (2, 5)], "k bigint, x bigint"), spark.createDataFrame([(1, 10), (3, 1)], "k bigint, y bigint")

    def total(a: pa.Table, b: pa.Table) -> pa.Table:
        key = (a if len(a) else b)["k"][0].as_py()
        return pa.table({"k": [key], "n": [sum(a["x"].to_pylist()) + sum(b["y"].to_pylist())]})

    assert {r.k: r.n for r in relational.cogroup_arrow(left, right, "k", total, "k bigint, n bigint").collect()} == {1: 15, 2: 5, 3: 1}
    assert sorted(tuple(r) for r in relational.pairs(left, "k", "x").collect()) == [(1, 2, 3)]
    d = spark.range(100).withColumn("g", F.col("id") % 3)
    s = relational.stratified_sample(d, "g", 5, "id")
    assert {r.g: r["count"] for r in s.groupBy("g").count().collect()} == {0: 5, 1: 5, 2: 5} and sorted(s.collect()) == sorted(relational.stratified_sample(d.orderBy(F.desc("id")), "g", 5, "id").collect())
    m = spark.createDataFrame([(["A", "C"],), ([],)], "s array<string>").select(relational.source_mask(F.col("s"), ["C", "A", "B"]).alias("m"))
    assert [r.m for r in m.collect()] == [5, 0]
    with pytest.raises(ValueError):
        relational.source_mask(F.col("s"), [str(i) for i in range(64)])
    assert relational.rank_in(d, ["g"], F.col("id"), kind="percent_rank").agg(F.max("rank")).first()[0] == 1.0


def test_streaming_helpers(spark, tmp_path):
    rows = [(1, "2024-01-01 00:00:00", 7), (2, "2024-01-01 00:10:00", 7), (2, "2024-01-01 00:10:00", 7), (3, "2024-01-01 02:00:00", 7), (4, "2024-01-01 00:05:00", 8)]
    e = spark.createDataFrame(rows, "event_id bigint, ts string, user_id bigint").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    assert sorted((r.user_id, r.n) for r in incremental.sessions(e).collect()) == [(7, 1), (7, 3), (8, 1)]
    early, late = incremental.split_late(e, "2024-01-01 00:10:00")
    assert (early.count(), late.count()) == (3, 2)
    e.write.parquet(str(tmp_path / "in"))
    stream = lambda: spark.readStream.schema(e.schema).parquet(str(tmp_path / "in"))

    def run(df, name):
        df.writeStream.format("memory").queryName(name).outputMode("append").trigger(availableNow=True).start().awaitTermination()
        return spark.table(name)

    assert sorted(r.event_id for r in run(incremental.deduplicate(stream()), "dedup").collect()) == [1, 2, 3, 4]
    got = run(incremental.interval_pairs(stream(), stream()), "pairs").where("left_id <> right_id").distinct().collect()
    assert {(r.left_id, r.right_id) for r in got} == {(1, 2)}


def test_star_of_a_chain(spark):
    e = [(1, 2, 0.9), (2, 3, 0.8), (3, 4, 0.9)]
    from linkcluster.operators import star

    v, d = spark.range(1, 6).select("id"), spark.createDataFrame(e, "src bigint, dst bigint, sim double")
    assert {(r.center, r.id) for r in star.star(v, d).collect()} == ref.star(range(1, 6), e, "degree")
