import random

import numpy as np
import pytest
from pyspark.sql import functions as F

import reference_impl as ref
from linkcluster import queries as q
from linkcluster.functions import geo, normalize, strings
from linkcluster.operators import blocking, components, intra, linking, measures, merge, preprocess, refine, representative, star, typegroup
from linkcluster.plans.config import LinkGraph
from linkcluster.sources import fixtures, sinks


def test_running_example(spark):
    v, links, sims = fixtures.running_example(spark)
    a = components.connected(v, links, "minlabel")
    assert {r.id: r.cid for r in a.collect()} == {1: 1, 2: 1, 3: 1, 4: 1, 5: 5, 6: 5, 7: 5}
    a, e = typegroup.split(a, sims, v)
    assert {r.id: r.cid for r in a.collect()} == {1: 1, 2: 1, 3: 3, 4: 3, 5: 5, 6: 5, 7: 5}
    asim = {r.id: round(r.asim, 6) for r in refine.average_similarity(e).collect()}
    assert (asim[5], asim[6], asim[7]) == (0.65, 0.6, 0.35)
    for strategy in ("grouped", "rounds", "auto"):
        got = {r.id: r.cid for r in refine.run(a, e, 0.5, strategy=strategy)[0].collect()}
        assert got == {1: 1, 2: 1, 3: 3, 4: 3, 5: 5, 6: 5, 7: 7}
    bulk = {r.id: r.cid for r in refine.run(a, e, 0.63, variant="bulk")[0].collect()}
    assert bulk[5] == 5 and bulk[6] == 6 and bulk[7] == 7
    final = {r.cid: (r.label, r.sources, r.members) for r in q.running_example(spark, None).collect()}
    assert final[1] == ("l1", "A|B|C|D", "1|2|5|6") and set(final) == {1, 3, 7}


def test_components_methods_agree(spark):
    rng = random.Random(3)
    ids = list(range(1300))
    links = [(i, i + 1) for i in range(0, 200)] + [(300, j) for j in range(301, 360)] + [tuple(rng.sample(range(400, 1300), 2)) for _ in range(500)] + [(5, 5), (400, 401), (401, 400)]
    v, e = spark.createDataFrame([(i,) for i in ids], "id bigint"), spark.createDataFrame(links, "src bigint, dst bigint")
    want = ref.components(ids, links)
    for m in ("minlabel", "stars", "local", "auto", "sized"):
        assert {r.id: r.cid for r in components.connected(v, e, m).collect()} == want, m
    for m in ("auto", "sized"):
        assert {r.cid for r in components.connected(v, e.limit(0), m).collect()} == set(ids)


def test_jaro_winkler_batch_matches_expression_and_known_values(spark):
    known = [("prefixabc", "prefixzzzzqqqq", 0.698412), ("", "a", 0.0), ("", "", 0.0), ("abcdefgh", "abcdefxy", 0.9), ("martha", "marhta", 0.961111), ("dixon", "dicksonx", 0.813333)]
    got = strings.jaro_winkler_batch([a for a, _, _ in known], [b for _, b, _ in known])
    assert np.allclose(got, [s for _, _, s in known], atol=1e-6)
    rng = random.Random(1)
    word = lambda: "".join(rng.choice("abcé") for _ in range(rng.randint(0, 9)))
    rows = [(word(), word()) for _ in range(300)] + [(None, "a"), ("a", None)]
    d = spark.createDataFrame(rows, "a string, b string")
    out = d.select(strings.jaro_winkler(F.col("a"), F.col("b")).alias("u"), strings.jaro_winkler_expr("a", "b").alias("e")).collect()
    for r in out:
        assert (r.u is None) == (r.e is None) and (r.u is None or abs(r.u - r.e) < 1e-12)


def test_normalisers(spark):
    d = spark.createDataFrame([("'06", "2m 4sec"), ("06", "02:04"), ("2006", "124000"), (None, "2.0667"), ("x", None)], "y string, t string")
    out = d.select(normalize.year(F.col("y")).alias("y"), normalize.length_seconds(F.col("t")).alias("t")).collect()
    assert [r.y for r in out] == [2006, 2006, 2006, None, None] and [r.t for r in out] == [124, 124, 124, 124, None]


def test_refine_strategies_and_reference(spark):
    rng = random.Random(7)
    rows, want = [], {}
    for c in range(60):
        ids = [c * 100 + i for i in range(rng.randint(2, 7))]
        e = {(a, b): rng.choice([0.3, 0.5, 0.6, 0.7, 0.9]) for i, a in enumerate(ids) for b in ids[i + 1 :]}
        rows += [(ids[0], a, b, s) for (a, b), s in e.items()]
        gone = set(ref.refine(e, 0.6))
        rest = [i for i in ids if i not in gone]
        want |= {i: i for i in gone} | {i: min(rest) for i in rest}
    edges = spark.createDataFrame(rows, "cid bigint, src bigint, dst bigint, sim double")
    assign = spark.createDataFrame([(i, i // 100 * 100) for i in want], "id bigint, cid bigint")
    for strategy in ("grouped", "rounds"):
        a, inside, _ = refine.run(assign, edges, 0.6, strategy=strategy)
        assert {r.id: r.cid for r in a.collect()} == want
        assert all(r.asim >= 0.6 - 1e-9 for r in refine.average_similarity(inside).collect())


def test_merge_strategies_and_reference(spark):
    rng = random.Random(9)
    rows, want = [], {}
    for b in range(120):
        ids = [b * 100 + i for i in range(rng.randint(2, 8))]
        src = {i: set(rng.sample("ABCDE", rng.randint(1, 2))) for i in ids}
        size = {i: len(src[i]) for i in ids}
        trip = [(x, rng.choice([0.8, 0.85, 0.9]), y) for n, x in enumerate(ids) for y in ids[n + 1 :] if not src[x] & src[y] and len(src[x] | src[y]) <= 4]
        rows += [(f"b{b}", x, y, int(s * 1e9), sorted(src[x]), sorted(src[y]), size[x], size[y], x, y) for x, s, y in trip]
        want |= {i: i for i in ids} | ref.merge(trip, {k: set(v) for k, v in src.items()}, dict(size), 4)
    work = spark.createDataFrame(rows, "block string, l bigint, r bigint, g bigint, sl array<string>, sr array<string>, nl int, nr int, ol bigint, orr bigint")
    assign = spark.createDataFrame([(i, i) for i in want], "id bigint, cid bigint")
    rounds = {}
    for strategy in ("block_best", "dominant", "grouped", "auto"):
        a, log = merge.run(assign, None, work, 4, strategy)
        assert {r.id: r.cid for r in a.collect()} == want, strategy
        rounds[strategy] = len(log)
    assert rounds["dominant"] <= rounds["block_best"] and rounds["auto"] == 1
    # some rounds first, the rest in one task
    moves, log = merge.loop(work, 4, "auto", finish_rows=200)
    assert len(log) > 1 and {r.id: r.cid for r in merge._moved(assign, moves).collect()} == want


def test_star_matches_sequential(spark):
    rng = random.Random(5)
    ids = list(range(60))
    e = sorted({tuple(sorted(rng.sample(ids, 2))) for _ in range(90)})
    e = [(a, b, rng.choice([0.5, 0.7, 0.9])) for a, b in e]
    v, d = spark.createDataFrame([(i,) for i in ids], "id bigint"), spark.createDataFrame(e, "src bigint, dst bigint, sim double")
    for order in ("degree", "mean_similarity"):
        assert {(r.center, r.id) for r in star.star(v, d, order).collect()} == ref.star(ids, e, order)


def test_geo_candidates_wrap_and_poles(spark):
    pts = [(1, "A", "x", 0.0, 179.9), (2, "B", "x", 0.0, -179.9), (3, "A", "x", 89.0, 10.0), (4, "B", "x", 89.0, -170.0), (5, "A", "x", -70.0, 0.0), (6, "B", "x", -70.0, 5.0), (7, "B", "x", 40.0, 40.0), (8, "A", "x", None, 1.0)]
    v = spark.createDataFrame(pts, "id bigint, source string, label string, lat double, lon double")
    for km in (100.0, 300.0, 600.0):
        got = {(r.l_id, r.r_id) for r in linking.geo_candidates(v, km).collect()}
        p = v.select(*[F.col(c).alias(f"a_{c}") for c in v.columns]).crossJoin(v.select(*[F.col(c).alias(f"b_{c}") for c in v.columns])).where("a_id < b_id and a_source <> b_source")
        want = {(r.a_id, r.b_id) for r in p.where(geo.haversine_km(F.col("a_lat"), F.col("a_lon"), F.col("b_lat"), F.col("b_lon")) <= km).collect()}
        assert got == want


def test_tiles_lose_no_pair(spark):
    reps = spark.createDataFrame([(i, "ab" if i % 3 else "cd") for i in range(50)], "cid bigint, block string")
    left, right = blocking.tile_pairs(reps, 4)
    p = left.select("block", "i", "j", F.col("cid").alias("x")).join(right.select("block", "i", "j", F.col("cid").alias("y")), ["block", "i", "j"]).where("i <> j or x < y").where("x <> y")
    got = sorted(tuple(sorted((r.x, r.y))) for r in p.collect())
    assert got == sorted({(a, b) for a in range(50) for b in range(a + 1, 50) if bool(a % 3) == bool(b % 3)})


def test_empty_and_degenerate_inputs(spark):
    from linkcluster.plans.workflow import cluster

    v, links, _ = fixtures.running_example(spark)
    v = v.withColumn("props", F.lit(None).cast("map<string,string>"))
    assert cluster(v.limit(0), links.limit(0)).reps.count() == 0
    g, counts = preprocess.validate_graph(LinkGraph(v, links.unionByName(spark.createDataFrame([(1, 1), (1, 99), (2, 1), (None, 3)], "src bigint, dst bigint"))))
    assert g.edges.count() == 6 and counts.first().links_in == 10


def test_measures(spark):
    a = spark.createDataFrame([(1, 1), (2, 1), (3, 3), (4, 3)], "id bigint, cid bigint")
    gold = spark.createDataFrame([(1, 1, "A"), (2, 1, "B"), (3, 1, "C"), (4, 2, "A")], "id bigint, gold bigint, source string")
    x, y = measures.cluster_quality(a, gold).first(), measures.link_quality(measures.pairs_of(a), linking.gold_links(gold)).first()
    assert x == y and (x.n_true, x.n_pred, x.n_gold) == (1, 2, 3) and x.f1 == 0.4
    t = spark.createDataFrame([(1, 100.0), (2, 60.0)], "workers int, seconds double")
    assert {r.workers: round(r.speedup, 3) for r in measures.speedup(t).collect()} == {1: 1.0, 2: 1.667}


def test_geojson_parses(spark, sf):
    import json

    d = sinks.geojson_points(q.geo_vertices(spark, sf), "id", "label").limit(20).collect()
    assert all(json.loads(r.value)["type"] == "Feature" for r in d)


def test_incremental_stream_equals_batch(spark, tmp_path):
    from linkcluster.functions import compose
    from linkcluster.streaming import incremental

    reps = spark.createDataFrame([(1, "berlin", ["t"], ["A"], 1), (2, "paris", ["t"], ["A", "B"], 2)], "cid bigint, label string, types array<string>, sources array<string>, n int")
    new = spark.createDataFrame([(10, "B", "berlin", ["t"], None, None, None), (11, "B", "paris", ["t"], None, None, None), (12, "C", "parsi", ["u"], None, None, None), (13, "B", "berlim", ["t"], None, None, None)], incremental.ENTITY)
    new.write.json(str(tmp_path / "in"))
    incremental.assign_stream(spark, str(tmp_path / "in"), reps, str(tmp_path / "out"), str(tmp_path / "ck"), 4, 0.8, compose.LABEL_LEVENSHTEIN).trigger(availableNow=True).start().awaitTermination()
    got = {r.id: r.cid for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    assert got == {r.id: r.cid for r in incremental.assign_batch(new, reps, 4, 0.8, compose.LABEL_LEVENSHTEIN).collect()} == {10: 1, 11: 11, 12: 12, 13: 13}


def test_stream_windows(spark, sf, tmp_path):
    from linkcluster.streaming import incremental

    e = spark.read.parquet(f"{sf}/events.parquet")
    want = {(r.start, r.event_type): r.n for r in incremental.rates(e).collect()}
    e.write.parquet(str(tmp_path / "in"))
    s = incremental.rates(spark.readStream.schema(e.schema).parquet(str(tmp_path / "in")), late="1000 days")
    s.writeStream.outputMode("complete").format("memory").queryName("rates").trigger(availableNow=True).start().awaitTermination()
    assert {(r.start, r.event_type): r.n for r in spark.table("rates").collect()} == want


@pytest.mark.parametrize("name", ["geo_entities", "music_entities", "normalize_year_length", "string_similarities", "best_links_mutual", "link_config1", "link_config3", "components_stars", "refine_grouped", "merge_candidates_tiled", "soft_tfidf_albums", "join_asof", "join_band", "window_ranks"])
def test_against_sql(spark, sf, name):
    import duckdb

    from linkcluster import oracles

    con = duckdb.connect()
    for t in ("nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "pages"):
        con.execute(f"create view {t} as select * from read_parquet('{sf}/{t}.parquet')")
    df = q.queries()[name](spark, sf)
    cols = sorted(df.columns)
    value = lambda x: round(x, 6) if isinstance(x, float) else x
    got = sorted((tuple(value(r[c]) for c in cols) for r in df.collect()), key=repr)
    names = ", ".join(f'"{c}"' for c in cols)
    want = sorted((tuple(value(x) for x in r) for r in con.execute(f"select {names} from ({oracles.oracle_sql()[name]})").fetchall()), key=repr)
    assert got == want


def test_soft_tfidf_links_against_all_pairs(spark, sf):
    """The seeds lose no pair: totals over all cross-source pairs give the same links."""
    from linkcluster.functions.tfidf import soft_tfidf

    v = q.music_vertices(spark, sf).where("gold < 60")
    sims = {}
    for c in ("title", "artist", "album"):
        vals = v.where(F.col(c).isNotNull()).select(F.col(c).alias("value")).distinct().withColumn("vid", F.col("value"))
        sims[c] = {(r.va, r.vb): r.sim for r in soft_tfidf(vals).collect()}
    rows = v.select("id", "source", "title", "artist", "album").collect()
    want = set()
    for a in rows:
        for b in rows:
            if a.id < b.id and a.source != b.source:
                s = 0.0
                for c, w in (("title", 0.6), ("artist", 0.3), ("album", 0.1)):
                    if a[c] is not None and b[c] is not None:
                        s += w * (1.0 if a[c] == b[c] else sims[c].get((min(a[c], b[c]), max(a[c], b[c])), 0.0))
                if s >= 0.35 + 1e-9:
                    want.add((a.id, b.id))
    got = {(r.src, r.dst): r.sim for r in linking.discover(v, "music").collect()}
    assert want <= set(got) and all(s < 0.35 + 1e-6 for k, s in got.items() if k not in want)
    assert intra.pairs(spark.createDataFrame([(1, 1), (2, 1)], "id bigint, cid bigint")).count() == 1
    assert representative.build(spark.createDataFrame([(1, 1)], "id bigint, cid bigint"), fixtures.running_example(spark)[0], "longest", "mean").first().label == "l1"


def test_stateful_counts_and_pair_table_function(spark, sf, tmp_path):
    from linkcluster.streaming import incremental

    e = spark.read.parquet(f"{sf}/events.parquet").select(F.col("user_id").cast("bigint").alias("user_id"))
    e.repartition(2).write.parquet(str(tmp_path / "in"))
    s = incremental.running_counts(spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in")))
    s.writeStream.outputMode("update").format("memory").queryName("counts").trigger(availableNow=True).start().awaitTermination()
    assert {r.user_id: r.m for r in spark.table("counts").groupBy("user_id").agg(F.max("n").alias("m")).collect()} == {r.user_id: r["count"] for r in e.groupBy("user_id").count().collect()}
    a = spark.createDataFrame([(1, 1), (2, 1), (5, 1), (7, 7)], "id bigint, cid bigint")
    assert sorted(intra.pairs_lateral(a).collect()) == sorted(intra.pairs(a).collect())


def test_label_candidates_lose_no_pair(spark):
    rng = random.Random(12)
    base = ["".join(rng.choice("abcdef") for _ in range(rng.randint(1, 22))) for _ in range(60)]
    def edit(x):
        w = list(x)
        for _ in range(rng.randint(0, 2)):
            i = rng.randrange(len(w) + 1)
            w[i : i + rng.randint(0, 1)] = rng.choice("abcdef") * rng.randint(0, 1)
        return "".join(w)
    labels = base + [edit(x) for x in base for _ in range(3)] + [""]
    v = spark.createDataFrame([(i, "AB"[i % 2], x) for i, x in enumerate(labels)], "id bigint, source string, label string")
    got = {(r.src, r.dst) for r in linking.label_candidates(v, 0.9).where("label_sim >= 0.9").collect()}
    ids = [(i, j) for i in range(len(labels)) for j in range(i + 1, len(labels)) if (i + j) % 2]
    s = strings.jaro_winkler_batch([labels[i] for i, _ in ids], [labels[j] for _, j in ids])
    assert got == {p for p, x in zip(ids, s) if x >= 0.9} and len(got) > 100


def test_near_copies_of_common_texts(spark, tmp_path):
    import random

    rng = random.Random(4)
    base = [f"w{rng.randrange(500)}" for _ in range(30)]
    texts = [" ".join(base)] * 56 + [" ".join(base[:cut] + [f"e{cut}"] + base[cut + 1 :]) for cut in (2, 9, 15, 22)] + [" ".join(base[:12]), "w1 w2 w3", "W1, w2 w3!", "a b", None]
    rows = [(i, f"s{i % 3}", t) for i, t in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id bigint, source string, text string").write.parquet(f"{tmp_path}/documents.parquet")

    def grams(t):
        w = "".join(c if c.isalnum() else " " for c in (t or "").lower()).split()
        return set(zip(w, w[1:], w[2:]))

    g = {i: grams(t) for i, _, t in rows}
    want = {(a, b): round(len(g[a] & g[b]) / len(g[a] | g[b]), 6) for a, s, _ in rows for b, z, _ in rows if a < b and s != z and g[a] and g[b] and len(g[a] & g[b]) / len(g[a] | g[b]) >= 0.3}
    assert {(r.src, r.dst): r.sim for r in q.documents_near_copies(spark, str(tmp_path)).collect()} == want


def test_geo_queries_read_every_customer(spark, tmp_path):
    spark.range(1000).selectExpr("id AS c_custkey", "cast(id % 25 AS int) AS c_nationkey").write.parquet(f"{tmp_path}/customer.parquet")
    golds = {r.gold for r in q.geo_entities(spark, str(tmp_path)).select("gold").collect()}
    assert golds == set(range(1000)) == {r.gold for r in q.geo_vertices(spark, str(tmp_path)).select("gold").collect()}
    assert q.overview_geo(spark, str(tmp_path)).first().clusters == 1000


def test_embedding_links_search_all_labels(spark, tmp_path):
    rows = [(0, 1, [1.0, 0.0]), (1, 1, [0.0, 1.0]), (2, 2, [1.0, 0.1]), (20, 3, [0.0, -1.0]), (3, 1, [0.1, -1.0]), (4, 3, [1.0, -1.0])]
    spark.createDataFrame(rows, "vec_id bigint, label int, embedding array<double>").write.parquet(f"{tmp_path}/embeddings.parquet")
    assert {(r.src, r.dst) for r in q.embedding_links(spark, str(tmp_path)).collect()} == {(0, 2), (20, 3)}
