"""Tests of the findings of round 2."""

import os
import random
from fractions import Fraction

import pytest

from linkcluster import oracles
from linkcluster import queries as q
from linkcluster.functions import compose, set_links, tfidf
from linkcluster.operators import blocking, merge
from linkcluster.plans.iterate import ensure_checkpoint_dir


def against_sql(df, name, folder):
    """The rows of ``df`` and of the query's SQL, and both lists of columns."""
    import os

    import duckdb

    con = duckdb.connect()
    for f in os.listdir(folder):
        path = f"{folder}/{f}/*.parquet" if os.path.isdir(f"{folder}/{f}") else f"{folder}/{f}"
        con.execute(f"create view {f.removesuffix('.parquet')} as select * from read_parquet('{path}')")
    sql = con.execute(oracles.oracle_sql()[name])
    names = [c[0] for c in sql.description]
    value = lambda x: round(x, 6) if isinstance(x, float) else x
    rows = lambda found: sorted((tuple(map(value, r)) for r in found), key=repr)
    assert sorted(df.columns) == sorted(names)
    assert rows(df.select(*names).collect()) == rows(sql.fetchall())


def test_running_example_has_the_columns_of_its_sql(spark, sf):
    against_sql(q.running_example(spark, sf), "running_example", sf)


def test_components_beyond_their_bounds(spark, monkeypatch):
    """Chains longer than the levels, and more walks than the rows, that recursive SQL allows; more links than the driver may hold."""
    from linkcluster.operators import components

    chain = [(i, i + 1) for i in range(300)]
    clique = [(1000 + i, 1000 + j) for i in range(12) for j in range(i)]
    star = [(2999, 2000 + i) for i in range(40)]
    links = spark.createDataFrame(chain + clique + star + [(1, None), (5000, 5000)], "src bigint, dst bigint")
    v = spark.createDataFrame([(i,) for i in [*range(301), *range(1000, 1012), *range(2000, 2040), 2999, 5000, 7000]], "id bigint")
    want = {i: 0 for i in range(301)} | {i: 1000 for i in range(1000, 1012)} | {i: 2000 for i in [*range(2000, 2040), 2999]} | {5000: 5000, 7000: 7000}
    for method, cap in (("sql", 10), ("local", 1_000), ("local", 10)):
        assert {r.id: r.cid for r in components.connected(v, links, method, cap).collect()} == want
    none = links.where("false")
    assert all(components.connected(v, none, m).where("id <> cid").count() == 0 for m in ("sql", "local"))


def _scattered(spark, n, seed):
    """Places along the date line, at the poles and in a crowd, with alike labels, some empty or without a place."""
    import random

    rng = random.Random(seed)
    rows = []
    for i in range(n):
        lat, lon = rng.choice([(0, 179.9), (0, -179.9), (89.5, rng.uniform(-180, 180)), (-89.9, 10), (50, 8), (50, 8), (51, 9), (rng.uniform(-80, 80), rng.uniform(-180, 180))])
        label = "".join(rng.choice("abcé") for _ in range(rng.choice([0, 1, 4, 6, 7, 8, 12])))
        gone = rng.random() < 0.05
        rows.append((i, rng.choice("ABCD"), label, None if gone else lat + rng.uniform(-0.4, 0.4), None if gone else lon + rng.uniform(-1, 1)))
    return spark.createDataFrame(rows, "id bigint, source string, label string, lat double, lon double")


def test_mean_bound_loses_no_pair(spark, monkeypatch):
    """Tiles, cubes, hot tiles and label bounds give the links of all pairs, and more entities than the cap are no error."""
    from linkcluster.functions import near_pairs
    from linkcluster.operators import linking

    v = _scattered(spark, 900, 5)
    links = lambda d: {(r.src, r.dst): round(r.sim, 9) for r in d.collect()}
    for config in ("config2", "config3"):
        want = links(linking.exhaustive(v, config))
        assert len(want) > 100 and links(linking.discover(v, config)) == want
        monkeypatch.setattr(near_pairs, "STEP", 50)
        monkeypatch.setattr(near_pairs, "TILE_POINTS", 40)
        assert links(linking.exhaustive(v, config, row_cap=10)) == want
        monkeypatch.undo()


def test_merge_without_blocks_of_many_clusters(spark, monkeypatch):
    """The pairs that the bound leaves give the candidates of all pairs, also where places are missing; no number of clusters is refused."""
    from pyspark.sql import functions as F

    from linkcluster.functions import compose, near_pairs
    from linkcluster.operators import blocking, merge

    v = _scattered(spark, 500, 6).withColumn("n", F.lit(1) + (F.col("id") % 4).cast("int"))
    reps = v.select(F.col("id").alias("cid"), "label", "lat", "lon", F.array().cast("array<string>").alias("types"), F.array("source").alias("sources"), "n")
    rows = lambda d: {(r.l, r.r): (r.g, r.nl, r.nr) for r in d.collect()}
    want = rows(merge.candidates(blocking.none(reps), compose.LABEL_GEO, 0.8, 4))
    monkeypatch.setattr(near_pairs, "TILE_POINTS", 40)
    assert len(want) > 50 and rows(merge.candidates(blocking.none(reps), compose.LABEL_GEO, 0.8, 4, pairs=merge.unblocked_pairs(reps, 0.8, 4))) == want
    assert blocking.none(spark.range(30_000)).count() == 30_000


def test_nearest_vectors_in_passes(spark, tmp_path, monkeypatch):
    """Ties go to the smaller id, also among copies in other passes and batches, as the SQL has it; no vector is compared row by row."""
    import numpy as np

    from linkcluster.functions import nearest

    rng = np.random.default_rng(3)
    x = rng.normal(size=(700, 16)).astype(np.float32)
    x[300:340], x[400:420], x[500] = x[0], x[20] * 2, x[40] + np.float32(1e-6)
    rows = [(i, [float(a) for a in v]) for i, v in enumerate(x)]
    spark.createDataFrame(rows, "vec_id bigint, embedding array<float>").repartition(5).write.parquet(f"{tmp_path}/embeddings.parquet")
    for size in (50_000, 7):
        monkeypatch.setattr(nearest, "QUERIES", size)
        monkeypatch.setattr(nearest, "STRIPE", 5)
        monkeypatch.setattr(nearest, "BLOCK", 33)
        df = q.embedding_links(spark, str(tmp_path))
        assert "CartesianProduct" not in (plan := df._jdf.queryExecution().toString()) and "NestedLoop" not in plan
        against_sql(df, "embedding_links", tmp_path)


def test_frequent_tokens_lead_nobody(spark):
    """Values of five frequent words and a rare one meet by the rare one only, and no pair is lost."""
    import random

    from linkcluster.functions import tfidf

    rng = random.Random(2)
    common = ["red", "green", "blue", "white", "black", "brown", "amber"]
    rare = ["".join(rng.choice("abcdefghijk") for _ in range(7)) for _ in range(60)]
    values = [" ".join([*rng.sample(common, 5), *(rng.sample(rare, 1) if i % 3 else [rare[i % 60][:6] + "x"]), *([rng.choice(rare)] if i % 2 else [])]) for i in range(240)]
    index = tfidf.index(spark.createDataFrame([(i, x) for i, x in enumerate(values)], "vid bigint, value string"))
    got = {(r.va, r.vb): round(r.sim, 9) for r in index.reaching(0.5).collect()}
    assert got == {(r.va, r.vb): round(r.sim, 9) for r in index.all_pairs().where("sim >= 0.5").collect()} and len(got) > 100
    assert not {r.token for r in index.leads(0.5).collect()} & set(common)


def test_label_keys_lose_no_pair_and_bring_few(spark):
    """Every close pair shares a key, at several bounds and lengths; random words of six letters share far fewer than letter subsets alone gave them."""
    import random

    from linkcluster.functions.close_labels import subset_keys
    from linkcluster.functions.strings import jaro_winkler_batch

    rng = random.Random(9)
    words = ["".join(rng.choice("abc") for _ in range(rng.choice([1, 2, 3, 4, 5, 6, 7, 8]))) for _ in range(250)]
    words += [w[:k] + w[k + 1 :] + w[k : k + 1] for w in words[:60] for k in (0, 2)]
    words = sorted(set(words))
    pairs = [(a, b) for a in words for b in words if a < b]
    sims = jaro_winkler_batch([a for a, _ in pairs], [b for _, b in pairs])
    turn = lambda k: k if k[0] == "e" else ("l" if k[0] == "s" else "s") + k[1:]
    for bound in (0.8, 0.9, 0.95):
        keys = {w: set(subset_keys(w, bound)) for w in words}
        lost = [(a, b) for (a, b), s in zip(pairs, sims) if s >= bound and a[:4] != b[:4] and not keys[a] & {turn(k) for k in keys[b]}]
        assert not lost and (sims >= bound).sum() > 50
    six = ["".join(rng.choice("bdfgklmnprstvzae") for _ in range(6)) for _ in range(1500)]
    held: dict = {}
    for w in six:
        for k in (k for k in subset_keys(w, 0.9) if k[0] == "e"):
            held.setdefault(k, []).append(w)
    old: dict = {}
    for w in six:
        for i in range(6):
            old.setdefault("".join(sorted(w[:i] + w[i + 1 :])), []).append(w)
    met = lambda d: sum(len(x) * (len(x) - 1) // 2 for x in d.values())
    assert 10 * met(held) < met(old)


def _state_bytes(spark):
    import urllib.parse

    top = urllib.parse.urlparse(spark.sparkContext.getCheckpointDir()).path
    return sum(os.path.getsize(os.path.join(r, f)) for r, _, names in os.walk(top) for f in names)


def test_near_copies_write_no_triples(spark, tmp_path):
    rng = random.Random(8)
    texts = [" ".join(f"w{rng.randrange(10**6)}" for _ in range(400)) for _ in range(300)]
    texts += [t.replace("w", "x", 40) for t in texts[:20]]
    spark.createDataFrame([(i, f"s{i % 7}", t) for i, t in enumerate(texts)], "doc_id bigint, source string, text string").write.parquet(f"{tmp_path}/documents.parquet")
    ensure_checkpoint_dir(spark)
    before = _state_bytes(spark)
    assert {(r.src, r.dst) for r in q.documents_near_copies(spark, str(tmp_path)).collect()} == {(i, 300 + i) for i in range(20) if i % 7 != (300 + i) % 7}
    assert _state_bytes(spark) - before < sum(map(len, texts)) / 4


@pytest.mark.parametrize("theta", [Fraction(3, 10), Fraction(4, 5)])
def test_shingle_links_lose_no_pair(spark, monkeypatch, theta):
    monkeypatch.setattr(set_links, "BUCKET_CHARS", 3_000)
    monkeypatch.setattr(set_links, "TILE_SHINGLES", 2_000)
    rng = random.Random(6)
    base = [[f"w{rng.randrange(40)}" for _ in range(rng.randrange(3, 60))] for _ in range(60)]
    edit = lambda w: [f"w{rng.randrange(40)}" if rng.random() < 0.12 else x for x in w][: rng.randrange(3, 80)]
    texts = base + [edit(rng.choice(base)) for _ in range(240)]
    sets = [set(zip(w, w[1:], w[2:])) for w in texts]
    sim = {(i, j): len(a & b) / len(a | b) for j, b in enumerate(sets) for i, a in enumerate(sets[:j])}
    v = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(texts)], "id bigint, body string")
    got = [(min(r.a, r.b), max(r.a, r.b), r.sim) for r in set_links.shingle_links(v, theta, 3, sum(map(len, texts)) * 40).collect()]
    assert len(got) == len(set(got)) > 20
    assert {(a, b): s for a, b, s in got} == {k: s for k, s in sim.items() if s >= float(theta)}


def test_likely_pairs_lose_none(spark, monkeypatch):
    """Blocks of many representatives are cut down to a few pairs before any similarity is taken; the triplets stay."""
    monkeypatch.setattr(merge, "PAIRS", 50)
    rng = random.Random(3)
    word = lambda n: "".join(rng.choice("abcdefghik") for _ in range(n))
    edit = lambda x: x and x[: (i := rng.randrange(3, len(x)))] + rng.choice("abcdefghik") + x[i + rng.randrange(2) :]
    rows = [(p + word(rng.randrange(4, 12)), word(9) if rng.random() < 0.9 else None, word(6) if rng.random() < 0.7 else None) for p in ("abc", "abd") for _ in range(60)]
    rows += [tuple(edit(x) for x in rng.choice(rows)) for _ in range(120)]
    data = [(i, t, [], sorted(rng.sample("ABCDE", rng.choice([1, 1, 2]))), 1 + i % 3, t, a, b) for i, (t, a, b) in enumerate(rows)] + [(999, "abc", [], ["A"], 1, None, None, None)]
    reps = spark.createDataFrame(data, "cid bigint, label string, types array<string>, sources array<string>, n int, title string, artist string, album string")
    blocks = blocking.prefix(reps, 3).cache()
    for cap in (20_000, 40):
        pairs = merge.likely_pairs(blocks, compose.MUSIC, 0.8, 5, cap)
        every = merge.candidates(blocks, compose.MUSIC, 0.8, 5)
        assert sorted(map(repr, merge.candidates(blocks, compose.MUSIC, 0.8, 5, pairs=pairs).collect())) == sorted(map(repr, every.collect()))
        assert 40 < every.count() <= pairs.count() == pairs.distinct().count() < 3_000


def test_soft_tfidf_scores_pairs_in_tiles(spark, monkeypatch):
    """With no bound the pairs grow with the square of the values, so they leave their tile scored and are not shuffled."""
    monkeypatch.setattr(tfidf, "TILE_ROWS", 20)
    monkeypatch.setattr(tfidf, "HITS", 40)
    rng = random.Random(2)
    words = ["promo", "promos", "steel", "steal", "brushed", "tin", "copper", "coper"]
    values = sorted({" ".join(rng.choice(words) for _ in range(rng.randrange(1, 5))) for _ in range(60)})
    found = tfidf.index(spark.createDataFrame([(x, x) for x in values] + [(None, "tin")], "vid string, value string"), 0.85)
    got = found.all_pairs()
    assert "hashpartitioning(va" not in got._jdf.queryExecution().toString()
    plain = found.score(found._side("a").join(found.close, "ta").join(found._side("b"), "tb").where("va < vb"))
    rows = lambda d: {(r.va, r.vb): round(r.sim, 9) for r in d.collect()}
    assert rows(got) == rows(plain) and len(rows(got)) == got.count() > 300
