"""Connected components over link tables.

``connected(vertices, edges, method)`` returns ``(id, cid)`` with ``cid`` the smallest
member id; every vertex appears, isolated ones as their own component.
Methods give the same answer at different cost:

* ``minlabel``  gather the neighbours' labels, keep the least, and follow labels of labels;
* ``stars``     alternate large-star and small-star rewrites of the edge table (few rounds on long chains);
* ``local``     union-find on the driver over two id columns; above ``row_cap`` links the rounds of ``auto`` do the whole job;
* ``sql``       recursive SQL over forests: each vertex below its least neighbour in a hashed order, then the trees linked
  by the edges between them, until no edge is left between two trees;
* ``auto``      ``minlabel`` for a few rounds, then ``stars`` on what is still moving;
* ``sized``     counts the links first: up to ``ONE_TASK_LINKS`` one executor task labels them, beyond it ``auto``.
"""

from __future__ import annotations

from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkcluster.plans.iterate import written

#: Links that one task may label: two id columns of 32 MB, some 200 MB with the working arrays.
ONE_TASK_LINKS = 2_000_000
#: Links whose two id columns the driver may hold, 64 MB.
LOCAL_LINKS = 4_000_000


def _both_ways(edges: DataFrame) -> DataFrame:
    e = edges.select(F.col("src").alias("a"), F.col("dst").alias("b")).where("a <> b")
    return e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct()


def _minlabel(edges: DataFrame, max_rounds: int | None) -> tuple[DataFrame, bool]:
    """(a, label) of every vertex with an edge; the flag tells whether it is at its fix point."""
    both = written(_both_ways(edges))
    labels = written(both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("label")))
    rounds = 0
    while max_rounds is None or rounds < max_rounds:
        heard = both.join(labels, "a").groupBy(F.col("b").alias("a")).agg(F.min("label").alias("heard"))
        lower = labels.join(heard, "a").select("a", "label", F.least("label", "heard").alias("next"))
        # a label is a vertex id: jump to that vertex's own label
        up = labels.select(F.col("a").alias("next"), F.col("label").alias("above"))
        step = lower.join(up, "next", "left").select(
            "a", F.least("next", F.coalesce("above", "next")).alias("label"), (F.least("next", F.coalesce("above", "next")) < F.col("label")).alias("moved")
        )
        step = written(step)
        moved = step.where("moved").limit(1).count()
        labels = step.select("a", "label")
        rounds += 1
        if not moved:
            return labels, True
    return labels, False


def _stars(edges: DataFrame) -> DataFrame:
    """(a, label) by alternating large-star and small-star until the edge table stops changing."""

    def fingerprint(e: DataFrame) -> tuple:
        r = e.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
        return r["n"], r["h"]

    e = written(edges.select(F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b")).where("a <> b").distinct())
    last = fingerprint(e)
    while last[0]:
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = written(large.where("a <> b").distinct())
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a")
        small = small.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
        e = written(small.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
        now = fingerprint(e)
        if now == last:
            break
        last = now
    return e.groupBy("a").agg(F.min("b").alias("label"))


def _local(edges: DataFrame) -> pa.Table:
    links = edges.select(F.col("src").cast("bigint").alias("src"), F.col("dst").cast("bigint").alias("dst")).toArrow()
    ids, label = label_links(links["src"].to_numpy(), links["dst"].to_numpy())
    return pa.table({"a": ids, "label": label})


@contextmanager
def _unlimited_recursion(spark):
    """Recursive SQL without its limits of rows and levels, both of which only guard against endless recursion."""
    names = ("spark.sql.cteRecursionRowLimit", "spark.sql.cteRecursionLevelLimit")
    before = {n: spark.conf.get(n) for n in names}
    try:
        for n in names:
            spark.conf.set(n, "-1")
        yield
    finally:
        for n, x in before.items():
            spark.conf.set(n, x)


def _sql(edges: DataFrame) -> DataFrame:
    """(a, label): rounds of forests, each walked from its roots by recursive SQL.

    A vertex hangs below its least neighbour in the order of hashes if that one comes before it, so walks have no
    cycle, make one row for each vertex and are short, also along chains.
    """
    spark = edges.sparkSession
    both = written(_both_ways(edges))
    tree = None
    while both.limit(1).count():
        below = written(
            spark.sql(
                "SELECT a, CASE WHEN p < struct(xxhash64(a), a) THEN p.id END AS up FROM "
                "(SELECT a, min(named_struct('h', xxhash64(b), 'id', b)) AS p FROM {both} GROUP BY a)",
                both=both,
            )
        )
        with _unlimited_recursion(spark):
            walked = written(
                spark.sql(
                    "WITH RECURSIVE r AS (SELECT a, a AS root FROM {f} WHERE up IS NULL UNION ALL SELECT f.a, r.root FROM r JOIN {f} f ON f.up = r.a) SELECT a, root FROM r",
                    f=below,
                )
            )
        of = lambda name, to: walked.select(F.col("a").alias(name), F.col("root").alias(to))
        both = written(both.join(of("a", "x"), "a").join(of("b", "y"), "b").where("x <> y").select(F.col("x").alias("a"), F.col("y").alias("b")).distinct())
        tree = walked if tree is None else written(tree.join(of("root", "top"), "root", "left").select("a", F.coalesce("top", "root").alias("root")))
    if tree is None:
        return edges.select(F.col("src").alias("a"), F.col("src").alias("label")).where("false")
    least = tree.groupBy("root").agg(F.min("a").alias("label"))
    return tree.join(least, "root").select("a", "label")


def label_links(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(vertex, least vertex of its component): roots hook onto smaller roots, then paths are halved."""
    ids, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
    a, b = at[: len(src)], at[len(src) :]
    label = np.arange(len(ids))
    while True:
        apart = label[a] != label[b]
        if not apart.any():
            return ids, ids[label]
        a, b = label[a[apart]], label[b[apart]]
        np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
        while (label != label[label]).any():
            label = label[label]


def _one_task(edges: DataFrame) -> DataFrame:
    def run(batches):
        got = [(np.asarray(b.column(0)), np.asarray(b.column(1))) for b in batches]
        if got:
            ids, label = label_links(*(np.concatenate(x) for x in zip(*got)))
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(label)], ["a", "label"])

    return edges.select(F.col("src").cast("bigint"), F.col("dst").cast("bigint")).repartition(1).mapInArrow(run, "a bigint, label bigint")


def connected(vertices: DataFrame, edges: DataFrame, method: str = "auto", row_cap: int = LOCAL_LINKS) -> DataFrame:
    ids = vertices.select("id")
    edges = edges.where("src is not null and dst is not null")
    if method == "minlabel":
        labels, _ = _minlabel(edges, None)
    elif method == "stars":
        labels = _stars(edges)
    elif method == "local" and edges.limit(row_cap + 1).count() <= row_cap:
        found = _local(edges)
        labels = edges.sparkSession.createDataFrame(found) if found.num_rows else edges.select(F.col("src").alias("a"), F.col("src").alias("label")).where("false")
    elif method == "sql":
        labels = _sql(edges)
    elif method == "sized" and edges.count() <= ONE_TASK_LINKS:
        labels = _one_task(edges)
    else:
        labels, done = _minlabel(edges, 6)
        if not done:
            links = edges.select("src", "dst").unionByName(labels.select(F.col("a").alias("src"), F.col("label").alias("dst")))
            labels = _stars(links)
    labels = labels.select(F.col("a").alias("id"), F.col("label").alias("cid"))
    return ids.join(labels, "id", "left").select("id", F.coalesce("cid", "id").alias("cid"))
