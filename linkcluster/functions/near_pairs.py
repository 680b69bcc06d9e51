"""Pairs of near places with like labels: one similarity join on the mean of both similarities.

A mean of at least t leaves a label similarity of at least 2 t - g to a pair whose places have similarity g.  Places become
points on the unit sphere, in cubic tiles with a margin as wide as the greatest distance; inside a tile numpy compares smaller
cubes.  A pair in reach is measured only if its common letters and first letters allow the label similarity that is left.  Both
bounds lose no pair.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkcluster.functions import geo
from linkcluster.functions.strings import _matrix, jaro_winkler_batch
from linkcluster.plans.iterate import written

SLACK = 1e-9
#: Error of a place similarity that comes from the cosine of the angle, which is coarse at small distances.
COARSE = 2e-4
#: Width of a tile in greatest distances; points of a tile, margin included, beyond which its points are dealt out to several tasks.
TILE, TILE_POINTS = 4, 60_000
#: Pairs that one step of the comparison holds.
STEP = 4_000_000
OUT = "l_id bigint, r_id bigint, label_sim double"


def letter_marks(labels: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(length, 64-bit mask of (letter, occurrence), first four letters as 16 bits each) of each label."""
    codes, n = _matrix(labels)
    inside = np.arange(codes.shape[1]) < n[:, None]
    ordered = np.sort(np.where(inside, codes, np.uint32(0xFFFFFFFF)), axis=1)
    at = np.broadcast_to(np.arange(codes.shape[1]), codes.shape)
    fresh = np.ones(codes.shape, dtype=bool)
    fresh[:, 1:] = ordered[:, 1:] != ordered[:, :-1]
    nth = at - np.maximum.accumulate(np.where(fresh, at, 0), axis=1)
    bit = ((ordered & 31) + 32 * (nth & 1) + 11 * (nth >> 1)) & 63
    mask = np.bitwise_or.reduce(np.where(ordered != 0xFFFFFFFF, np.uint64(1) << bit.astype(np.uint64), np.uint64(0)), axis=1)
    first = np.zeros(len(labels), dtype=np.uint64)
    for i in range(min(4, codes.shape[1])):
        first |= (codes[:, i].astype(np.uint64) & np.uint64(0xFFFF)) << np.uint64(16 * i)
    return n, mask, first


def at_most(a: tuple, b: tuple, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """An upper bound on the Jaro-Winkler similarity of label i of ``a`` and label j of ``b``."""
    n1, n2, x, y = a[0][i], b[0][j], a[1][i], b[1][j]
    common = np.minimum(n1 - np.bitwise_count(x & ~y), n2 - np.bitwise_count(y & ~x))
    jaro = np.where(common > 0, (common / np.maximum(n1, 1) + common / np.maximum(n2, 1) + 1) / 3, 0.0)
    apart = a[2][i] ^ b[2][j]
    low = apart & (~apart + np.uint64(1))
    prefix = np.where(apart == 0, 4, np.bitwise_count(low - np.uint64(1)) >> 4)
    return np.where(jaro > 0.7, jaro + 0.1 * prefix * (1 - jaro), jaro)


def _measured(left: dict, right: dict, i: np.ndarray, j: np.ndarray, least: np.ndarray | float) -> list[pa.RecordBatch]:
    """Of the pairs (i, j) those whose labels reach ``least``, measured."""
    can = at_most(left["marks"], right["marks"], i, j) >= least - SLACK
    i, j, out = i[can], j[can], []
    least = least[can] if isinstance(least, np.ndarray) else least
    for s in range(0, len(i), 4096):
        p, q = i[s : s + 4096], j[s : s + 4096]
        sim = jaro_winkler_batch(left["label"][p].tolist(), right["label"][q].tolist())
        ok = sim >= (least[s : s + 4096] if isinstance(least, np.ndarray) else least) - SLACK
        if ok.any():
            out.append(pa.RecordBatch.from_arrays([pa.array(left["id"][p[ok]]), pa.array(right["id"][q[ok]]), pa.array(sim[ok])], ["l_id", "r_id", "label_sim"]))
    return out


def _side(t: pa.Table) -> dict:
    label = t["label"].to_pylist()
    side = {"id": t["id"].to_numpy(), "label": np.array(label, dtype=object), "marks": letter_marks(label)}
    return side | {"kind": t["kind"].combine_chunks().dictionary_encode().indices.to_numpy()} if "kind" in t.column_names else side


def _table(out: list[pa.RecordBatch]) -> pa.Table:
    return pa.Table.from_batches(out, pa.schema([("l_id", pa.int64()), ("r_id", pa.int64()), ("label_sim", pa.float64())]))


def _tile(bound: float, h: float):
    least_geo = 2 * bound - 1
    reach = math.cos((1 - least_geo) * geo.MAX_KM / geo.EARTH_KM) - 1e-12

    def run(t: pa.Table) -> pa.Table:
        side = _side(t)
        xyz = np.column_stack([t[c].to_numpy() for c in "xyz"])
        home = t["home"].to_numpy(zero_copy_only=False)
        cube = np.floor(xyz / h).astype(np.int64)
        cube -= cube.min(axis=0) - 1
        wide = cube.max(axis=0) + 2
        key = (cube[:, 0] * wide[1] + cube[:, 1]) * wide[2] + cube[:, 2]
        order = np.argsort(key, kind="stable")
        key, xyz, home = key[order], xyz[order], home[order]
        side = {k: tuple(m[order] for m in v) if k == "marks" else v[order] for k, v in side.items()}
        mine = np.flatnonzero(home)
        starts = np.flatnonzero(np.diff(key[mine], prepend=-1))
        out: list[pa.RecordBatch] = []

        def compare(rows: np.ndarray, others: np.ndarray) -> None:
            per = max(1, STEP // max(1, len(others)))
            for s in range(0, len(rows), per):
                part = rows[s : s + per]
                dot = xyz[part] @ xyz[others].T
                near = np.flatnonzero(dot.ravel() >= reach)
                a, b = np.divmod(near, len(others))
                i, j, dot = part[a], others[b], dot.ravel()[near]
                ok = side["id"][i] < side["id"][j]
                if "kind" in side:
                    ok &= side["kind"][i] != side["kind"][j]
                i, j, dot = i[ok], j[ok], dot[ok]
                g = 1 - np.arccos(np.minimum(dot, 1.0)) * geo.EARTH_KM / geo.MAX_KM
                out.extend(_measured(side, side, i, j, 2 * bound - np.minimum(1.0, g + COARSE)))

        if len(mine) * len(key) <= STEP:
            compare(mine, np.arange(len(key)))
            return _table(out)
        steps = [(dx * wide[1] + dy) * wide[2] for dx in (-1, 0, 1) for dy in (-1, 0, 1)]
        for s, e in zip(starts, [*starts[1:], len(mine)]):
            k = key[mine[s]]
            runs = [np.arange(*np.searchsorted(key, [k + d - 1, k + d + 2])) for d in steps]
            compare(mine[s:e], np.concatenate(runs))
        return _table(out)

    return run


def near_pairs(v: DataFrame, bound: float, kind: str | None = None) -> DataFrame:
    """(l_id, r_id, label_sim), l_id < r_id, of every pair of (id, label, lat, lon) whose mean of label and place similarity
    reaches ``bound``; and of some that just miss it, so the caller takes the exact mean.  Rows with an equal value in the column ``kind`` do not meet."""
    h = 2 * math.sin((2 - 2 * bound) * geo.MAX_KM / geo.EARTH_KM / 2) * (1 + SLACK)
    lat, lon = F.radians("lat"), F.radians("lon")
    v = v if kind is None else v.where(F.col(kind).isNotNull())
    p = v.where("lat is not null and lon is not null and label is not null").select("id", "label", *([F.col(kind).alias("kind")] if kind else []), (F.cos(lat) * F.cos(lon)).alias("x"), (F.cos(lat) * F.sin(lon)).alias("y"), F.sin(lat).alias("z"))
    own = {c: F.floor(F.col(c) / (TILE * h)).cast("int") for c in "xyz"}
    for c in "xyz":
        touched = F.sequence(F.floor((F.col(c) - h) / (TILE * h)).cast("int"), F.floor((F.col(c) + h) / (TILE * h)).cast("int"))
        p = p.withColumn(f"t{c}", F.explode(touched))
    p = p.withColumn("home", (F.col("tx") == own["x"]) & (F.col("ty") == own["y"]) & (F.col("tz") == own["z"]))
    tile = ["tx", "ty", "tz"]
    sizes = written(p.groupBy(*tile).agg(F.count(F.lit(1)).alias("n"), F.count_if("home").alias("homes")))
    large = sizes.where((F.col("n") > TILE_POINTS) & (F.col("homes") > 0)).select(*tile, F.ceil(F.col("n") / TILE_POINTS).cast("int").alias("parts"))
    if large.limit(1).count():
        p = p.join(large, tile, "left").withColumn("parts", F.coalesce("parts", F.lit(1))).withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
        p = p.withColumn("home", F.col("home") & (F.pmod(F.xxhash64("id"), F.col("parts")) == F.col("part"))).drop("parts")
        tile = [*tile, "part"]
    return p.groupBy(*tile).applyInArrow(_tile(bound, h), OUT)


def label_pairs(some: DataFrame, v: DataFrame, bound: float, parts: int) -> DataFrame:
    """(l_id, r_id, label_sim) of ``some`` of the rows (id, label) against all with a label similarity of at least ``bound``.

    All rows are dealt out to ``parts`` tasks, each of which gets every row of ``some``.
    """

    def run(t: pa.Table) -> pa.Table:
        probe = t["probe"].to_numpy(zero_copy_only=False)
        left, right = _side(t.filter(pa.array(probe))), _side(t.filter(pa.array(~probe)))
        out: list[pa.RecordBatch] = []
        per = max(1, STEP // max(1, len(right["id"])))
        for s in range(0, len(left["id"]), per):
            part = np.arange(s, min(s + per, len(left["id"])))
            i, j = np.repeat(part, len(right["id"])), np.tile(np.arange(len(right["id"])), len(part))
            ok = left["id"][i] != right["id"][j]
            out.extend(_measured(left, right, i[ok], j[ok], bound))
        return _table(out)

    cols = ["id", "label"]
    a = some.where("label is not null").select(F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), *cols, F.lit(True).alias("probe"))
    b = v.where("label is not null").select(F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int").alias("part"), *cols, F.lit(False).alias("probe"))
    p = a.unionByName(b).groupBy("part").applyInArrow(run, OUT)
    return p.select(F.least("l_id", "r_id").alias("l_id"), F.greatest("l_id", "r_id").alias("r_id"), "label_sim").dropDuplicates(["l_id", "r_id"])
