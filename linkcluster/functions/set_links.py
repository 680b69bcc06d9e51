"""Exact Jaccard join of the word shingles of texts.

Shingles are counted without their texts: each batch deals its 64-bit hashes out to buckets as packed arrays, and a bucket
numbers the shingles of more than one text, rarest first, by 32 bits.  That number is the global order of a prefix filter: a
pair at ``theta`` meets in the rarest shingles of both, of which the smaller text needs fewer.  Texts that have such shingles
are compared in tiles, each by an inverted index, and every pair that meets is counted out.  No link is lost.
"""

from __future__ import annotations

from fractions import Fraction
from math import ceil

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkcluster.functions import text_arrays as _text
from linkcluster.plans.iterate import written

#: Characters of text for each bucket of shingles, that are packed together, and that are worked on at once; they bound a worker's memory.
BUCKET_CHARS, PACK, PIECE = 12_000_000, 6_000_000, 500_000
#: Shingles of the texts on each side of a tile, and the fewest sides.
TILE_SHINGLES, SIDES = 6_000_000, 3
#: Shingles that are renumbered at once.
STEP = 1_000_000
PACKED = "bucket int, doc binary, total binary, hash binary"
NUMBERED = "part int, doc binary, total binary, held binary, token binary"
SETS = "id bigint, n int, lead int, reach int, token binary"
OUT = "a bigint, b bigint, sim double"


def _bytes(x: np.ndarray) -> bytes:
    return np.ascontiguousarray(x).tobytes()


def _joined(col: pa.ChunkedArray, kind) -> np.ndarray:
    return np.frombuffer(b"".join(col.to_pylist()), dtype=kind)


def shingles(bodies: list[str], words: int) -> tuple[np.ndarray, np.ndarray]:
    """(owner, hash) of the distinct shingles of texts whose words are parted by single spaces, sorted."""
    codes, at = _text.code_points(bodies)
    s, e = _text.runs((codes != 32) & (codes != 10))
    h = _text.span_hashes(codes, s, e)
    owner = np.searchsorted(at, s, side="right") - 1
    g, first = _text.ngram_hashes(h, words), owner[: max(0, len(owner) - words + 1)]
    inside = first == owner[words - 1 :]
    g, first = g[inside], first[inside]
    order = np.lexsort((g, first))
    g, first = g[order], first[order]
    fresh = np.ones(len(g), dtype=bool)
    fresh[1:] = (g[1:] != g[:-1]) | (first[1:] != first[:-1])
    return first[fresh], g[fresh]


def _dealt(ids: np.ndarray, doc: np.ndarray, h: np.ndarray, buckets: int) -> pa.RecordBatch:
    bucket = (h % np.uint64(buckets)).astype(np.int32)
    order = np.argsort(bucket, kind="stable")
    edge = np.searchsorted(bucket[order], np.arange(buckets + 1))
    rows: dict[str, list] = {"bucket": [], "doc": [], "total": [], "hash": []}
    for k in np.flatnonzero(np.diff(edge)):
        at = order[edge[k] : edge[k + 1]]
        own, n = np.unique(doc[at], return_counts=True)
        rows["bucket"].append(int(k))
        rows["doc"].append(_bytes(ids[own].astype(np.int64)))
        rows["total"].append(_bytes(n.astype(np.int32)))
        # a bucket keeps seven bytes of what it does not tell itself: 59 bits in all at 8 buckets, more with more
        rows["hash"].append(_bytes((h[at] // np.uint64(buckets)).view(np.uint8).reshape(-1, 8)[:, :7]))
    return pa.RecordBatch.from_pydict(rows, schema=pa.schema([("bucket", pa.int32()), ("doc", pa.binary()), ("total", pa.binary()), ("hash", pa.binary())]))


def _packed(words: int, buckets: int):
    def run(batches):
        for batch in batches:
            ids, sizes = batch["id"].to_numpy(zero_copy_only=False), pc.utf8_length(batch["body"]).to_pylist()
            for start, end in _text.pieces(sizes, PACK):
                docs, hashes = [], []
                for lo, hi in _text.pieces(sizes[start:end], PIECE):
                    o, g = shingles(batch["body"].slice(start + lo, hi - lo).to_pylist(), words)
                    docs.append((o + (start + lo)).astype(np.int32))
                    hashes.append(g)
                yield _dealt(ids, np.concatenate(docs), np.concatenate(hashes), buckets)

    return run


def _numbered(buckets: int, parts: int):
    def run(t: pa.Table) -> pa.Table:
        bucket = t["bucket"][0].as_py()
        doc, n = _joined(t["doc"], np.int64), _joined(t["total"], np.int32)
        seven = _joined(t["hash"], np.uint8).reshape(-1, 7)
        wide = np.zeros((len(seven), 8), dtype=np.uint8)
        wide[:, :7] = seven
        h = wide.view(np.uint64).ravel()
        del seven, wide
        owner = np.repeat(np.arange(len(doc), dtype=np.int32), n)
        order = np.argsort(h, kind="stable")
        h = h[order]
        ends = np.flatnonzero(np.append(h[1:] != h[:-1], True))
        del h
        df = np.diff(ends, prepend=-1)
        common = df > 1
        rank = np.zeros(len(df), dtype=np.int64)
        many = np.flatnonzero(common)
        rank[many[np.argsort(df[many], kind="stable")]] = np.arange(len(many))
        if len(many) * buckets >= 1 << 32:
            raise ValueError("more repeated shingles than 32 bits can number")
        # rank is by frequency in this bucket; the numbers of all buckets interleave
        keep = np.repeat(common, df)
        own, token = owner[order[keep]], np.repeat((rank[common] * buckets + bucket).astype(np.uint32), df[common])
        del owner, order, keep
        part = (_text.mix(doc.astype(np.uint64)) % np.uint64(parts)).astype(np.int64)
        by = np.lexsort((own, part[own]))
        own, token = own[by], token[by]
        held = np.bincount(own, minlength=len(doc)).astype(np.int32)
        docs = np.argsort(part, kind="stable")
        lo, at = np.searchsorted(part[docs], np.arange(parts + 1)), np.searchsorted(part[own], np.arange(parts + 1))
        rows: dict[str, list] = {"part": [], "doc": [], "total": [], "held": [], "token": []}
        for p in np.flatnonzero(np.diff(lo)):
            d = docs[lo[p] : lo[p + 1]]
            rows["part"].append(int(p))
            rows["doc"].append(_bytes(doc[d]))
            rows["total"].append(_bytes(n[d]))
            rows["held"].append(_bytes(held[d]))
            rows["token"].append(_bytes(token[at[p] : at[p + 1]]))
        return pa.table(rows, schema=pa.schema([("part", pa.int32()), ("doc", pa.binary()), ("total", pa.binary()), ("held", pa.binary()), ("token", pa.binary())]))

    return run


def prefixes(n: np.ndarray, theta: Fraction) -> tuple[np.ndarray, np.ndarray]:
    """(lead, reach): how many of its n rarest shingles a text must show as the smaller and as the larger of a pair.

    At ``theta`` both share theta / (1 + theta) of the sum of their sizes, and theta of the larger.
    """
    both = theta / (1 + theta) * 2
    up = lambda f: -(-n * f.numerator // f.denominator)
    return n - up(both) + 1, n - up(theta) + 1


def _sets(theta: Fraction):
    def run(t: pa.Table) -> pa.Table:
        doc, total, held = _joined(t["doc"], np.int64), _joined(t["total"], np.int32), _joined(t["held"], np.int32)
        token = _joined(t["token"], np.uint32)
        ids, at = np.unique(doc, return_inverse=True)
        n, own = np.bincount(at, total).astype(np.int64), np.repeat(at, held)
        order = np.lexsort((token, own))
        token, edge = token[order], np.searchsorted(own[order], np.arange(len(ids) + 1))
        alone = n - np.diff(edge)
        lead, reach = (np.clip(p - alone, 0, np.diff(edge)) for p in prefixes(n, theta))
        keep = np.flatnonzero(reach > 0)
        cols = [pa.array(ids[keep]), pa.array(n[keep].astype(np.int32)), pa.array(lead[keep].astype(np.int32)), pa.array(reach[keep].astype(np.int32)), pa.array([_bytes(token[edge[k] : edge[k + 1]]) for k in keep], pa.binary())]
        return pa.table(cols, schema=pa.schema([("id", pa.int64()), ("n", pa.int32()), ("lead", pa.int32()), ("reach", pa.int32()), ("token", pa.binary())]))

    return run


def _spans(start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """The places start .. start + length of all spans, one after another."""
    end = np.cumsum(length)
    return np.arange(end[-1] if len(end) else 0) + np.repeat(start - (end - length), length)


def _tile(theta: Fraction):
    least = float(theta)

    def run(t: pa.Table) -> pa.Table:
        size = t["n"].to_numpy()
        order = np.lexsort((t["id"].to_numpy(), size))
        ids, n, lead, reach, side = (t[c].to_numpy()[order] for c in ("id", "n", "lead", "reach", "own"))
        i, j = t["i"][0].as_py(), t["j"][0].as_py()
        lists = t["token"].take(pa.array(order)).to_pylist()
        count = np.array([len(x) // 4 for x in lists], dtype=np.int64)
        at = np.cumsum(count) - count
        token = np.frombuffer(b"".join(lists), dtype=np.uint32)
        del lists, t
        names = np.unique(token)
        wide, token = token, np.empty(len(token), dtype=np.int32)
        for s in range(0, len(wide), STEP):
            token[s : s + STEP] = np.searchsorted(names, wide[s : s + STEP])
        del wide
        index = {}
        for s in np.unique(side):
            # postings of the texts of one side, smaller texts first
            mine = np.flatnonzero(side == s)
            post, who = token[_spans(at[mine], lead[mine].astype(np.int64))], np.repeat(mine.astype(np.int32), lead[mine])
            by = np.argsort(post, kind="stable")
            index[s] = who[by], np.searchsorted(post[by], np.arange(len(names) + 1))
        mark = np.zeros(len(names), dtype=bool)
        out: list[tuple] = []
        for b in range(len(ids)):
            other = index.get(i + j - side[b])
            if other is None:
                continue
            who, edge = other
            mine = token[at[b] : at[b] + count[b]]
            show = mine[: reach[b]]
            near = who[_spans(edge[show], edge[show + 1] - edge[show])]
            near = np.unique(near[near < b])
            near = near[n[near] >= least * n[b] - 1e-6]
            if not len(near):
                continue
            mark[mine] = True
            shared = np.add.reduceat(mark[token[_spans(at[near], count[near])]], np.cumsum(count[near]) - count[near], dtype=np.int64)
            mark[mine] = False
            sim = shared / (n[near].astype(np.int64) + n[b] - shared)
            ok = sim >= least
            if ok.any():
                out.append((ids[near[ok]], np.full(int(ok.sum()), ids[b]), sim[ok]))
        cols = [np.concatenate(x) for x in zip(*out)] if out else [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]
        return pa.table(cols, names=["a", "b", "sim"])

    return run


def shingle_links(texts: DataFrame, theta: Fraction, words: int, chars: int) -> DataFrame:
    """(a, b, sim), each pair once, of the texts (id, body) with a Jaccard similarity of at least ``theta`` of their sets of
    ``words``-word shingles.  ``body`` holds its words parted by single spaces, ``chars`` is about the length of all."""
    buckets = parts = max(8, ceil(chars / BUCKET_CHARS))
    packed = texts.select("id", "body").mapInArrow(_packed(words, buckets), PACKED)
    numbered = packed.groupBy("bucket").applyInArrow(_numbered(buckets, parts), NUMBERED)
    sets = written(numbered.groupBy("part").applyInArrow(_sets(theta), SETS))
    held = sets.agg(F.coalesce(F.sum(F.length("token") / 4), F.lit(0))).first()[0]
    sides = max(SIDES, ceil(held / TILE_SHINGLES))
    dealt = sets.withColumn("own", F.pmod(F.xxhash64("id"), F.lit(sides)).cast("int")).withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(sides - 1))))
    dealt = dealt.withColumn("i", F.least("own", "k")).withColumn("j", F.greatest("own", "k")).drop("k")
    return dealt.groupBy("i", "j").applyInArrow(_tile(theta), OUT)
