"""Quality rules: base text measures and a hashed n-gram log-likelihood ratio.

Word unigrams and bigrams are hashed into a fixed number of buckets.  Two multinomials are
counted over all rows: the raw corpus (every document) and the trusted target (documents
whose label marks them good).  A document's score is the mean over its n-grams of
log p_target - log p_raw, so it is length-normalised; it is kept when the score reaches
``min_score``, a fixed parameter, and no base rule fails.

Defined cases: a null or empty text has no words, fails the base rule and is dropped; with
no trusted document the ratio is 0 everywhere and only the base rules decide; equal texts
get equal verdicts; a very long text is a piece of its own, read whole; other columns may have any name.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkcluster.functions import text_arrays as _text
from linkcluster.llm._frame import small

MIN_WORDS = 50
SYMBOLS = b"#*$%&|<>"


@dataclass(frozen=True)
class QualityConfig:
    buckets: int = 10_000
    smoothing: float = 20.0
    #: Nats for each n-gram below which a document is dropped.
    min_score: float = -0.045


def _words(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    space = (raw == 0x20) | ((raw >= 0x09) & (raw <= 0x0D))
    return _text.runs(~space)


def _grams(texts: list[str], buckets: int):
    """Words of the texts and their hashed n-grams: (raw bytes, text starts, word starts, ends, hashes, owner, gram owner, gram bucket)."""
    raw, at = _text.utf8_bytes(texts)
    s, e = _words(raw)
    h = _text.span_hashes(raw, s, e)
    owner = np.searchsorted(at, s, side="right") - 1
    two = np.flatnonzero(owner[:-1] == owner[1:]) if len(owner) else np.zeros(0, np.int64)
    pair = _text.ngram_hashes(h, 2)[two] if len(two) else np.zeros(0, np.uint64)
    gram_owner = np.concatenate([owner, owner[two]])
    bucket = (np.concatenate([h, pair]) % np.uint64(buckets)).astype(np.int64)
    return raw, at, s, e, h, owner, gram_owner, bucket


def measures(texts: list[str], buckets: int = 0) -> dict[str, np.ndarray]:
    """Base measures of whole texts; with ``buckets`` also the owner and bucket of each n-gram."""
    n = len(texts)
    raw, at, s, e, h, owner, gram_owner, bucket = _grams(texts, max(1, buckets))
    count = lambda who: np.bincount(who, minlength=n)[:n]
    lead = np.concatenate(([0], np.cumsum((raw & 0xC0) != 0x80)))
    chars = np.bincount(owner, weights=lead[e] - lead[s], minlength=n)[:n].astype(np.int64) if len(s) else np.zeros(n, np.int64)
    sym = np.flatnonzero(np.isin(raw, np.frombuffer(SYMBOLS, np.uint8)))
    out = {"n_words": count(owner), "word_chars": chars, "n_symbols": count(np.searchsorted(at, sym, side="right") - 1)}
    # lines with a word that equal an earlier line of their text
    ends = np.flatnonzero(raw == 0x0A)
    starts = np.concatenate(([0], ends[:-1] + 1)) if len(ends) else ends
    line_owner = np.searchsorted(at, starts, side="right") - 1
    has = np.searchsorted(s, ends) > np.searchsorted(s, starts)
    starts, ends, line_owner = starts[has], ends[has], line_owner[has]
    key = _text.mix(_text.span_hashes(raw, starts, ends) ^ _text.mix(line_owner.astype(np.uint64)))
    first = np.zeros(len(key), dtype=bool)
    first[np.unique(key, return_index=True)[1]] = True
    out["n_dup_lines"] = count(line_owner[~first])
    # words inside a three-word window that its text holds twice or more
    covered = np.zeros(len(s), dtype=bool)
    if len(s) >= 3:
        inside = np.flatnonzero(owner[:-2] == owner[2:])
        tri = _text.mix(_text.ngram_hashes(h, 3)[inside] ^ _text.mix(owner[inside].astype(np.uint64)))
        _, back, times = np.unique(tri, return_inverse=True, return_counts=True)
        twice = inside[times[back] > 1]
        for i in range(3):
            covered[twice + i] = True
    out["n_repeat_words"] = count(owner[covered])
    out["gram_owner"], out["bucket"] = gram_owner, bucket
    return out


def bucket_counts(docs: DataFrame, trusted: DataFrame, cfg: QualityConfig, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(bucket, n_raw, n_target) over all rows; ``trusted`` has one row for each good document."""
    good = trusted.select(F.col(key)).where(F.col(key).isNotNull()).distinct().withColumn("good", F.lit(True))
    rows = docs.select(key, text).join(small(good), key, "left").select(text, F.coalesce("good", F.lit(False)).alias("good"))

    def run(batches):
        raw, target = np.zeros(cfg.buckets, np.int64), np.zeros(cfg.buckets, np.int64)
        for b in batches:
            good = np.asarray(b.column(1).to_pylist(), dtype=bool)
            sizes = [len(t.as_buffer()) if t.is_valid else 0 for t in b.column(0)]
            for lo, hi in _text.pieces(sizes):
                *_, who, bucket = _grams([t or "" for t in b.column(0).slice(lo, hi - lo).to_pylist()], cfg.buckets)
                raw += np.bincount(bucket, minlength=cfg.buckets)
                target += np.bincount(bucket[good[lo:hi][who]], minlength=cfg.buckets)
        some = np.flatnonzero(raw)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(raw[some]), pa.array(target[some])], ["bucket", "n_raw", "n_target"])

    part = rows.mapInArrow(run, "bucket bigint, n_raw bigint, n_target bigint")
    return part.groupBy("bucket").agg(F.sum("n_raw").alias("n_raw"), F.sum("n_target").alias("n_target"))


def log_ratio(counts: DataFrame, cfg: QualityConfig) -> np.ndarray:
    """log p_target - log p_raw of each bucket; the table has ``cfg.buckets`` entries at any corpus size."""
    raw, target = np.zeros(cfg.buckets), np.zeros(cfg.buckets)
    for r in counts.collect():  # at most cfg.buckets rows
        raw[r["bucket"]], target[r["bucket"]] = r["n_raw"], r["n_target"]
    if not target.sum():
        return np.zeros(cfg.buckets)
    # the target is smoothed towards the raw corpus, so a rare n-gram of a small target is no evidence
    p_raw = (raw + cfg.smoothing) / (raw.sum() + cfg.smoothing * cfg.buckets)
    return np.log((target + cfg.smoothing * cfg.buckets * p_raw) / (target.sum() + cfg.smoothing * cfg.buckets)) - np.log(p_raw)


def _verdicts(texts: pa.Array, ratio: np.ndarray, cfg: QualityConfig):
    """For each piece of the texts (n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, llr)."""
    for lo, hi in _text.pieces([len(t.as_buffer()) if t.is_valid else 0 for t in texts]):
        m = measures([t or "" for t in texts.slice(lo, hi - lo).to_pylist()], cfg.buckets)
        grams = np.bincount(m["gram_owner"], minlength=hi - lo)
        total = np.bincount(m["gram_owner"], weights=ratio[m["bucket"]], minlength=hi - lo)
        llr = np.floor(total / np.maximum(grams, 1) * 1e9 + 0.5) / 1e9
        bad = (m["n_words"] < MIN_WORDS) | (100 * m["n_repeat_words"] > 50 * m["n_words"])
        yield m["n_words"], m["word_chars"], m["n_symbols"], m["n_dup_lines"], m["n_repeat_words"], bad, ~bad & (llr >= cfg.min_score), llr


def score(docs: DataFrame, ratio: np.ndarray, cfg: QualityConfig = QualityConfig(), key: str = "doc_id", text: str = "text") -> DataFrame:
    """Measures, score and verdict of every whole text."""
    shared = docs.sparkSession.sparkContext.broadcast(ratio)
    kinds = "n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, base_failed boolean, kept boolean, llr double"

    def run(batches):
        for b in batches:
            got = list(_verdicts(b.column(1), shared.value, cfg))
            cols = [np.concatenate(c) for c in zip(*got)] if got else [np.zeros(0, t) for t in (np.int64,) * 5 + (bool, bool, float)]
            cols = [pa.array(c.astype(np.int64) if c.dtype.kind in "iu" else c) for c in cols]
            yield pa.RecordBatch.from_arrays([b.column(0), *cols], [key, *[k.split()[0] for k in kinds.split(", ")]])

    slim = docs.select(key, text)
    return slim.mapInArrow(run, f"`{key}` {dict(slim.dtypes)[key]}, {kinds}")


def trusted_rows(labels: DataFrame, key: str = "doc_id") -> DataFrame:
    return labels.where((F.col("quality") == 1) & (F.coalesce("toxic", F.lit(0)) == 0)).select(key)


def judge(docs: DataFrame, labels: DataFrame, cfg: QualityConfig = QualityConfig()) -> DataFrame:
    """Both passes: corpus and target counts over all rows, then a verdict for every document."""
    ratio = log_ratio(bucket_counts(docs, trusted_rows(labels), cfg), cfg)
    return score(docs, ratio, cfg)


def filter_documents(docs: DataFrame, labels: DataFrame, cfg: QualityConfig = QualityConfig(), text: str = "text") -> DataFrame:
    """The documents that are kept, with all their columns, without a join: the text passes through the scorer."""
    ratio = log_ratio(bucket_counts(docs, trusted_rows(labels), cfg), cfg)
    shared = docs.sparkSession.sparkContext.broadcast(ratio)
    at = docs.columns.index(text)

    def run(batches):
        for b in batches:
            keep = [v[6] for v in _verdicts(b.column(at), shared.value, cfg)]
            yield b.filter(pa.array(np.concatenate(keep) if keep else np.zeros(0, bool)))

    return docs.mapInArrow(run, docs.schema)
