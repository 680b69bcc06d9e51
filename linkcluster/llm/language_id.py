"""Language identification: averaged hashed subword embeddings under a linear softmax.

A text is lower-cased, everything but letters becomes a boundary, and all subwords of two
to four characters that do not cross a word are hashed into a table of embeddings.  Their
average goes through a linear softmax.  Both are trained by mini-batch stochastic gradient
descent in numpy on a bounded, documented sample of labelled rows (``max_per_lang`` a
language); the temperature and the rejection threshold come from a calibration part of
that sample that training does not see.

Defined cases: a null text or one without a letter is ``und`` with score 0 and is not
accepted; with no labelled row every text is ``und``; ties go to the lesser language name.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkcluster.functions import text_arrays as _text

UNKNOWN = "und"


@dataclass(frozen=True)
class LanguageConfig:
    buckets: int = 1 << 14
    dim: int = 16
    sizes: tuple[int, ...] = (2, 3, 4)
    #: Bound on the labelled rows of a language that are fitted.
    max_per_lang: int = 500
    epochs: int = 8
    #: A small sample is passed over more often, until this many steps are done.
    min_steps: int = 1200
    rate: float = 20.0
    batch: int = 16
    #: Share of right calibration predictions that rejection may cost.
    reject_quantile: float = 0.01
    seed: int = 7


@dataclass(frozen=True)
class LanguageModel:
    langs: list[str]
    #: Embedding table times softmax weights: bucket by language.
    table: np.ndarray = field(repr=False)
    bias: np.ndarray = field(repr=False)
    temperature: float
    threshold: float
    config: LanguageConfig


def subwords(texts: list[str], cfg: LanguageConfig) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each size: (number of the text, bucket) of every subword, by text."""
    low = [t.lower() for t in texts]
    codes, starts = _text.code_points(low)
    c = np.where(_text.letters(codes), codes, 0).astype(np.uint64)
    keep = (c != 0) | np.concatenate(([True], c[:-1] != 0))
    doc = np.repeat(np.arange(len(texts)), np.diff(starts))[keep]
    c = np.concatenate(([np.uint64(0)], c[keep]))
    doc = np.concatenate(([0], doc))
    out = []
    for n in cfg.sizes:
        m = len(c) - n + 1
        if m <= 0:
            out.append((np.zeros(0, np.int64), np.zeros(0, np.int64)))
            continue
        ok = np.ones(m, dtype=bool)
        for i in range(1, n - 1):
            ok &= c[i : i + m] != 0
        if n == 2:
            ok &= (c[:m] != 0) | (c[1 : 1 + m] != 0)
        at = np.flatnonzero(ok)
        h = np.zeros(len(at), dtype=np.uint64)
        for i in range(n):
            h = h * np.uint64(_text.BASE) + c[at + i]
            h ^= h >> np.uint64(31)
        owner = doc[at + (c[at] == 0)]
        out.append((owner, ((h * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(40)).astype(np.int64) & (cfg.buckets - 1)))
    return out


def _counts(texts: list[str], cfg: LanguageConfig) -> list[tuple[np.ndarray, np.ndarray]]:
    parts = subwords(texts, cfg)
    owner, bucket = np.concatenate([o for o, _ in parts]), np.concatenate([b for _, b in parts])
    both, n = np.unique(owner * cfg.buckets + bucket, return_counts=True)
    who = both // cfg.buckets
    cut = np.searchsorted(who, np.arange(len(texts) + 1))
    return [((both[a:b] % cfg.buckets).astype(np.int32), n[a:b].astype(np.int32)) for a, b in zip(cut[:-1], cut[1:])]


def held_out(key: str = "doc_id"):
    """Rows whose crc32 of the id as text leaves 2 by 4; a null id is not held out."""
    return F.coalesce(F.crc32(F.col(key).cast("string")) % 4 == 2, F.lit(False))


def training_sample(docs: DataFrame, cfg: LanguageConfig, key: str, text: str, label: str) -> list:
    """Bounded sample with sparse subword counts: [(label, calibration?, buckets, counts)]."""
    rows = docs.where(F.col(text).isNotNull() & F.col(label).isNotNull() & F.col(key).isNotNull() & ~held_out(key))
    sizes = {r[0]: r[1] for r in rows.groupBy(label).count().collect()}  # one row a language
    if not sizes:
        return []
    share = F.lit(0)
    for lang, n in sorted(sizes.items()):
        share = F.when(F.col(label) == lang, F.lit(int(min(1.0, cfg.max_per_lang / n) * 1_000_000))).otherwise(share)
    drawn = F.pmod(F.xxhash64(F.col(key), F.lit(cfg.seed)), F.lit(1_000_000))
    chosen = rows.where(drawn < share).select(
        F.col(label).alias("label"), (F.pmod(F.xxhash64(F.col(key), F.lit(cfg.seed + 1)), F.lit(5)) == 0).alias("calibration"), F.xxhash64(F.col(key)).alias("k"), F.col(text).alias("text")
    )

    def run(batches):
        for b in batches:
            texts = b.column(3).to_pylist()
            got: list = []
            for lo, hi in _text.pieces([len(t) for t in texts]):
                got += _counts(texts[lo:hi], cfg)
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(1), b.column(2), pa.array([x[0].tolist() for x in got], pa.list_(pa.int32())), pa.array([x[1].tolist() for x in got], pa.list_(pa.int32()))], ["label", "calibration", "k", "buckets", "counts"]
            )

    got = chosen.mapInArrow(run, "label string, calibration boolean, k bigint, buckets array<int>, counts array<int>").toArrow()
    order = np.argsort(np.asarray(got.column("k").combine_chunks()), kind="stable")
    cols = {n: got.column(n).combine_chunks() for n in ("label", "calibration", "buckets", "counts")}
    return [(cols["label"][int(i)].as_py(), cols["calibration"][int(i)].as_py(), np.asarray(cols["buckets"][int(i)].values), np.asarray(cols["counts"][int(i)].values)) for i in order if len(cols["buckets"][int(i)].values)]


def _softmax(z: np.ndarray) -> np.ndarray:
    z = np.exp(z - z.max(axis=-1, keepdims=True))
    return z / z.sum(axis=-1, keepdims=True)


def fit(sample: list, cfg: LanguageConfig = LanguageConfig()) -> LanguageModel | None:
    """Stochastic gradient descent on the sample; None when nothing is labelled."""
    if not sample:
        return None
    langs = sorted({s[0] for s in sample})
    rng = np.random.default_rng(cfg.seed)
    emb = rng.normal(0, 0.1, (cfg.buckets, cfg.dim))
    out = rng.normal(0, 0.1, (cfg.dim, len(langs)))
    bias = np.zeros(len(langs))
    y = np.array([langs.index(s[0]) for s in sample])
    weight = [s[3] / s[3].sum() for s in sample]
    train = [i for i, s in enumerate(sample) if not s[1]] or list(range(len(sample)))
    check = [i for i, s in enumerate(sample) if s[1]] or train
    a_pass = -(-len(train) // cfg.batch)
    epochs = max(cfg.epochs, -(-cfg.min_steps // a_pass))
    steps, done = epochs * a_pass, 0
    for _ in range(epochs):
        order = rng.permutation(train)
        for at in range(0, len(order), cfg.batch):
            rate = cfg.rate * (1 - done / (steps + 1)) / cfg.batch
            done += 1
            ids = order[at : at + cfg.batch]
            mean = np.stack([weight[i] @ emb[sample[i][2]] for i in ids])
            gap = _softmax(mean @ out + bias)
            gap[np.arange(len(ids)), y[ids]] -= 1
            back = gap @ out.T
            out -= 0.1 * rate * mean.T @ gap
            bias -= 0.01 * rate * gap.sum(axis=0)
            for j, i in enumerate(ids):
                emb[sample[i][2]] -= rate * weight[i][:, None] * back[j]
    table = emb @ out
    z = np.stack([weight[i] @ table[sample[i][2]] for i in check]) + bias
    heat = min(np.geomspace(0.05, 20, 60), key=lambda t: -np.log(np.maximum(1e-12, _softmax(z / t)[np.arange(len(check)), y[check]])).mean())
    p = _softmax(z / heat)
    right = p.argmax(axis=1) == y[check]
    threshold = float(np.quantile(p.max(axis=1)[right], cfg.reject_quantile)) if right.any() else 1.0
    return LanguageModel(langs, table, bias, float(heat), threshold, cfg)


def predict_texts(texts: list[str], model: LanguageModel | None) -> tuple[list[str], list[float], list[bool]]:
    if model is None:
        return [UNKNOWN] * len(texts), [0.0] * len(texts), [False] * len(texts)
    total, n = np.zeros((len(texts), len(model.langs))), np.zeros(len(texts))
    for owner, bucket in subwords(texts, model.config):
        if len(owner):
            first = np.flatnonzero(np.concatenate(([True], owner[1:] != owner[:-1])))
            total[owner[first]] += np.add.reduceat(model.table[bucket], first, axis=0)
            n += np.bincount(owner, minlength=len(texts))
    p = _softmax((total / np.maximum(n, 1)[:, None] + model.bias) / model.temperature)
    best, score = p.argmax(axis=1), p.max(axis=1)
    some = n > 0
    return [model.langs[b] if s else UNKNOWN for b, s in zip(best, some)], np.where(some, score, 0.0).tolist(), (some & (score >= model.threshold)).tolist()


def predict(docs: DataFrame, model: LanguageModel | None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, lang_pred, score, accepted) of every whole text.  The model is a fixed-size table and is broadcast."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in batches:
            texts = b.column(1)
            lang, score, ok = [], [], []
            sizes = [len(t.as_buffer()) if t.is_valid else 0 for t in texts]
            for lo, hi in _text.pieces(sizes):
                x, y, z = predict_texts([t or "" for t in texts.slice(lo, hi - lo).to_pylist()], shared.value)
                lang, score, ok = lang + x, score + y, ok + z
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(ok, pa.bool_())], [key, "lang_pred", "score", "accepted"])

    slim = docs.select(key, text)
    return slim.mapInArrow(run, f"`{key}` {dict(slim.dtypes)[key]}, lang_pred string, score double, accepted boolean")


def train(docs: DataFrame, cfg: LanguageConfig = LanguageConfig(), key: str = "doc_id", text: str = "text", label: str = "lang") -> LanguageModel | None:
    return fit(training_sample(docs, cfg, key, text, label), cfg)
