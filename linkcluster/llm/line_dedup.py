"""Line deduplication by content-defined line chunks.

Lines are hashed; a rolling hash over ``window`` line hashes decides after which lines a
chunk ends, so boundaries depend on the lines around them alone and an insertion
shifts nothing beyond it.  A line of ``long_words`` or more is a chunk by itself, since a
long passage on one line is worth a chunk.  Chunks of several lines, and such long lines,
that occur again anywhere in the corpus are removed but for their first occurrence (least
document, then position), after their bytes have been compared with those of the kept one.
So are passages: runs of adjacent lines of ``long_words`` or more together.  They are looked up
from every line, so a repeated passage goes whole, whatever stands around it.  A repeat that
overlaps its own first occurrence stays.

Defined cases: a null text stays null with no line; an empty text has one empty line; blank
chunks are never removed; repeated rows and ties in id are ordered by the text's hash, then
position, and rows alike in id and text keep or lose the same chunks; very long texts are worked on
whole; other columns may have any name, and those named ``n_lines`` or ``n_removed_lines`` are
replaced; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkcluster.llm._frame import HOT_ROWS, cut, flagged, flags, join_hot, packed, unpacked


@dataclass(frozen=True)
class ChunkConfig:
    window: int = 2
    #: One line in ``divisor`` ends a chunk.
    divisor: int = 4
    long_words: int = 50
    seed: int = 3


def row_key(key: str, text: str) -> Column:
    return F.xxhash64(F.coalesce(F.col(key).cast("string"), F.lit("")), F.col(text))


def n_words(line: Column) -> Column:
    """Runs without blanks in a line: single spaces between them are counted, which is far faster than matching each run."""
    t = F.btrim(F.regexp_replace(line, r"[\x09-\x0D][\x20\x09-\x0D]*|\x20[\x20\x09-\x0D]+", " "), F.lit(" "))
    return F.when(t == "", 0).otherwise(F.octet_length(t) - F.octet_length(F.replace(t, F.lit(" "), F.lit(""))) + 1)


def with_chunks(df: DataFrame, text: str, cfg: ChunkConfig) -> DataFrame:
    """Adds ``lines`` and ``chunks``: array of (first, n, long) over the lines."""
    d = df.withColumn("lines", F.split(F.col(text), "\n", -1)).withColumn("lh", F.transform("lines", lambda x: F.xxhash64(x)))
    d = d.withColumn("words", F.transform("lines", n_words)).withColumn("big", F.transform("words", lambda n: n >= cfg.long_words))
    back = ", ".join(f"IF(i >= {k}, lh[i - {k}], 0L)" for k in range(cfg.window))
    ends = f"(pmod(xxhash64({back}, {cfg.seed}), {cfg.divisor}) = 0)"
    d = d.withColumn("starts", F.expr(f"filter(sequence(0, size(lines) - 1), j -> j = 0 OR big[j] OR big[j - 1] OR exists(array(j - 1), i -> {ends}))"))
    d = d.withColumn("chunks", F.expr("transform(starts, (s, k) -> struct(s AS first, IF(k + 1 < size(starts), starts[k + 1], size(lines)) - s AS n, big[s] AS long))"))
    return d.drop("big", "starts")


def with_passages(df: DataFrame, cfg: ChunkConfig) -> DataFrame:
    """Adds to ``chunks`` the runs of adjacent lines that just reach ``long_words``: on from each line with words, and back from each.

    A run of that many words is the union of the passages inside it, and a passage does not depend on
    the lines around it.
    """
    unit, most = 1 << 20, cfg.long_words  # words times ``unit`` plus lines; so many lines with words are enough
    reach = lambda part: f"transform(sequence(0, size(at) - 1), k -> named_struct('k', k, 'a', aggregate({part}, 0L, (a, x) -> IF(a >= {most * unit}L, a, a + x * {unit}L + 1L))))"
    run = lambda part, lo, hi: F.expr(f"IF(size(at) = 0, cast(array() AS array<struct<first: int, n: int>>), transform(filter({reach(part)}, x -> x.a >= {most * unit}L), x -> named_struct('first', at[{lo}], 'n', at[{hi}] - at[{lo}] + 1)))")
    d = df.withColumn("at", F.expr("filter(sequence(0, size(lines) - 1), i -> words[i] > 0)")).withColumn("w", F.expr("transform(at, i -> words[i])"))
    length = f"cast(x.a % {unit} AS int)"
    on = run(f"slice(w, k + 1, {most})", "x.k", f"x.k + {length} - 1")
    back = run(f"reverse(slice(w, greatest(k + 2 - {most}, 1), least(k + 1, {most})))", f"x.k - {length} + 1", "x.k")
    return d.withColumn("chunks", F.array_union("chunks", F.array_union(on, back))).drop("at", "w")


def chunk_rows(docs: DataFrame, cfg: ChunkConfig, key: str, text: str) -> DataFrame:
    """(id, row, first, n, h, g) of all chunks and passages that may be removed."""
    d = with_chunks(docs.select(F.col(key).alias("id"), row_key(key, text).alias("row"), F.col(text).alias("text")).where("text is not null"), "text", cfg)
    worded = F.expr("filter(chunks, c -> (c.n >= 2 OR c.long) AND exists(slice(words, c.first + 1, c.n), x -> x > 0))")
    d = with_passages(d.withColumn("chunks", F.transform(worded, lambda c: F.struct(c["first"].alias("first"), c["n"].alias("n")))), cfg)
    hashed = F.expr(f"transform(chunks, c -> named_struct('first', c.first, 'n', c.n, 'h', xxhash64(slice(lh, c.first + 1, c.n)), 'g', xxhash64({cfg.seed}, slice(lh, c.first + 1, c.n))))")
    return d.select("id", "row", F.explode(hashed).alias("c")).select("id", "row", "c.*")


def removals(docs: DataFrame, cfg: ChunkConfig = ChunkConfig(), key: str = "doc_id", text: str = "text") -> DataFrame:
    """(row, gone, copies): for each row with repeated chunks, its (first, n) ranges of lines to remove."""
    chunks = cut(chunk_rows(docs, cfg, key, text))
    # hashes first: only what is seen twice sends its bytes
    groups = chunks.groupBy("h", "g").agg(F.count(F.lit(1)).alias("times"), F.min(F.struct("id", "row", "first")).alias("kept"))
    twice = cut(groups.where("times > 1").select("h", "g", "times", "kept"))
    often = F.col("times") > HOT_ROWS
    hits = join_hot(chunks, twice, ["h", "g"], often, "row", may_broadcast=False)
    one = F.struct("first", "n", "h", "g", "times", "kept", F.struct("id", "row", "first").eqNullSafe(F.col("kept")).alias("is_kept"))
    # rows alike in id and text share a key and their hits
    hits = cut(hits.groupBy("row").agg(F.collect_set(one).alias("hits"), F.count(F.lit(1)).alias("rows")).withColumn("copies", F.col("rows") / F.size("hits")))
    # only texts with hits travel
    texts = flagged(docs.where(F.col(text).isNotNull()).select(row_key(key, text).alias("row"), F.col(text).alias("text")), "row", flags(hits, "row")).where("maybe__")
    found = join_hot(texts, hits, ["row"], F.col("copies") > HOT_ROWS, "text", may_broadcast=False).withColumn("lines", F.split("text", "\n", -1))
    seen = cut(found.select("row", "copies", F.explode(F.expr("transform(hits, c -> struct(c.*, array_join(slice(lines, c.first + 1, c.n), '\n') AS chunk))".replace("c.*", ", ".join(f"c.{x} AS {x}" for x in ("first", "n", "h", "g", "times", "kept", "is_kept"))))).alias("c")).select("row", "copies", "c.*"))
    model = cut(seen.where("is_kept").groupBy("h", "g").agg(F.first("chunk").alias("model"), F.first("times").alias("times")))
    apart = (F.col("row") != F.col("kept.row")) | (F.col("first") >= F.col("kept.first") + F.col("n"))
    same = join_hot(seen.where(~F.col("is_kept") & apart).drop("times"), model, ["h", "g"], often, "row", may_broadcast=False).where("chunk = model")
    return same.groupBy("row").agg(F.collect_set(F.struct("first", "n")).alias("gone"), F.max("copies").alias("copies"))


def dedup(docs: DataFrame, cfg: ChunkConfig = ChunkConfig(), key: str = "doc_id", text: str = "text") -> DataFrame:
    """All columns of ``docs``; the text without repeated chunks, and ``n_lines``, ``n_removed_lines``."""
    gone = cut(removals(docs, cfg, key, text))
    d = flagged(packed(docs, row=row_key(key, text), body=F.col(text)), "row", flags(gone, "row"))
    # texts that lose nothing stay where they are
    rest = d.where(~F.col("maybe__")).select("doc__", "body", F.lit(None).cast(gone.schema["gone"].dataType).alias("gone"))
    d = join_hot(d.where("maybe__"), gone, ["row"], F.col("copies") > HOT_ROWS, "body", "left", may_broadcast=False).select("doc__", "body", "gone").unionByName(rest)
    lines = F.split("body", "\n", -1)
    out = F.array_distinct(F.flatten(F.transform("gone", lambda g: F.sequence(g["first"], g["first"] + g["n"] - 1))))
    n_lines = F.coalesce(F.when(F.col("body").isNotNull(), F.size(lines)), F.lit(0)).cast("bigint")
    n_gone = F.coalesce(F.when(F.col("gone").isNotNull(), F.size(out)), F.lit(0)).cast("bigint")
    kept = F.transform(F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), out), lambda i: F.get(lines, i))
    new = F.when(F.col("gone").isNull(), F.col("body")).otherwise(F.array_join(kept, "\n"))
    return unpacked(d, docs, **{text: new, "n_lines": n_lines, "n_removed_lines": n_gone})
