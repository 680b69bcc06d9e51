"""Streaming: arrival rates, deduplication, late rows and incremental entity assignment."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkcluster.functions.compose import LABEL, PairMeasure
from linkcluster.functions.normalize import grid
from linkcluster.operators import blocking
from linkcluster.operators.preprocess import compatible
from linkcluster.plans.config import ENTITY


def events(stream: DataFrame, ts: str = "ts") -> DataFrame:
    """Event time as a zoned timestamp; watermarks need one."""
    return stream.withColumn(ts, F.col(ts).cast("timestamp"))


def rates(stream: DataFrame, window: str = "1 hour", slide: str | None = None, by: list[str] = ("event_type",), late: str = "10 minutes") -> DataFrame:
    """Counts over tumbling or sliding windows."""
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    return events(stream).withWatermark("ts", late).groupBy(w.alias("w"), *by).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *by, "n")


def sessions(stream: DataFrame, gap: str = "30 minutes", by: str = "user_id", late: str = "10 minutes") -> DataFrame:
    return events(stream).withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), by).agg(F.count(F.lit(1)).alias("n")).select(by, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def deduplicate(stream: DataFrame, key: str = "event_id", late: str = "10 minutes") -> DataFrame:
    return events(stream).withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def interval_pairs(left: DataFrame, right: DataFrame, by: str = "user_id", within: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Stream-stream join: right rows of the same user at most ``within`` after a left row."""
    a = events(left).withWatermark("ts", late).select(F.col(by).alias("k"), F.col("ts").alias("t1"), F.col("event_id").alias("left_id"))
    b = events(right).withWatermark("ts", late).select(F.col(by).alias("k2"), F.col("ts").alias("t2"), F.col("event_id").alias("right_id"))
    return a.join(b, F.expr(f"k = k2 AND t2 >= t1 AND t2 <= t1 + INTERVAL {within}"))


def split_late(batch: DataFrame, seen_until, ts: str = "ts") -> tuple[DataFrame, DataFrame]:
    """(rows in time, late rows) against an event time already closed; for use inside foreachBatch."""
    d = events(batch, ts)
    return d.where(F.col(ts) >= F.lit(seen_until)), d.where(F.col(ts) < F.lit(seen_until))


def assign_batch(new: DataFrame, reps: DataFrame, k: int, theta: float, measure: PairMeasure = LABEL, prefix: int = 3) -> DataFrame:
    """(id, cid) of new entities: the most similar compatible representative of the same block, or a cluster
    of their own.  Of several entities of one source that choose the same cluster, the best gets it."""
    a = blocking.prefix(new, prefix)
    left = a.select("block", *[F.col(c).alias(f"l_{c}") for c in dict.fromkeys(("id", "source", "types", *measure.columns))])
    right = blocking.prefix(reps, prefix).select("block", *[F.col(c).alias(f"r_{c}") for c in dict.fromkeys(("cid", "types", "sources", "n", *measure.columns))])
    p = left.join(right, "block").where(~F.array_contains("r_sources", F.col("l_source")) & (F.col("r_n") < k))
    p = measure.apply(p.where(compatible(F.col("l_types"), F.col("r_types")))).where(F.col("sim") >= theta)
    best = p.groupBy("l_id", "l_source").agg(F.max_by(F.struct("r_cid", "sim"), F.struct(grid(F.col("sim")), -F.col("r_cid"))).alias("b"))
    won = best.withColumn("nth", F.expr("row_number() over (partition by b.r_cid, l_source order by b.sim desc, l_id)")).where("nth = 1").select(F.col("l_id").alias("id"), F.col("b.r_cid").alias("cid"))
    return new.select("id").join(won, "id", "left").select("id", F.coalesce("cid", "id").alias("cid"))


def assign_stream(spark: SparkSession, path: str, reps: DataFrame, out: str, checkpoint: str, k: int, theta: float, measure: PairMeasure = LABEL):
    """A running query that assigns arriving JSON entities to clusters; each batch is written once under its number."""
    arriving = spark.readStream.schema(ENTITY).json(path)

    def one(batch: DataFrame, n: int) -> None:
        assign_batch(batch.dropDuplicates(["id"]), reps, k, theta, measure).write.mode("overwrite").parquet(f"{out}/batch={n}")

    return arriving.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint)


def running_counts(stream: DataFrame, by: str = "user_id") -> DataFrame:
    """Arbitrary state: how many rows each key has sent so far, given out anew whenever it changes."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(key, frames, state):
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({by: [key[0]], "n": [n]})

    return stream.select(by).groupBy(by).applyInPandasWithState(step, f"{by} bigint, n bigint", "n bigint", "update", GroupStateTimeout.NoTimeout)
