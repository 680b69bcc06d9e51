"""Relational helpers around the methods, each one plan."""

from __future__ import annotations

from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def join(left: DataFrame, right: DataFrame, on, how: str = "inner", hint: str | None = None, extra: Column | None = None) -> DataFrame:
    """Equi-join with an optional strategy hint and residual condition (inner joins)."""
    out = left.join(right.hint(hint) if hint else right, on, how)
    return out if extra is None else out.where(extra)


def cross(left: DataFrame, right: DataFrame, cap: int = 10_000) -> DataFrame:
    """Nested loop; refuses when the smaller side has more than ``cap`` rows."""
    if right.limit(cap + 1).count() > cap and left.limit(cap + 1).count() > cap:
        raise ValueError(f"both sides have more than {cap} rows")
    return left.crossJoin(right)


def band_join(left: DataFrame, right: DataFrame, lcol: str, rcol: str, width: float) -> DataFrame:
    """Pairs with values at most ``width`` apart: buckets of that width meet their neighbours."""
    b = lambda c: F.floor(F.col(c) / width).cast("bigint")
    spread = left.withColumn("__b", F.explode(F.array(b(lcol) - 1, b(lcol), b(lcol) + 1)))
    return spread.join(right.withColumn("__b", b(rcol)), "__b").where(F.abs(F.col(lcol) - F.col(rcol)) <= width).drop("__b")


def interval_join(left: DataFrame, right: DataFrame, by: list[str], t: str, u: str, lo: int, hi: int) -> DataFrame:
    """Pairs with the same ``by`` and right time in [t + lo, t + hi] seconds; buckets as wide as the interval keep keys even."""
    step = max(1, hi - lo)
    left = left.withColumn("__t", F.unix_timestamp(F.col(t).cast("timestamp")))
    right = right.withColumn("__u", F.unix_timestamp(F.col(u).cast("timestamp")))
    first, last = F.floor((F.col("__t") + lo) / step), F.floor((F.col("__t") + hi) / step)
    a = left.withColumn("__b", F.explode(F.sequence(first, last)))
    return a.join(right.withColumn("__b", F.floor(F.col("__u") / step)), [*by, "__b"]).where(F.col("__u").between(F.col("__t") + lo, F.col("__t") + hi)).drop("__b", "__t", "__u")


def asof_join(left: DataFrame, right: DataFrame, by: list[str], t: str, u: str, keep: list[str]) -> DataFrame:
    """For each left row the last right row of the same ``by`` with u <= t: one union and one window, no nested loop."""
    row = F.struct(F.col(u).alias("__u"), *[F.col(c) for c in keep])
    a = left.withColumn("__row", F.lit(None).cast(right.select(row.alias("r")).schema["r"].dataType)).withColumn("__side", F.lit(1)).withColumn("__at", F.col(t))
    b = right.select(*by, F.col(u).alias("__at"), row.alias("__row")).withColumn("__side", F.lit(0))
    w = W.partitionBy(*by).orderBy("__at", "__side", "__row").rowsBetween(W.unboundedPreceding, W.currentRow)
    both = a.unionByName(b, allowMissingColumns=True).withColumn("__hit", F.last("__row", ignorenulls=True).over(w))
    return both.where("__side = 1").select(*left.columns, *[F.col(f"__hit.{c}").alias(c) for c in keep])


def pairs(df: DataFrame, key: str, id: str) -> DataFrame:
    a, b = df.select(key, F.col(id).alias("a")), df.select(key, F.col(id).alias("b"))
    return a.join(b, key).where("a < b")


def cogroup_arrow(left: DataFrame, right: DataFrame, by: str, fn: Callable[[pa.Table, pa.Table], pa.Table], schema: str) -> DataFrame:
    return left.groupBy(by).cogroup(right.groupBy(by)).applyInArrow(fn, schema)


def best_by(df: DataFrame, by: list[str], value: list[str], *rank: Column) -> DataFrame:
    """The row of each group with the greatest rank, without a sort."""
    return df.groupBy(*by).agg(F.max_by(F.struct(*value), F.struct(*rank)).alias("__b")).select(*by, *[f"__b.{c}" for c in value])


dedupe_best = best_by


def gather(df: DataFrame, by: list[str], col: str, distinct: bool = True) -> DataFrame:
    return df.groupBy(*by).agg(F.array_sort(F.collect_set(col) if distinct else F.collect_list(col)).alias(col))


def distinct_count(df: DataFrame, by: list[str], col: str, approx: bool = False) -> DataFrame:
    return df.groupBy(*by).agg((F.approx_count_distinct(col) if approx else F.countDistinct(col)).alias("n"))


def quantiles(df: DataFrame, by: list[str], col: str, at: list[float], approx: bool = False) -> DataFrame:
    f = F.percentile_approx(col, at) if approx else F.percentile(col, at)
    return df.groupBy(*by).agg(f.alias("q"))


def multi_group(df: DataFrame, sets: list[list[str]], cols: list[str], *aggs: Column) -> DataFrame:
    return df.groupingSets([[F.col(c) for c in s] for s in sets], *cols).agg(*aggs)


def pivot(df: DataFrame, by: str, col: str, values: list, agg: Column) -> DataFrame:
    return df.groupBy(by).pivot(col, values).agg(agg)


def rank_in(df: DataFrame, by: list[str], *order: Column, kind: str = "row_number", name: str = "rank", n: int = 4) -> DataFrame:
    w = W.partitionBy(*by).orderBy(*order)
    f = {"row_number": F.row_number, "rank": F.rank, "dense_rank": F.dense_rank, "percent_rank": F.percent_rank, "ntile": lambda: F.ntile(n)}[kind]()
    return df.withColumn(name, f.over(w))


def shift(df: DataFrame, by: list[str], order: list, col: str, by_rows: int = 1, name: str = "previous") -> DataFrame:
    w = W.partitionBy(*by).orderBy(*order)
    return df.withColumn(name, F.lag(col, by_rows).over(w) if by_rows > 0 else F.lead(col, -by_rows).over(w))


def running(df: DataFrame, by: list[str], order: Column, agg: Column, lo, hi, rows: bool = True, name: str = "running") -> DataFrame:
    w = W.partitionBy(*by).orderBy(order)
    return df.withColumn(name, agg.over(w.rowsBetween(lo, hi) if rows else w.rangeBetween(lo, hi)))


def topk(df: DataFrame, order: list[Column], k: int, per: list[str] | None = None) -> DataFrame:
    if not per:
        return df.orderBy(*order).limit(k)
    return df.withColumn("__n", F.row_number().over(W.partitionBy(*per).orderBy(*order))).where(F.col("__n") <= k).drop("__n")


def stratified_sample(df: DataFrame, by: str, per_stratum: int, key: str, seed: int = 1) -> DataFrame:
    """A repeatable sample of at most ``per_stratum`` rows of each stratum, for review by hand."""
    return topk(df.withColumn("__h", F.xxhash64(F.col(key), F.lit(seed))), [F.col("__h"), F.col(key)], per_stratum, [by]).drop("__h")


def source_mask(sources: Column, order: list[str]) -> Column:
    """Sources as bits of a BIGINT (up to 63 sources): overlap tests become one AND."""
    if len(order) > 63:
        raise ValueError("more than 63 sources: keep arrays")
    bit = F.create_map(*[F.lit(x) for i, s in enumerate(sorted(order)) for x in (s, 1 << i)])
    return F.aggregate(sources, F.lit(0).cast("bigint"), lambda m, s: m.bitwiseOR(F.coalesce(bit[s].cast("bigint"), F.lit(0).cast("bigint"))))
