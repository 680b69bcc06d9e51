"""DataFrame helpers of this subpackage: checked broadcasts, joins on hot keys, and names that do not clash."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from linkcluster.plans.iterate import cut, ensure_checkpoint_dir  # noqa: F401

#: Bytes, as measured by ``sized``, up to which a materialised side is broadcast; beyond it the join shuffles.
BROADCAST_BYTES = 24 << 20
#: Rows of one key beyond which a join deals the key out to several tasks.
HOT_ROWS = 500
SALTS = 64


def _bytes(c: Column, kind: T.DataType) -> Column:
    if isinstance(kind, (T.StringType, T.BinaryType)):
        return F.coalesce(F.octet_length(c), F.lit(0)).cast("bigint") + 16
    if isinstance(kind, T.ArrayType):
        each = sum(8 for _ in kind.elementType.fields) if isinstance(kind.elementType, T.StructType) else 8
        if isinstance(kind.elementType, (T.StringType, T.BinaryType)):
            return F.aggregate(c, F.lit(16).cast("bigint"), lambda n, x: n + F.coalesce(F.octet_length(x), F.lit(0)) + 16)
        return F.coalesce(F.size(c), F.lit(0)).cast("bigint") * (each + 8) + 16
    if isinstance(kind, T.StructType):
        return sum((_bytes(c.getField(f.name), f.dataType) for f in kind.fields), F.lit(16).cast("bigint"))
    return F.lit(8).cast("bigint")


def sized(df: DataFrame) -> int:
    """Bytes of all rows of a materialised side, from the lengths of its values."""
    one = sum((_bytes(F.col(f"`{f.name}`"), f.dataType) for f in df.schema.fields), F.lit(16).cast("bigint"))
    return df.agg(F.coalesce(F.sum(one), F.lit(0))).first()[0]


def fits(df: DataFrame) -> bool:
    return sized(df) <= BROADCAST_BYTES


def small(df: DataFrame) -> DataFrame:
    """Hint a broadcast only after the bytes of a materialised side have been measured."""
    return F.broadcast(df) if fits(df) else df


#: Words of 64 bits in the mask of ``flags``: at most 16 MB as rows, whatever the corpus.
FLAG_WORDS = 1 << 20


def flags(keys: DataFrame, key: str) -> DataFrame:
    """(word__, bits__): a bit for each 64-bit hash in column ``key``, as a mask of bounded size.

    Rows whose bit is not set have no such key; the few others that share a bit must still be joined.
    """
    word, bit = F.pmod(F.shiftright(key, 6), F.lit(FLAG_WORDS)).cast("int"), F.expr(f"shiftleft(1L, cast({key} & 63 AS int))")
    return cut(keys.groupBy(word.alias("word__")).agg(F.bit_or(bit).alias("bits__")))


def flagged(rows: DataFrame, key: str, mask: DataFrame) -> DataFrame:
    """``rows`` with the boolean ``maybe__``: whether the bit of their key is set."""
    out = rows.withColumn("word__", F.pmod(F.shiftright(key, 6), F.lit(FLAG_WORDS)).cast("int")).join(F.broadcast(mask), "word__", "left")
    return out.withColumn("maybe__", F.coalesce(F.expr(f"(shiftrightunsigned(bits__, cast({key} & 63 AS int)) & 1) = 1"), F.lit(False))).drop("word__", "bits__")


def join_hot(rows: DataFrame, table: DataFrame, on: list[str], heavy: Column, spread: str, how: str = "inner", may_broadcast: bool = True) -> DataFrame:
    """``rows`` joined to the materialised ``table`` of one row for each key.

    ``heavy`` marks the keys of the table that many rows may carry.  A table that fits is broadcast. Else
    the heavy keys get ``SALTS`` salted copies, and rows of such a key, or with a null key, are dealt
    out by the hash of ``spread``.  Should even the list of heavy keys be too long to broadcast,
    all rows are salted.  ``may_broadcast=False`` is for tables that grow with the corpus, so that the
    plan is the same at every size.
    """
    if may_broadcast and fits(table):
        return rows.join(F.broadcast(table), on, how)
    hot = cut(table.where(heavy).select(*on))
    many = F.pmod(F.xxhash64(spread), F.lit(SALTS)).cast("int")
    every = F.sequence(F.lit(0), F.lit(SALTS - 1))
    if fits(hot):
        rows = rows.join(F.broadcast(hot.withColumn("hot__", F.lit(True))), on, "left")
        loose = F.coalesce("hot__", F.lit(False))
        for c in on:
            loose |= F.col(c).isNull()
        rows = rows.withColumn("salt__", F.when(loose, many).otherwise(F.lit(0))).drop("hot__")
        table = table.withColumn("salt__", F.explode(F.when(heavy, every).otherwise(F.array(F.lit(0)))))
    else:
        rows, table = rows.withColumn("salt__", many), table.withColumn("salt__", F.explode(every))
    return rows.join(table, [*on, "salt__"], how).drop("salt__")


def packed(df: DataFrame, **columns: Column) -> DataFrame:
    """All columns of ``df`` as the one struct ``doc__`` beside new ones, so that no name can clash."""
    return df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("doc__"), *[c.alias(n) for n, c in columns.items()])


def unpacked(df: DataFrame, like: DataFrame, **changed: Column) -> DataFrame:
    """The columns of ``like`` out of ``doc__``; those named in ``changed`` are replaced, or added at the end."""
    old = [changed.get(c, F.col("doc__").getField(c)).alias(c) for c in like.columns]
    return df.select(*old, *[v.alias(n) for n, v in changed.items() if n not in like.columns])


def read(spark, sf_dir: str, table: str, *cols: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    return df.select(*cols) if cols else df
