"""Joins that Spark has no operator for, as compositions of its own: as-of, band and salted joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """left with the value of right's latest row of the same key at or before its time; null if there is none.

    One shuffle on the key, no pairs: both sides are merged in time order and the last value carried on. At equal times right's rows
    come first; of right's rows of one time the largest value counts.
    """
    names = left.columns
    a = left.select(F.col(key).alias("_k"), F.col(time).alias("_t"), F.lit(1).alias("_side"), F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.struct(*names).alias("_row"))
    one = right.groupBy(key, time).agg(F.max(value).alias(value))
    b = one.select(F.col(key).alias("_k"), F.col(time).alias("_t"), F.lit(0).alias("_side"), F.col(value).alias("_v"), F.lit(None).cast(a.schema["_row"].dataType).alias("_row"))
    w = W.partitionBy("_k").orderBy("_t", "_side").rowsBetween(W.unboundedPreceding, W.currentRow)
    return a.union(b).withColumn("_last", F.last("_v", ignorenulls=True).over(w)).where("_side = 1").select("_row.*", F.col("_last").alias(value))


def band(left: DataFrame, right: DataFrame, key: str, at: str, low: str, high: str, width: float) -> DataFrame:
    """Rows of left (key, at) with rows of right (key, low, high) where low <= at <= high: an equi-join on cells of the given width.

    A row of right is copied to each cell of its band, so width should be near the usual length of a band.
    """
    cell = lambda c: F.floor(F.col(c) / width).cast("bigint")
    b = right.withColumn("_cell", F.explode(F.sequence(cell(low), cell(high))))
    return left.withColumn("_cell", cell(at)).join(b, [key, "_cell"]).where((F.col(at) >= F.col(low)) & (F.col(at) <= F.col(high))).drop("_cell")


def salted(left: DataFrame, right: DataFrame, key: str, salts: int, by: str) -> DataFrame:
    """Equi-join on key where left's rows of a hot key are dealt over salts tasks by the hash of column by; right's rows are copied to each.

    A sort-merge join: the copies of right, which Spark's size estimate leaves out, are not to be broadcast.
    """
    a = left.withColumn("_salt", F.pmod(F.xxhash64(by), F.lit(salts)).cast("int"))
    b = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b.hint("merge"), [key, "_salt"]).drop("_salt")
