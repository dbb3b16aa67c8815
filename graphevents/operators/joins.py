"""Joins that the methods need and Spark has no single operator for."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, key: str, left_ts: str, right_ts: str, value: str) -> DataFrame:
    """``left`` with the latest ``value`` of ``right`` at or before its time. Both sides are laid into one stream of rows by key and
    time, and the last value seen is carried forward: one shuffle by key, no join, no product."""
    names = left.columns
    a = left.select(F.col(key).alias("__k"), F.col(left_ts).alias("__t"), F.lit(1).alias("__o"), F.lit(None).cast(right.schema[value].dataType).alias("__v"), F.struct(*names).alias("__row"))
    b = right.select(F.col(key).alias("__k"), F.col(right_ts).alias("__t"), F.lit(0).alias("__o"), F.col(value).alias("__v"), F.lit(None).cast(a.schema["__row"].dataType).alias("__row"))
    w = Window.partitionBy("__k").orderBy("__t", "__o").rowsBetween(Window.unboundedPreceding, 0)
    out = a.unionByName(b).withColumn("__last", F.last("__v", ignorenulls=True).over(w)).filter("__o = 1")
    return out.select("__row.*", F.col("__last").alias(value))


def range_join(points: DataFrame, spans: DataFrame, key: str, point: str, start: str, end: str, width: int) -> DataFrame:
    """Points inside spans of the same key. Spans are put in every bucket of ``width`` they touch and points in theirs, so the join is by
    equality and each pair meets once; choose ``width`` near the usual span."""
    bucket = lambda c: F.floor(c / width)
    s = spans.withColumn("__b", F.explode(F.sequence(bucket(F.col(start)), bucket(F.col(end)))))
    p = points.withColumn("__b", bucket(F.col(point)))
    return p.join(s, [key, "__b"]).filter((F.col(point) >= F.col(start)) & (F.col(point) <= F.col(end))).drop("__b")


def salted_join(big: DataFrame, small: DataFrame, key: str, salts: int) -> DataFrame:
    """An equality join for a hot key: rows of ``big`` are dealt to ``salts`` copies of ``small``."""
    b = big.withColumn("__s", F.pmod(F.xxhash64(*big.columns), F.lit(salts)).cast("int"))
    s = small.withColumn("__s", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return b.join(s, [key, "__s"]).drop("__s")


def top_k(df: DataFrame, group: str, order, k: int) -> DataFrame:
    """The first k rows of each group; Spark keeps k a task and group before the shuffle."""
    return df.withColumn("__r", F.row_number().over(Window.partitionBy(group).orderBy(*order))).filter(F.col("__r") <= k).drop("__r")
