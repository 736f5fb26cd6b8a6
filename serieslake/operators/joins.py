"""Joins that Spark has no single operator for: as-of, interval by buckets, salted skew join."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, values: list[str]) -> DataFrame:
    """Each left row with ``values`` of the last right row of its key at or before its time (nulls if none).
    One union and one window by key and time; a right row comes before a left row of the same time."""
    a = left.withColumn("_t", F.col(left_time)).withColumn("_side", F.lit(1))
    b = right.select(key, F.col(right_time).alias("_t"), F.struct(*values).alias("_v")).withColumn("_side", F.lit(0))
    both = a.unionByName(b, allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    got = both.withColumn("_last", F.last("_v", ignorenulls=True).over(w)).where("_side = 1")
    return got.select(*left.columns, *(F.col(f"_last.{v}").alias(v) for v in values))


def interval(left: DataFrame, right: DataFrame, point: str, start: str, end: str, width: float) -> DataFrame:
    """Left rows with the right rows whose [start, end] holds their point: an equi-join on buckets of
    ``width`` with the range as residual, never a nested loop. A right row goes to each bucket it touches."""
    a = left.withColumn("_b", F.floor(F.col(point) / width))
    b = right.withColumn("_b", F.explode(F.sequence(F.floor(F.col(start) / width), F.floor(F.col(end) / width))))
    return a.join(b, "_b").where((F.col(point) >= F.col(start)) & (F.col(point) <= F.col(end))).drop("_b")


def salted(big: DataFrame, small: DataFrame, key: str, salts: int, how: str = "inner") -> DataFrame:
    """Equi-join with the big side's keys dealt over ``salts`` and the small side repeated for each salt.
    The salt is a hash of the row, so a retried task deals it the same way. Both sides are shuffled: Spark's estimate
    of the small side knows nothing of the repetition, so it would be broadcast at any number of rows."""
    salt = F.pmod(F.xxhash64(*big.columns), F.lit(salts)).cast("int")
    repeated = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return big.withColumn("_salt", salt).join(repeated.hint("merge"), [key, "_salt"], how).drop("_salt")


def max_per_bucket(df: DataFrame, key: Column) -> DataFrame:
    """(rows of the largest key, rows in all): how skewed a join or aggregation on ``key`` would be."""
    return df.groupBy(key.alias("k")).agg(F.count(F.lit(1)).alias("n")).agg(F.max("n").alias("largest"), F.sum("n").alias("rows"))
