"""Joins that Spark has no operator for: as-of, interval by time bins, and salted joins of skewed keys."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, by: str, left_time: str, right_time: str, columns: list[str]) -> DataFrame:
    """Each left row with the columns of the last right row of its key at or before its time; nulls if there is none.

    Both sides are put in one order and the last right row is carried on, in one window; no row is joined with many.
    """
    own = [F.col(c) for c in left.columns]
    a = left.select(F.col(by).alias("_by"), F.col(left_time).alias("_t"), F.lit(1).alias("_side"), F.struct(*own).alias("_left"), F.lit(None).cast(right.select(F.struct(*columns)).schema[0].dataType).alias("_right"))
    b = right.select(F.col(by).alias("_by"), F.col(right_time).alias("_t"), F.lit(0).alias("_side"), F.lit(None).cast(a.schema["_left"].dataType).alias("_left"), F.struct(*columns).alias("_right"))
    order = W.partitionBy("_by").orderBy("_t", "_side").rowsBetween(W.unboundedPreceding, W.currentRow)
    carried = a.unionAll(b).withColumn("_last", F.last("_right", ignorenulls=True).over(order)).where("_side = 1")
    return carried.select("_left.*", *[F.col("_last")[c].alias(c) for c in columns])


def interval(points: DataFrame, time: str, spans: DataFrame, start: str, stop: str, bin_seconds: int) -> DataFrame:
    """Points within [start, stop) of a span: spans go to each time bin they touch, so the join is by bin."""
    seconds = lambda c: F.unix_seconds(F.col(c).cast("timestamp"))
    binned = points.withColumn("_bin", F.floor(seconds(time) / bin_seconds))
    touched = spans.withColumn("_span_bin", F.explode(F.sequence(F.floor(seconds(start) / bin_seconds), F.floor(seconds(stop) / bin_seconds))))
    joined = binned.join(touched, F.col("_bin") == F.col("_span_bin"))
    return joined.where((F.col(time) >= F.col(start)) & (F.col(time) < F.col(stop))).drop("_bin", "_span_bin")


def salted(large: DataFrame, small: DataFrame, condition_keys: tuple[str, str], salts: int = 16, row_id: str | Column = "l_orderkey") -> DataFrame:
    """A join whose hot keys are split over ``salts`` tasks: large rows draw one by a hash, small rows stand once in each.

    The copies of the small rows are never sent to all: Spark estimates them as if each row stood once, and they would meet on the driver.
    """
    salt = F.pmod(F.xxhash64(row_id), F.lit(salts))
    spread = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    left, right = condition_keys
    return large.withColumn("_s", salt).join(spread.hint("merge"), (F.col(left) == F.col(right)) & (F.col("_s") == F.col("_salt"))).drop("_s", "_salt")
