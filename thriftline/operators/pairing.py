"""The 1-factor schedule of an all-to-all exchange and a model of its time."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def partner(round_: int, u: int, shards: int) -> int:
    """Whom shard u meets in a round; meeting is mutual."""
    return (round_ - u) % shards


def schedule(spark: SparkSession, shards: int) -> DataFrame:
    """(round, u, v) for all rounds; each pair meets once, in both directions, and each shard once a round."""
    cells = spark.range(shards * shards)
    step, u = F.floor(F.col("id") / shards).cast("long"), (F.col("id") % shards).cast("long")
    return cells.select(step.alias("round"), u.alias("u")).withColumn("v", F.pmod(F.col("round") - F.col("u"), F.lit(shards)).cast("long"))


def makespan(volumes: DataFrame, shards: int) -> DataFrame:
    """From (src, dst, volume): volume on the critical path with the schedule, and if the busiest shard sends or receives all at once."""
    rounds = volumes.withColumn("round", F.pmod(F.col("src") + F.col("dst"), F.lit(shards)))
    paired = rounds.where("src <> dst").groupBy("round").agg(F.max("volume").alias("m")).agg(F.coalesce(F.sum("m"), F.lit(0)).cast("long").alias("scheduled"))
    moved = volumes.where("src <> dst")
    out = moved.groupBy(F.col("src").alias("s")).agg(F.sum("volume").alias("v")).unionAll(moved.groupBy(F.col("dst").alias("s")).agg(F.sum("volume").alias("v")))
    return paired.crossJoin(out.agg(F.coalesce(F.max("v"), F.lit(0)).cast("long").alias("busiest")))
