"""Baselines for top-k over distributed sums: full sums, a threshold algorithm and a three-phase uniform threshold."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from thriftline.operators.topk_merge import with_ties
from thriftline.shipping import written


def full(partials: DataFrame, k: int, ties: bool = True) -> DataFrame:
    """(key, total) of the k best after summing every part in full."""
    sums = partials.groupBy("key").agg(F.sum("val").alias("total"))
    return with_ties(sums, F.col("total"), k) if ties else sums.orderBy(F.col("total").desc(), "key").limit(k)


@dataclass
class Accesses:
    df: DataFrame
    sorted_accesses: int
    random_accesses: int


def threshold_algorithm(partials: DataFrame, k: int, batch: int = 64, ties: bool = True) -> Accesses:
    """Sorted access to all shards in lockstep, full sums of the keys seen, until the k-th is at least the sum of the frontier.

    The depth doubles, so there are few rounds; only a frontier value and a count come to the driver.
    """
    partials = written(partials)
    order = W.partitionBy("shard").orderBy(F.col("val").desc(), "key")
    depth, deepest = batch, partials.groupBy("shard").count().agg(F.max("count").alias("r")).first()["r"] or 0
    while True:
        # Only ranks up to the depth are worked out, so each task's rows are cut to it before the exchange.
        seen = partials.withColumn("_rank", F.row_number().over(order)).where(F.col("_rank") <= depth)
        keys = seen.select("key").distinct()
        sums = partials.join(keys, "key", "left_semi").groupBy("key").agg(F.sum("val").alias("total"))
        kth = sums.orderBy(F.col("total").desc()).limit(k).agg(F.count("*").alias("n"), F.min("total").alias("t")).first()
        # A shard that ended before this depth has nothing more to add.
        frontier = seen.where(F.col("_rank") == depth).agg(F.sum("val").alias("f")).first()["f"] or 0
        if depth >= deepest or (kth["n"] == k and kth["t"] > frontier) or (kth["n"] == k and not ties and kth["t"] >= frontier):
            break
        depth *= 2
    n = seen.count()
    looked = partials.join(keys, "key", "left_semi").count() - n
    out = with_ties(sums, F.col("total"), k) if ties else sums.orderBy(F.col("total").desc(), "key").limit(k)
    return Accesses(out, n, looked)


def uniform_threshold(partials: DataFrame, shards: int, k: int) -> Accesses:
    """Three rounds: local best k give a first bound; all parts of at least a P-th of it give bounds; the rest of the candidates."""
    partials = written(partials)
    first = partials.withColumn("_rank", F.row_number().over(W.partitionBy("shard").orderBy(F.col("val").desc(), "key"))).where(F.col("_rank") <= k)
    t1 = first.groupBy("key").agg(F.sum("val").alias("s")).orderBy(F.col("s").desc()).limit(k).agg(F.min("s").alias("t")).first()["t"] or 0
    cut = max(1, t1 // shards) if t1 > 0 else t1
    sent = partials.where(F.col("val") >= cut)
    bounds = sent.groupBy("key").agg(F.sum("val").alias("lo"), F.count("*").alias("n")).withColumn("hi", F.col("lo") + (shards - F.col("n")) * F.lit(max(cut - 1, 0)))
    second = bounds.orderBy(F.col("lo").desc()).limit(k).agg(F.min("lo").alias("t"), F.count("*").alias("n")).first()
    least = max(t1, second["t"]) if second["n"] == k else t1
    keys = bounds.where(F.col("hi") >= least).select("key")
    sums = partials.join(keys, "key", "left_semi").groupBy("key").agg(F.sum("val").alias("total"))
    return Accesses(with_ties(sums, F.col("total"), k), sent.count(), partials.join(keys, "key", "left_semi").where(F.col("val") < cut).count())
