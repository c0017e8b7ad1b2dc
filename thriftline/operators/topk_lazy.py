"""Top-k under a remote filter, asked for in rank order and only as far as needed."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from thriftline.operators import semifilter, topk_merge
from thriftline.shipping import durable, written


@dataclass
class LazyResult:
    df: DataFrame
    asked: int
    rounds: int


def run(rows: DataFrame, score: str, key: str, fk: str, remote: DataFrame, pk: str, condition: Column, k: int, chunk: int | None = None, growth: float = 2.0, prune_every: int = 0, shard: str = "shard") -> LazyResult:
    """The k rows of largest score (then smallest key) whose partner qualifies.

    Each shard ranks its rows and asks for the filter of the next chunk of ranks until it has k rows that pass or none left.  With
    ``prune_every`` a shard stops too, every so many rounds, if its next score is below the k-th passing score of all shards.
    Chunks grow by ``growth``, so the rounds are logarithmic.  Only one row a shard comes to the driver in a round.
    """
    order = W.partitionBy(shard).orderBy(F.col(score).desc(), F.col(key))
    rows = written(rows)
    # Ranks up to a bound only: Spark cuts each task's rows to it before the exchange, so no shard is sorted whole.
    ranked = lambda most: rows.withColumn("_place", F.row_number().over(order)).where(F.col("_place") <= most)
    sizes = {r[shard]: r["n"] for r in rows.groupBy(shard).agg(F.count("*").alias("n")).collect()}
    active, low, step, asked, rounds = set(sizes), 0, chunk or max(1, k), 0, 0
    passed: DataFrame | None = None
    while active and k > 0:
        high = low + int(step)
        part = ranked(high).where((F.col("_place") > low) & F.col(shard).isin(sorted(active)))
        asked += sum(max(0, min(high, sizes[s]) - low) for s in active)
        good = semifilter.late(part, fk, remote, pk, condition)
        good = durable(good)
        passed = good if passed is None else durable(topk_merge.local(passed.unionAll(good), [F.col(score).desc(), F.col(key)], k, shard))
        have = {r[shard]: r["n"] for r in passed.groupBy(shard).agg(F.count("*").alias("n")).collect()}
        rounds += 1
        active = {s for s in active if have.get(s, 0) < k and sizes[s] > high}
        if active and prune_every and rounds % prune_every == 0:
            best = passed.orderBy(F.col(score).desc(), F.col(key)).limit(k).agg(F.count("*").alias("n"), F.min(score).alias("t")).first()
            if best["n"] == k:
                nxt = {r[shard]: r["s"] for r in ranked(high + 1).where((F.col("_place") == high + 1) & F.col(shard).isin(sorted(active))).select(shard, F.col(score).alias("s")).collect()}
                # A row as good as the k-th may still win on its key.
                active = {s for s in active if s in nxt and nxt[s] >= best["t"]}
        low, step = high, step * growth
    if passed is None:
        passed = ranked(1).limit(0)
    out = topk_merge.gather(passed, [F.col(score).desc(), F.col(key)], k).drop("_place")
    return LazyResult(out, asked, rounds)


def eager(rows: DataFrame, score: str, key: str, fk: str, remote: DataFrame, pk: str, condition: Column, k: int) -> DataFrame:
    """Baseline: filter everything, then cut."""
    return topk_merge.gather(semifilter.bitset(rows, fk, remote, pk, condition), [F.col(score).desc(), F.col(key)], k)
