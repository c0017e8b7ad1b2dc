"""Top-k of rows that are whole on their shard: local lists, a gather, a merge tree, and ties."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def local(df: DataFrame, by: list[Column], k: int, shard: str = "shard") -> DataFrame:
    """The first k rows of each shard; Spark cuts groups before the exchange as well."""
    return df.withColumn("_rank", F.row_number().over(W.partitionBy(shard).orderBy(*by))).where(F.col("_rank") <= k).drop("_rank")


def gather(df: DataFrame, by: list[Column], k: int) -> DataFrame:
    """Baseline: k rows of each task meet in one."""
    return df.orderBy(*by).limit(k)


def tree(df: DataFrame, by: list[Column], k: int, fanin: int = 8, shard: str = "shard", shards: int = 8) -> DataFrame:
    """Lists of k rows merge ``fanin`` at a time until one is left; no task sees more than fanin * k rows after the first round."""
    out, left = local(df, by, k, shard), shards
    while left > 1:
        out = local(out.withColumn(shard, F.floor(F.col(shard) / fanin).cast("long")), by, k, shard)
        left = -(-left // fanin)
    return out


def with_ties(df: DataFrame, by: Column, k: int) -> DataFrame:
    """All rows that are at least as good as the k-th (by a descending score)."""
    kth = df.select(by.alias("_s")).orderBy(F.col("_s").desc()).limit(k).agg(F.min("_s").alias("_kth"))
    return df.crossJoin(F.broadcast(kth)).where(by >= F.col("_kth")).drop("_kth")


def kbest(df: DataFrame, group: list[str], score: str, key: str, k: int) -> DataFrame:
    """The k best (score, key) of each group as one sorted list.  Lists of k are cut in each salt of a group first, so no list grows with it."""
    salted = df.withColumn("_salt", F.pmod(F.xxhash64(key), F.lit(64)))
    order = [F.col(score).desc(), F.col(key)]
    first = salted.withColumn("_r", F.row_number().over(W.partitionBy(*group, "_salt").orderBy(*order))).where(F.col("_r") <= k)
    item = F.struct((-F.col(score)).alias("s"), F.col(key).alias("key"))
    lists = first.groupBy(*group).agg(F.slice(F.array_sort(F.collect_list(item)), 1, k).alias("best"))
    return lists.select(*group, F.transform("best", lambda x: F.struct((-x["s"]).alias(score), x["key"].alias(key))).alias("best"))


def threshold_select(df: DataFrame, score: str, k: int, ways: int = 64) -> int | None:
    """The k-th largest whole score by narrowing an interval ``ways`` at a time: a few rounds of counts, no sort."""
    low, high, n = df.agg(F.min(score), F.max(score), F.count(score)).first()
    if not n:
        return None
    if n <= k:
        return low
    above = 0
    while low < high:
        step = max(1, -(-(high - low + 1) // ways))
        part = F.floor((F.col(score) - F.lit(low)) / F.lit(step)).cast("long")
        counts = {r["p"]: r["n"] for r in df.where(F.col(score).between(low, high)).groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect()}
        for p in sorted(counts, reverse=True):
            if above + counts[p] >= k:
                low, high = low + p * step, min(high, low + (p + 1) * step - 1)
                break
            above += counts[p]
    return low
