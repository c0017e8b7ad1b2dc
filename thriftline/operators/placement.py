"""Data distribution: every table is partitioned over P shards by a rule on its data, tiny tables are replicated.

A shard id is a function of the row, never of a task, so a task that runs again places rows alike.
"""

from __future__ import annotations

import hashlib
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from thriftline.shipping import shared_dir
from thriftline.sources.catalog import load

#: An odd multiplier that spreads dense keys.
SPREAD = 2654435761


def range_shard(key: str, shards: int, keys: int) -> Column:
    """Dense keys 0..keys-1 in equal intervals; keys outside go to the nearest end."""
    return F.least(F.greatest(F.floor(F.col(key) * shards / F.lit(keys)), F.lit(0)), F.lit(shards - 1)).cast("long")


def bounds_shard(key: str, bounds: list) -> Column:
    """The number of bounds that are at most the key."""
    out = F.lit(0)
    for bound in bounds:
        out = out + F.when(F.col(key) >= bound, 1).otherwise(0)
    return out.cast("long")


def hash_shard(key: str, shards: int) -> Column:
    return F.pmod(F.shiftright(F.pmod(F.col(key), F.lit(1 << 31)) * SPREAD, 8), F.lit(shards)).cast("long")


def key_shard(key: str, shards: int) -> Column:
    return F.pmod(F.col(key), F.lit(shards)).cast("long")


def place(df: DataFrame, key: str, shards: int, how: str = "hash", bounds: list | None = None, keys: int | None = None) -> DataFrame:
    """Adds ``shard``: by hash (default), key modulus, range (of dense ``keys``, explicit ``bounds`` or quantiles) or round robin.

    Round robin deals rows in key order: ranks come from ranges of the key and the counts of the ranges before, so no task
    sorts the whole table.
    """
    if how == "hash":
        return df.withColumn("shard", hash_shard(key, shards))
    if how == "modulus":
        return df.withColumn("shard", key_shard(key, shards))
    if how == "range":
        if bounds is None and keys is not None:
            return df.withColumn("shard", range_shard(key, shards, keys))
        if bounds is None:
            bounds = df.approxQuantile(key, [i / shards for i in range(1, shards)], 0.001)
        return df.withColumn("shard", bounds_shard(key, bounds))
    if how == "round_robin":
        return ranked(df, key).withColumn("shard", F.pmod("rank", F.lit(shards)).cast("long")).drop("rank")
    raise ValueError(how)


def ranked(df: DataFrame, key: str, rows_per_range: int = 1 << 20) -> DataFrame:
    """Adds ``rank`` from 0 in key order, by ranges of bounded size; ties are ranked in any order."""
    low, high, n = df.agg(F.min(key), F.max(key), F.count(key)).first()
    parts = max(1, -(-(n or 0) // rows_per_range))
    width = max(1, ((high or 0) - (low or 0)) // parts + 1)
    cut = df.withColumn("_range", F.floor((F.col(key) - F.lit(low)) / F.lit(width)).cast("long"))
    counts = cut.groupBy("_range").agg(F.count("*").alias("_n"))
    before = counts.select("_range", F.coalesce(F.sum("_n").over(W.orderBy("_range").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    own = F.row_number().over(W.partitionBy("_range").orderBy(key)) - 1
    return cut.join(F.broadcast(before), "_range").withColumn("rank", (F.col("_before") + own).cast("long")).drop("_range", "_before")


def replicate(df: DataFrame, max_rows: int = 50) -> DataFrame:
    """A broadcast of a table of constant size; larger tables are refused."""
    if df.limit(max_rows + 1).count() > max_rows:
        raise ValueError(f"more than {max_rows} rows are not replicated")
    return F.broadcast(df)


def colocate(child: DataFrame, parent: DataFrame, fk: str, pk: str, shards: int) -> tuple[DataFrame, DataFrame]:
    """Both sides dealt by the key they join on: a join of the two moves nothing more."""
    return child.repartition(shards, F.col(fk)), parent.repartition(shards, F.col(pk))


def store_bucketed(df: DataFrame, table: str, key: str, shards: int) -> DataFrame:
    """Writes the table bucketed and sorted by key; later joins of such tables on their keys need no exchange."""
    df.write.mode("overwrite").format("parquet").bucketBy(shards, key).sortBy(key).saveAsTable(table)
    return df.sparkSession.table(table)


def placed(spark: SparkSession, sf_dir: str, name: str, key: str, shards: int = 16) -> DataFrame:
    """A base table as it was placed once for this application: bucketed by ``key`` in the shared folder, so that queries need not move it."""
    return _once(spark, sf_dir, f"placed_{name}", key, shards, lambda: load(spark, sf_dir, name))


def held(spark: SparkSession, sf_dir: str, name: str, key: str, fk: str, parent: str, pk: str, columns: list[str], shards: int = 16) -> DataFrame:
    """``placed`` with attributes of the remote partner that each shard holds since loading, so a filter on them asks nobody; null without a partner."""

    def rows():
        remote = load(spark, sf_dir, parent).select(F.col(pk).alias("_pk"), *columns)
        return load(spark, sf_dir, name).join(remote, F.col(fk) == F.col("_pk"), "left").drop("_pk")

    return _once(spark, sf_dir, f"held_{name}_{parent}_{'_'.join(columns)}", key, shards, rows)


def _once(spark: SparkSession, sf_dir: str, what: str, key: str, shards: int, rows) -> DataFrame:
    table = f"{what}_{key}_{shards}_{hashlib.md5(sf_dir.encode()).hexdigest()[:10]}"
    if not spark.catalog.tableExists(table):
        path = f"{shared_dir(spark)}/{table}-{uuid.uuid4().hex}"
        # One file a bucket: rows are dealt before they are written.
        rows().repartition(shards, F.col(key)).write.format("parquet").bucketBy(shards, key).sortBy(key).option("path", path).saveAsTable(table)
    return spark.table(table)


def imbalance(df: DataFrame, condition: Column | None = None, shards: int | None = None) -> DataFrame:
    """shards, rows, largest and largest over mean of a placed table (after a filter); shards without rows count if ``shards`` is given."""
    rows = df if condition is None else df.where(condition)
    per = rows.groupBy("shard").agg(F.count("*").alias("n"))
    count = F.lit(shards).cast("long") if shards else F.count("*")
    return per.agg(count.alias("shards"), F.sum("n").alias("n_rows"), F.max("n").alias("largest")).withColumn("over_mean", F.col("largest") * F.col("shards") / F.col("n_rows"))


def local_fraction(child: DataFrame, fk_shard: Column, own_shard: Column) -> DataFrame:
    """How many child rows stand on the shard of their parent."""
    return child.agg(F.count("*").alias("n_rows"), F.sum(F.when(fk_shard == own_shard, 1).otherwise(0)).cast("long").alias("local_rows"))
