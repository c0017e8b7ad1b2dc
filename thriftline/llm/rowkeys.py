"""Keys that tell rows apart which share a doc_id but not a text."""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from thriftline.llm.arrowrun import fresh
from thriftline.shipping import durable, written


class Told(NamedTuple):
    """Rows with their key, whether keys differ from doc_ids, and whether any doc_id stands in two rows."""

    docs: DataFrame
    renumbered: bool
    repeated: bool


def told_apart(docs: DataFrame, key: str) -> Told:
    """``docs`` with a long column ``key`` that is equal where doc_id and text are, and null where doc_id is.

    Keys are in the order of doc_id, and of a digest of the text under one doc_id.  If no doc_id has two texts, the key is the doc_id;
    else the distinct pairs of doc_id and digest are numbered, range by range, so no task sees all of them.
    """
    doc_id = F.col("doc_id").cast("long")
    pairs = docs.where("doc_id is not null").select(doc_id.alias("_id"), F.xxhash64("text").alias("_digest"))
    each = pairs.groupBy("_id").agg((F.min("_digest") < F.max("_digest")).alias("odd"), (F.count("*") > 1).alias("more"))
    odd, more = each.agg(F.max("odd"), F.max("more")).first()
    if not odd:
        return Told(docs.withColumn(key, doc_id), False, bool(more))
    # A range of the order is a partition; its number is kept, so ranges can be put one after another.
    ranged = durable(pairs.distinct().repartitionByRange("_id", "_digest").withColumn("_range", F.spark_partition_id()))
    sizes = ranged.groupBy("_range").agg(F.count("*").alias("_n"))
    before = sizes.select("_range", F.coalesce(F.sum("_n").over(W.orderBy("_range").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    own = F.row_number().over(W.partitionBy("_range").orderBy("_id", "_digest")) - 1
    keys = ranged.join(F.broadcast(before), "_range").select("_id", "_digest", (F.col("_before") + own).cast("long").alias(key))
    at, digest = fresh("_key_id", docs.columns), fresh("_key_digest", docs.columns)
    keys = keys.withColumnsRenamed({"_id": at, "_digest": digest})
    rows = docs.withColumns({at: doc_id, digest: F.xxhash64("text")})
    return Told(written(rows.join(keys, [at, digest], "left").drop(at, digest)), True, True)
