"""Structured streaming over ``events``: windows, late rows, deduplication, a static filter and continuous top-k.

Each query here drains the source once (``availableNow``) and gives back what the stream wrote, so it can be compared with a batch.
State and progress are kept in the shared folder; a run that starts again with the same folder goes on from there.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from thriftline.functions.money import cents
from thriftline.operators import semifilter, topk_merge
from thriftline.shipping import shared_dir
from thriftline.sources.catalog import SCHEMAS, load

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str):
    def register(f):
        QUERIES[name], ORACLES[name] = f, sql
        return f

    return register


def read_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream; the time column is cast for watermarks, which refuse times without a zone."""
    raw = spark.readStream.schema(SCHEMAS["events"]).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs the stream to the end of its input and reads what it wrote."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        run = stream.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").outputMode("append").trigger(availableNow=True).start()
        run.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/out")

    # A complete result is written anew by each batch; only the newest counts.
    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={number:09d}")

    run = stream.writeStream.foreachBatch(keep).option("checkpointLocation", f"{base}/state").outputMode(mode).trigger(availableNow=True).start()
    run.awaitTermination()
    out = spark.read.schema(stream.schema.add("batch", "long")).parquet(f"{base}/out")
    return out.where(F.col("batch") == out.agg(F.max("batch")).first()[0]).drop("batch")


def tumbling(events: DataFrame, width: str = "1 day", delay: str = "1 hour") -> DataFrame:
    counted = events.withWatermark("ts", delay).groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"))
    return counted.select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str, step: str) -> DataFrame:
    counted = events.withWatermark("ts", "1 hour").groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n"))
    return counted.select(F.col("window.start").alias("start"), "n")


def session(events: DataFrame, gap: str) -> DataFrame:
    grouped = events.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return grouped.select("user_id", F.col("session_window.start").alias("start"), "n")


_NTZ = "cast(start as timestamp_ntz) as start"


@query("stream_tumbling", "SELECT date_trunc('day', ts) AS start, event_type, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    return drained(tumbling(read_events(spark, sf_dir)), "complete").selectExpr(_NTZ, "event_type", "n")


@query("stream_sliding", """SELECT start, CAST(count(*) AS BIGINT) AS n FROM (SELECT time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 12 HOUR * i AS start FROM events, range(2) t(i)) GROUP BY 1""")
def stream_sliding(spark, sf_dir):
    return drained(sliding(read_events(spark, sf_dir), "1 day", "12 hours"), "complete").selectExpr(_NTZ, "n")


@query("stream_session", """WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events),
 s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, min(ts) AS start, CAST(count(*) AS BIGINT) AS n FROM s GROUP BY user_id, k""")
def stream_session(spark, sf_dir):
    return drained(session(read_events(spark, sf_dir), "6 hours"), "complete").selectExpr("user_id", _NTZ, "n")


@query("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, sf_dir):
    return drained(read_events(spark, sf_dir).select("user_id", "event_type").dropDuplicates(["user_id", "event_type"]))


@query("stream_static_filter", "SELECT event_type, CAST(count(*) AS BIGINT) AS n FROM events WHERE user_id IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING') GROUP BY 1")
def stream_static_filter(spark, sf_dir):
    customers = load(spark, sf_dir, "customer")
    kept = semifilter.replicated(read_events(spark, sf_dir), "user_id", customers, "c_custkey", F.col("c_mktsegment") == "BUILDING")
    return drained(kept.groupBy("event_type").agg(F.count("*").alias("n")), "complete")


@query("stream_topk", "SELECT user_id, CAST(sum(CAST(round(value*100) AS BIGINT)) AS BIGINT) AS total FROM events WHERE event_type = 'purchase' GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 10")
def stream_topk(spark, sf_dir):
    sums = read_events(spark, sf_dir).where("event_type = 'purchase'").groupBy("user_id").agg(F.sum(cents("value")).alias("total"))
    return drained(sums, "complete").orderBy(F.col("total").desc(), "user_id").limit(10)


def merged_topk(stream: DataFrame, by: list[Column], k: int, base: str) -> DataFrame:
    """Continuous top-k of single rows: each batch's k best merge with the k best so far, so the state is k rows whatever has passed.

    The vector of a batch is worked out from that of the batch before and written under the batch's number, so a batch that runs again, and a
    stream that starts again from ``base``, give the same.
    """
    spark, schema = stream.sparkSession, stream.schema

    def merge(batch: DataFrame, number: int) -> None:
        rows = batch
        if number:
            rows = rows.unionByName(batch.sparkSession.read.schema(schema).parquet(f"{base}/best/batch={number - 1:09d}"))
        topk_merge.gather(rows, by, k).write.mode("overwrite").parquet(f"{base}/best/batch={number:09d}")

    run = stream.writeStream.foreachBatch(merge).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    run.awaitTermination()
    out = spark.read.schema(schema.add("batch", "long")).parquet(f"{base}/best")
    return out.where(F.col("batch") == out.agg(F.max("batch")).first()[0]).drop("batch")


@query("stream_topk_vectors", "SELECT event_id, user_id, CAST(round(value*100) AS BIGINT) AS value_c FROM events WHERE event_type = 'purchase' ORDER BY 3 DESC, 1 LIMIT 10")
def stream_topk_vectors(spark, sf_dir):
    bought = read_events(spark, sf_dir).where("event_type = 'purchase'").select("event_id", "user_id", cents("value").alias("value_c"))
    return merged_topk(bought, [F.col("value_c").desc(), F.col("event_id")], 10, f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}")
