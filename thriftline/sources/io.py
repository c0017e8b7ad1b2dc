"""Sources and sinks: round trips through file formats, partitioned and bucketed tables, in the shared folder."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame

from thriftline.shipping import shared_dir


def round_trip(df: DataFrame, kind: str, **options) -> DataFrame:
    """Writes the rows as csv, json, orc or parquet and reads them with the same schema."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{kind}-{uuid.uuid4().hex}"
    df.write.format(kind).options(**options).mode("overwrite").save(path)
    return spark.read.format(kind).schema(df.schema).options(**options).load(path)


def partitioned(df: DataFrame, column: str) -> tuple[DataFrame, str]:
    """Writes Parquet in one folder for each value; a filter on the column reads those folders only."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/partitioned-{uuid.uuid4().hex}"
    df.write.partitionBy(column).mode("overwrite").parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def discard(df: DataFrame) -> None:
    """Runs the plan to its end and keeps nothing; for timing."""
    df.write.format("noop").mode("overwrite").save()
