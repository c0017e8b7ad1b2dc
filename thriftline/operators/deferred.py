"""Late fetching of output columns for a result of bounded size."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def attach(result: DataFrame, key: str, source: DataFrame, source_key: str, columns: list[str], bound: int | None = None) -> DataFrame:
    """The result with columns of its source rows; a result known to have at most ``bound`` rows travels to the source, else both meet by key."""
    side = F.broadcast(result) if bound is not None and bound <= 100_000 else result
    return source.select(F.col(source_key).alias("_k"), *columns).join(side, F.col("_k") == F.col(key)).drop("_k")


def eager(rows: DataFrame, key: str, source: DataFrame, source_key: str, columns: list[str]) -> DataFrame:
    """Baseline: every row carries the columns from the start."""
    return rows.join(source.select(F.col(source_key).alias("_k"), *columns), F.col(key) == F.col("_k")).drop("_k")
