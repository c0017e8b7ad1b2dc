"""Which parts of a query need only local data, from the foreign keys they follow."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame

from thriftline.sources.catalog import FkEdge


def classify(edges: Iterable[FkEdge]) -> str:
    """'local' if every edge stays on its shard, else 'remote'."""
    return "local" if all(e.local for e in edges) else "remote"


def split(edges: Iterable[FkEdge]) -> tuple[list[FkEdge], list[FkEdge]]:
    """The edges that a shard follows alone, and those that need a request or a handover."""
    edges = list(edges)
    return [e for e in edges if e.local], [e for e in edges if not e.local]


def exchanges(df: DataFrame) -> int:
    """Exchanges in the physical plan; those of broadcasts count too."""
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange ")
