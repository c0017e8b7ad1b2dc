"""The collectives of a message-passing program as DataFrame operations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from thriftline.operators import pairing
from thriftline.shipping import written


def gather(df: DataFrame) -> DataFrame:
    """All rows in one task; for results of bounded size."""
    return df.coalesce(1)


def allgather(df: DataFrame, budget_bytes: int = 64 << 20, row_bytes: int = 64) -> DataFrame:
    """All rows on every executor; refused beyond a budget."""
    if df.count() * row_bytes > budget_bytes:
        raise ValueError("too large to be sent to all")
    return F.broadcast(df)


def scatter(root: DataFrame, key: str, rows: DataFrame, owner: str) -> DataFrame:
    """Each row of a small root table goes to the shard that owns its key."""
    return rows.join(root, rows[owner] == root[key], "left_semi")


def exchange(df: DataFrame, owner: str, shards: int) -> DataFrame:
    """Personalised all-to-all: every row to the partition of its owner's number."""
    return df.repartitionById(shards, F.col(owner).cast("int"))


def exchange_rounds(df: DataFrame, source: str, owner: str, shards: int) -> list[DataFrame]:
    """The same by the 1-factor schedule: what every source sends to its partner of a round, one table a round.

    Each round ends, its rows written in the shared folder, before the next begins; so no two pairs of a shard are under way at once.
    """
    rows, out = written(df), []
    for step in range(shards):
        meets = F.array(*[F.lit(pairing.partner(step, u, shards)) for u in range(shards)])
        sent = rows.where(F.col(owner) == F.get(meets, F.col(source).cast("int")))
        out.append(written(exchange(sent, owner, shards)))
    return out


def reduce(df: DataFrame, *operators: Column) -> DataFrame:
    """One row combined from all; partial results are combined in each task first."""
    return df.agg(*operators)


def allreduce(df: DataFrame, operator: Column, name: str) -> DataFrame:
    """The combined value beside every row."""
    return df.crossJoin(F.broadcast(df.agg(operator.alias(name))))


def handover(df: DataFrame, key: str, shards: int | None = None) -> DataFrame:
    """Processing state moves to the owner of its key, which goes on from there; without a number of shards as many as the session shuffles to."""
    return df.repartition(F.col(key)) if shards is None else df.repartition(shards, F.col(key))


def request(keys: DataFrame, key: str, remote: DataFrame, pk: str, columns: list[str]) -> DataFrame:
    """Request and response: attributes of the remote rows whose keys are asked for, each once."""
    wanted = keys.where(F.col(key).isNotNull()).select(F.col(key).alias("_wanted")).distinct()
    return remote.select(F.col(pk).alias(key), *columns).join(wanted, F.col(key) == F.col("_wanted"), "left_semi")
