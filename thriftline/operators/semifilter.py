"""Rows of a local table whose partner in a remote table meets a condition, five ways with one result.

``late`` asks the owners of the wanted keys only, after all local filters, and ``packed`` does so in packed blocks with one bit for an answer; ``bitset`` sends everybody one bit for each remote key that
qualifies; ``replicated`` keeps the remote attribute everywhere; ``auto`` picks by modelled bits from a pilot.
Null keys and null conditions never qualify.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from thriftline.operators import collectives, costmodel, keycodec


def late(local: DataFrame, fk: str, remote: DataFrame, pk: str, condition: Column) -> DataFrame:
    """Distinct wanted keys go to their owners, which answer with those that qualify; both sides are dealt by key."""
    wanted = local.where(F.col(fk).isNotNull()).select(F.col(fk).alias("_wanted")).distinct()
    answer = remote.where(condition).select(F.col(pk).alias("_owned")).join(wanted, F.col("_owned") == F.col("_wanted"), "left_semi")
    return local.join(answer, F.col(fk) == F.col("_owned"), "left_semi")


def packed(local: DataFrame, fk: str, remote: DataFrame, pk: str, condition: Column, sort_for_wire: bool = True) -> DataFrame:
    """``late`` with the wire format spelt out: each task's wanted keys travel as packed blocks to their owners, one bit a key comes back."""
    asked = keycodec.requests(local, fk, sort_for_wire)
    answer = keycodec.answered(keycodec.replies(asked, keycodec.to_bitset(remote.where(condition), pk)), "_owned")
    return local.join(answer, F.col(fk) == F.col("_owned"), "left_semi")


def bitset(local: DataFrame, fk: str, remote: DataFrame, pk: str, condition: Column, budget_bytes: int = costmodel.BUDGET_BYTES) -> DataFrame:
    """Qualifying keys as blocks of bits, sent to all if they fit the budget and else dealt by key range with the local rows."""
    blocks = keycodec.to_bitset(remote.where(condition), pk).withColumnRenamed("bucket", "_bucket").withColumnRenamed("bits", "_bits")
    span = remote.agg(F.max(pk).alias("h"), F.min(pk).alias("l")).first()
    size = 0 if span["h"] is None else (span["h"] - min(span["l"], 0)) // 8
    side = F.broadcast(blocks) if size <= budget_bytes else blocks
    probe = local.where(F.col(fk).isNotNull()).join(side, F.bitmap_bucket_number(fk) == F.col("_bucket"))
    return probe.where(keycodec.bit_of(F.col("_bits"), F.bitmap_bit_position(fk))).select(*local.columns)


def replicated(local: DataFrame, fk: str, remote: DataFrame, pk: str, condition: Column, budget_bytes: int = costmodel.BUDGET_BYTES) -> DataFrame:
    """The remote key and condition stand on every shard; beyond the budget they are joined by key instead."""
    side = remote.select(F.col(pk).alias("_pk"), condition.alias("_ok"))
    rows = remote.select(pk).count()
    # About 64 bytes a row in a hash relation.
    side = F.broadcast(side) if rows * 64 <= budget_bytes else side
    return local.join(side.where("_ok").select("_pk"), F.col(fk) == F.col("_pk"), "left_semi")


@dataclass
class Choice:
    variant: str
    n: float
    m: int
    gamma: float
    late_bits: float
    bitset_bits: float


def choose(local: DataFrame, fk: str, remote: DataFrame, pk: str, condition: Column, shards: int, budget_bytes: int = costmodel.BUDGET_BYTES) -> Choice:
    """Sizes from counts, the share that qualifies from a pilot of the remote keys, the wanted keys from a pilot of the local ones."""
    m = remote.count()
    seen, hit = costmodel.pilot(remote, condition, pk, 100)
    gamma = hit / seen if seen else 1.0
    wanted = local.where(costmodel.in_pilot(fk, 100)).select(fk).distinct().count() * 10.0
    variant = costmodel.choose_filter(wanted, m, gamma, shards, budget_bytes)
    return Choice(variant, wanted, m, gamma, costmodel.bits_late(wanted, max(m, 1), shards), costmodel.bits_bitset(m, gamma))


def auto(local: DataFrame, fk: str, remote: DataFrame, pk: str, condition: Column, shards: int = 8) -> DataFrame:
    variant = choose(local, fk, remote, pk, condition, shards).variant
    return {"late": late, "bitset": bitset, "replicated": replicated}[variant](local, fk, remote, pk, condition)


VARIANTS = {"late": late, "packed": packed, "bitset": bitset, "replicated": replicated, "auto": auto}


def fetch(local: DataFrame, fk: str, remote: DataFrame, pk: str, columns: list[str]) -> DataFrame:
    """Local rows with attributes of their partner, asked for once for each distinct key."""
    answer = collectives.request(local.select(F.col(fk).alias("_owned")), "_owned", remote, pk, columns)
    return local.join(answer, F.col(fk) == F.col("_owned")).drop("_owned")
