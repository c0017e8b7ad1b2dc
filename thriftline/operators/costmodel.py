"""Communication costs in bits, selectivities from a small pilot, and the choice of a variant."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Most that is sent to all: it passes through the driver.
BUDGET_BYTES = 64 << 20
BLOCK_KEYS = 32768


def bits_late(n: float, m: float, shards: float) -> float:
    """Bits a shard sends to ask for n/P of m remote keys as increasing sequences; for n/P < m."""
    return 0.0 if n <= 0 else n / shards * math.log2(max(m * shards / n, 1))


def bits_reply(n: float, shards: float) -> float:
    """One bit for each key asked."""
    return n / shards


def bits_bitset(m: float, gamma: float) -> float:
    """Bits of a bitset over m keys of which a share gamma is set, leading term."""
    return 0.0 if gamma <= 0 else gamma * m * math.log2(1 / gamma)


def bits_bitset_entropy(m: float, gamma: float) -> float:
    """The same with the full entropy of the bits."""
    return 0.0 if gamma <= 0 or gamma >= 1 else m * (gamma * math.log2(1 / gamma) + (1 - gamma) * math.log2(1 / (1 - gamma)))


def late_cost(n: Column, m: Column, shards: Column) -> Column:
    return F.when(n <= 0, F.lit(0.0)).otherwise(n / shards * F.log2(F.greatest(m * shards / n, F.lit(1.0))))


def bitset_cost(m: Column, gamma: Column) -> Column:
    return F.when(gamma <= 0, F.lit(0.0)).otherwise(gamma * m * F.log2(1 / gamma))


def in_pilot(key: str, per_mille: int = 10) -> Column:
    """A share of the keys that is the same on every run: a hash of the key decides."""
    return F.pmod(F.pmod(F.col(key), F.lit(1 << 31)) * 2654435761, F.lit(1000)) < per_mille


def pilot(df: DataFrame, condition: Column, key: str, per_mille: int = 10) -> tuple[int, int]:
    """Rows of the pilot and those that meet the condition."""
    row = df.where(in_pilot(key, per_mille)).agg(F.count("*").alias("n"), F.count(F.when(condition, 1)).alias("hit")).first()
    return row["n"], row["hit"]


def choose_filter(n: float, m: float, gamma: float, shards: int, budget_bytes: int = BUDGET_BYTES, replicated: bool = False) -> str:
    """'replicated' if the attribute already is, else the cheaper of 'late' and 'bitset'; a bitset beyond the budget is never chosen."""
    if replicated:
        return "replicated"
    if m / 8 > budget_bytes:
        return "late"
    if n / shards >= m:
        return "bitset"
    return "bitset" if bits_bitset(m, gamma) <= bits_late(n, m, shards) + bits_reply(n, shards) else "late"


def choose_topk(largest: int, smallest: int, width: int) -> str:
    """'full' where codes save too little (values of at most twice their width) or bounds do not hold (negative values)."""
    return "full" if smallest < 0 or largest.bit_length() <= 2 * width else "bounds"


def worth_compressing(size: float, ratio: float, cpu_bytes_s: float, net_bytes_s: float) -> bool:
    """Whether packing and sending fewer bytes takes less time than sending all."""
    return size / cpu_bytes_s + size / ratio / net_bytes_s < size / net_bytes_s
