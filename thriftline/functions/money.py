"""Exact money: whole cents, whole percents, and revenue in units of a hundredth of a cent."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def cents(name: str) -> Column:
    return F.round(F.col(name) * 100).cast("long")


def quantity() -> Column:
    return F.col("l_quantity").cast("long")


def rev4() -> Column:
    """Discounted price in 1/10,000 of a currency unit, a whole number."""
    return cents("l_extendedprice") * (100 - cents("l_discount"))


def day(text: str) -> Column:
    return F.lit(text).cast("timestamp_ntz")


def whole(column: Column) -> Column:
    """A sum that cannot overflow at any scale, given back as BIGINT."""
    return F.sum(column.cast("decimal(38,0)")).cast("long")


#: The same expressions for the oracles.
SQL_REV4 = "CAST(round(l_extendedprice*100) AS BIGINT)*(100-CAST(round(l_discount*100) AS BIGINT))"
SQL_OFFERS = "SELECT l_partkey AS ps_partkey, l_suppkey AS ps_suppkey, min(CAST(round(l_extendedprice*100) AS BIGINT)//CAST(l_quantity AS BIGINT)) AS ps_cost_c, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS ps_qty FROM lineitem GROUP BY 1, 2"
