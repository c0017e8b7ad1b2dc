"""Joins on keys of which a few may hold a large part of all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: A key is hot if it has more rows than the first, and more than one part in the second of all: so there are fewer hot keys than that.
LEAST, PARTS = 512, 4096


def hot_bound(total: int) -> int:
    """Rows of a key beyond which it is hot."""
    return max(LEAST, total // PARTS)


def joined(left: DataFrame, right: DataFrame, key: list[str], weight: str, total: int, outer: bool = False) -> DataFrame:
    """``left`` with the columns of ``right``, which has each key once, with the number of left rows that have it (``weight``, dropped).

    Hot keys, fewer than ``PARTS`` of them, are sent to where their rows are; the others meet by key.  With ``outer``, left rows without a partner
    stay, with nulls; rows whose key is null have none and are not moved.  ``left`` is read twice, so it should be a table.
    """
    bound = hot_bound(total)
    hot, rest = right.where(F.col(weight) > bound).drop(weight), right.where(F.col(weight) <= bound).drop(weight)
    known = left.where(" and ".join(f"`{k}` is not null" for k in key))
    first = known.join(F.broadcast(hot), key)
    second = known.join(F.broadcast(hot.select(*key)), key, "left_anti").join(rest, key, "left" if outer else "inner")
    out = first.unionByName(second)
    if outer:
        out = out.unionByName(left.where(" or ".join(f"`{k}` is null" for k in key)), allowMissingColumns=True)
    return out
