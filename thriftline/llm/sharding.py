"""Shards of nearly equal bytes by minimax contiguous partition, with DataFrame functions only.

Equal texts form an atomic group.  A group larger than an equal part comes first and has a shard of its own, so that it does not set the
capacity of the others.  The other groups are ordered by a 60-bit key of their text.  The smallest capacity is sought for which
greedy filling, in that order, needs no more shards than wanted; the cuts of that filling bound the shards.

Sizes are never gathered: sums over ``FAN`` ranges of the key come first, and only ranges in which a cut can still fall are split
again, ``FAN`` ways at a time.  The binary search over capacities runs on these few sums, with lower and upper bounds where a range is
not yet split; it is exact once every range that holds a cut is a single group.  A level reads a narrow
table (id, key, size) once; the number of levels is at most 60 / log2(FAN).  Slots are counted in sub-shards of bounded size.
"""

from __future__ import annotations

import bisect

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from thriftline.shipping import durable

KEY_BITS, FAN_BITS = 60, 12
FAN = 1 << FAN_BITS
#: Rows of a sub-shard, about.
SLOT_ROWS = 50_000


class Ranges:
    """Ordered key ranges (low, high, bytes, single, first key) that cover all groups; ``single`` ones hold one group."""

    def __init__(self, ranges: list[tuple[int, int, int, bool, int]]):
        self.ranges = sorted(ranges)
        self.ends = []
        total = 0
        for _, _, size, _, _ in self.ranges:
            total += size
            self.ends.append(total)
        self.total = total

    def below(self, limit: int) -> int:
        """The largest known border that is not above ``limit``."""
        at = bisect.bisect_right(self.ends, limit)
        return self.ends[at - 1] if at else 0

    def fill(self, capacity: int, shards: int) -> tuple[int, int, list[tuple[int, int]]]:
        """Greedy filling: least and most bytes that fit, and for each cut the least and most bytes before it."""
        low = high = 0
        cuts = []
        for _ in range(shards):
            low = self.below(low + capacity)
            reach = min(high + capacity, self.total)
            at = bisect.bisect_right(self.ends, reach)
            # Inside a single group no cut can fall.
            high = reach if at < len(self.ranges) and not self.ranges[at][3] else (self.ends[at - 1] if at else 0)
            cuts.append((low, high))
        return low, high, cuts

    def search(self, shards: int) -> tuple[int, int]:
        """Bounds of the smallest capacity that suffices: surely too small below the first, surely enough at the second."""

        def least(enough) -> int:
            a, b = 1, max(self.total, 1)
            while a < b:
                middle = (a + b) // 2
                if enough(middle):
                    b = middle
                else:
                    a = middle + 1
            return a

        return least(lambda c: self.fill(c, shards)[1] >= self.total), least(lambda c: self.fill(c, shards)[0] >= self.total)

    def open(self, shards: int) -> list[int]:
        """The ranges, by number, that must be split before the cuts are known; none if they are."""
        first, last = self.search(shards)
        low, high = self.fill(first, shards)[2], self.fill(last, shards)[2]
        out: set[int] = set()
        for (a, _), (_, b) in zip(low, high, strict=True):
            i = bisect.bisect_left(self.ends, a + 1)
            while i < len(self.ranges) and (self.ends[i - 1] if i else 0) <= b:
                if not self.ranges[i][3]:
                    out.add(i)
                i += 1
        return sorted(out)


def _oversized(ranges: list, shards: int) -> tuple[list[int], list[int]]:
    """The single groups larger than an equal part of what is left without them, and the ranges that may still hide one."""
    left, held = sum(r[2] for r in ranges), []
    while shards - len(held) > 1:
        more = [i for i, r in enumerate(ranges) if r[3] and i not in held and r[2] * (shards - len(held)) > left][: shards - 1 - len(held)]
        if not more:
            break
        held += more
        left -= sum(ranges[i][2] for i in more)
    return held, [i for i, r in enumerate(ranges) if not r[3] and r[2] * (shards - len(held)) > left]


def _numbers(df: DataFrame, numbers: list[int]) -> DataFrame:
    """A table of a few numbers, at most ``FAN`` for each cut."""
    return df.sparkSession.range(1).select(F.explode(F.array(*[F.lit(n).cast("long") for n in numbers])).alias("_open"))


def contiguous_cuts(groups: DataFrame, shards: int) -> tuple[list[int], list[int], int]:
    """For rows (key, size) whose equal keys are one group: the keys of groups with a shard of their own, the first keys of the second and
    later shards of the others, and the capacity of these.
    """
    width = 1 << KEY_BITS
    found: list[tuple[int, int, int, bool, int]] = []
    todo: list[tuple[int, int]] = [(0, width)]
    while True:
        span = todo[0][1] - todo[0][0]
        # Open ranges are told by their number, in one look-up whatever their count.
        own = F.shiftright("key", span.bit_length() - 1)
        inside = groups if span == width else groups.join(F.broadcast(_numbers(groups, [a // span for a, _ in todo])), own == F.col("_open"), "left_semi")
        step = max(1, span >> FAN_BITS)
        part = F.shiftright("key", step.bit_length() - 1)
        sums = inside.groupBy(part.alias("part")).agg(F.sum("size").alias("size"), F.min("key").alias("a"), F.max("key").alias("b")).collect()
        found += [(r["part"] * step, (r["part"] + 1) * step, r["size"], r["a"] == r["b"], r["a"]) for r in sums]
        found.sort()
        alone, hidden = _oversized(found, shards)
        rest = [i for i in range(len(found)) if i not in set(alone)]
        ranges, left = Ranges([found[i] for i in rest]), shards - len(alone)
        split = sorted({*hidden, *(rest[i] for i in ranges.open(left))}) if rest else hidden
        if not split:
            break
        # Ranges of one width are split at a time, the widest first.
        widest = max(found[i][1] - found[i][0] for i in split)
        gone = {i for i in split if found[i][1] - found[i][0] == widest}
        todo = [(found[i][0], found[i][1]) for i in sorted(gone)]
        found = [r for i, r in enumerate(found) if i not in gone]
    keys = [found[i][4] for i in sorted(alone)]
    if not rest:
        return keys, [], 0
    capacity = ranges.search(left)[1]
    firsts = []
    for _, high in ranges.fill(capacity, left)[2]:
        if high >= ranges.total:
            break
        firsts.append(ranges.ranges[bisect.bisect_right(ranges.ends, high)][4])
    return keys, firsts, capacity


def shard_documents(docs: DataFrame, shards: int = 24) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot and grown_shard for each row of ``docs`` (doc_id, text); the law is ``bytes``.

    A row's size is the bytes of its text plus 8.  Null texts have none and are one group; their checksum is that of no bytes.  Equal texts
    share a shard, so one group larger than a shard's part has a shard of its own.  Null and repeated doc_ids are rows
    like others.  Slots of a shard count from 0 without a gap.  Extra columns are left.  No rows in, no rows out.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    # 60 bits of the digest; the marker keeps null apart from empty.
    key = F.conv(F.substring(F.md5(F.concat(F.when(F.col("text").isNull(), "0").otherwise("1"), text).cast("binary")), 1, 15), 16, 10).cast("long")
    narrow = durable(docs.select(F.col("doc_id"), key.alias("key"), (F.octet_length(text) + 8).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32")))
    alone, firsts, _ = contiguous_cuts(narrow.select("key", "size"), shards)
    shard = F.lit(len(alone))
    if firsts:
        shard = shard + F.size(F.filter(F.array(*[F.lit(k) for k in firsts]), lambda first: first <= F.col("key")))
    if alone:
        shard = F.coalesce(F.nullif(F.array_position(F.array(*[F.lit(k) for k in alone]), F.col("key")), F.lit(0)) - 1, shard)
    rows = narrow.count()
    subs = max(1, -(-rows // SLOT_ROWS))
    dealt = narrow.withColumn("shard", shard.cast("int")).withColumn("sub", F.pmod(F.xxhash64("doc_id", "key"), F.lit(subs)))
    counts = dealt.groupBy("shard", "sub").agg(F.count("*").alias("n"))
    order = W.partitionBy("shard").orderBy("sub").rowsBetween(W.unboundedPreceding, -1)
    offsets = counts.select("shard", "sub", F.coalesce(F.sum("n").over(order), F.lit(0)).alias("before"))
    own = W.partitionBy("shard", "sub").orderBy("doc_id", "key")
    numbered = dealt.withColumn("rank", F.row_number().over(own)).join(offsets, ["shard", "sub"])
    slot = (F.col("before") + F.col("rank") - 1).cast("long")
    return numbered.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", slot.alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
