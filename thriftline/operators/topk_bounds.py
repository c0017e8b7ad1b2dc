"""Top-k over sums whose parts are spread over shards, by exchanging a few bits of each part.

The parts of a shard are taken in groups of neighbouring keys.  All of a group are cut to ``width`` bits below the highest bit of its largest
part and travel as one block of codes with a presence bitmap and one shift.  Dropped bits are all 0 or all 1, so the codes give a lower
and an upper bound of each key's sum.  Keys whose upper bound is below the k-th largest lower bound cannot be among the best;
the parts of the few others are summed in full.  Exact for every width, group size and number of shards, for parts of 0 or more.

``run_rows`` takes rows as they are stored: sums and codes are made by the task that scans them, and no full value is exchanged but those of
survivors.  ``run`` takes parts that are already summed by a shard id in the data.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from thriftline.operators import costmodel, topk_baselines
from thriftline.operators.topk_merge import with_ties
from thriftline.shipping import ship, written

BLOCKS = "shard long, grp long, shift int, n int, present binary, codes binary"


@dataclass
class BoundsResult:
    df: DataFrame
    survivors: DataFrame
    bits: int
    full_bits: int


def code_columns(partials: DataFrame, width: int, group: int) -> DataFrame:
    """(shard, key, val, grp, shift, code, lo, hi) with built-in functions: the definition the blocks are packed by."""
    from pyspark.sql import Window as W

    cut = partials.withColumn("grp", F.floor(F.col("key") / group).cast("long"))
    top = F.max("val").over(W.partitionBy("shard", "grp"))
    cut = cut.withColumn("shift", F.greatest(F.length(F.bin(top)) - width, F.lit(0)).cast("long"))
    cut = cut.withColumn("code", F.expr("shiftright(val, cast(shift as int))"))
    low = F.expr("shiftleft(code, cast(shift as int))")
    return cut.withColumn("lo", low).withColumn("hi", F.expr("lo + shiftleft(1L, cast(shift as int)) - 1"))


def _pack(width: int, group: int):
    kind = np.uint8 if width <= 8 else np.uint16

    def block(shard: int, grp: int, keys: np.ndarray, values: np.ndarray):
        shift = max(0, int(values.max()).bit_length() - width)
        slots = (keys - grp * group).astype(np.int64)
        order = np.argsort(slots, kind="stable")
        present = np.zeros(group, bool)
        present[slots] = True
        return shard, grp, shift, len(keys), np.packbits(present).tobytes(), (values[order] >> shift).astype(kind).tobytes()

    def run(batches):
        held, name = [], None
        for batch in batches:
            s, g, k, v = (batch.column(i).to_numpy() for i in range(4))
            cuts = [0, *(np.flatnonzero((s[1:] != s[:-1]) | (g[1:] != g[:-1])) + 1).tolist(), len(s)]
            out = []
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if a == b:
                    continue
                now = (int(s[a]), int(g[a]))
                if now != name:
                    if held:
                        out.append(block(*name, *(np.concatenate(x) for x in zip(*held, strict=True))))
                    held, name = [], now
                held.append((k[a:b], v[a:b]))
            if out:
                yield _rows(out)
        if held:
            yield _rows([block(*name, *(np.concatenate(x) for x in zip(*held, strict=True)))])

    def _rows(rows):
        kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=["shard", "grp", "shift", "n", "present", "codes"])

    return run


def code_rows(rows: DataFrame, width: int = 8, group: int = 1024) -> DataFrame:
    """Blocks (grp, shift, n, present, codes, low, high, size) of the rows (key, val), without an exchange: each task adds up the values of its
    own rows by key and codes the sums, so a task's input is a shard.  ``low`` and ``high`` are the least and largest sum of a block, ``size`` the bits it has.
    """
    if not 1 <= width <= 16:
        raise ValueError("codes have 1 to 16 bits")
    ship(rows.sparkSession)
    kind = np.uint8 if width <= 8 else np.uint16

    def run(batches):
        held: list[tuple[np.ndarray, np.ndarray]] = []
        waiting = 0

        def summed():
            keys, at = np.unique(np.concatenate([k for k, _ in held]), return_inverse=True)
            values = np.zeros(len(keys), np.int64)
            np.add.at(values, at, np.concatenate([v for _, v in held]))
            return keys, values

        for batch in batches:
            held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
            waiting += batch.num_rows
            if waiting > 1 << 21:
                held = [summed()]
                waiting = 0
        if not held:
            return
        keys, values = summed()
        groups = np.floor_divide(keys, group)
        cuts = np.concatenate(([0], np.flatnonzero(groups[1:] != groups[:-1]) + 1, [len(keys)]))
        for first in range(0, len(cuts) - 1, 4096):
            out = []
            for a, b in zip(cuts[first : first + 4096].tolist(), cuts[first + 1 : first + 4097].tolist(), strict=False):
                if a == b:
                    continue
                own, name = values[a:b], int(groups[a])
                low, high = int(own.min()), int(own.max())
                shift = max(0, high.bit_length() - width) if low >= 0 else 0
                present = np.zeros(group, bool)
                present[keys[a:b] - name * group] = True
                bits, codes = np.packbits(present).tobytes(), (own >> shift).astype(kind).tobytes()
                out.append((name, shift, b - a, bits, codes, low, high, 8 * (len(bits) + len(codes) + 1)))
            if out:
                kinds = (pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.int64(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], names=["grp", "shift", "n", "present", "codes", "low", "high", "size"])

    typed = rows.where("key is not null and val is not null").select(F.col("key").cast("long"), F.col("val").cast("long"))
    return typed.mapInArrow(run, "grp long, shift int, n int, present binary, codes binary, low long, high long, size long")


def run_rows(rows: DataFrame, k: int, width: int = 8, group: int = 1024, ties: bool = True) -> BoundsResult:
    """Top-k (key, total) of the sums of rows (key, val): the first exchange carries blocks of codes only, the second the rows of survivors.

    Rows are read twice, so they should be a scan with filters.  Negative sums of a task, and values that codes save nothing on, are summed in full.
    """
    blocks = written(code_rows(rows, width, group))
    row = blocks.agg(F.min("low").alias("a"), F.max("high").alias("b"), F.sum("n").alias("n"), F.sum("size").alias("bits")).first()
    full_bits = 64 * (row["n"] or 0)
    if not row["n"] or k <= 0 or costmodel.choose_topk(row["b"], row["a"], width) == "full":
        return BoundsResult(topk_baselines.full(rows, k, ties), rows.select("key").distinct(), full_bits, full_bits)
    bounds = written(survivors(decode_sum(blocks, width, group), k))
    few = F.broadcast(bounds.select("key")) if bounds.count() * 8 <= costmodel.BUDGET_BYTES else bounds.select("key")
    sums = rows.join(few, "key", "left_semi").groupBy("key").agg(F.sum("val").alias("total"))
    out = with_ties(sums, F.col("total"), k) if ties else sums.orderBy(F.col("total").desc(), "key").limit(k)
    return BoundsResult(out, bounds, row["bits"], full_bits)


def encode(partials: DataFrame, width: int = 8, group: int = 1024) -> DataFrame:
    """Blocks of the parts (shard, key, val) of 16 bits a code at most; one row for each shard and group of keys."""
    if not 1 <= width <= 16:
        raise ValueError("codes have 1 to 16 bits")
    ship(partials.sparkSession)
    rows = partials.select(F.col("shard").cast("long"), F.floor(F.col("key") / group).cast("long").alias("grp"), F.col("key").cast("long"), F.col("val").cast("long"))
    return rows.repartition("shard", "grp").sortWithinPartitions("shard", "grp").mapInArrow(_pack(width, group), BLOCKS)


def decode_sum(blocks: DataFrame, width: int = 8, group: int = 1024) -> DataFrame:
    """(key, lo, hi): the sums of the bounds of all blocks, which meet by group of keys; an absent part counts 0 in both."""
    kind = np.uint8 if width <= 8 else np.uint16

    def run(batches):
        name, low, high, seen = None, None, None, None

        def sums():
            slots = np.flatnonzero(seen)
            return pa.RecordBatch.from_arrays([pa.array(name * group + slots), pa.array(low[slots]), pa.array(high[slots])], names=["key", "lo", "hi"])

        for batch in batches:
            for grp, shift, n, present, codes in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
                if grp != name:
                    if name is not None:
                        yield sums()
                    name, low, high, seen = grp, np.zeros(group, np.int64), np.zeros(group, np.int64), np.zeros(group, bool)
                slots = np.flatnonzero(np.unpackbits(np.frombuffer(present, np.uint8), count=group))
                values = np.frombuffer(codes, kind, n).astype(np.int64) << shift
                low[slots] += values
                high[slots] += values + ((1 << shift) - 1)
                seen[slots] = True
        if name is not None:
            yield sums()

    dealt = blocks.select("grp", "shift", "n", "present", "codes").repartition("grp").sortWithinPartitions("grp")
    return dealt.mapInArrow(run, "key long, lo long, hi long")


def survivors(bounds: DataFrame, k: int) -> DataFrame:
    """Keys whose upper bound reaches the k-th largest lower bound; ties stay."""
    best = bounds.orderBy(F.col("lo").desc()).limit(k).agg(F.min("lo").alias("t")).first()["t"]
    return bounds.limit(0) if best is None else bounds.where(F.col("hi") >= best)


def finish(partials: DataFrame, keys: DataFrame, k: int, ties: bool = True) -> DataFrame:
    """(key, total): the full sums of the survivors, cut to the k best."""
    sums = partials.join(keys.select("key"), "key", "left_semi").groupBy("key").agg(F.sum("val").alias("total"))
    return with_ties(sums, F.col("total"), k) if ties else sums.orderBy(F.col("total").desc(), "key").limit(k)


def finish_residual(partials: DataFrame, bounds: DataFrame, width: int, group: int, k: int) -> DataFrame:
    """The same from the dropped low bits alone: each survivor's lower bound plus the bits its parts lost."""
    kept = code_columns(partials, width, group).join(bounds.select("key"), "key", "left_semi")
    lost = kept.groupBy("key").agg(F.sum(F.col("val") - F.col("lo")).alias("rest"))
    sums = bounds.join(lost, "key").select("key", (F.col("lo") + F.col("rest")).alias("total"))
    return with_ties(sums, F.col("total"), k)


def run(partials: DataFrame, k: int, width: int = 8, group: int = 1024, ties: bool = True, residual: bool = False) -> BoundsResult:
    """Top-k (key, total) of the parts (shard, key, val).  Negative or small values are summed in full, where codes gain nothing."""
    partials = written(partials)
    row = partials.agg(F.min("val").alias("a"), F.max("val").alias("b"), F.count("*").alias("n")).first()
    full_bits = 64 * row["n"]
    if not row["n"] or k <= 0 or costmodel.choose_topk(row["b"], row["a"], width) == "full":
        return BoundsResult(topk_baselines.full(partials, k, ties), partials.select("key").distinct(), full_bits, full_bits)
    blocks = written(encode(partials, width, group))
    bounds = written(survivors(decode_sum(blocks, width, group), k))
    cost = blocks.agg((F.sum(F.length("codes") + F.length("present")) * 8 + F.count("*") * 8).alias("bits")).first()["bits"]
    out = finish_residual(partials, bounds, width, group, k) if residual else finish(partials, bounds, k, ties)
    return BoundsResult(out, bounds, cost, full_bits)
