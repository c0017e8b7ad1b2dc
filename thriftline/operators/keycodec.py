"""Key sets on the wire: bitsets, gaps of increasing sequences, variable-length codes and dictionary codes."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from thriftline.shipping import ship


def to_bitset(df: DataFrame, key: str) -> DataFrame:
    """(bucket, bits): one block of 32,768 bits for each range of keys that has any."""
    return df.where(F.col(key).isNotNull()).groupBy(F.bitmap_bucket_number(key).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(key)).alias("bits"))


def bit_of(bits: Column, position: Column) -> Column:
    """The bit at a position of a block: bytes in order, lowest bit first."""
    byte = F.conv(F.hex(F.substring(bits, F.floor(position / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    return F.getbit(byte, (position % 8).cast("int")) == 1


def from_bitset(blocks: DataFrame) -> DataFrame:
    """The keys of a bitset, in any order."""
    spread = blocks.select("bucket", "bits", F.explode(F.sequence(F.lit(0), F.lit(32767))).alias("bit"))
    # Bucket 0 holds what is not positive, bucket b the keys from (b-1) * 32768 + 1 on.
    key = F.when(F.col("bucket") <= 0, F.col("bucket") * 32768 - F.col("bit")).otherwise((F.col("bucket") - 1) * 32768 + F.col("bit") + 1)
    return spread.where(bit_of(F.col("bits"), F.col("bit"))).select(key.cast("long").alias("key"))


def deltas(df: DataFrame, key: str, by: str) -> DataFrame:
    """(by, key, gap): distinct keys of each receiver in order; the first gap is the key itself."""
    rows = df.where(F.col(key).isNotNull()).select(F.col(by).alias("by"), F.col(key).alias("key")).distinct()
    return rows.withColumn("gap", F.col("key") - F.coalesce(F.lag("key").over(W.partitionBy("by").orderBy("key")), F.lit(0)))


def varint_size(gap: Column) -> Column:
    """Bytes of a number in groups of 7 bits."""
    size = F.lit(1)
    for power in range(1, 9):
        size = size + F.when(gap >= F.lit(1 << 7 * power), 1).otherwise(0)
    return size.cast("long")


def wire_bytes(df: DataFrame, key: str, by: str, code: str = "varint") -> DataFrame:
    """(by, n_keys, bytes) for a code of the gaps: raw (8 each), varint, bitpack (all with the bits of the largest) or elias_gamma; heads not counted."""
    gaps = deltas(df, key, by)
    size = {"raw": F.count("*") * 8, "varint": F.sum(varint_size(F.col("gap"))), "bitpack": F.ceil(F.count("*") * F.length(F.bin(F.max("gap"))) / 8), "elias_gamma": F.ceil(F.sum(2 * F.length(F.bin(F.col("gap") + 1)) - 1) / 8)}[code]
    return gaps.groupBy("by").agg(F.count("*").alias("n_keys"), size.cast("long").alias("bytes"))


def encode_varint(gaps: np.ndarray) -> bytes:
    """Non-negative numbers in groups of 7 bits, lowest first, the high bit marking that more follow."""
    rest = gaps.astype(np.uint64)
    widths = np.ones(len(gaps), np.int64)
    for power in range(1, 10):
        widths += (rest >> np.uint64(7 * power)) > 0
    out = np.zeros(int(widths.sum()), np.uint8)
    at = np.cumsum(widths) - widths
    for k in range(int(widths.max()) if len(widths) else 0):
        live = widths > k
        value = (rest[live] >> np.uint64(7 * k)) & np.uint64(127)
        out[at[live] + k] = value.astype(np.uint8) | np.where(widths[live] > k + 1, 128, 0).astype(np.uint8)
    return out.tobytes()


def decode_varint(data: bytes) -> np.ndarray:
    raw = np.frombuffer(data, np.uint8)
    ends = np.flatnonzero(raw < 128)
    starts = np.concatenate(([0], ends[:-1] + 1)) if len(ends) else ends
    place = np.arange(len(raw)) - np.repeat(starts, ends - starts + 1)
    values = (raw & 127).astype(np.uint64) << (7 * place).astype(np.uint64)
    return np.add.reduceat(values, starts) if len(starts) else values


def _bit_lengths(values: np.ndarray) -> np.ndarray:
    """Bits of each number, 1 for zero."""
    out = np.ones(len(values), np.int64)
    for k in range(1, 64):
        out += (values >> np.uint64(k)) > 0
    return out


def encode_bitpack(gaps: np.ndarray) -> bytes:
    """Non-negative numbers with the bits of the largest; 8 bytes ahead hold their count, one their width."""
    values = np.asarray(gaps).astype(np.uint64)
    width = int(_bit_lengths(values).max()) if len(values) else 1
    bits = (values[:, None] >> np.arange(width, dtype=np.uint64)) & np.uint64(1)
    return len(values).to_bytes(8, "little") + bytes([width]) + np.packbits(bits.astype(np.uint8).ravel(), bitorder="little").tobytes()


def decode_bitpack(data: bytes) -> np.ndarray:
    n, width = int.from_bytes(data[:8], "little"), data[8]
    bits = np.unpackbits(np.frombuffer(data, np.uint8, offset=9), count=n * width, bitorder="little").reshape(n, width)
    return (bits.astype(np.uint64) << np.arange(width, dtype=np.uint64)).sum(axis=1, dtype=np.uint64)


def encode_elias_gamma(gaps: np.ndarray) -> bytes:
    """Non-negative numbers, each one more as a unary length and the bits below its highest; 8 bytes ahead hold their count.

    All lengths come before all other bits, so neither end loops over numbers; the size is that of the interleaved code.
    """
    values = np.asarray(gaps).astype(np.uint64) + np.uint64(1)
    lengths = _bit_lengths(values)
    unary = np.zeros(int(lengths.sum()), np.uint8)
    unary[np.cumsum(lengths) - 1] = 1
    below = np.zeros(len(unary) - len(values), np.uint8)
    ends = np.cumsum(lengths - 1)
    for k in range(int(lengths.max()) - 1 if len(values) else 0):
        live = lengths > k + 1
        below[ends[live] - 1 - k] = (values[live] >> np.uint64(k)) & np.uint64(1)
    return len(values).to_bytes(8, "little") + np.packbits(np.concatenate((unary, below))).tobytes()


def decode_elias_gamma(data: bytes) -> np.ndarray:
    n = int.from_bytes(data[:8], "little")
    bits = np.unpackbits(np.frombuffer(data, np.uint8, offset=8))
    last = np.flatnonzero(bits)[:n]
    lengths = np.diff(last, prepend=-1)
    ends = (int(last[-1]) + 1 if n else 0) + np.cumsum(lengths - 1)
    values = np.uint64(1) << (lengths - 1).astype(np.uint64)
    for k in range(int(lengths.max()) - 1 if n else 0):
        live = lengths > k + 1
        values[live] |= bits[ends[live] - 1 - k].astype(np.uint64) << np.uint64(k)
    return values - np.uint64(1)


def pack_keys(keys: np.ndarray, code: str = "varint") -> bytes:
    """A strictly increasing sequence of non-negative keys as gaps in a code of CODES; ``raw`` and ``block`` take keys in any order."""
    keys = np.asarray(keys, np.int64)
    if code in ("raw", "block"):
        return keys.tobytes() if code == "raw" else block(keys.tobytes())
    return {"varint": encode_varint, "bitpack": encode_bitpack, "elias_gamma": encode_elias_gamma}[code](np.diff(keys, prepend=0))


def unpack_keys(data: bytes, code: str = "varint") -> np.ndarray:
    if code in ("raw", "block"):
        return np.frombuffer(data if code == "raw" else unblock(data), np.int64)
    return np.cumsum({"varint": decode_varint, "bitpack": decode_bitpack, "elias_gamma": decode_elias_gamma}[code](data).astype(np.int64))


CODES = ("varint", "bitpack", "elias_gamma", "raw", "block")


def requests(df: DataFrame, key: str, sort_for_wire: bool = True) -> DataFrame:
    """(bucket, n, keys): the distinct keys that each task wants, a block for each range of 32,768 keys, made without an exchange.

    Sorted keys travel as variable-length gaps; ``sort_for_wire`` off leaves them in any order, 8 bytes each.  Keys are those of ``to_bitset``.
    """
    import pyarrow as pa

    ship(df.sparkSession)

    def run(batches):
        held, waiting = [], 0
        for batch in batches:
            held.append(batch.column(0).to_numpy())
            waiting += batch.num_rows
            if waiting > 1 << 21:
                held, waiting = [np.unique(np.concatenate(held))], 0
        if not held:
            return
        keys = np.unique(np.concatenate(held))
        bucket = np.where(keys > 0, 1 + (keys - 1) // 32768, -(-keys // 32768))
        order = np.argsort(bucket, kind="stable")
        keys, bucket = keys[order], bucket[order]
        cuts = np.concatenate(([0], np.flatnonzero(bucket[1:] != bucket[:-1]) + 1, [len(keys)]))
        for first in range(0, len(cuts) - 1, 4096):
            out = []
            for a, b in zip(cuts[first : first + 4096].tolist(), cuts[first + 1 : first + 4097].tolist(), strict=False):
                if a < b:
                    small = sort_for_wire and keys[a] >= 0
                    out.append((int(bucket[a]), b - a, bool(small), pack_keys(keys[a:b]) if small else keys[a:b].tobytes()))
            if out:
                kinds = (pa.int64(), pa.int32(), pa.bool_(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], names=["bucket", "n", "gaps", "keys"])

    return df.where(F.col(key).isNotNull()).select(F.col(key).cast("long")).mapInArrow(run, "bucket long, n int, gaps boolean, keys binary")


def replies(asked: DataFrame, blocks: DataFrame) -> DataFrame:
    """(gaps, keys, n, reply): for each block of requests one bit for each key, set if the bitset ``blocks`` (bucket, bits) of its owner has it."""
    import pyarrow as pa

    def run(batches):
        for batch in batches:
            out = []
            for gaps, data, bits in zip(*(batch.column(i).to_pylist() for i in (0, 1, 3)), strict=True):
                keys = unpack_keys(data) if gaps else np.frombuffer(data, np.int64)
                at = np.where(keys > 0, (keys - 1) % 32768, -keys % 32768)
                out.append(np.packbits(np.unpackbits(np.frombuffer(bits, np.uint8), bitorder="little")[at]).tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(out, pa.binary())], names=["gaps", "keys", "n", "reply"])

    met = asked.join(blocks, "bucket").select("gaps", "keys", "n", "bits")
    return met.mapInArrow(run, "gaps boolean, keys binary, n int, reply binary")


def answered(replied: DataFrame, name: str) -> DataFrame:
    """The keys whose bit is set."""
    import pyarrow as pa

    def run(batches):
        for batch in batches:
            for gaps, data, n, reply in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                keys = unpack_keys(data) if gaps else np.frombuffer(data, np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(keys[np.unpackbits(np.frombuffer(reply, np.uint8), count=n).astype(bool)])], names=[name])

    return replied.mapInArrow(run, f"`{name}` long")


def packed(df: DataFrame, key: str, by: str, chunk: int = 1 << 16, code: str = "varint") -> DataFrame:
    """(by, piece, n_keys, data): the distinct keys of each receiver, packed by a code of CODES in pieces of key ranges of bounded size."""
    import pyarrow as pa

    ship(df.sparkSession)
    rows = df.where(F.col(key).isNotNull()).select(F.col(by).cast("long").alias("by"), F.floor(F.col(key) / chunk).cast("long").alias("piece"), F.col(key).cast("long").alias("key")).distinct()

    def run(batches):
        held, name = [], None

        def block():
            keys = np.concatenate(held)
            return pa.RecordBatch.from_arrays([pa.array([name[0]]), pa.array([name[1]]), pa.array([len(keys)]), pa.array([pack_keys(keys, code)])], names=["by", "piece", "n_keys", "data"])

        for batch in batches:
            a, b, k = (batch.column(i).to_numpy() for i in range(3))
            cuts = [0, *(np.flatnonzero((a[1:] != a[:-1]) | (b[1:] != b[:-1])) + 1).tolist(), len(a)]
            for s, e in zip(cuts[:-1], cuts[1:], strict=True):
                if s == e:
                    continue
                if name != (int(a[s]), int(b[s])):
                    if held:
                        yield block()
                    held, name = [], (int(a[s]), int(b[s]))
                held.append(k[s:e])
        if held:
            yield block()

    dealt = rows.repartition("by", "piece").sortWithinPartitions("by", "piece", "key")
    return dealt.mapInArrow(run, "by long, piece long, n_keys long, data binary")


def unpacked(blocks: DataFrame, code: str = "varint") -> DataFrame:
    """(by, key) of packed blocks."""
    import pyarrow as pa

    ship(blocks.sparkSession)

    def run(batches):
        for batch in batches:
            for by, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                keys = unpack_keys(data, code)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), by)), pa.array(keys)], names=["by", "key"])

    return blocks.select("by", "data").mapInArrow(run, "by long, key long")


def dictionary(df: DataFrame, column: str) -> DataFrame:
    """(value, code): the distinct values of a column in order, coded from 0; for columns of few values."""
    return df.where(F.col(column).isNotNull()).select(F.col(column).alias("value")).distinct().withColumn("code", (F.row_number().over(W.orderBy("value")) - 1).cast("long"))


def dense_ids(df: DataFrame, column: str, parts: int = 256) -> DataFrame:
    """(value, key): the distinct values of a column with ids from 0 without gaps, for columns of any number of values.

    Values are numbered within hash parts, and parts start where the one before ends, so no task sees all of them.
    """
    values = df.where(F.col(column).isNotNull()).select(F.col(column).alias("value")).distinct().withColumn("_part", F.pmod(F.xxhash64("value"), F.lit(parts)))
    sizes = values.groupBy("_part").agg(F.count("*").alias("_n"))
    before = sizes.select("_part", F.coalesce(F.sum("_n").over(W.orderBy("_part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    own = F.row_number().over(W.partitionBy("_part").orderBy("value")) - 1
    return values.join(F.broadcast(before), "_part").select("value", (F.col("_before") + own).cast("long").alias("key"))


def block(data: bytes, codec: str = "lz4") -> bytes:
    """Dictionary compression for bytes in no order; Spark's shuffle does the same to its own blocks."""
    import pyarrow as pa

    return len(data).to_bytes(8, "little") + pa.compress(data, codec=codec, asbytes=True)


def unblock(data: bytes, codec: str = "lz4") -> bytes:
    import pyarrow as pa

    return pa.decompress(data[8:], decompressed_size=int.from_bytes(data[:8], "little"), codec=codec, asbytes=True)
