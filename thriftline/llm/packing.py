"""Packing as vector bin packing with the dot-product heuristic.

An example is a vector of tokens, segments (1) and loss-bearing tokens; a sequence has a limit on each.  A sequence is filled with that
example of the pool, among those that fit, whose vector has the largest dot product with what is left of the limits (both in shares of
the limits).  Where examples may be cut, whole sequences are cut off long ones first, and a sequence into which nothing fits
any more is filled up with a piece of the largest example; what is left at the end of a task goes into sequences whose lengths
are powers of two.  The pool is bounded in tokens and in examples, so a task holds no more than it whatever the input; no row moves
between tasks.  ``pack_documents`` has loss on every token, where the best example is the longest that fits (``LinePool``);
``pack_examples`` weighs all three.
"""

from __future__ import annotations

import bisect

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from thriftline.llm.arrowrun import columns_of, give_back, pieces
from thriftline.llm.tokens import encoder_for
from thriftline.shipping import ship

#: A task's pool: from so many sequences or examples it packs, down to so many sequences and examples.
HIGH, LOW = 256, 64
HIGH_COUNT, LOW_COUNT = 1 << 16, 1 << 14


class Pool:
    """Examples waiting for a sequence, by their vectors: equal vectors share a place, so a search looks at each vector once."""

    def __init__(self, limits: tuple[int, int, int]):
        self.limits = np.array(limits, float)
        self.vectors = np.full((64, 3), np.inf)
        self.waiting: list[list] = [[] for _ in range(64)]
        self.place: dict[tuple[int, int], int] = {}
        self.free = list(range(63, -1, -1))
        self.count = 0

    def add(self, payload, tokens: int, loss: int) -> None:
        at = self.place.get((tokens, loss))
        if at is None:
            if not self.free:
                n = len(self.waiting)
                self.vectors = np.concatenate((self.vectors, np.full((n, 3), np.inf)))
                self.waiting += [[] for _ in range(n)]
                self.free = list(range(2 * n - 1, n - 1, -1))
            at = self.place[tokens, loss] = self.free.pop()
            self.vectors[at] = (tokens, 1, loss)
        self.waiting[at].append(payload)
        self.count += 1

    def take(self, at: int):
        payload = self.waiting[at].pop()
        if not self.waiting[at]:
            del self.place[int(self.vectors[at, 0]), int(self.vectors[at, 2])]
            self.vectors[at] = np.inf
            self.free.append(at)
        self.count -= 1
        return payload

    def best(self, left: np.ndarray) -> int:
        """The place of the fitting vector with the largest dot product, or -1; the first place on a tie."""
        fits = (self.vectors <= left).all(axis=1)
        if not fits.any():
            return -1
        places = np.flatnonzero(fits)
        return int(places[((self.vectors[places] / self.limits) @ (left / self.limits)).argmax()])


class LinePool:
    """The pool where every token bears loss: vectors (n, 1, n) lie on a line, along which the dot product grows with n.

    So the best example is the longest that fits, found by bisection among the lengths there are, and it stays the best while it fits.
    """

    def __init__(self):
        self.lengths: list[int] = []
        self.waiting: dict[int, list] = {}
        self.tokens = self.count = 0

    def add(self, payload, tokens: int) -> None:
        if tokens not in self.waiting:
            bisect.insort(self.lengths, tokens)
            self.waiting[tokens] = []
        self.waiting[tokens].append(payload)
        self.tokens += tokens
        self.count += 1

    def take(self, tokens: int, times: int = 1) -> list:
        own = self.waiting[tokens]
        out = own[-times:][::-1]
        del own[-times:]
        if not own:
            del self.waiting[tokens]
            del self.lengths[bisect.bisect_left(self.lengths, tokens)]
        self.tokens -= tokens * times
        self.count -= times
        return out

    def best(self, room: int) -> int:
        """The length of the best example within ``room`` tokens, or 0."""
        at = bisect.bisect_right(self.lengths, room)
        return self.lengths[at - 1] if at else 0


def _powers(n: int) -> list[int]:
    return [1 << b for b in range(n.bit_length() - 1, -1, -1) if n >> b & 1]


class Packer:
    """Sequences of (payload, start, length) pieces, examples being cut where that fills one; every token bears loss."""

    def __init__(self, tokens: int, segments: int, loss: int):
        self.tokens, self.segments, self.whole = tokens, segments, min(tokens, loss)
        self.pool = LinePool()

    def add(self, payload, tokens: int):
        """Takes an example; yields the whole sequences that can be cut off it, and others while the pool is full."""
        start = 0
        while tokens - start >= self.whole:
            yield [(payload, start, self.whole)]
            start += self.whole
        if tokens > start:
            self.pool.add((payload, start, tokens - start), tokens - start)
        if self.pool.tokens > HIGH * self.tokens or self.pool.count > HIGH_COUNT:
            yield from self.pack(LOW * self.tokens, LOW_COUNT)

    def pack(self, until: int, count: int):
        pool = self.pool
        while pool.count and (pool.tokens >= until or pool.count > count):
            room, segments, out = self.whole, self.segments, []
            while pool.count and room and segments:
                length = pool.best(room)
                if length:
                    times = min(len(pool.waiting[length]), room // length, segments)
                    out += pool.take(length, times)
                    room, segments = room - times * length, segments - times
                else:
                    (payload, start, length), = pool.take(pool.lengths[-1])
                    out.append((payload, start, room))
                    pool.add((payload, start + room, length - room), length - room)
                    room = 0
            if not room:
                yield out
            else:
                yield from _tail(out)

    def finish(self):
        yield from self.pack(0, 0)


def _tail(pieces_left: list) -> list[list]:
    """Sequences of power-of-two lengths from the pieces of a short one."""
    out, queue = [], list(pieces_left)[::-1]
    for size in _powers(sum(p[2] for p in queue)):
        own = []
        while size:
            payload, start, length = queue.pop()
            use = min(size, length)
            own.append((payload, start, use))
            if use < length:
                queue.append((payload, start + use, length - use))
            size -= use
        out.append(own)
    return out


def pack_documents(docs: DataFrame, path: str, end_id: int = 2, tokens: int = 4096, segments: int = 1024, loss: int | None = None, drop_space: bool = True) -> DataFrame:
    """One row for each piece: doc_id, start, length, ids (unsigned 32-bit, little endian), doc_tokens, sequence_id, offset.

    A document is the ids of its text by the tokenizer file at ``path`` and then ``end_id``; null and empty texts are ``end_id`` alone.
    ``loss`` limits loss-bearing tokens (all of them here; as many as tokens if not given).  Rows that repeat a document, or have no
    doc_id, are packed as rows of their own.  Sequence ids are the task's number times 2**36 plus a count, so a task that runs
    again gives them again.  No rows in, no rows out.
    """
    ship(docs.sparkSession)
    rows = columns_of(docs, "doc_id", "text")
    limit = tokens if loss is None else loss
    schema = T.StructType([rows.schema["doc_id"]])
    for name, kind in (("start", T.LongType()), ("length", T.LongType()), ("ids", T.BinaryType()), ("doc_tokens", T.LongType()), ("sequence_id", T.LongType()), ("offset", T.LongType())):
        schema = schema.add(name, kind)
    id_type = rows.schema["doc_id"].dataType

    def run(batches):
        from pyspark.sql.pandas.types import to_arrow_type

        kind = to_arrow_type(id_type)
        encoder, packer = encoder_for(path, drop_space, with_ids=True), Packer(tokens, segments, limit)
        number = TaskContext.get().partitionId() << 36
        out: list[list] = [[] for _ in range(7)]
        held = 0

        def put(sequence):
            nonlocal number, held
            at = 0
            for (doc_id, ids), start, length in sequence:
                for column, value in zip(out, (doc_id, start, length, ids[start : start + length].tobytes(), len(ids), number, at), strict=True):
                    column.append(value)
                at += length
            held += at
            number += 1

        def batch():
            nonlocal held
            made = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, (kind, pa.int64(), pa.int64(), pa.binary(), *[pa.int64()] * 3), strict=True)], names=schema.names)
            for column in out:
                column.clear()
            held = 0
            return made

        for arrived in batches:
            for piece in pieces(arrived, 1, 2 << 20):
                names = piece.column(0).to_pylist()
                for i, j, flat, begin in encoder.rows(piece.column(1)):
                    flat = np.insert(flat, begin[1:], np.uint32(end_id))
                    begin = (begin + np.arange(len(begin))).tolist()
                    for r in range(j - i):
                        ids = flat[begin[r] : begin[r + 1]].copy()
                        for sequence in packer.add((names[i + r], ids), len(ids)):
                            put(sequence)
                    if held > 1 << 20:
                        yield batch()
        for sequence in packer.finish():
            put(sequence)
        if out[0]:
            yield batch()
        del packer
        give_back()

    return rows.mapInArrow(run, schema)


def pack_examples(examples: DataFrame, tokens: int = 4096, segments: int = 64, loss: int = 2048) -> DataFrame:
    """Packs whole examples (example_id, n_tokens, n_loss) under all three limits, uncut: example_id, sequence_id, offset, fits.

    An example beyond a limit cannot be placed: it has a sequence of its own and fits is false.  Null counts are 0.  Each task packs
    its own rows from a bounded pool.
    """
    ship(examples.sparkSession)
    rows = columns_of(examples, "example_id", "n_tokens", "n_loss")
    rows = rows.select("example_id", F.coalesce(F.col("n_tokens").cast("long"), F.lit(0)).alias("n_tokens"), F.coalesce(F.col("n_loss").cast("long"), F.lit(0)).alias("n_loss"))
    schema = T.StructType([rows.schema["example_id"]]).add("sequence_id", T.LongType()).add("offset", T.LongType()).add("fits", T.BooleanType())

    def run(batches):
        pool, number = Pool((tokens, segments, loss)), TaskContext.get().partitionId() << 36
        out: list[tuple] = []

        def pack(until: int):
            nonlocal number
            while pool.count > until:
                left, at = pool.limits.copy(), 0
                while (place := pool.best(left)) >= 0:
                    vector = pool.vectors[place].copy()
                    out.append((pool.take(place), number, at, True))
                    at += int(vector[0])
                    left -= vector
                number += 1

        def batch():
            a, b, c, d = zip(*out, strict=True)
            out.clear()
            return pa.RecordBatch.from_arrays([pa.array(a), pa.array(b, pa.int64()), pa.array(c, pa.int64()), pa.array(d)], names=schema.names)

        for arrived in batches:
            for name, n, n_loss in zip(*(arrived.column(k).to_pylist() for k in range(3)), strict=True):
                if n > tokens or n_loss > loss:
                    out.append((name, number, 0, False))
                    number += 1
                    continue
                pool.add(name, n, n_loss)
                if pool.count > 4096:
                    pack(1024)
            if out:
                yield batch()
        pack(0)
        if out:
            yield batch()

    return rows.mapInArrow(run, schema)
