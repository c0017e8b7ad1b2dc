"""Exact removal of repeated word windows by super-k-mer partitioning.

A window is ``window`` consecutive words of one document.  Its minimiser is the smallest hash among its runs of ``mer`` words.
Consecutive windows with the same minimiser travel as one packed string (a super-k-mer) to the bucket of that minimiser, so equal
windows always meet.  A bucket takes the strings apart again and sorts the fingerprints of its windows (two 64-bit hashes of the word sequence, which
share the 64-bit hash of each word) together with where they start; every window but the first of an equal run is a repeat.

Skew: equal super-k-mers of a piece are settled where they are read and only the first travels; the windows of the few minimisers
whose super-k-mers have more bytes than a part of a bucket travel one by one to buckets of their own fingerprints.  A task
remembers the hot windows it has sent and sends an equal one only if it starts earlier, so a bucket gets about one copy from each task of a window
that every document holds.
Buckets and parts have bounded sizes, so their number grows with the input and no task holds more than one at a time.
Strings and rows travel in compressed blocks, one for each bucket and batch.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from thriftline.llm import rowkeys
from thriftline.llm import textscan as ts
from thriftline.llm.arrowrun import fresh, give_back, pieces
from thriftline.shipping import ship

MER = 4
#: Text bytes worked on at once, and held before blocks are sent.
PIECE, BATCH = 3 << 20, 8 << 20
#: Bytes of text (before compression) of a bucket and of a part.
BUCKET_BYTES = 12 << 20
#: Partitions of an exchange at most; beyond it a task works on several buckets, one after another.
PARTITIONS = 50_000
#: A minimiser is hot if it has more super-k-mers than the first and they have more bytes than a bucket divided by the second.
HOT_LEAST, HOT_SHARE = 1, 4
#: Hot windows that a task remembers; then it starts anew.
HOT_HELD = 1 << 20
_SECOND = np.uint64(0xA0761D6478BD642F)


def _prefix(h: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    powers, inverses = ts._power_tables(len(h) + 1)
    with np.errstate(over="ignore"):
        sums = np.zeros(len(h) + 1, np.uint64)
        np.cumsum(h * powers[: len(h)], out=sums[1:])
    return sums, powers, inverses


def sequence_hashes(h: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two hashes of the word sequences start..stop; equal words enter both alike."""
    out = []
    for words in (h, ts.mix(h ^ _SECOND)):
        sums, _, inverses = _prefix(words)
        with np.errstate(over="ignore"):
            out.append(ts.mix((sums[stops] - sums[starts]) * inverses[starts]))
    return out[0], out[1]


def _sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    have = 1
    while have * 2 <= width:
        x = np.minimum(x[:-have], x[have:])
        have *= 2
    return np.minimum(x[: len(x) - (width - have)], x[width - have :]) if width > have else x


class Cut:
    """The super-k-mers of a block: first and last window, minimiser and row of each."""

    def __init__(self, spans: ts.Spans, h: np.ndarray, window: int, mer: int):
        n = len(h) - window + 1
        if n <= 0:
            self.first = self.last = self.row = np.zeros(0, np.int64)
            self.low = np.zeros(0, np.uint64)
            return
        low = _sliding_min(ts.window_hashes(h, mer), window - mer + 1)
        row = spans.rows[:n]
        valid = row == spans.rows[window - 1 :]
        begins = valid.copy()
        begins[1:] &= ~(valid[:-1] & (low[1:] == low[:-1]) & (row[1:] == row[:-1]))
        self.first = np.flatnonzero(begins)
        ends = valid.copy()
        ends[:-1] &= ~(valid[1:] & (low[1:] == low[:-1]) & (row[1:] == row[:-1]))
        self.last = np.flatnonzero(ends)
        self.low, self.row = low[self.first], row[self.first]


def _hot_minimisers(docs: DataFrame, window: int, mer: int) -> tuple[np.ndarray, int, int]:
    """The hot minimisers, fewer than ``HOT_SHARE`` for each bucket; bytes of text; bytes of super-k-mers.

    Every minimiser is counted, in each batch, then in each task, then over all, and none is left out before its total is known.
    """

    def run(batches):
        total = packed = 0
        for batch in batches:
            seen, sizes = [], []
            for piece in pieces(batch, 0, PIECE):
                raw, offs, _ = ts.text_buffers(piece.column(0))
                total += int(offs[-1] - offs[0])
                for i, j in ts.blocks(offs):
                    spans = ts.Spans(raw, offs[i : j + 1], ts.NON_SPACE)
                    cut = Cut(spans, spans.hashes(), window, mer)
                    if len(cut.first):
                        sizes.append(spans.ends[cut.last + window - 1] - spans.starts[cut.first])
                        seen.append(cut.low)
            if not seen:
                continue
            low, size = np.concatenate(seen), np.concatenate(sizes)
            packed += int(size.sum())
            order = np.argsort(low)
            low, size = low[order], size[order]
            begin = np.flatnonzero(np.concatenate(([True], low[1:] != low[:-1])))
            times = np.diff(np.append(begin, len(low)))
            yield pa.RecordBatch.from_arrays([pa.array(low[begin].view(np.int64)), pa.array(times), pa.array(np.add.reduceat(size, begin).astype(np.int64))], names=["low", "n", "size"])
        # Totals under two reserved kinds, told apart by counts of 0.
        yield pa.RecordBatch.from_arrays([pa.array([0, 1]), pa.array([0, 0]), pa.array([total, packed])], names=["low", "n", "size"])
        give_back()

    found = docs.select("text").mapInArrow(run, "low long, n long, size long").withColumn("kind", F.col("n") == 0)
    sums = found.groupBy("kind", "low").agg(F.sum("n").alias("n"), F.sum("size").alias("size"))
    rows = sums.where(F.col("kind") | ((F.col("n") > HOT_LEAST) & (F.col("size") > BUCKET_BYTES // HOT_SHARE))).collect()
    totals = {r["low"]: r["size"] for r in rows if r["kind"]}
    hot = [r["low"] for r in rows if not r["kind"]]
    return np.sort(np.array(hot, np.int64).view(np.uint64)), totals.get(0, 0), totals.get(1, 0)


def _pack(*arrays: np.ndarray) -> bytes:
    """Arrays (the last one bytes) in one compressed block, with their length before it."""
    body = b"".join(np.ascontiguousarray(a).tobytes() for a in arrays)
    head = np.array([len(arrays[0]), len(body)], np.int64).tobytes()
    return head + pa.compress(body, codec="zstd", asbytes=True)


def _unpack(block: bytes, kinds: tuple) -> list[np.ndarray]:
    n, size = np.frombuffer(block, np.int64, 2).tolist()
    body = pa.decompress(block[16:], decompressed_size=size, codec="zstd", asbytes=True)
    out, at = [], 0
    for kind in kinds:
        width = np.dtype(kind).itemsize
        out.append(np.frombuffer(body, kind, n, at))
        at += n * width
    out.append(np.frombuffer(body, np.uint8, offset=at))
    return out


def _owner(ids: np.ndarray, parts: int) -> np.ndarray:
    return (ts.mix(ids.astype(np.int64).view(np.uint64)) % np.uint64(parts)).astype(np.int64)


class _Sender:
    """Collects slices by bucket and gives them as blocks."""

    def __init__(self):
        self.held: dict[int, list] = {}
        self.size = 0

    def add(self, bucket: np.ndarray, columns: tuple, raw: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> None:
        order = np.argsort(bucket, kind="stable")
        bucket, columns, starts, lengths = bucket[order], [c[order] for c in columns], starts[order], lengths[order]
        text = raw[ts.ranges(starts, lengths)]
        edge = np.concatenate(([0], np.cumsum(lengths)))
        cuts = np.concatenate(([0], np.flatnonzero(bucket[1:] != bucket[:-1]) + 1, [len(bucket)]))
        for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            self.held.setdefault(int(bucket[a]), []).append(([c[a:b] for c in columns], lengths[a:b].astype(np.int32), text[edge[a] : edge[b]]))
        self.size += len(text)

    def blocks(self):
        for bucket in sorted(self.held):
            parts = self.held[bucket]
            columns = [np.concatenate(c) for c in zip(*(p[0] for p in parts), strict=True)]
            yield bucket, _pack(*columns, np.concatenate([p[1] for p in parts]), np.concatenate([p[2] for p in parts]))
        self.held, self.size = {}, 0


def _batch(rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
    a, b, c = zip(*rows, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int32()), pa.array(c, pa.binary())], names=["bucket", "kind", "block"])


class _Sent:
    """The hot windows that a task has sent, by fingerprint, with the earliest place of each."""

    def __init__(self):
        self.one = self.two = np.zeros(0, np.uint64)
        self.owner = self.begin = np.zeros(0, np.int64)

    def later(self, one: np.ndarray, two: np.ndarray, owner: np.ndarray, begin: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of distinct windows, those that start after an equal one sent before, and those sent before from the same place; others count as sent now."""
        if len(self.one) > HOT_HELD:
            self.__init__()
        known = np.zeros(len(one), bool)
        if len(self.one):
            place = np.minimum(np.searchsorted(self.one, one), len(self.one) - 1)
            known = (self.one[place] == one) & (self.two[place] == two)
            own = place[known]
            after = (owner[known] > self.owner[own]) | ((owner[known] == self.owner[own]) & (begin[known] > self.begin[own]))
            again = (owner[known] == self.owner[own]) & (begin[known] == self.begin[own])
            self.owner[own[~after]], self.begin[own[~after]] = owner[known][~after], begin[known][~after]
        late, twice = known.copy(), known.copy()
        if known.any():
            late[known], twice[known] = after, again
        new = np.flatnonzero(~known)
        new = new[np.argsort(one[new], kind="stable")]
        at = np.searchsorted(self.one, one[new])
        self.one, self.two = np.insert(self.one, at, one[new]), np.insert(self.two, at, two[new])
        self.owner, self.begin = np.insert(self.owner, at, owner[new]), np.insert(self.begin, at, begin[new])
        return late, twice


def _send(window: int, mer: int, hot, buckets: int):
    """Rows (doc_id, text) to blocks: kind 0 holds repeats already settled here, kind 1 super-k-mers."""

    def run(batches):
        sender, runs, sent = _Sender(), [], _Sent()

        def flush():
            rows = [(b, 1, block) for b, block in sender.blocks()]
            if runs:
                ids, first, stop = (np.concatenate(c) for c in zip(*runs, strict=True))
                rows.append((int(ids[0] % buckets), 0, _pack(ids, first.astype(np.int32), stop.astype(np.int32), np.zeros(0, np.uint8))))
                runs.clear()
            for at in range(0, len(rows), 256):
                yield _batch(rows[at : at + 256])

        for batch in batches:
            for piece in pieces(batch, 1, PIECE):
                ids = piece.column(0).to_numpy()
                raw, offs, _ = ts.text_buffers(piece.column(1))
                spans = ts.Spans(raw, offs, ts.NON_SPACE)
                h = spans.hashes()
                cut = Cut(spans, h, window, mer)
                if not len(cut.first):
                    continue
                first, last, low, row = cut.first, cut.last, cut.low, cut.row
                if len(hot.value):
                    known = hot.value[np.minimum(np.searchsorted(hot.value, low), len(hot.value) - 1)] == low
                    each = ts.ranges(first[known], (last - first + 1)[known])
                    times = (last - first + 1)[known]
                    single = np.concatenate((np.zeros((~known).sum(), bool), np.ones(len(each), bool)))
                    first, last = np.concatenate((first[~known], each)), np.concatenate((last[~known], each))
                    row, low = np.concatenate((row[~known], np.repeat(row[known], times))), np.concatenate((low[~known], np.repeat(low[known], times)))
                else:
                    single = np.zeros(len(first), bool)
                one, two = sequence_hashes(h, first, last + window)
                begin = first - spans.first[row]
                owner = ids[row]
                order = np.argsort(one, kind="stable")
                alike = one[order][1:] == one[order][:-1]
                among = np.zeros(len(first), bool)
                among[order[1:][alike]] = True
                among[order[:-1][alike]] = True
                travels = np.ones(len(first), bool)
                sub = np.flatnonzero(among)
                if len(sub):
                    sub = sub[np.lexsort((begin[sub], owner[sub], two[sub], one[sub]))]
                    head = np.concatenate(([True], (one[sub][1:] != one[sub][:-1]) | (two[sub][1:] != two[sub][:-1])))
                    leader = sub[np.flatnonzero(head)[np.cumsum(head) - 1]]
                    travels[sub[~head]] = False
                    later = ~head & ((owner[sub] != owner[leader]) | (begin[sub] != begin[leader]))
                    gone = sub[later]
                    if len(gone):
                        runs.append((owner[gone], begin[gone], begin[gone] + (last - first)[gone] + window))
                if (hot_at := np.flatnonzero(travels & single)).size:
                    late, twice = sent.later(one[hot_at], two[hot_at], owner[hot_at], begin[hot_at])
                    travels[hot_at[late | twice]] = False
                    if late.any():
                        gone = hot_at[late]
                        runs.append((owner[gone], begin[gone], begin[gone] + window))
                bucket = (np.where(single, ts.mix(one ^ two), ts.mix(low)) % np.uint64(buckets)).astype(np.int64)
                go = np.flatnonzero(travels)
                starts = spans.starts[first[go]]
                sender.add(bucket[go], (owner[go], begin[go].astype(np.int32)), spans.raw, starts, spans.ends[last[go] + window - 1] - starts)
                if sender.size >= 2 * BATCH:
                    yield from flush()
        yield from flush()
        give_back()

    return run


def _repeats(window: int, parts: int):
    """Blocks of buckets, ordered by bucket, to blocks of repeated word runs by part."""

    def settle(blocks: list[bytes]):
        ids, begin, sizes, text = (np.concatenate(c) for c in zip(*(_unpack(b, (np.int64, np.int32, np.int32)) for b in blocks), strict=True))
        offs = np.concatenate(([0], np.cumsum(sizes, dtype=np.int64)))
        h, counts = [], []
        for i, j in ts.blocks(offs):
            spans = ts.Spans(text, offs[i : j + 1], ts.NON_SPACE)
            h.append(spans.hashes())
            counts.append(spans.counts)
        counts = np.concatenate(counts)
        first = np.cumsum(counts) - counts
        h = np.concatenate(h)
        windows = counts - window + 1
        at = ts.ranges(first, windows)
        owner = np.repeat(np.arange(len(counts)), windows)
        one, two = sequence_hashes(h, at, at + window)
        del h
        order = np.argsort(one)
        sorted_one = one[order]
        alike = sorted_one[1:] == sorted_one[:-1]
        mask = np.concatenate(([False], alike)) | np.concatenate((alike, [False]))
        sub = order[mask]
        if not len(sub):
            return None
        place = begin[owner[sub]] + (at[sub] - first[owner[sub]])
        who = ids[owner[sub]]
        rank = np.lexsort((place, who, two[sub], one[sub]))
        sub, place, who = sub[rank], place[rank], who[rank]
        head = np.concatenate(([True], (one[sub][1:] != one[sub][:-1]) | (two[sub][1:] != two[sub][:-1])))
        leader = np.flatnonzero(head)[np.cumsum(head) - 1]
        later = ~head & ((who != who[leader]) | (place != place[leader]))
        if not later.any():
            return None
        sub, who, place = sub[later], who[later], place[later].astype(np.int64)
        order = np.lexsort((place, who))
        who, place = who[order], place[order]
        new = np.concatenate(([True], (who[1:] != who[:-1]) | (place[1:] > place[:-1] + 1)))
        starts = np.flatnonzero(new)
        lasts = np.concatenate((starts[1:], [len(who)])) - 1
        return who[starts], place[starts], place[lasts] + window

    def run(batches):
        held, key, runs, size = [], None, [], 0

        def flush():
            if not runs:
                return
            ids, first, stop = (np.concatenate(c) for c in zip(*runs, strict=True))
            runs.clear()
            part = _owner(ids, parts)
            order = np.argsort(part, kind="stable")
            cuts = np.concatenate(([0], np.flatnonzero(np.diff(part[order])) + 1, [len(order)]))
            rows = []
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                o = order[a:b]
                rows.append((int(part[o[0]]), 0, _pack(ids[o], first[o].astype(np.int32), stop[o].astype(np.int32), np.zeros(0, np.uint8))))
            for at in range(0, len(rows), 256):
                yield _batch(rows[at : at + 256])

        for batch in batches:
            for bucket, kind, block in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                if bucket != key:
                    if held and (found := settle(held)):
                        runs.append(found)
                        size += len(found[0])
                    held, key = [], bucket
                if kind:
                    held.append(block)
                else:
                    found = _unpack(block, (np.int64, np.int32, np.int32))[:3]
                    runs.append((found[0], found[1].astype(np.int64), found[2].astype(np.int64)))
                    size += len(found[0])
                if size > 1 << 20:
                    yield from flush()
                    size = 0
        if held and (found := settle(held)):
            runs.append(found)
        held = []
        yield from flush()
        give_back()

    return run


def _row_blocks(parts: int, id_at: int, text_at: int):
    """Whole rows to compressed Arrow blocks by part (kind 1)."""

    def run(batches):
        for batch in batches:
            for piece in pieces(batch, text_at, BATCH):
                ids = piece.column(id_at)
                part = _owner(ids.fill_null(0).to_numpy(), parts)
                order = np.argsort(part, kind="stable")
                cuts = np.concatenate(([0], np.flatnonzero(np.diff(part[order])) + 1, [len(order)]))
                rows = []
                for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                    sink = pa.BufferOutputStream()
                    own = piece.take(pa.array(order[a:b]))
                    with pa.ipc.new_stream(sink, own.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
                        out.write_batch(own)
                    rows.append((int(part[order[a]]), 1, sink.getvalue().to_pybytes()))
                for at in range(0, len(rows), 64):
                    yield _batch(rows[at : at + 64])
        give_back()

    return run


def _kept(id_at: int, text_at: int, kept_at: list[int], names: list[str]):
    """Blocks of runs, then of rows, of each part, to rows with the kept text and word counts."""

    def run(batches):
        key, runs = None, []
        table = None
        for batch in batches:
            for part, kind, block in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                if part != key:
                    key, runs, table = part, [], None
                if kind == 0:
                    runs.append(_unpack(block, (np.int64, np.int32, np.int32))[:3])
                    continue
                if table is None:
                    ids, first, stop = (np.concatenate(c) for c in zip(*runs, strict=True)) if runs else (np.zeros(0, np.int64),) * 3
                    order = np.argsort(ids, kind="stable")
                    table = (ids[order], first[order], stop[order])
                for rows in pa.ipc.open_stream(block):
                    for piece in pieces(rows, text_at, PIECE):
                        texts, counts, removed = _cleaned(piece.column(id_at), piece.column(text_at), table)
                        columns = [piece.column(i) for i in kept_at]
                        yield pa.RecordBatch.from_arrays([*columns, texts, counts, removed], names=names)
        give_back()

    def _cleaned(ids, column, table):
        raw, offs, _ = ts.text_buffers(column)
        spans = ts.Spans(raw, offs, ts.NON_SPACE)
        known = np.asarray(ids.is_valid())
        own = ids.fill_null(0).to_numpy()
        a, b = np.searchsorted(table[0], own, "left"), np.searchsorted(table[0], own, "right")
        b = np.where(known, b, a)
        which = ts.ranges(a, b - a)
        row = np.repeat(np.arange(len(own)), b - a)
        first = np.minimum(spans.first[row] + table[1][which], spans.first[row + 1])
        stop = np.minimum(spans.first[row] + table[2][which], spans.first[row + 1])
        edge = np.zeros(len(spans) + 1, np.int64)
        np.add.at(edge, first, 1)
        np.add.at(edge, stop, -1)
        gone = np.cumsum(edge[:-1]) > 0
        stay = np.flatnonzero(~gone)
        # Kept words with one space after each; the last of a row has none.
        lengths = spans.ends[stay] - spans.starts[stay]
        out = np.full(int(lengths.sum()) + len(stay), 0x20, np.uint8)
        target = np.cumsum(lengths + 1) - (lengths + 1)
        out[ts.ranges(target, lengths)] = spans.raw[ts.ranges(spans.starts[stay], lengths)]
        per_row = np.bincount(spans.rows[stay], minlength=len(own))
        sizes = np.bincount(spans.rows[stay], weights=lengths + 1, minlength=len(own)).astype(np.int64)
        ends = np.cumsum(sizes)
        last = ends[per_row > 0] - 1
        keep = np.ones(len(out), bool)
        keep[last] = False
        offsets = np.concatenate(([0], np.cumsum(sizes - (per_row > 0)))).astype(np.int64)
        texts = pa.Array.from_buffers(pa.large_string(), len(own), [None, pa.py_buffer(offsets.tobytes()), pa.py_buffer(out[keep].tobytes())])
        counts = spans.counts.astype(np.int64)
        return texts.cast(pa.string()), pa.array(counts), pa.array(counts - per_row)

    return run


def _dealt(blocks: DataFrame, buckets: int) -> DataFrame:
    """Blocks by the number of their bucket itself, so that no two buckets meet in a partition by chance."""
    n = min(buckets, PARTITIONS)
    return blocks.repartitionById(n, F.pmod("bucket", F.lit(n)).cast("int"))


def cleaned(docs: DataFrame, window: int = 20, mer: int = MER) -> tuple[DataFrame, tuple[str, str, str]]:
    """All columns of ``docs`` and three more: kept text, words and removed words; and the names of the three.

    A word goes if a window that covers it has a word sequence that also starts earlier in the input: in a document of smaller
    doc_id, or earlier in the same one.  Null texts and texts without words have no words and an empty kept text.  A row without doc_id
    keeps all words and counts for none.  Rows that repeat doc_id and text are copies of one document: a window is not earlier than itself.
    Rows of one doc_id and different texts are different documents, in the order of a digest of the text.
    Texts shorter than a window lose nothing.  No rows in, no rows out.
    """
    key = fresh("row_key", docs.columns)
    out, added = _cleaned_by(rowkeys.told_apart(docs, key).docs, key, window, mer)
    return out.drop(key), added


def _cleaned_by(docs: DataFrame, key: str, window: int, mer: int) -> tuple[DataFrame, tuple[str, str, str]]:
    """``cleaned`` of rows whose documents are told apart by ``key``."""
    from pyspark.sql import types as T

    spark = docs.sparkSession
    ship(spark)
    known = docs.select(F.col(key).alias("doc_id"), "text").where("doc_id is not null and text is not null")
    hot, total, packed = _hot_minimisers(known, window, mer)
    hot = spark.sparkContext.broadcast(hot)
    buckets, parts = 1 + packed // BUCKET_BYTES, 1 + total // BUCKET_BYTES
    sent = known.mapInArrow(_send(window, mer, hot, buckets), "bucket long, kind int, block binary")
    met = _dealt(sent, buckets).sortWithinPartitions("bucket")
    runs = met.mapInArrow(_repeats(window, parts), "bucket long, kind int, block binary")
    names = docs.columns
    id_at, text_at = names.index(key), names.index("text")
    rows = docs.mapInArrow(_row_blocks(parts, id_at, text_at), "bucket long, kind int, block binary")
    together = _dealt(runs.unionAll(rows), parts).sortWithinPartitions("bucket", "kind")
    schema, added = T.StructType(list(docs.schema.fields)), []
    for field, kind in (("kept_text", T.StringType()), ("n_words", T.LongType()), ("n_removed", T.LongType())):
        added.append(fresh(field, names + added))
        schema = schema.add(added[-1], kind)
    return together.mapInArrow(_kept(id_at, text_at, list(range(len(names))), schema.names), schema), tuple(added)


def substring_dedup(docs: DataFrame, window: int = 20, mer: int = MER) -> DataFrame:
    """doc_id, text (kept words joined by one space), n_words and n_removed for each row; see ``cleaned``."""
    out, (text, words, removed) = cleaned(docs.select("doc_id", "text"), window, mer)
    return out.select("doc_id", F.col(text).alias("text"), F.col(words).alias("n_words"), F.col(removed).alias("n_removed"))
