"""Benchmark decontamination as a prefix-filtered containment join.

A benchmark item gives windows of ``window`` consecutive words (one window if it has fewer).  A window's shingles are ordered by
rarity in the whole corpus; a document that holds the window holds all its shingles, so for containment 1 the prefix that must be
joined is the single rarest shingle.  Document shingles are joined with these prefix tokens only; the token's offset in
the window fixes where the window would start (positional bound), the window's length must fit into the document from there
(length bound), and all words of the window are then compared.  Shingles are three words, or the whole window if shorter.

The benchmark is joined from memory in blocks of about ``BLOCK_BYTES`` of item text, whatever its size; each block is two passes over
the documents, one that counts its shingles and one that joins, without a shuffle of documents.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from thriftline.llm import textscan as ts
from thriftline.llm.arrowrun import annotate, columns_of, fresh, give_back
from thriftline.shipping import ship

WINDOW, SHINGLE = 10, 3
#: Item text held by a task at once; it is 5 to 10 times that in index arrays (8 bytes a word, about 21 a window).
BLOCK_BYTES = 16 << 20
_FILTER_BITS = 20


def _words(column: pa.Array):
    raw, offs, _ = ts.text_buffers(column)
    for i, j in ts.blocks(offs):
        spans = ts.Spans(raw, offs[i : j + 1], ts.ALNUM, ts.FOLD_ASCII)
        yield i, j, spans, spans.hashes()


class Windows:
    """The item windows of a block: all words of the items in one row, where each window begins in it, and how long it is."""

    def __init__(self, items: list[tuple[str, str]], window: int):
        self.items = sorted({k for k, _ in items})
        place = {k: n for n, k in enumerate(self.items)}
        hashes, counts = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
        for _, _, spans, h in _words(pa.array([t for _, t in items], pa.string())):
            hashes.append(h)
            counts.append(spans.counts)
        self.words, counts = np.concatenate(hashes), np.concatenate(counts)
        size = np.minimum(window, counts)
        each = np.where(size > 0, counts - size + 1, 0)
        first = np.cumsum(counts) - counts
        self.start = ts.ranges(first, each).astype(np.int32)
        self.length = np.repeat(size, each).astype(np.int16)
        self.owner = np.repeat(np.array([place[k] for k, _ in items], np.int32), each)
        self.window = window

    def shingles(self):
        """For each length of windows: the width of its shingles, its windows by number, and for each offset their hashes."""
        for size in np.unique(self.length).tolist():
            rows, width = np.flatnonzero(self.length == size), min(SHINGLE, size)
            h = ts.window_hashes(self.words, width)
            yield width, rows, [h[self.start[rows] + offset] for offset in range(size - width + 1)]

    def tokens(self) -> dict[int, np.ndarray]:
        """The distinct shingles by width, in order."""
        out: dict[int, np.ndarray] = {}
        for width, _, hashes in self.shingles():
            out[width] = np.unique(np.concatenate([out.get(width, np.zeros(0, np.uint64)), *hashes]))
        return out

    def prefixes(self, tokens: dict[int, np.ndarray], counts: dict[int, np.ndarray]) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """By width: the rarest shingle of each window (the smaller hash, then the first, on a tie), in order, with its window and offset.

        Windows with a shingle that no document has go.
        """
        out: dict[int, list] = {}
        for width, rows, hashes in self.shingles():
            best = np.zeros(len(rows), np.int8)
            token = hashes[0]
            least = counts[width][np.searchsorted(tokens[width], token)]
            for offset, h in enumerate(hashes[1:], 1):
                n = counts[width][np.searchsorted(tokens[width], h)]
                rarer = (n < least) | ((n == least) & (h < token))
                best, token, least = np.where(rarer, np.int8(offset), best), np.where(rarer, h, token), np.where(rarer, n, least)
            seen = least > 0
            out.setdefault(width, []).append((token[seen], rows[seen].astype(np.int32), best[seen]))
        merged = {w: tuple(np.concatenate(c) for c in zip(*parts, strict=True)) for w, parts in out.items()}
        return {w: tuple(c[np.argsort(t, kind="stable")] for c in (t, n, o)) for w, (t, n, o) in merged.items() if len(t)}


def _filter(tokens: np.ndarray) -> np.ndarray:
    bits = np.zeros(1 << _FILTER_BITS, bool)
    bits[(tokens & np.uint64((1 << _FILTER_BITS) - 1)).astype(np.int64)] = True
    return bits


def _found(h: np.ndarray, tokens: np.ndarray, bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions whose hash is one of the sorted tokens, and the first place of it there."""
    at = np.flatnonzero(bits[(h & np.uint64((1 << _FILTER_BITS) - 1)).astype(np.int64)])
    place = np.searchsorted(tokens, h[at])
    same = tokens[np.minimum(place, len(tokens) - 1)] == h[at]
    return at[same], place[same]


def _within(spans: ts.Spans, at: np.ndarray, width: int) -> np.ndarray:
    """Whether the words from each position on are of one row."""
    return at + width <= spans.first[1:][spans.rows[at]]


def shingle_counts(docs: DataFrame, tokens: dict[int, np.ndarray]) -> dict[int, np.ndarray]:
    """How often each of the given shingles occurs in all documents; as many numbers as there are tokens."""
    out = {w: np.zeros(len(t), np.int64) for w, t in tokens.items()}
    if not any(len(t) for t in tokens.values()):
        return out
    shared = docs.sparkSession.sparkContext.broadcast(tokens)

    def run(batches):
        held = {w: (t, _filter(t)) for w, t in shared.value.items() if len(t)}
        sums = {w: np.zeros(len(t), np.int64) for w, (t, _) in held.items()}
        for batch in batches:
            for _, _, spans, h in _words(batch.column(0)):
                for w, (t, bits) in held.items():
                    at, place = _found(ts.window_hashes(h, w), t, bits)
                    keep = _within(spans, at, w)
                    sums[w] += np.bincount(place[keep], minlength=len(t))
        for w in held:
            seen = np.flatnonzero(sums[w])
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(seen), w)), pa.array(seen), pa.array(sums[w][seen])], names=["width", "token", "n"])
        give_back()

    partial = columns_of(docs, "text").mapInArrow(run, "width long, token long, n long")
    rows = partial.groupBy("width", "token").agg(F.sum("n").alias("n")).toArrow()
    width, token, n = (rows.column(k).to_numpy() for k in ("width", "token", "n"))
    for w in out:
        out[w][token[width == w]] = n[width == w]
    return out


def _marker(windows: Windows, prefixes: dict):
    """Returns the function from texts (and earlier cover and items) to the new cover bits, items and word counts."""
    held = {w: (t, n, o, np.unique(t)) for w, (t, n, o) in prefixes.items()}
    held = {w: (t, n, o, _filter(u), np.searchsorted(t, u, "left"), np.searchsorted(t, u, "right"), u) for w, (t, n, o, u) in held.items()}

    def hits(spans: ts.Spans, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Starts and window numbers of all occurrences."""
        starts, numbers = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for w, (_, number, offset, bits, lo, hi, distinct) in held.items():
            at, place = _found(ts.window_hashes(h, w), distinct, bits)
            # Each position with each window of its token.
            times = (hi - lo)[place]
            which = ts.ranges(lo[place], times)
            at = np.repeat(at, times)
            n, start = number[which], at - offset[which]
            row = spans.rows[at]
            fits = (start >= spans.first[row]) & (start + windows.length[n] <= spans.first[row + 1])
            n, start = n[fits], start[fits]
            for k in range(windows.window):
                needed = windows.length[n] > k
                same = ~needed | (h[np.minimum(start + k, len(h) - 1)] == windows.words[np.minimum(windows.start[n] + k, len(windows.words) - 1)])
                n, start = n[same], start[same]
            starts.append(start)
            numbers.append(n)
        return np.concatenate(starts), np.concatenate(numbers)

    def work(texts: pa.Array, cover: pa.Array | None = None, items: pa.Array | None = None):
        covers, lists, counts = [], [], []
        for i, j, spans, h in _words(texts):
            start, n = hits(spans, h)
            edge = np.zeros(len(h) + 1, np.int64)
            np.add.at(edge, start, 1)
            np.add.at(edge, start + windows.length[n], -1)
            hit = np.cumsum(edge[:-1]) > 0
            row = spans.rows[start]
            pairs = np.unique(np.stack((row, windows.owner[n])), axis=1) if len(n) else np.zeros((2, 0), np.int64)
            ends = np.searchsorted(pairs[0], np.arange(j - i + 1))
            for r in range(j - i):
                bits = hit[spans.first[r] : spans.first[r + 1]]
                named = {windows.items[k] for k in pairs[1, ends[r] : ends[r + 1]].tolist()}
                if cover is not None:
                    old = np.unpackbits(np.frombuffer(cover[i + r].as_py(), np.uint8), count=len(bits)).astype(bool)
                    bits, named = bits | old, named | set(items[i + r].as_py())
                covers.append(np.packbits(bits).tobytes())
                lists.append(sorted(named))
                counts.append(len(bits))
        return [pa.array(covers, pa.binary()), pa.array(lists, pa.list_(pa.string())), pa.array(counts, pa.int64())]

    return work


def marked(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> tuple[DataFrame, tuple[str, str, str]]:
    """All columns of ``docs`` and three more: cover bits (binary), items (array of item_ids as strings) and word count.

    Returns the names of the three too, which get underscores before them if ``docs`` has such columns.
    """
    ship(docs.sparkSession)
    items = columns_of(benchmark, "item_id", "text").where("text is not null and item_id is not null")
    total = items.agg(F.sum(F.octet_length("text")).alias("b")).first()["b"] or 0
    parts = 1 + total // block_bytes
    names: tuple = ()
    out = docs
    for part in range(parts):
        rows = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == part).collect()
        windows = Windows([(str(r["item_id"]), r["text"]) for r in rows], window)
        tokens = windows.tokens()
        held = docs.sparkSession.sparkContext.broadcast((windows, windows.prefixes(tokens, shingle_counts(docs, tokens))))
        fields = ("cover", "items", "n_words")
        kinds = ("binary", "array<string>", "long")
        before = out.columns
        added = [(fresh(f"{f}_{part}", before), k) for f, k in zip(fields, kinds, strict=True)]
        out = annotate(out, lambda held=held: _marker(*held.value), added, inputs=names[:2])
        if names:
            out = out.drop(*names)
        names = tuple(n for n, _ in added)
    return out, names


def decontaminate(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items, items_sha256 and contaminated for each row of ``docs`` (doc_id, text).

    Words are runs of ASCII letters and digits and of all characters outside ASCII, with A-Z lower-cased.  Null and empty texts have no
    words and are clean.  Items without text, words or item_id are left out; equal items and repeated rows count as the distinct item_ids
    they have.  An empty benchmark leaves every document clean; no documents give no rows.
    """
    out, (cover, items, n_words) = marked(columns_of(docs, "doc_id", "text"), benchmark, window, block_bytes)
    out = annotate(out, _counted, [("n_hit", "long"), ("digest", "string")], inputs=(cover, items), keep_text=False)
    return out.select("doc_id", F.col(n_words).alias("n_words"), "n_hit", F.size(items).cast("long").alias("n_items"), F.col(items).alias("items"), F.col("digest").alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def _counted():
    def work(texts: pa.Array, cover: pa.Array, items: pa.Array):
        hits = [int(np.unpackbits(np.frombuffer(b, np.uint8)).sum()) for b in cover.to_pylist()]
        digests = [hashlib.sha256(",".join(x).encode()).hexdigest() for x in items.to_pylist()]
        return [pa.array(hits, pa.int64()), pa.array(digests, pa.string())]

    return work
