"""Batch encoding of whole texts: token counts, and the token ids that packing needs.

Texts are split at safe boundaries: places that no token of the tokenizer can span, whatever stands around them, in ASCII or not.
Equal pieces of a batch are encoded once, and each Python worker keeps the pieces it has met, by a 64-bit hash of their bytes, up to
``KEPT`` of them with ``KEPT_IDS`` ids; long pieces (scripts without spaces) are encoded anew each time.  Batches for the library are
balanced by bytes, not by rows.  Texts that hold a special string are encoded whole.
"""

from __future__ import annotations

import itertools
import os
import unicodedata

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from thriftline.llm import textscan as ts
from thriftline.llm.arrowrun import annotate, columns_of, kept

#: Pieces and token ids that a worker remembers; beyond either it starts anew.  A longer piece is not remembered.
KEPT, KEPT_IDS, LONG = 1 << 20, 1 << 22, 256
#: Bytes of distinct pieces handed to the library at once.
CALL_BYTES = 1 << 18

_SPACE, _LETTER, _SIGN, _QUOTE, _ODD, _MARK, _WIDE_LETTER, _WIDE_SIGN = range(8)
#: The kind of each byte of ASCII: white space, letter, digit or sign, apostrophe, and what is left (controls).
_kinds = bytearray([_ODD] * 256)
for _b in range(0x21, 0x7F):
    _kinds[_b] = _SIGN
for _b in ts.SPACE_BYTES:
    _kinds[_b] = _SPACE
for _b in (*range(0x41, 0x5B), *range(0x61, 0x7B)):
    _kinds[_b] = _LETTER
_kinds[0x27] = _QUOTE
KINDS = bytes(_kinds)
_wide: np.ndarray | None = None


def _wide_kinds() -> np.ndarray:
    """The kind of each code point of two or three bytes, by categories that have been the same since Unicode 3.2.

    Characters that lower case or the normal form turns into something else than one letter are left out.
    """
    global _wide
    if _wide is None:
        out = np.full(1 << 16, _ODD, np.uint8)
        for c in range(0x80, 1 << 16):
            now, old = unicodedata.category(chr(c)), unicodedata.ucd_3_2_0.category(chr(c))
            if now == old and unicodedata.is_normalized("NFC", chr(c)) and len(chr(c).lower()) == 1:
                out[c] = {"L": _WIDE_LETTER, "P": _WIDE_SIGN, "S": _WIDE_SIGN, "M": _MARK, "N": _MARK}.get(now[0], _ODD)
        _wide = out
    return _wide


def _pairs(*pairs: tuple[int, int]) -> bytes:
    out = np.zeros(256, np.uint8)
    for a, b in pairs:
        out[a * 8 + b] = 1
    return out.tobytes()


#: Cuts between a character of the first kind and one of the second.  White space belongs to what follows; letters end before a
#: sign, and signs but the apostrophe (contractions) end before a letter.  No normal form joins characters over such a place.
CUTS = _pairs(
    *[(k, _SPACE) for k in (_LETTER, _SIGN, _QUOTE, _MARK, _WIDE_LETTER, _WIDE_SIGN)],
    *[(k, s) for k in (_LETTER, _WIDE_LETTER) for s in (_SIGN, _QUOTE)], (_WIDE_LETTER, _WIDE_SIGN),
    (_SIGN, _LETTER), (_SIGN, _WIDE_LETTER), (_WIDE_SIGN, _WIDE_LETTER),
)
_UPPER = ts.table(range(0x41, 0x5B))


def kinds_of(raw: np.ndarray) -> np.ndarray:
    """The kind of each byte; bytes of a character outside ASCII all have its kind."""
    kinds = np.frombuffer(raw.tobytes().translate(KINDS), np.uint8)
    lead = np.flatnonzero(raw >= 0xC0)
    if not len(lead):
        return kinds
    kinds, wide, size = kinds.copy(), _wide_kinds(), len(raw)
    for low, high, width in ((0xC0, 0xE0, 2), (0xE0, 0xF0, 3)):
        at = lead[(raw[lead] >= low) & (raw[lead] < high)]
        at = at[at + width <= size]
        point = (raw[at] & (0x1F if width == 2 else 0x0F)).astype(np.int64)
        for k in range(1, width):
            point = (point << 6) | (raw[at + k] & 0x3F)
        for k in range(width):
            kinds[at + k] = wide[point]
    return kinds


def encoder_for(path: str, drop_space: bool, with_ids: bool) -> Encoder:
    """The encoder of this Python worker, which the tasks it runs share with all pieces they have met."""
    key = (path, drop_space, with_ids)
    return kept(key, lambda: Encoder(*key))


def _room(held: np.ndarray, used: int, more: int) -> np.ndarray:
    """An array with places for ``more`` values after those used; at least half as large again if it must grow."""
    if used + more <= len(held):
        return held
    out = np.empty(max(used + more, len(held) * 3 // 2), held.dtype)
    out[:used] = held[:used]
    return out


class Encoder:
    """Token ids of text pieces by one tokenizer file, remembering pieces."""

    def __init__(self, path: str, drop_space: bool, with_ids: bool):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.special = [t.content.encode() for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.drop_space, self.with_ids = drop_space, with_ids
        self.forget()

    def forget(self) -> None:
        # Runs of keys in order with the number of each piece, the longest first, each at least twice as long as the next.
        self.runs: list[tuple[np.ndarray, np.ndarray]] = []
        self.sizes, self.places, self.ids = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint32)
        self.count = self.total = 0

    def folded(self, raw: np.ndarray) -> np.ndarray:
        """A-Z in lower case where the tokenizer does that anyway: not before a byte outside ASCII, which may be a combining mark."""
        if not self.drop_space or not len(raw):
            return raw
        upper = ts.translated(raw, _UPPER).copy()
        upper[:-1] &= (raw[1:] < 0x80).view(np.uint8)
        return raw + (upper << 5)

    def whole(self, texts: list[str]) -> list[list[int]]:
        return [e.ids for e in self.tokenizer.encode_batch(texts, add_special_tokens=False)]

    def cut(self, raw: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Starts and ends of the pieces of a block, the number of the first piece of each row, and whether a piece follows white space and ends without."""
        n = len(raw)
        kinds = kinds_of(raw)
        pairs = (kinds[:-1] << 3) + kinds[1:]
        flags = np.zeros(n + 1, np.uint8)
        if n:
            flags[1:n] = np.frombuffer(pairs.tobytes().translate(CUTS), np.uint8)
            flags[1:n] &= (raw[1:] & 0xC0) != 0x80
            flags[offs] = 1
        edges = np.flatnonzero(flags)
        starts, ends = edges[:-1], edges[1:]
        first = np.searchsorted(starts, offs)
        first[-1] = len(starts)
        if not n:
            return starts, ends, first, np.zeros(0, bool)
        spaced = kinds[starts] == _SPACE
        if self.drop_space:
            return starts + spaced, ends, first, np.ones(len(starts), bool)
        return starts, ends, first, spaced & (kinds[ends - 1] != _SPACE) & (kinds[ends - 1] != _ODD)

    def look_up(self, raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, chains: np.ndarray) -> np.ndarray:
        """The number of each piece, after encoding the new ones; numbers hold until the next call."""
        if self.count > KEPT or self.total > KEPT_IDS:
            self.forget()
        keys, where, inverse = np.unique(ts.span_hashes(raw, starts, ends), return_index=True, return_inverse=True)
        at = np.full(len(keys), -1, np.int64)
        for known, number in self.runs:
            place = np.minimum(np.searchsorted(known, keys), len(known) - 1)
            at = np.where((at < 0) & (known[place] == keys), number[place], at)
        new = np.flatnonzero(at < 0)
        if len(new):
            a, b = starts[where[new]], ends[where[new]]
            long = b - a > LONG
            new = np.concatenate((new[~long], new[long]))
            n, short = self.count, len(new) - int(long.sum())
            at[new] = n + np.arange(len(new))
            self._learn(raw, starts[where[new]], ends[where[new]], chains[where[new]], short)
            if short:
                self._remember(keys[new[:short]], n + np.arange(short))
        return at[inverse]

    def _remember(self, keys: np.ndarray, numbers: np.ndarray) -> None:
        self.runs.append((keys, numbers))
        while len(self.runs) > 1 and len(self.runs[-2][0]) < 2 * len(self.runs[-1][0]):
            (a, x), (b, y) = self.runs.pop(), self.runs.pop()
            keys, numbers = np.concatenate((b, a)), np.concatenate((y, x))
            order = np.argsort(keys, kind="stable")
            self.runs.append((keys[order], numbers[order]))

    def _learn(self, raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, chains: np.ndarray, short: int) -> None:
        """Encodes pieces; only the first ``short`` of them count as remembered, the others hold until the next call."""
        sizes = np.zeros(len(starts), np.int64)
        found: list[tuple[np.ndarray, np.ndarray]] = []
        for those, encode in ((np.flatnonzero(chains), self._chained), (np.flatnonzero(~chains), self._listed)):
            if not len(those):
                continue
            cuts = np.searchsorted(np.cumsum((ends - starts)[those]), np.arange(0, int((ends - starts)[those].sum()) + CALL_BYTES, CALL_BYTES))
            cuts = np.unique(np.concatenate((cuts, [0, len(those)])))
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                own = those[a:b]
                sizes[own], ids = encode(raw, starts[own], ends[own])
                if self.with_ids:
                    found.append((own, ids))
        n = self.count
        self.sizes = _room(self.sizes, n, len(sizes))
        self.sizes[n : n + len(sizes)] = sizes
        self.count = n + short
        if self.with_ids:
            places = self.total + np.cumsum(sizes) - sizes
            self.places = _room(self.places, n, len(sizes))
            self.places[n : n + len(sizes)] = places
            self.ids = _room(self.ids, self.total, int(sizes.sum()))
            for own, ids in found:
                self.ids[ts.ranges(places[own], sizes[own])] = ids
            self.total += int(sizes[:short].sum())

    def _chained(self, raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Sizes and ids of pieces that may stand one after another in one text: the library works on it at once and names the place of each token."""
        lengths, gap = ends - starts, int(self.drop_space)
        text = np.full(int(lengths.sum()) + gap * len(starts), 0x20, np.uint8)
        target = np.cumsum(lengths + gap) - (lengths + gap)
        text[ts.ranges(target, lengths)] = raw[ts.ranges(starts, lengths)]
        heads = np.concatenate(([0], np.cumsum((text & 0xC0) != 0x80)))[target]
        found = self.tokenizer.encode(text.tobytes().decode(), add_special_tokens=False)
        first = np.fromiter((a for a, _ in found.offsets), np.int64, len(found))
        sizes = np.bincount(np.searchsorted(heads, first, side="right") - 1, minlength=len(starts))
        return sizes, np.array(found.ids, np.uint32) if self.with_ids else np.zeros(0, np.uint32)

    def _listed(self, raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The same of pieces that must stand alone."""
        found = self.tokenizer.encode_batch([raw[s:e].tobytes().decode() for s, e in zip(starts.tolist(), ends.tolist(), strict=True)], add_special_tokens=False)
        sizes = np.fromiter(map(len, found), np.int64, len(found))
        return sizes, np.array(list(itertools.chain.from_iterable(e.ids for e in found)), np.uint32) if self.with_ids else np.zeros(0, np.uint32)

    def counts(self, texts: pa.Array) -> np.ndarray:
        """The number of tokens of each text; null texts are empty."""
        raw, offs, _ = ts.text_buffers(texts)
        out = np.zeros(len(offs) - 1, np.int64)
        for i, j in ts.blocks(offs, 2 << 20):
            own = offs[i : j + 1] - offs[i]
            body = raw[offs[i] : offs[j]]
            if not len(body):
                continue
            starts, ends, first, chains = self.cut(body, own)
            at = self.look_up(self.folded(body), starts, ends, chains)
            sizes = np.concatenate(([0], np.cumsum(self.sizes[at])))
            out[i:j] = sizes[first[1:]] - sizes[first[:-1]]
            for r in self.odd(body, own):
                out[i + r] = len(self.whole([body[own[r] : own[r + 1]].tobytes().decode()])[0])
        return out

    def rows(self, texts: pa.Array):
        """The token ids of each text: row numbers i..j, flat ids, and where each row begins in them."""
        raw, offs, _ = ts.text_buffers(texts)
        for i, j in ts.blocks(offs, 2 << 20):
            own = offs[i : j + 1] - offs[i]
            body = raw[offs[i] : offs[j]]
            if not len(body):
                yield i, j, np.zeros(0, np.uint32), np.zeros(j - i + 1, np.int64)
                continue
            starts, ends, first, chains = self.cut(body, own)
            at = self.look_up(self.folded(body), starts, ends, chains)
            sizes = self.sizes[at]
            flat = self.ids[ts.ranges(self.places[at], sizes)]
            begin = np.concatenate(([0], np.cumsum(sizes)))[first]
            if odd := self.odd(body, own):
                parts = [flat[a:b] for a, b in zip(begin[:-1], begin[1:], strict=True)]
                for r in odd:
                    parts[r] = np.array(self.whole([body[own[r] : own[r + 1]].tobytes().decode()])[0], np.uint32)
                flat, begin = np.concatenate(parts), np.concatenate(([0], np.cumsum([len(p) for p in parts])))
            yield i, j, flat, begin

    def odd(self, body: np.ndarray, offs: np.ndarray) -> list[int]:
        """Rows that hold a special string."""
        text = body.tobytes()
        if not any(s in text for s in self.special):
            return []
        return [r for r in range(len(offs) - 1) if any(s in text[offs[r] : offs[r + 1]] for s in self.special)]


def token_counts(docs: DataFrame, path: str, limit: int = 512, drop_space: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_tokens and over_limit for each row of ``docs`` (doc_id, text), by the tokenizer file at ``path``.

    ``drop_space`` is for tokenizers that drop white space and lower-case.  Null and empty texts have no bytes and no tokens; repeated rows and
    null doc_ids are rows like others.  No rows in, no rows out.
    """

    def make():
        encoder = encoder_for(path, drop_space, with_ids=False)

        def work(texts: pa.Array):
            return [pa.array(encoder.counts(texts))]

        return work

    sized = columns_of(docs, "doc_id", "text").withColumn("n_bytes", F.coalesce(F.octet_length("text").cast("long"), F.lit(0).cast("long")))
    out = annotate(sized, make, [("n_tokens", "long")], keep_text=False)
    return out.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
