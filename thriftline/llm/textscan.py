"""Vectorised scanning of Arrow text columns: blocks of whole texts, spans of words, 64-bit span hashes.

Everything here works on the UTF-8 bytes of many texts at once and never on a prefix of a text.  A block is a run of
whole rows of about ``BLOCK_BYTES``; a longer text is a block of its own.  All separators used by the operators are ASCII
bytes, so cutting at them never splits a code point.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

BLOCK_BYTES = 1 << 20
_MULT = np.uint64(0x9E3779B97F4A7C15 | 1)
_INV = np.uint64(pow(int(_MULT), -1, 1 << 64))
_powers = np.ones(1, np.uint64)
_inverses = np.ones(1, np.uint64)


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the multiplier and of its inverse modulo 2**64, at least ``n`` of each."""
    global _powers, _inverses
    if len(_powers) < n:
        size = max(n, BLOCK_BYTES + 1)
        with np.errstate(over="ignore"):
            _powers = np.cumprod(np.concatenate(([np.uint64(1)], np.full(size, _MULT))))
            _inverses = np.cumprod(np.concatenate(([np.uint64(1)], np.full(size, _INV))))
    return _powers, _inverses


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and odd multiplications); a bijection."""
    with np.errstate(over="ignore"):
        x = x ^ (x >> np.uint64(31))
        x = x * np.uint64(0x7FB5D329728EA185)
        x ^= x >> np.uint64(27)
        x *= np.uint64(0x81DADEF4BC2DD44D)
        x ^= x >> np.uint64(33)
    return x


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The bytes of a string column, its n+1 offsets and a validity mask; null texts are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    valid = np.asarray(column.is_valid())
    if column.null_count:
        column = column.fill_null("")
    n, (_, offsets, data) = len(column), column.buffers()
    offs = np.frombuffer(offsets, np.int64, n + 1, column.offset * 8) if n else np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw, offs, valid


def blocks(offs: np.ndarray, target: int = BLOCK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of at most ``target`` bytes; a longer row stands alone."""
    n, i = len(offs) - 1, 0
    while i < n:
        j = int(np.searchsorted(offs, offs[i] + target, side="right")) - 1
        j = min(max(j, i + 1), n)
        yield i, j
        i = j


def translated(raw: np.ndarray, table: bytes) -> np.ndarray:
    """Each byte looked up in a table of 256."""
    return np.frombuffer(raw.tobytes().translate(table), np.uint8)


class Spans:
    """Words of a block: byte starts and ends, the row of each, and for each row its first word."""

    def __init__(self, raw: np.ndarray, offs: np.ndarray, is_word: bytes, fold: bytes | None = None):
        base = int(offs[0])
        self.raw = raw[base : int(offs[-1])]
        self.offs = offs - base
        if fold is not None:
            self.raw = translated(self.raw, fold)
        n = len(self.raw)
        inside = np.zeros(n + 2, np.uint8)
        inside[1:-1] = translated(self.raw, is_word)
        steps = np.flatnonzero(inside[1:] != inside[:-1])
        starts, ends = steps[0::2], steps[1::2]
        # A row border ends a word as a separator would.
        cuts = self.offs[1:-1]
        cuts = np.unique(cuts[(cuts > 0) & (cuts < n)])
        both = cuts[(inside[cuts] == 1) & (inside[cuts + 1] == 1)]
        if len(both):
            starts = np.sort(np.concatenate((starts, both)), kind="stable")
            ends = np.sort(np.concatenate((ends, both)), kind="stable")
        self.starts, self.ends = starts, ends
        self.first = np.searchsorted(starts, self.offs)
        self.first[-1] = len(starts)
        self.counts = np.diff(self.first)
        self.rows = np.repeat(np.arange(len(self.counts)), self.counts)

    def __len__(self) -> int:
        return len(self.starts)

    def hashes(self) -> np.ndarray:
        return span_hashes(self.raw, self.starts, self.ends)


def span_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each byte span, equal for equal bytes wherever they stand."""
    powers, inverses = _power_tables(len(raw) + 1)
    with np.errstate(over="ignore"):
        sums = np.empty(len(raw) + 1, np.uint64)
        sums[0] = 0
        np.add(raw, np.uint64(1), out=sums[1:])
        sums[1:] *= powers[: len(raw)]
        np.cumsum(sums[1:], out=sums[1:])
        out = (sums[ends] - sums[starts]) * inverses[starts]
        out += (ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
    return mix(out)


def window_hashes(words: np.ndarray, width: int, seed: int = 1) -> np.ndarray:
    """Hash of each ``width`` consecutive word hashes; len(words)-width+1 values, order matters."""
    n = len(words) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    with np.errstate(over="ignore"):
        out = np.full(n, np.uint64(seed))
        for i in range(width):
            out = (out ^ words[i : i + n]) * np.uint64(0xC2B2AE3D27D4EB4F) + np.uint64(0x165667B19E3779F9)
            out ^= out >> np.uint64(29)
    return mix(out)


def run_ids(first: np.ndarray, size: int) -> np.ndarray:
    """0,1,2,... within consecutive runs that start at ``first`` (the last entry is the end)."""
    counts = np.diff(first)
    return np.arange(size) - np.repeat(first[:-1], counts)


def ranges(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The concatenation of arange(start, start+length) over all pairs."""
    starts, lengths = np.asarray(starts, np.int64), np.asarray(lengths, np.int64)
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, np.int64)
    shift = np.cumsum(lengths) - lengths
    return np.arange(total, dtype=np.int64) + np.repeat(starts - shift, lengths)


def table(allowed) -> bytes:
    """A byte table of 0 and 1, for translated()."""
    out = np.zeros(256, np.uint8)
    out[list(allowed)] = 1
    return out.tobytes()


#: Words between white space: every byte but space and 0x09 to 0x0D.
SPACE_BYTES = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)
NON_SPACE = table(b for b in range(256) if b not in SPACE_BYTES)
#: Words of letters, digits and every byte outside ASCII.
ALNUM = table([*range(0x30, 0x3A), *range(0x41, 0x5B), *range(0x61, 0x7B), *range(0x80, 0x100)])
FOLD_ASCII = bytes(b + 0x20 if 0x41 <= b < 0x5B else b for b in range(256))
