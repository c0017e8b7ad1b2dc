"""Columns computed from whole texts in Arrow batches, beside the columns of the input."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from thriftline.shipping import ship

#: Rows of a batch are cut into pieces of about this many bytes before a function sees them.
PIECE_BYTES = 8 << 20
#: What this Python worker holds for later tasks, and whether the task at hand has asked for it.
_kept: dict = {}
_asked = False


def kept(key, make: Callable):
    """What ``make()`` gives, held for the tasks that follow until one of them ends without asking for it."""
    global _asked
    if key not in _kept:
        _kept.clear()
        _kept[key] = make()
    _asked = True
    return _kept[key]


def give_back() -> None:
    """Returns freed memory to the system, at the end of a task: Python workers live on and share an executor's memory.

    What the task has not asked for is let go: workers outlive the stage that needed it.
    """
    global _asked
    if not _asked:
        _kept.clear()
    _asked = False
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def fresh(name: str, taken: Iterable[str]) -> str:
    """The name, with underscores before it while a column of the input has it (in any case)."""
    lower = {x.lower() for x in taken}
    while name.lower() in lower:
        name = "_" + name
    return name


def pieces(batch: pa.RecordBatch, column: int, target: int = PIECE_BYTES) -> Iterator[pa.RecordBatch]:
    """Slices of a batch of about ``target`` bytes of one text column; one row at least."""
    lengths = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False))
    at, done = 0, 0
    while at < batch.num_rows:
        to = max(at + 1, int(np.searchsorted(lengths, done + target, side="right")))
        yield batch.slice(at, to - at)
        done, at = int(lengths[to - 1]), to


def annotate(df: DataFrame, make: Callable[[], Callable], fields: list[tuple[str, str]], text: str = "text", keep_text: bool = True, inputs: tuple[str, ...] = ()) -> DataFrame:
    """Adds ``fields`` (name, DDL type) to every row.

    ``make()`` is called once a task and returns a function from (text array, *input arrays) to a list of arrays, one for each
    field.  Columns of the input keep their names; a field whose name is taken gets underscores before it (see ``fresh``).
    """
    ship(df.sparkSession)
    names = df.columns
    kept = [c for c in names if keep_text or c != text]
    out = T.StructType([df.schema[c] for c in kept])
    for name, kind in fields:
        out = out.add(fresh(name, kept), T._parse_datatype_string(kind) if isinstance(kind, str) else kind)
    at, others, places = names.index(text), [names.index(c) for c in inputs], [names.index(c) for c in kept]
    labels = [f.name for f in out.fields]

    def run(batches):
        work = make()
        for batch in batches:
            for piece in pieces(batch, at):
                made = work(piece.column(at), *[piece.column(i) for i in others])
                yield pa.RecordBatch.from_arrays([piece.column(i) for i in places] + list(made), names=labels)
        give_back()

    return df.mapInArrow(run, out)


def columns_of(df: DataFrame, *names: str) -> DataFrame:
    """Only these columns; extra ones, whatever their names, are left."""
    return df.select(*[F.col(f"`{n}`") for n in names])
