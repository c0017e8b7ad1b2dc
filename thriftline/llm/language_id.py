"""Language identification with hyperdimensional profiles.

Each letter symbol has a random vector of +1 and -1.  The vector of an n-gram binds (multiplies) the vectors of its letters, each
permuted (rolled) once for every letter after it.  A profile bundles (adds) the vectors of all n-grams of a text; a language
prototype bundles those of all its training texts.  A document goes to the prototype with the largest cosine.

As bundling is linear, the dot product of a document with a prototype is the sum over its n-grams of that n-gram's dot product
with the prototype.  These numbers depend on the n-gram only, so they are worked out once for all ``SYMBOLS ** 3`` n-grams (one
MB a language) and whole texts are scored by table look-ups; the result is that of the bundled vectors.  The training texts
are read as n-gram counts by language, a table bounded by n-grams times languages, and bundled where these meet.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Iterable, Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from thriftline.llm import textscan as ts
from thriftline.llm.arrowrun import annotate, fresh, give_back
from thriftline.shipping import ship

BITS, DIMENSIONS, SEED = 6, 1024, 11
SYMBOLS = 1 << BITS
#: Languages in one table; more are scored in further tables.
AT_ONCE = 32
_symbol: np.ndarray | None = None


def symbols() -> np.ndarray:
    """The symbol of each code point: 0 for what is no letter, 1 to 26 for a to z in any case, the others share the rest."""
    global _symbol
    if _symbol is None:
        out = np.zeros(0x110000, np.uint8)
        for c in range(0x110000):
            if unicodedata.category(chr(c))[0] == "L":
                low = ord(chr(c).lower()[0])
                out[c] = low - 96 if 97 <= low <= 122 else 27 + (low * 2654435761 >> 8) % (SYMBOLS - 27)
        _symbol = out
    return _symbol


def _grams(texts: pa.Array):
    """Blocks of rows i..j with the n-gram numbers of all of them, the start of each row, and whether it has a letter."""
    raw, offs, _ = ts.text_buffers(texts)
    table = symbols()
    for i, j in ts.blocks(offs):
        body = raw[offs[i] : offs[j]]
        heads = np.concatenate(([0], np.cumsum((body & 0xC0) != 0x80)))
        at = heads[offs[i : j + 1] - offs[i]]
        points = np.frombuffer(body.tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32)
        # Each row is framed by two non-letters, so no n-gram joins two rows.
        framed = np.zeros(len(points) + 2 * (j - i) + 2, np.uint8)
        place = np.arange(len(points)) + 1 + 2 * np.repeat(np.arange(j - i), np.diff(at))
        framed[place] = table[points]
        begin = at + 2 * np.arange(j - i + 1)
        wide = framed.astype(np.int32)
        gram = (wide[:-2] << 2 * BITS) | (wide[1:-1] << BITS) | wide[2:]
        # Without those that have two non-letters side by side.
        use = ~(((wide[:-2] == 0) & (wide[1:-1] == 0)) | ((wide[1:-1] == 0) & (wide[2:] == 0)))
        kept = np.flatnonzero(use)
        yield i, j, gram[kept], np.searchsorted(kept, begin)


class Profile(NamedTuple):
    """A language: the bundle of its training n-grams, how many they are, and the sum of squares of how often each n-gram stands."""

    bundle: np.ndarray
    total: int
    squares: float


def _letters(seed: int) -> np.ndarray:
    return np.random.Generator(np.random.PCG64(seed)).choice(np.array([-1, 1], np.int8), (SYMBOLS, DIMENSIONS))


def _bound(seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The letters' vectors as the first, second and third of an n-gram."""
    letters = _letters(seed).astype(np.float32)
    return np.roll(letters, 2, axis=1), np.roll(letters, 1, axis=1), letters


def bundle(counts: np.ndarray, seed: int = SEED) -> Profile:
    """The profile of n-gram counts (one for each n-gram number)."""
    first, second, third = _bound(seed)
    cube = counts.reshape(SYMBOLS, SYMBOLS, SYMBOLS).astype(np.float64)
    out = np.zeros(DIMENSIONS)
    for a in np.flatnonzero(cube.any(axis=(1, 2))):
        out += first[a] * ((cube[a] @ third) * second).sum(axis=0)
    return Profile(out, int(counts.sum()), float((counts.astype(np.float64) ** 2).sum()))


def profiles(training: DataFrame) -> dict[str, Profile]:
    """The profile of each language over all training rows (lang, text).

    Tasks count n-grams; the counts of a language, a number for each n-gram at most, meet in one task, which bundles them.  One vector a language
    comes to the driver.
    """
    size = SYMBOLS**3

    def run(batches):
        sums: dict[str, np.ndarray] = {}

        def flush():
            for lang, n in sums.items():
                at = np.flatnonzero(n)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at), pa.array(n[at])], names=["lang", "gram", "n"])
            sums.clear()

        for batch in batches:
            langs = batch.column(0).to_pylist()
            for i, j, gram, begin in _grams(batch.column(1)):
                for lang in sorted(set(langs[i:j])):
                    mine = np.concatenate([gram[begin[r] : begin[r + 1]] for r in range(j - i) if langs[i + r] == lang])
                    if lang not in sums:
                        if len(sums) >= AT_ONCE:
                            yield from flush()
                        sums[lang] = np.zeros(size, np.int64)
                    sums[lang] += np.bincount(mine, minlength=size)
        yield from flush()
        give_back()

    def bundled(batches):
        lang, held = None, np.zeros(size, np.int64)

        def done():
            own = bundle(held)
            return pa.RecordBatch.from_arrays([pa.array([lang], pa.string()), pa.array([own.bundle.tobytes()]), pa.array([own.total]), pa.array([own.squares])], names=["lang", "bundle", "total", "squares"])

        for batch in batches:
            names = batch.column(0).to_pylist()
            gram, n = batch.column(1).to_numpy(), batch.column(2).to_numpy()
            cuts = [0, *(i for i in range(1, len(names)) if names[i] != names[i - 1]), len(names)]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if a < b and names[a] != lang:
                    if lang is not None:
                        yield done()
                    lang, held = names[a], np.zeros(size, np.int64)
                held[gram[a:b]] += n[a:b]
        if lang is not None:
            yield done()

    partial = training.mapInArrow(run, "lang string, gram long, n long")
    # Counts of a task go to its language's task, in order; there is no more than one for each n-gram and task.
    summed = partial.groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    tasks = max(int(training.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    met = summed.repartition(tasks, "lang").sortWithinPartitions("lang")
    rows = met.mapInArrow(bundled, "lang string, bundle binary, total long, squares double").collect()
    return {r["lang"]: Profile(np.frombuffer(r["bundle"]), r["total"], r["squares"]) for r in sorted(rows, key=lambda r: r["lang"])}


def score_tables(learned: dict[str, Profile | np.ndarray], seed: int = SEED) -> Iterator[tuple[list[str], np.ndarray]]:
    """For blocks of languages, one after another, the dot product of each n-gram's vector with each prototype of length 1.

    A language is a profile, or its n-gram counts.
    """
    first, second, third = _bound(seed)
    langs = list(learned)
    for at in range(0, len(langs), AT_ONCE):
        own = langs[at : at + AT_ONCE]
        table = np.empty((SYMBOLS, SYMBOLS, SYMBOLS, len(own)), np.float32)
        for n, lang in enumerate(own):
            known = learned[lang] if isinstance(learned[lang], Profile) else bundle(learned[lang], seed)
            prototype = (known.bundle / max(np.linalg.norm(known.bundle), 1e-30)).astype(np.float32)
            for a in range(SYMBOLS):
                table[a, :, :, n] = (second * (first[a] * prototype)) @ third.T
        yield own, table.reshape(SYMBOLS**3, len(own))


#: Likeness under which the different n-grams of a text are counted.
WEAK = 0.5


def _predict(langs: list[str], held, own: list[float] | None = None):
    def make():
        table = held.value

        def work(texts: pa.Array):
            best = np.full(len(texts), -1, np.int64)
            top, total = np.full(len(texts), -np.inf), np.zeros(len(texts))
            count, different = np.zeros(len(texts), np.int64), np.zeros(len(texts), np.int64)
            for i, j, gram, begin in _grams(texts):
                full = np.flatnonzero(begin[1:] > begin[:-1])
                if not len(full):
                    continue
                sums = np.add.reduceat(table[gram], begin[full], axis=0, dtype=np.float64)
                best[i + full] = sums.argmax(axis=1)
                top[i + full] = sums.max(axis=1)
                total[i + full] = np.maximum(sums, 0).sum(axis=1)
                count[i + full] = different[i + full] = np.diff(begin)[full]
                if own is not None:
                    # Repeats tell nothing new; they are only looked for where it can matter.
                    weak = sums.max(axis=1) < WEAK * count[i + full] * np.array(own)[sums.argmax(axis=1)]
                    for k in full[weak].tolist():
                        different[i + k] = len(np.unique(gram[begin[k] : begin[k + 1]]))
            names = [langs[b] if b >= 0 else None for b in best.tolist()]
            return [pa.array(names, pa.string()), pa.array(top), pa.array(total), pa.array(count), pa.array(different)]

        return work

    return make


def _best(docs: DataFrame, tables: Iterable[tuple[list[str], np.ndarray]], own: dict[str, float] | None = None):
    """``docs`` with one set of columns for each table; the best language with its sum; all positive sums; n-grams, all and different; the added names."""
    out, added = docs, []
    for n, (langs, table) in enumerate(tables):
        held = docs.sparkSession.sparkContext.broadcast(np.ascontiguousarray(table, np.float32))
        names = [fresh(f"{k}_{n}", out.columns) for k in ("lang", "top", "total", "grams", "different")]
        out = annotate(out, _predict(langs, held, own and [own[k] for k in langs]), list(zip(names, ("string", "double", "double", "long", "long"), strict=True)))
        added.append(names)
    best = F.array_max(F.array(*[F.struct(F.col(t).alias("top"), F.lit(-n).alias("n"), F.col(k).alias("lang")) for n, (k, t, *_) in enumerate(added)]))
    total = sum((F.col(s) for _, _, s, _, _ in added), F.lit(0.0))
    different = F.array_min(F.array(*[F.col(names[4]) for names in added]))
    return out, best, total, (F.col(added[0][3]), different), [n for names in added for n in names]


def identified(docs: DataFrame, known: dict[str, Profile]) -> tuple[DataFrame, tuple[str, str]]:
    """All columns of ``docs`` and two more: language and score; and the names of the two.

    The score is the best prototype's share of all positive cosines: 1 if no other is alike.  A null text or one without a
    letter is ``und`` with score 0; so is every text if no language was learned.  Ties go to the first language in order.
    """
    lang, score = fresh("lang_pred", docs.columns), fresh("score", docs.columns)
    if not known:
        return docs.withColumns({lang: F.lit("und"), score: F.lit(0.0)}), (lang, score)
    out, best, total, _, added = _best(docs, score_tables(known))
    found = best["lang"].isNotNull()
    out = out.withColumns({lang: F.coalesce(best["lang"], F.lit("und")), score: F.when(found & (total > 0), F.greatest(best["top"], F.lit(0.0)) / total).otherwise(F.lit(0.0))})
    return out.drop(*added), (lang, score)


def likened(docs: DataFrame, known: dict[str, Profile]) -> tuple[DataFrame, tuple[str, str, str]]:
    """All columns of ``docs`` and three more: language, likeness and number of n-grams (different ones if it is under ``WEAK``); and their names.

    The likeness is the mean product of a text's n-grams with the prototype of its best language, over the mean of that language's own
    text: about 1 for its texts, about 0 for n-grams it does not have.  Other languages do not enter it.
    ``und`` as in ``identified``, with likeness and number 0.
    """
    lang, alike, grams = (fresh(k, docs.columns) for k in ("lang_pred", "alike", "n_grams"))
    if not known:
        return docs.withColumns({lang: F.lit("und"), alike: F.lit(0.0), grams: F.lit(0).cast("long")}), (lang, alike, grams)
    # Vectors of different n-grams are nearly orthogonal, so a prototype is as long as this before it is made a unit.
    own = {k: float(np.sqrt(DIMENSIONS * p.squares)) / max(p.total, 1) for k, p in known.items()}
    out, best, _, (n, different), added = _best(docs, score_tables(known), own)
    typical = F.create_map(*[F.lit(x) for pair in own.items() for x in pair])
    found = best["lang"].isNotNull()
    out = out.withColumns({lang: F.coalesce(best["lang"], F.lit("und")), alike: F.when(found, best["top"] / n / typical[best["lang"]]).otherwise(F.lit(0.0)), grams: different})
    return out.drop(*added), (lang, alike, grams)


def learned(docs: DataFrame, folds: int = 5) -> dict[str, Profile]:
    """Profiles of the languages of all rows whose crc32(doc_id) mod ``folds`` is not 0; rows without lang, text or doc_id are left."""
    ship(docs.sparkSession)
    fold = F.crc32(F.col("doc_id").cast("string").cast("binary")) % folds
    return profiles(docs.where(fold != 0).where("lang is not null and text is not null").select("lang", "text"))


def identify_languages(docs: DataFrame, folds: int = 5) -> DataFrame:
    """doc_id, held_out, lang_pred and score for each row of ``docs`` (doc_id, text, lang), learned from the other folds.

    Languages, sources and ids are no input of a prediction.  Repeated rows count as often as they stand in training; null doc_ids
    are neither training nor held out (held_out is false).  See ``identified`` for texts without letters.
    """
    fold = F.crc32(F.col("doc_id").cast("string").cast("binary")) % folds
    out, (lang, score) = identified(docs.select("doc_id", "text"), learned(docs, folds))
    return out.select("doc_id", F.coalesce(fold == 0, F.lit(False)).alias("held_out"), F.col(lang).alias("lang_pred"), F.col(score).alias("score"))
