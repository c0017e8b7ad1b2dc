"""Quality grades by ordinal cumulative-link regression on hashed text.

Grades are ordered: 0 toxic, 1 of low quality, 2 of good quality.  P(grade > k) = logistic(score - threshold_k), with one shared weight
vector over hashed text features for all k and ordered thresholds.  Features are presences: hashed lower-cased words, hashed
runs of signs, and bands of the share of repeated words.  Weights are fitted with a sparse penalty, so that words without information
have none.  The model gives the expected grade and the tail probabilities for selection.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from thriftline.llm import textscan as ts
from thriftline.llm.arrowrun import annotate, columns_of
from thriftline.shipping import ship

BUCKETS = 1 << 17
#: At most so many labelled rows, chosen by a hash of their ids, with at most so many bytes of text (but one row at least) fit the
#: model: the documented bounds of the sample.
SAMPLE_ROWS, SAMPLE_BYTES = 8000, 256 << 20
GRADES = 3
_SIGNS = ts.table(b for b in range(0x21, 0x80) if not (0x30 <= b < 0x3A or 0x41 <= b < 0x5B or 0x61 <= b < 0x7B))


def features(texts: pa.Array):
    """For blocks of rows i..j: distinct feature numbers of each row, one row after another, and where each begins."""
    raw, offs, _ = ts.text_buffers(texts)
    for i, j in ts.blocks(offs):
        words = ts.Spans(raw, offs[i : j + 1], ts.ALNUM, ts.FOLD_ASCII)
        signs = ts.Spans(raw, offs[i : j + 1], _SIGNS)
        hashed = words.hashes() % np.uint64(BUCKETS - 64)
        marks = ts.mix(signs.hashes() + np.uint64(1)) % np.uint64(BUCKETS - 64)
        rows = np.concatenate((words.rows, signs.rows)).astype(np.uint64)
        pairs = np.unique((rows << np.uint64(20)) | np.concatenate((hashed, marks)))
        row, number = (pairs >> np.uint64(20)).astype(np.int64), (pairs & np.uint64((1 << 20) - 1)).astype(np.int64)
        distinct = np.bincount((np.unique((words.rows.astype(np.uint64) << np.uint64(20)) | hashed) >> np.uint64(20)).astype(np.int64), minlength=j - i)
        # Ten bands of the share of distinct words, for texts of at least 20 words.
        band = BUCKETS - 64 + np.where(words.counts >= 20, np.minimum(9, 10 * distinct // np.maximum(words.counts, 1)), 10)
        row, number = np.concatenate((row, np.arange(j - i))), np.concatenate((number, band))
        order = np.argsort(row, kind="stable")
        row, number = row[order], number[order]
        yield i, j, number, np.searchsorted(row, np.arange(j - i + 1))


class Model:
    """Shared weights and ordered thresholds."""

    def __init__(self, weights: np.ndarray, thresholds: np.ndarray):
        self.weights, self.thresholds = weights, thresholds

    def tails(self, number: np.ndarray, begin: np.ndarray) -> np.ndarray:
        """P(grade > k) for each row and k."""
        sums = np.concatenate(([0.0], np.cumsum(self.weights[number])))
        score = sums[begin[1:]] - sums[begin[:-1]]
        return 1 / (1 + np.exp(-np.clip(score[:, None] - self.thresholds[None, :], -40, 40)))


def fit(number: np.ndarray, begin: np.ndarray, grade: np.ndarray, rounds: int = 300, penalty: float = 4e-4, least: int = 4) -> Model:
    """Minimises the negative log-likelihood, grades weighted by the root of their rarity, with an absolute-value penalty on the weights.

    Each weight steps by its gradient over the running root mean square of it, is shrunk towards 0 by the penalty, and carries momentum;
    thresholds take clipped gradient steps and are put in order after each.
    """
    n, levels = len(grade), GRADES - 1
    row = np.repeat(np.arange(n), np.diff(begin))
    often = np.bincount(number, minlength=BUCKETS) >= least
    use = often[number]
    row, column = row[use], np.cumsum(often)[number[use]] - 1
    width = int(often.sum())
    above = (grade[:, None] > np.arange(levels)[None, :]).astype(float)
    share = np.clip(above.mean(axis=0), 1e-3, 1 - 1e-3)
    start = np.log((1 - share) / share)
    cuts = np.maximum.accumulate(start + 1e-3 * np.arange(levels))
    w = np.zeros(width)
    z, momentum, step = w.copy(), 1.0, 0.5
    classes = np.eye(GRADES)[grade]
    weight = n / (GRADES * np.maximum(classes.sum(axis=0), 1))
    own = weight[grade] ** 0.5
    squares = np.zeros(width) + 1e-8
    for _ in range(rounds):
        score = np.bincount(row, z[column], minlength=n)
        tail = 1 / (1 + np.exp(-np.clip(score[:, None] - cuts[None, :], -40, 40)))
        full = np.concatenate((np.ones((n, 1)), tail, np.zeros((n, 1))), axis=1)
        p = np.maximum((full[:, :-1] - full[:, 1:])[np.arange(n), grade], 1e-9)
        slope = full * (1 - full)
        # d(-log p)/d(score) and by threshold
        g = -(slope[np.arange(n), grade] - slope[np.arange(n), grade + 1]) / p * own
        gradient = np.bincount(column, g[row], minlength=width) / n
        squares = 0.9 * squares + 0.1 * gradient**2
        rate = step / (np.sqrt(squares) + 2e-3) * 0.1
        new = z - rate * gradient
        new = np.sign(new) * np.maximum(np.abs(new) - rate * penalty, 0)
        follow = (1 + np.sqrt(1 + 4 * momentum**2)) / 2
        z = new + min(0.8, (momentum - 1) / follow) * (new - w)
        w, momentum = new, follow
        for k in range(levels):
            low = np.where(grade == k, 1.0, 0.0) - np.where(grade == k + 1, 1.0, 0.0)
            gc = -(low * slope[:, k + 1] / p * own).mean()
            cuts[k] -= 0.5 * np.clip(gc * 10, -0.3, 0.3)
        cuts = np.maximum.accumulate(cuts)
        cuts += 1e-6 * np.arange(levels)
    weights = np.zeros(BUCKETS)
    weights[often] = w
    return Model(weights, cuts)


def graded(labels: DataFrame) -> DataFrame:
    """(doc_id, grade) of labelled ids: 0 if toxic, else 1 or 2 by quality.  Nulls in a rating leave the row out; repeated ids get the lowest."""
    rated = columns_of(labels, "doc_id", "quality", "toxic").where("doc_id is not null and quality is not null and toxic is not null")
    return rated.groupBy("doc_id").agg(F.min(F.when(F.col("toxic") > 0, 0).when(F.col("quality") > 0, 2).otherwise(1)).alias("grade"))


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS, sample_bytes: int = SAMPLE_BYTES) -> Model | None:
    """Fits on at most ``sample_rows`` labelled documents with the smallest id hashes, and ``sample_bytes`` of their text; None without labelled texts."""
    ship(docs.sparkSession)
    chosen = graded(labels).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)
    found = columns_of(docs, "doc_id", "text").where("text is not null").join(F.broadcast(chosen), "doc_id")
    # Rows that repeat a labelled doc_id count against both bounds.
    order = [F.xxhash64("doc_id"), F.col("doc_id"), F.xxhash64("text")]
    sizes = found.select("doc_id", F.xxhash64("text").alias("digest"), F.octet_length("text").alias("size")).orderBy(F.xxhash64("doc_id"), "doc_id", "digest").limit(sample_rows).toPandas()
    room = max(1, int((sizes["size"].cumsum() <= sample_bytes).sum()))
    texts = found.select("doc_id", "grade", "text")
    if len(sizes) == sample_rows or room < len(sizes):
        texts = texts.orderBy(*order).limit(room)

    def work_of():
        def work(column: pa.Array):
            out = []
            for _, _, number, begin in features(column):
                out.extend(number[a:b].astype(np.int32).tobytes() for a, b in zip(begin[:-1], begin[1:], strict=True))
            return [pa.array(out, pa.binary())]

        return work

    rows = annotate(texts, work_of, [("found", "binary")], keep_text=False).toPandas().sort_values("doc_id", kind="stable")
    if not len(rows):
        return None
    parts = [np.frombuffer(b, np.int32) for b in rows["found"]]
    begin = np.concatenate(([0], np.cumsum([len(p) for p in parts])))
    return fit(np.concatenate(parts).astype(np.int64), begin, rows["grade"].to_numpy(np.int64))


def grade_documents(docs: DataFrame, labels: DataFrame, least: float = 0.5, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id, expected_grade, p_acceptable (grade above 0), p_good (grade above 1) and kept (p_good >= least) for each row.

    Null, empty and odd texts are graded by the features they have.  Without labelled texts every document has null grades and is
    kept.  Repeated rows are graded alike; extra columns are left.  No rows in, no rows out.
    """
    model = train(docs, labels, sample_rows)
    rows = columns_of(docs, "doc_id", "text")
    if model is None:
        none = F.lit(None).cast("double")
        return rows.select("doc_id", none.alias("expected_grade"), none.alias("p_acceptable"), none.alias("p_good"), F.lit(True).alias("kept"))
    held = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        def work(column: pa.Array):
            tails = [held.value.tails(number, begin) for _, _, number, begin in features(column)]
            tail = np.concatenate(tails) if tails else np.zeros((0, GRADES - 1))
            return [pa.array(tail.sum(axis=1)), pa.array(tail[:, 0]), pa.array(tail[:, 1])]

        return work

    out = annotate(rows, make, [("expected_grade", "double"), ("p_acceptable", "double"), ("p_good", "double")], keep_text=False)
    return out.withColumn("kept", F.col("p_good") >= least)
