"""Positive-unlabelled quality classifier.

A linear model over character-class statistics of the whole text is fitted by minimising the non-negative unbiased risk
``prior * E_pos[l(f)] + max(0, E_unl[l(-f)] - prior * E_pos[l(-f)])`` with the logistic loss: trusted positives against
unlabelled text, under a class prior estimated from the share of positives among the labels. Negative labels enter only
that share. Learning reads at most ``max_positive`` + ``max_unlabelled`` rows (documented parameters, chosen by a hash of
the key); scoring reads every text from end to end.

Rows whose crc32 of the key's text is divisible by ``folds`` are held out of everything that is learned; so are rows
without a key.

Defined cases: null and empty texts get the score of an empty text; repeated labels of a key count as positive only if
all are; without positives every score is 0.5; repeated rows score alike; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from phraseloom.llm import byte_words as bw
from phraseloom.llm.common import release_memory, tidy

FOLDS = 5
THRESHOLD = 0.3
MAX_POSITIVE = 10_000
MAX_UNLABELLED = 20_000
SLICE = 1 << 19
ROWS = 1024

#: Byte classes by members; a byte of none of them is of class 0 (controls), from 0x80 on of the last.
CLASSES = ("abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789", " \t", "\n\r", ".,;:", "!?", "'\"`", "#*$%&|<>", "@^~_=+\\/", "()[]{}", "-")
_CLASS = np.zeros(256, np.int64)
for _k, _members in enumerate(CLASSES):
    _CLASS[[ord(c) for c in _members]] = _k + 1
N_CLASSES = len(CLASSES) + 2
_CLASS[0x80:] = N_CLASSES - 1
N_WORD_FEATURES = 9
N_FEATURES = N_CLASSES + N_CLASSES**2 + N_WORD_FEATURES


def features(column: pa.Array) -> np.ndarray:
    """One row of statistics per text."""
    raw, offsets = bw.buffers(column)
    out = np.zeros((len(offsets) - 1, N_FEATURES), np.float32)
    for first, last in bw.slices(offsets, SLICE):
        low, high = offsets[first], offsets[last]
        rows, sizes = last - first, np.diff(offsets[first : last + 1])
        part = raw[low:high]
        kind = _CLASS[part]
        row = np.repeat(np.arange(rows), sizes)
        part_out = out[first:last]
        size = np.maximum(sizes, 1)[:, None]
        part_out[:, :N_CLASSES] = np.bincount(row * N_CLASSES + kind, minlength=rows * N_CLASSES).reshape(rows, -1) / size
        if len(part) > 1:
            pair = kind[:-1] * N_CLASSES + kind[1:]
            inside = row[:-1] == row[1:]
            counted = np.bincount(row[:-1][inside] * N_CLASSES**2 + pair[inside], minlength=rows * N_CLASSES**2).reshape(rows, -1)
            part_out[:, N_CLASSES : N_CLASSES + N_CLASSES**2] = np.sqrt(counted / size)
        hashes, at = bw.words(part, offsets[first : last + 1] - low, bw.NOT_SPACE)
        lines = np.bincount(row[part == 10], minlength=rows) + 1
        words = np.diff(at)
        w = np.maximum(words, 1)
        distinct = np.diff(bw.distinct_sorted(hashes, at)[1])
        triples = np.diff(bw.shingles(hashes, at, 3)[1])
        repeats = np.concatenate([[0], np.cumsum(np.append(False, hashes[1:] == hashes[:-1]) if len(hashes) else [])]).astype(np.int64)
        part_out[:, -N_WORD_FEATURES:] = np.stack([np.log1p(sizes) / 10, np.log1p(words) / 10, sizes / w / 10, distinct / w, triples / w, lines / w, np.log1p(sizes / lines) / 10, sizes == 0, (repeats[at[1:]] - repeats[at[:-1]]) / w], axis=1)
    return out


@dataclass
class Model:
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    bias: float
    prior: float

    def scores(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.scale, -6, 6) @ self.weights + self.bias
        return 1 / (1 + np.exp(-np.clip(z.astype(np.float64), -40, 40)))


def fit(positive: np.ndarray, unlabelled: np.ndarray, prior: float, steps: int = 500, rate: float = 0.03, decay: float = 1e-3) -> Model:
    """Adam on the non-negative risk; where the corrected negative part falls below zero its gradient is turned round.

    Both arrays of float32 rows are standardised in place, so that no second copy is held.
    """
    if not len(positive) or not len(unlabelled):
        return Model(np.zeros(N_FEATURES), np.ones(N_FEATURES), np.zeros(N_FEATURES), 0.0, 0.5)
    mean = unlabelled.mean(axis=0)
    scale = np.sqrt(np.array([np.square(unlabelled[:, c] - mean[c]).mean() for c in range(unlabelled.shape[1])], np.float32)) + np.float32(1e-3)
    p, u = positive, unlabelled
    for x in (p, u):
        x -= mean
        x /= scale
        np.clip(x, -6, 6, out=x)
    weights, bias = np.zeros(p.shape[1], np.float32), 0.0
    m, v = np.zeros(p.shape[1] + 1), np.zeros(p.shape[1] + 1)
    logistic = lambda z: 1 / (1 + np.exp(-np.clip(z, -40, 40)))
    for step in range(1, steps + 1):
        fp, fu = p @ weights + np.float32(bias), u @ weights + np.float32(bias)
        negative = np.logaddexp(0, fu).mean() - prior * np.logaddexp(0, fp).mean()
        up_p, up_u = logistic(fp) / np.float32(len(p)), logistic(fu) / np.float32(len(u))
        as_negative = np.append(u.T @ up_u - prior * (p.T @ up_p), up_u.sum() - prior * up_p.sum())
        down = (logistic(fp) - 1) / np.float32(len(p))
        as_positive = prior * np.append(p.T @ down, down.sum())
        grad = as_positive + as_negative if negative >= 0 else -as_negative
        grad[:-1] += decay * weights
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
        move = rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
        weights, bias = weights - move[:-1].astype(np.float32), bias - move[-1]
    return Model(mean, scale, weights, float(bias), prior)


def held_out(key: str = "doc_id", folds: int = FOLDS) -> Column:
    return F.coalesce(F.crc32(F.col(key).cast("string")) % folds == 0, F.lit(True))


def train(docs: DataFrame, labels: DataFrame, max_positive: int = MAX_POSITIVE, max_unlabelled: int = MAX_UNLABELLED, key: str = "doc_id", text: str = "text", label: str = "quality") -> Model:
    known = labels.where(~held_out(key)).where(F.col(label).isNotNull()).groupBy(key).agg(F.min(label).alias("_label"))
    shares = known.agg(F.count(F.lit(1)), F.count_if(F.col("_label") == 1)).first()
    prior = min(0.97, max(0.03, (shares[1] + 1) / (shares[0] + 2)))
    by_hash = lambda seed: F.xxhash64(F.lit(seed), F.col("id"))
    positive = known.where("_label = 1").select(F.col(key).cast("long").alias("id")).orderBy(by_hash("positive"), "id").limit(max_positive)
    rest = docs.where(~held_out(key)).select(F.col(key).cast("long").alias("id")).orderBy(by_hash("unlabelled"), "id").limit(max_unlabelled)
    chosen = positive.select("id", F.lit(1).alias("_p")).unionByName(rest.select("id", F.lit(0).alias("_p"))).groupBy("id").agg(F.max("_p").alias("_p"), F.min("_p").alias("_u"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tidy(batches):
            x = features(batch.column(1))
            yield pa.record_batch([*(batch.column(c) for c in (0, 2, 3, 4)), pa.FixedSizeListArray.from_arrays(pa.array(x.reshape(-1)), N_FEATURES).cast(pa.list_(pa.float32()))], names=["id", "_p", "_u", "h", "x"])

    texts = docs.select(F.col(key).cast("long").alias("id"), F.col(text).alias("_text")).join(F.broadcast(chosen), "id")  # at most max_positive + max_unlabelled keys
    rows = texts.select("id", "_text", "_p", "_u", F.xxhash64("_text").alias("h")).mapInArrow(run, "id long, _p int, _u int, h long, x array<float>")
    one = rows.groupBy("id").agg(F.min(F.struct("h", "_p", "_u", "x")).alias("r")).select("id", "r._p", "r._u", "r.x")  # of repeated keys the same one each time
    got = one.toArrow()
    order = np.argsort(got.column("id").to_numpy())
    x = np.concatenate([c.flatten().to_numpy() for c in got.column("x").chunks] or [np.zeros(0, np.float32)]).reshape(-1, N_FEATURES)
    known, free = got.column("_p").to_numpy()[order] == 1, got.column("_u").to_numpy()[order] == 0
    del got
    p, u = x[order[known]], x[order[free]]
    del x
    model = fit(p, u, prior)
    del p, u
    release_memory()
    return model


def score(docs: DataFrame, model: Model, threshold: float = THRESHOLD, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``(doc_id, held_out, score, predicted)`` for every row."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tidy(batches):
            got = sent.value.scores(features(batch.column(1)))
            yield pa.record_batch([batch.column(0), batch.column(2), pa.array(got), pa.array((got >= threshold).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    return docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text), held_out(key).alias("held_out")).mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def keep_accepted(docs: DataFrame, model: Model, threshold: float = THRESHOLD, text: str = "text") -> DataFrame:
    """The rows whose score reaches the threshold, all columns kept."""
    sent = docs.sparkSession.sparkContext.broadcast(model)
    place = docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tidy(batches):
            for low in range(0, batch.num_rows, ROWS):
                part = batch.slice(low, ROWS)
                yield part.filter(pa.array(sent.value.scores(features(part.column(place))) >= threshold))

    return docs.mapInArrow(run, docs.schema)
