"""Toxicity by FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Features are the distinct words, word pairs, one-word skip pairs and word beginnings (so that
inflected forms share a feature) of a text, hashed into 2^BITS slots. Training follows the
follow-the-regularised-leader proximal rule with a learning rate per coordinate; its L1 term leaves few weights that are not zero, and those are broadcast (at most
2^BITS pairs, whatever the corpus). Training reads a bounded sample of labelled rows: the
max_train rows with the smallest hash of their id.

Defined results: null text is empty text, scored by the bias alone; labels come from rows whose
crc32(doc_id) mod folds is not 0; several labels of a document count as toxic if any is; null labels
are ignored; without any training row every score is 0; repeated rows are scored each; an empty table
gives an empty result; further columns, also one named toxic, are ignored; texts of any length are read
whole, in slices of bounded size.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifloom.llm import arrays
from motifloom.llm.common import ship, text_bytes

BITS = 18
MAX_TRAIN = 8_000
EPOCHS = 4
FOLDS = 5
#: Lengths of word beginnings, in bytes.
HEADS = (4, 5, 6, 7)
ALPHA, BETA, L1, L2 = 0.15, 1.0, 6.0, 0.05
BIAS = 0
_MASK = np.uint64((1 << BITS) - 1)


def features(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Slots (1 and up; 0 is the bias) of every n-gram of every text, and each one's text."""
    h, first, *heads = arrays.words(data, offsets, arrays.PUNCTUATION, prefixes=HEADS)
    owner = np.repeat(np.arange(len(first) - 1), np.diff(first))
    parts = [(h, owner), arrays.pairs(h, first, 1), arrays.pairs(h, first, 2)]
    parts += [(x[x != 0], owner[x != 0]) for x in heads]
    slots = np.concatenate([(p[0] & _MASK).astype(np.int32) for p in parts])
    slots[slots == BIAS] = 1
    return slots, np.concatenate([p[1] for p in parts])


def fit(rows: list[np.ndarray], labels: np.ndarray, epochs: int = EPOCHS) -> tuple[np.ndarray, np.ndarray]:
    """FTRL-proximal over sparse binary rows: indices and values of the weights that are not zero."""
    z, n = np.zeros(1 << BITS), np.zeros(1 << BITS)
    l1 = np.full(1 << BITS, L1)
    l1[BIAS] = 0.0

    def weights(at):
        zi = z[at]
        w = (np.sign(zi) * l1[at] - zi) / ((BETA + np.sqrt(n[at])) / ALPHA + L2)
        return np.where(np.abs(zi) <= l1[at], 0.0, w)

    for epoch in range(epochs):
        for i in np.random.default_rng(epoch).permutation(len(rows)):
            at = rows[i]
            w = weights(at)
            g = 1.0 / (1.0 + np.exp(-np.clip(w.sum(), -35, 35))) - labels[i]
            sigma = (np.sqrt(n[at] + g * g) - np.sqrt(n[at])) / ALPHA
            z[at] += g - sigma * w
            n[at] += g * g
    w = weights(np.arange(1 << BITS))
    kept = np.flatnonzero(w)
    return kept, w[kept]


def _rows_of(batch: pa.RecordBatch, column: str) -> Iterator[np.ndarray]:
    for piece in arrays.slices(batch, column):
        data, offsets = arrays.raw(piece.column(piece.schema.get_field_index(column)))
        slots, owner = features(data, offsets)
        slots = slots[np.argsort(owner, kind="stable")]
        cut = np.zeros(len(offsets), np.int64)
        np.cumsum(np.bincount(owner, minlength=len(offsets) - 1), out=cut[1:])
        for a, b in zip(cut, cut[1:]):
            yield np.concatenate([np.array([BIAS], np.int32), np.unique(slots[a:b])])


def _train(epochs: int):
    def run(batches):
        rows, labels = [], []
        for batch in batches:
            rows += list(_rows_of(batch, "body"))
            labels += batch.column(batch.schema.get_field_index("toxic")).to_pylist()
        if rows:
            at, w = fit(rows, np.array(labels, float), epochs)
            yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(w, pa.float64())], ["slot", "weight"])

    return run


def held_out(folds: int = FOLDS) -> Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % folds == 0, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, max_train: int = MAX_TRAIN, epochs: int = EPOCHS, folds: int = FOLDS) -> tuple[np.ndarray, np.ndarray]:
    """Weights from a bounded sample of labelled rows; one task fits, the driver gets non-zero weights."""
    ship(docs.sparkSession)
    allowed = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(folds))
    allowed = allowed.groupBy("doc_id").agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    sample = allowed.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_train)
    rows = docs.select("doc_id", text_bytes().alias("body")).join(F.broadcast(sample), "doc_id")  # at most max_train ids
    rows = rows.repartitionByRange(1, F.xxhash64("doc_id"), "doc_id").sortWithinPartitions(F.xxhash64("doc_id"), "doc_id", "body")
    got = rows.select("body", "toxic").mapInArrow(_train(epochs), "slot int, weight double").toPandas()
    return got["slot"].to_numpy(np.int32), got["weight"].to_numpy(float)


def _score(shared):
    def run(batches):
        at, values = shared.value
        dense = np.zeros(1 << BITS, np.float32)
        dense[at] = values
        bias = float(dense[BIAS])
        known = dense != 0
        known[BIAS] = False
        for batch in batches:
            scores = []
            for piece in arrays.slices(batch, "body"):
                data, offsets = arrays.raw(piece.column(piece.schema.get_field_index("body")))
                slots, owner = features(data, offsets)
                hit = known[slots]
                key = np.unique(owner[hit].astype(np.int64) << np.int64(BITS) | slots[hit])
                sums = np.bincount(key >> np.int64(BITS), dense[key & np.int64((1 << BITS) - 1)], len(offsets) - 1)
                scores.append(1.0 / (1.0 + np.exp(-np.clip(sums + bias, -35, 35))) if len(at) else np.zeros(len(offsets) - 1))
            rest = [c for i, c in enumerate(batch.columns) if batch.schema.names[i] != "body"]
            names = [c for c in batch.schema.names if c != "body"]
            yield pa.RecordBatch.from_arrays([*rest, pa.array(np.concatenate(scores) if scores else [], pa.float64())], [*names, "score"])

    return run


def score(docs: DataFrame, weights: tuple[np.ndarray, np.ndarray], folds: int = FOLDS) -> DataFrame:
    """doc_id, held_out, score, predicted for every row of docs."""
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(weights)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(folds).alias("held_out"), text_bytes().alias("body"))
    out = rows.mapInArrow(_score(shared), "doc_id long, held_out boolean, score double")
    return out.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def keep_clean(docs: DataFrame, weights: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """The rows of docs that score below one half, with all their columns."""
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(weights)
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), text_bytes().alias("body"))
    kind = docs.schema.simpleString()
    return rows.mapInArrow(_score(shared), f"row {kind}, score double").where("score < 0.5").select("row.*")
