"""Toxicity: FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

The model is fitted once on a bounded sample of labelled rows, in one task; what comes back is a list of the
coordinates that the L1 penalty left, which is broadcast. The margin at which a text counts as toxic is chosen on rows that
a model of the other folds scores, and the bias is moved so that this margin scores the threshold. Every whole text is then
scored in Arrow batches.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from .common import slim, text_batches, text_values

#: Bits of the feature space; how many labelled rows the fit takes at most, those with the least hash of their id; how
#: many coordinates their rows may have together (4 bytes each; the rows from there on are left out).
BITS, SAMPLE, COORDINATES = 20, 12_000, 40_000_000
#: FTRL-proximal: learning rate, its offset, L1 strength for each square root of a row (as the noise of summed
#: gradients grows), L2 strength, passes over the sample.
ALPHA, BETA, L1, L2, EPOCHS = 1.0, 1.0, 0.2, 1.0, 4
#: Bytes of a word that make its stem.
STEM = 5
#: Score from which a text counts as toxic; folds of the sample that place it; toxic texts that one clean text weighs there.
THRESHOLD, FOLDS, CLEAN = 0.7, 3, 5.0

#: A-Z to a-z; all other ASCII but digits and letters to spaces; bytes of other characters stay.
_FOLD = bytes((b + 32 if 65 <= b <= 90 else b) if b > 127 or chr(b).isalnum() else 32 for b in range(256))
_MIX = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9))


def features(text: str | None, bits: int = BITS, stem: int = STEM) -> np.ndarray:
    """The different hashed coordinates of a text's words, their stems (the first bytes of longer words), pairs of neighbours
    and pairs with one word between, ascending."""
    words = (text or "").encode().translate(_FOLD).split()
    h = np.fromiter(map(xxh64_intdigest, words), np.uint64, len(words))
    stems = {w[:stem] for w in words if len(w) > stem}
    parts = [h * _MIX[0], np.fromiter((xxh64_intdigest(w, 1) for w in stems), np.uint64, len(stems))]
    if len(h) > 1:
        parts.append((h[:-1] * _MIX[1] + h[1:]) * _MIX[0])
    if len(h) > 2:
        parts.append((h[:-2] * _MIX[2] + h[2:]) * _MIX[0])
    return np.unique((np.concatenate(parts) >> np.uint64(64 - bits)).astype(np.int32))


@dataclass
class Weights:
    """Sparse weights: their coordinates in ascending order, their values, and the bias. known: a row was learnt from."""

    at: np.ndarray
    value: np.ndarray
    bias: float
    known: bool
    bits: int = BITS

    def dense(self) -> np.ndarray:
        w = np.zeros(1 << self.bits)
        w[self.at] = self.value
        return w

    def margin(self, dense: np.ndarray, row: np.ndarray) -> float:
        """The log odds of a row of coordinates."""
        found = dense[row]
        return self.bias + float(found[found != 0].sum())

    def score(self, dense: np.ndarray, text: str | None) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.margin(dense, features(text, self.bits)), -35, 35)))) if self.known else 0.0


def ftrl(rows: list[np.ndarray], labels: list[int], bits: int = BITS, alpha=ALPHA, beta=BETA, l1=L1, l2=L2, epochs=EPOCHS) -> Weights:
    """Fits on rows of different coordinates in the order given. The last coordinate is the bias, free of L1."""
    size = 1 << bits
    z, n = np.zeros(size + 1), np.zeros(size + 1)
    strength = np.full(size + 1, l1 * np.sqrt(len(rows)))
    strength[size] = 0
    last = np.array([size], np.int32)
    rows = list(rows)

    def weight(i):
        zi = z[i]
        return np.where(np.abs(zi) <= strength[i], 0.0, -(zi - np.sign(zi) * strength[i]) / ((beta + np.sqrt(n[i])) / alpha + l2))

    for _ in range(epochs):
        for row, y in zip(rows, labels, strict=True):
            i = np.concatenate([row, last])
            w = weight(i)
            g = 1 / (1 + np.exp(-np.clip(w.sum(), -35, 35))) - y
            sigma = (np.sqrt(n[i] + g * g) - np.sqrt(n[i])) / alpha
            z[i] += g - sigma * w
            n[i] += g * g
    w = weight(np.arange(size + 1))
    at = np.flatnonzero(w[:size])
    return Weights(at, w[at], float(w[size]), bool(rows), bits)


def cut_margin(margins: np.ndarray, labels: np.ndarray, clean: float = CLEAN) -> float | None:
    """The margin from which on rows count as toxic: where the share of toxic rows caught, less ``clean`` times the share of
    clean rows caught, is greatest; in the middle of the gap there. None if no margin is better than catching nothing."""
    order = np.argsort(-margins, kind="stable")
    z, y = margins[order], labels[order].astype(bool)
    if not y.any() or y.all():
        return None
    gain = np.cumsum(y) / y.sum() - clean * np.cumsum(~y) / (~y).sum()
    ends = np.append(z[1:] < z[:-1], True)  # equal margins go together
    gain = np.where(ends, gain, -np.inf)
    k = int(gain.argmax())
    if gain[k] <= 0:
        return None
    return float(z[k] + z[k + 1]) / 2 if k + 1 < len(z) else float(z[k])


def calibrated(rows: list[np.ndarray], labels: list[int], bits: int = BITS, threshold: float = THRESHOLD, folds: int = FOLDS) -> Weights:
    """Weights fitted on all rows, the bias moved so that ``threshold`` falls at the margin that the folds choose."""
    y, at = np.array(labels, int), np.arange(len(rows)) % folds
    margins = np.zeros(len(rows))
    for k in range(folds if len(rows) >= 10 * folds else 0):
        w = ftrl([r for r, f in zip(rows, at, strict=True) if f != k], y[at != k].tolist(), bits)
        dense = w.dense()
        for i in np.flatnonzero(at == k):
            margins[i] = w.margin(dense, rows[i])
    whole = ftrl(rows, labels, bits)
    cut = cut_margin(margins, y) if len(rows) >= 10 * folds else None
    if cut is not None:
        whole.bias += float(np.log(threshold / (1 - threshold))) - cut
    return whole


def fit(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "toxic", sample: int = SAMPLE, bits: int = BITS, coordinates: int = COORDINATES) -> Weights:
    """Learns from the ``sample`` labelled rows with the least hash of the key (ties by key and label), as far as their
    coordinates come to ``coordinates`` together.

    Rows with a null key or label are not learnt from. A key that is labelled twice counts twice. The sample's
    labels are at most ``sample`` rows, so they are broadcast; its texts meet in one task, which holds their coordinates.
    """
    chosen = (
        labels.select(F.col(key).alias("_k"), F.col(label).cast("int").alias("_y"))
        .where("_k is not null and _y is not null")
        .orderBy(F.xxhash64("_k"), "_k", "_y")
        .limit(sample)
    )
    given = docs.select(F.col(key).alias("_k"), F.col(text).alias("_t")).join(F.broadcast(chosen), "_k")

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, ys, left = [], [], coordinates
        for b in text_batches(batches, "_t"):
            for t, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                row = features(t, bits)
                if left >= len(row):
                    rows.append(row)
                    ys.append(y)
                left -= len(row)
        w = calibrated(rows, ys, bits)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(w.at, -1 if w.known else -2), pa.int64()), pa.array(np.append(w.value, w.bias))], names=["at", "value"])
        del rows
        slim()

    ordered = given.repartition(1).sortWithinPartitions(F.xxhash64("_k"), "_k", "_y", F.xxhash64("_t")).select("_t", "_y")
    got = ordered.mapInArrow(learn, "at long, value double").toPandas().sort_values("at")
    head = got["at"].to_numpy() < 0
    return Weights(got["at"].to_numpy()[~head], got["value"].to_numpy()[~head], float(got["value"][head].sum()), bool((got["at"] == -1).any()), bits)


def score(docs: DataFrame, weights: Weights, text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """Adds score (0 to 1) and predicted (1 from ``threshold`` on) to every row; columns with these names are replaced.

    A null text counts as empty and has the score of the bias alone. If nothing was learnt every score is 0. Only texts go
    to Python, and only scores come back.
    """
    added = docs.drop("predicted").withColumn("score", _score(docs, weights, text))
    return added.withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def _score(docs: DataFrame, weights: Weights, text: str) -> Column:
    sent = docs.sparkSession.sparkContext.broadcast(weights)  # at most 2^bits coordinates

    def each(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        w = sent.value
        dense = w.dense()
        yield from text_values(texts, lambda ts: pa.array([w.score(dense, t) for t in ts.to_pylist()], pa.float64()))

    return F.arrow_udf(each, "double")(F.col(text))


def without_toxic(docs: DataFrame, weights: Weights, text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` that score below ``threshold``, with their columns as they are, whatever their names."""
    own = "_toxicity" + "_" * max(map(len, docs.columns))
    return docs.withColumn(own, _score(docs, weights, text)).where(F.col(own) < threshold).drop(own)


def held_out(key: str = "doc_id"):
    """True for a third of the keys, whose labels no model sees."""
    return F.coalesce(F.crc32(F.col(key).cast("string")) % 3 == 1, F.lit(False))
