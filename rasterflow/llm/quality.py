"""Quality classifier: an SVM on n-gram indicators scaled by class log-count ratios.

Features are the distinct byte n-grams of a whole text and n-grams of its stream of repeated words, hashed into
2**BITS places.  Each indicator is scaled by the
log ratio of its smoothed frequencies in the two classes, rows are brought to unit length, and a linear hinge-loss
model is fitted by dual coordinate descent; its weights are drawn towards their mean size.  Labelled rows that were
set aside turn margins into probabilities.

Training takes at most SAMPLE labelled rows (those with the smallest hash of doc_id); scoring covers every row.
Labels of one document that disagree count as the smaller.  Null labels are left out.  Without rows of both classes
the score is the smoothed share of label 1.  Null and empty texts get the score of a text without n-grams.  Repeated
rows get equal scores; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from operator import eq
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import crc_of_id, raw_texts, settled, slices

BITS = 18
SIZES = (3, 5)
#: Bound on the labelled rows that the model is fitted on.
SAMPLE = 4000


def grams(text: bytes) -> np.ndarray:
    """Hashed places of the distinct n-grams, ascending."""
    b = np.frombuffer(text, np.uint8).astype(np.uint64)
    found = []
    for n in SIZES:
        if len(b) >= n:
            code = np.zeros(len(b) - n + 1, np.uint64)
            for k in range(n):
                code = code << np.uint64(8) | b[k : len(b) - n + 1 + k]
            found.append(((code + np.uint64(n)) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - BITS)).astype(np.int32))
    found.append(repeats(text))
    x = np.sort(np.concatenate(found))
    return x[np.concatenate(([True], x[1:] != x[:-1]))] if len(x) else x


def repeats(text: bytes) -> np.ndarray:
    """Places of n-grams over the stream that says of each word whether it was the last or the second last word too, and of the share of distinct words."""
    words = text.split()
    found = []
    for lag in (1, 2):
        same = bytes(map(eq, words, words[lag:]))
        found += [f"repeat {lag} {n}" for n in (2, 4, 8) if b"\1" * n in same]
    if len(words) >= 16:
        found.append(f"distinct {10 * len(set(words)) // len(words)} {len(words).bit_length()}")
    return np.array([crc32(x.encode()) >> 32 - BITS for x in found], np.int32)


@dataclass
class Model:
    """ratio: log-count ratios; weights: of the scaled indicators; slope and shift turn margins into probabilities."""

    ratio: np.ndarray
    weights: np.ndarray
    bias: float
    slope: float
    shift: float

    def margin(self, x: np.ndarray) -> float:
        r = self.ratio[x]
        norm = float(np.sqrt(np.dot(r, r)))
        return (float(np.dot(self.weights[x], r)) / norm if norm else 0.0) + self.bias

    def score(self, x: np.ndarray) -> float:
        z = self.slope * self.margin(x) + self.shift
        return float(1 / (1 + np.exp(-np.clip(z, -60, 60))))


def log_ratio(rows: list[np.ndarray], y: np.ndarray, smooth: float = 1.0) -> np.ndarray:
    out = []
    for label in (1, -1):
        own = [r for r, v in zip(rows, y, strict=True) if v == label]
        count = np.bincount(np.concatenate([*own, np.empty(0, np.int32)]), minlength=1 << BITS) + smooth
        out.append(np.log(count / (len(own) + 2 * smooth)))
    return (out[0] - out[1]).astype(np.float32)


def coordinate_descent(rows: list[np.ndarray], values: list[np.ndarray], y: np.ndarray, cost: np.ndarray, epochs: int = 12, seed: int = 0) -> tuple[np.ndarray, float]:
    """Weights and bias of the hinge-loss model, from its dual: one variable at a time, in a new order each epoch."""
    w, bias, alpha = np.zeros(1 << BITS, np.float64), 0.0, np.zeros(len(rows))
    square = np.array([float(np.dot(v, v)) + 1.0 for v in values])
    rng = np.random.default_rng(seed)
    for _ in range(epochs):
        moved = 0.0
        for i in rng.permutation(len(rows)):
            x, v = rows[i], values[i]
            slope = y[i] * (float(np.dot(w[x], v)) + bias) - 1.0
            new = min(max(alpha[i] - slope / square[i], 0.0), cost[i])
            if (step := (new - alpha[i]) * y[i]) != 0.0:
                w[x] += step * v
                bias += step
                alpha[i] = new
                moved = max(moved, abs(step))
        if moved < 1e-4:
            break
    return w, bias


def calibrated(margins: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and shift of the logistic curve through margins, with targets drawn in from 0 and 1."""
    up, down = int((y > 0).sum()), int((y < 0).sum())
    target = np.where(y > 0, (up + 1) / (up + 2), 1 / (down + 2))
    a, b = 1.0, 0.0
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a * margins + b, -60, 60)))
        d, h = p - target, np.maximum(p * (1 - p), 1e-9)
        g = np.array([np.dot(d, margins) + 1e-3 * a, d.sum()])
        m = np.array([[np.dot(h, margins**2) + 1e-3, np.dot(h, margins)], [np.dot(h, margins), h.sum() + 1e-9]])
        step = np.linalg.solve(m, g)
        step *= min(1.0, 5.0 / max(np.abs(step).max(), 1e-12))
        a, b = a - step[0], b - step[1]
        if np.abs(step).max() < 1e-8:
            break
    return max(float(a), 1e-3), float(b)


def fit(rows: list[np.ndarray], labels: np.ndarray, c: float = 4.0, kept: float = 0.9) -> Model:
    """A model from n-gram rows and labels 0/1; every fifth row only serves to turn margins into probabilities."""
    y = np.where(labels > 0, 1, -1)
    aside = np.arange(len(y)) % 5 == 4
    if len({*y[~aside]}) < 2 or len({*y[aside]}) < 2:
        p = ((y > 0).sum() + 1) / (len(y) + 2)
        return Model(np.zeros(1 << BITS, np.float32), np.zeros(1 << BITS, np.float32), 0.0, 1.0, float(np.log(p / (1 - p))))
    own, own_y = [r for r, a in zip(rows, aside, strict=True) if not a], y[~aside]
    ratio = log_ratio(own, own_y)
    values = []
    for r in own:
        v = ratio[r]
        values.append(v / np.float32(np.linalg.norm(v) or 1.0))
    w, bias = coordinate_descent(own, values, own_y, np.full(len(own), c))
    w = (1 - kept) * np.abs(w[w != 0]).mean() + kept * w if (w != 0).any() else w
    model = Model(ratio, w.astype(np.float32), bias, 1.0, 0.0)
    model.slope, model.shift = calibrated(np.array([model.margin(r) for r, a in zip(rows, aside, strict=True) if a]), y[aside])
    return model


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> Model:
    """Fit on at most `sample` labelled rows, none of them held out."""
    known = labels.where(F.col(id_col).isNotNull() & F.col(label_col).isNotNull() & (crc_of_id(id_col) % 4 != 2))
    known = known.groupBy(id_col).agg(F.min(label_col).cast("int").alias("label"))
    known = known.orderBy(F.xxhash64(id_col), id_col).limit(sample)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, text_col):
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([grams(x).tobytes() for x in raw_texts(b, text_col)], pa.binary())], ["id", "label", "grams"])

    chosen = docs.select(id_col, text_col).join(F.broadcast(known), id_col).select(id_col, "label", text_col)  # `sample` rows at most
    kind = docs.schema[id_col].dataType.simpleString()
    got = chosen.mapInArrow(settled(run), f"id {kind}, label int, grams binary").toArrow().combine_chunks()
    if not got.num_rows:
        return fit([], np.empty(0, np.int64))
    # views of one buffer, in the order of ids: the sample is in the driver's memory once
    ids, (column,) = got["id"].to_pylist(), got["grams"].chunks
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int32)[column.offset : column.offset + len(column) + 1] // 4
    flat = np.frombuffer(data, np.int32) if data is not None and data.size else np.empty(0, np.int32)
    first: dict[int, int] = {}
    for i, x in enumerate(ids):
        first.setdefault(x, i)
    order = [first[x] for x in sorted(first)]
    labels_ = got["label"].to_numpy()
    return fit([flat[at[i] : at[i + 1]] for i in order], labels_[order].astype(np.int64))


def score(docs: DataFrame, model: Model, threshold: float = 0.7, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, held_out, score, predicted)."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = held.value
        for b in slices(batches, text_col):
            s = [model.score(grams(x)) for x in raw_texts(b, text_col)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(s, pa.float64()), pa.array([int(x >= threshold) for x in s], pa.int32())], [id_col, "held_out", "score", "predicted"])

    rows = docs.select(id_col, F.coalesce(crc_of_id(id_col) % 4 == 2, F.lit(False)).alias("held_out"), text_col)
    kind = docs.schema[id_col].dataType.simpleString()
    return rows.mapInArrow(settled(run), f"{id_col} {kind}, held_out boolean, score double, predicted int")


def accepted(docs: DataFrame, model: Model, threshold: float = 0.7, text_col: str = "text") -> DataFrame:
    """The rows, all their columns as they are, whose text has a score of at least `threshold`."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = held.value
        for b in slices(batches, text_col):
            yield b.filter(pa.array([model.score(grams(x)) >= threshold for x in raw_texts(b, text_col)], pa.bool_()))

    return docs.mapInArrow(settled(run), docs.schema)
