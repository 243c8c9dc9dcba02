"""The model stage: decoding, preparing and scoring renditions in one pass over Arrow batches.

Decoding threads fill a bounded queue while one consumer scores; histograms go into recycled buffers, and only ids
and results leave.  Switches turn each of these off.
"""

from __future__ import annotations

import json
import queue
import zlib
from collections import deque
from collections.abc import Iterator
from concurrent.futures import Future, ThreadPoolExecutor
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from . import codec


@dataclass(frozen=True)
class Runtime:
    """threads: decoders beside the consumers (0: none, decode and score in turn; None: one for each core of a task); work: times that the model runs, to stand for a deeper one.

    reuse: buffers are recycled.  A CPU worker has no pinned memory; its counterpart here is that a buffer is
    contiguous, made once, and filled in place from views of Arrow's own memory.
    """

    threads: int | None = 1
    consumers: int = 1
    batch: int = 64
    depth: int = 4
    reuse: bool = True
    work: int = 1


def default_producers(spark: SparkSession) -> int:
    """Decoding threads of a task: the cores that it has (spark.task.cpus)."""
    return max(1, int(spark.sparkContext.getConf().get("spark.task.cpus", "1")))


@dataclass
class Softmax:
    """Softmax over square-rooted byte histograms: 16, 64 or 256 bins stand for nets of rising depth."""

    bins: int
    labels: list[str]
    weights: np.ndarray
    bias: np.ndarray
    training: str = "regular"

    def scores(self, features: np.ndarray) -> np.ndarray:
        z = features @ self.weights + self.bias
        z = np.exp(z - z.max(1, keepdims=True))
        return z / z.sum(1, keepdims=True)


BINS = {"tiny": 4, "res18": 16, "res34": 64, "res50": 256}


def features(r: np.ndarray, bins: int, out: np.ndarray | None = None) -> np.ndarray:
    count = np.bincount(r.ravel() >> (8 - bins.bit_length() + 1), minlength=bins)
    value = np.sqrt(count / max(1, r.size))
    if out is None:
        return value
    out[:] = value
    return out


def lowres(r: np.ndarray, quality: int | None = None) -> np.ndarray:
    """What a small rendition keeps: halved (through the block codec if a quality is given) and doubled again."""
    small = codec.half(r)
    if quality is not None:
        small = codec.dct_decode(*codec.dct_encode(small, quality))
    return codec.double(small, *r.shape)


def renditions(blobs: DataFrame, formats: tuple[str, ...] = codec.FORMATS, width: int = 32) -> DataFrame:
    """Rows (raster_id, label, format_id, height, width, n_bytes, index, payload) from rows (raster_id, payload, label)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                r = codec.text_raster(b.column(1)[i].as_py(), width)
                made = [codec.encode(f, r) for f in formats]
                n = len(formats)
                same = lambda c: b.column(c).take(pa.array([i] * n))  # noqa: B023, E731
                yield pa.RecordBatch.from_arrays(
                    [same(0), same(2), pa.array(formats), pa.array([r.shape[0]] * n, pa.int32()), pa.array([r.shape[1]] * n, pa.int32()), pa.array([len(p) for p, _ in made], pa.int64()), pa.array([x for _, x in made], pa.list_(pa.int64())), pa.array([p for p, _ in made], pa.binary())],
                    ["raster_id", "label", "format_id", "height", "width", "n_bytes", "index", "payload"],
                )

    return blobs.select("raster_id", "payload", "label").mapInArrow(run, "raster_id long, label string, format_id string, height int, width int, n_bytes long, index array<long>, payload binary")


def infer(rows: DataFrame, model: Softmax, runtime: Runtime = Runtime(), deblock: bool = True) -> DataFrame:  # noqa: B008
    """Rows (raster_id, label, guess, score, error) from renditions; a payload that can't be decoded gets an error."""
    held = rows.sparkSession.sparkContext.broadcast(model)
    threads = default_producers(rows.sparkSession) if runtime.threads is None else runtime.threads

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = held.value
        pool: queue.SimpleQueue = queue.SimpleQueue()
        for _ in range(runtime.depth + 1 if runtime.reuse else 0):
            pool.put(np.empty((runtime.batch, model.bins)))

        def prepared(b: pa.RecordBatch):
            x = pool.get() if runtime.reuse else np.empty((runtime.batch, model.bins))
            errors: list[str | None] = []
            for i, (f, p, index) in enumerate(zip(b.column(2).to_pylist(), b.column(3).to_pylist(), b.column(4).to_pylist(), strict=True)):
                try:
                    r = codec.decode(f, p, index or [], deblock)
                    features(r, model.bins, x[i])
                    errors.append(None)
                except (ValueError, TypeError, zlib.error) as e:
                    x[i] = 0
                    errors.append(str(e) or type(e).__name__)
            return b, x, errors

        def result(b: pa.RecordBatch, x: np.ndarray, errors: list[str | None]) -> pa.RecordBatch:
            for _ in range(runtime.work):
                p = model.scores(x[: b.num_rows])
            if runtime.reuse:
                pool.put(x)
            best = p.argmax(1)
            ok = [e is None for e in errors]
            return pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([model.labels[k] if o else None for k, o in zip(best, ok, strict=True)], pa.string()), pa.array([float(v) if o else None for v, o in zip(p.max(1), ok, strict=True)], pa.float64()), pa.array(errors, pa.string())], ["raster_id", "label", "guess", "score", "error"])

        parts = (b.slice(i, runtime.batch) for b in batches for i in range(0, b.num_rows, runtime.batch))
        if not threads:
            for part in parts:
                yield result(*prepared(part))
            return
        # both pools end with the task, whether it finishes, fails or is stopped early
        with ThreadPoolExecutor(threads) as makers, ThreadPoolExecutor(runtime.consumers) as takers:
            open_: deque[Future] = deque()
            try:
                for part in parts:
                    if len(open_) >= runtime.depth:
                        yield open_.popleft().result()
                    made = makers.submit(prepared, part)
                    open_.append(takers.submit(lambda made=made: result(*made.result())))
                while open_:
                    yield open_.popleft().result()
            finally:
                makers.shutdown(wait=False, cancel_futures=True)
                for f in open_:
                    f.cancel()

    return rows.select("raster_id", "label", "format_id", "payload", "index").mapInArrow(run, "raster_id long, label string, guess string, score double, error string")


def infer_all(rows: DataFrame, models: dict[str, Softmax]) -> DataFrame:
    """Rows (raster_id, label, format_id, model, guess): every model on every rendition, each decoded once."""
    held = rows.sparkSession.sparkContext.broadcast(models)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        models = held.value
        sizes = sorted({m.bins for m in models.values()})
        for b in batches:
            for i in range(0, b.num_rows, 256):
                part = b.slice(i, 256)
                rasters = [codec.decode(f, p, x or []) for f, p, x in zip(part.column(2).to_pylist(), part.column(3).to_pylist(), part.column(4).to_pylist(), strict=True)]
                x = {n: np.stack([features(r, n) for r in rasters]) for n in sizes}
                for name, m in models.items():
                    guess = [m.labels[k] for k in m.scores(x[m.bins]).argmax(1)]
                    yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), part.column(2), pa.array([name] * len(guess)), pa.array(guess, pa.string())], ["raster_id", "label", "format_id", "model", "guess"])

    return rows.select("raster_id", "label", "format_id", "payload", "index").mapInArrow(run, "raster_id long, label string, format_id string, model string, guess string")


def augmented(r: np.ndarray, key: int) -> np.ndarray:
    """Standard augmentation: a flip and a shift by up to one pixel in each direction (edges held), from a row's own key."""
    if key & 1:
        r = r[:, ::-1]
    h, w = r.shape
    rows, cols = (np.clip(np.arange(n) + d, 0, n - 1) for n, d in ((h, key // 2 % 3 - 1), (w, key // 6 % 3 - 1)))
    return r[rows[:, None], cols[None, :]]


def training_rows(blobs: DataFrame, bins: int, training: str = "regular", width: int = 32, augment: bool = False) -> DataFrame:
    """Rows (pick, raster_id, label, x array<double>): features of whole rasters, or of what small renditions keep of them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for key, p in zip(b.column(0).to_pylist(), b.column(3).to_pylist(), strict=True):
                r = codec.text_raster(p, width)
                r = augmented(r, key) if augment else r
                out.append(features(codec.half(r) if training == "lowres" else r, bins))
            yield pa.RecordBatch.from_arrays([*b.columns[:3], pa.array([x.tolist() for x in out], pa.list_(pa.float64()))], ["pick", "raster_id", "label", "x"])

    return blobs.select("pick", "raster_id", "label", "payload").mapInArrow(run, "pick long, raster_id long, label string, x array<double>")


def train(blobs: DataFrame, bins: int, training: str = "regular", rounds: int = 150, rate: float = 4.0, bound: int = 4000, start: Softmax | None = None, augment: bool = False) -> Softmax:
    """A softmax head, fitted by momentum on at most `bound` training rows (features of a few KB each).

    Rows are picked by a threshold on a hash of their id, so others' payloads go no further than the scan.
    """
    blobs = blobs.where(F.col("label").isNotNull()).withColumn("pick", F.pmod(F.xxhash64("raster_id"), F.lit(1 << 30)))
    share = min(1.0, 1.2 * bound / max(1, blobs.count()))
    rows = training_rows(blobs.where(F.col("pick") < int(share * (1 << 30))), bins, training, augment=augment).orderBy("pick", "raster_id").limit(bound).toArrow()
    labels = start.labels if start else sorted(set(rows["label"].to_pylist()))
    x = np.array(rows["x"].to_pylist()).reshape(-1, bins)
    y = np.eye(len(labels))[[labels.index(v) for v in rows["label"].to_pylist()]]
    w = start.weights.copy() if start else np.zeros((bins, len(labels)))
    b = start.bias.copy() if start else np.zeros(len(labels))
    model, v = Softmax(bins, labels, w, b, training), np.zeros_like(w)
    for _ in range(rounds // 3 if start else rounds):
        g = model.scores(x) - y
        v = 0.9 * v - rate * (x.T @ g / len(x) + 1e-5 * model.weights)
        model.weights += v
        model.bias -= rate * g.mean(0)
    return model


def saved(model: Softmax) -> str:
    """A model as one JSON line."""
    return json.dumps({"bins": model.bins, "labels": model.labels, "weights": model.weights.tolist(), "bias": model.bias.tolist(), "training": model.training})


def imported(spark: SparkSession, folder: str, names: str = "*.json") -> dict[str, Softmax]:
    """Models trained elsewhere: one for each JSON file of a folder, by the file's name."""
    out = {}
    for r in spark.read.format("binaryFile").option("pathGlobFilter", names).load(folder).collect():  # weights of a few MB at most, for the driver to broadcast
        x = json.loads(bytes(r["content"]))
        out[r["path"].rsplit("/", 1)[-1].rsplit(".", 1)[0]] = Softmax(x["bins"], x["labels"], np.array(x["weights"]), np.array(x["bias"]), x["training"])
    return out


@dataclass
class Ladder:
    """Models by (depth name, training); with `blobs`, those that aren't there are trained when they are first asked for."""

    models: dict[tuple[str, str], Softmax] = field(default_factory=dict)
    blobs: DataFrame | None = None
    names: tuple[str, ...] = ("res18", "res34", "res50")

    def __getitem__(self, key: tuple[str, str]) -> Softmax:
        if key not in self.models:
            name, training = key
            if self.blobs is None or name not in self.names:
                raise KeyError(key)
            start = self[name, "regular"] if training == "lowres" else None
            self.models[key] = train(self.blobs, BINS[name], training, start=start)
        return self.models[key]


def ladder(blobs: DataFrame, names: tuple[str, ...] = ("res18", "res34", "res50"), trainings: tuple[str, ...] = ("regular", "lowres"), lazy: bool = False) -> Ladder:
    """The models named with the trainings named, now or (lazy) on demand; the low-resolution one starts from the other's weights and takes a third of the rounds."""
    out = Ladder(blobs=blobs, names=names)
    for key in [(n, t) for n in names for t in trainings] if not lazy else []:
        out[key]
    return out
