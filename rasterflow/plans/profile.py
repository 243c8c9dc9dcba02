"""Measured throughput of the stages of a plan: preparation alone, the model alone on made input, and both together."""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ..operators import codec, inference as I


def seconds(df: DataFrame, repeats: int = 1) -> float:
    """The least time of `repeats` runs into nothing."""
    took = []
    for _ in range(repeats):
        began = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        took.append(time.perf_counter() - began)
    return min(took)


def preparation(rows: DataFrame, bins: int) -> DataFrame:
    """Decode and take features, no model."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = [float(I.features(codec.decode(f, p, i or []), bins)[0]) for f, p, i in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.float64())], ["x"])

    return rows.select("format_id", "payload", "index").mapInArrow(run, "x double")


def execution(rows: DataFrame, model: I.Softmax, runtime: I.Runtime) -> DataFrame:
    """The model on made features, one for each row; payloads aren't read."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, runtime.batch):
                x = np.full((min(runtime.batch, b.num_rows - i), model.bins), 0.1)
                for _ in range(runtime.work):
                    p = model.scores(x)
                yield pa.RecordBatch.from_arrays([pa.array(p[:, 0])], ["x"])

    return rows.select("raster_id").mapInArrow(run, "x double")


def measure(rows: DataFrame, model: I.Softmax, runtime: I.Runtime, repeats: int = 2) -> dict[str, float]:
    """Rows a second of pre, exec and e2e; the cost of a job over nothing but the scan is taken off each."""
    n = rows.count()
    base = seconds(rows.select("raster_id"), repeats)
    rate = lambda df: n / max(1e-3, seconds(df, repeats) - base)
    return {"n": float(n), "pre": rate(preparation(rows, model.bins)), "exec": rate(execution(rows, model, runtime)), "measured": rate(I.infer(rows, model, runtime))}
