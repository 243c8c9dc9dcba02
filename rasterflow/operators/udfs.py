"""The same score as a row-at-a-time UDF, a pandas UDF, an Arrow UDF and a table function: the software-stack baseline."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import arrow_udf, pandas_udf, udf, udtf


def brightness(payload: bytes | None) -> float:
    return float(np.frombuffer(payload, np.uint8).mean()) if payload else 0.0


by_row = udf(brightness, T.DoubleType())


@pandas_udf(T.DoubleType())
def by_series(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
    for p in parts:
        yield p.map(brightness)


def by_batch(rows: DataFrame) -> DataFrame:
    """Whole Arrow batches: one pass over the joined bytes, sums between the offsets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            size = np.array([len(x or b"") for x in b.column(1).to_pylist()])
            flat = np.frombuffer(b"".join(x or b"" for x in b.column(1).to_pylist()), np.uint8)
            total = np.concatenate([[0], np.cumsum(flat, dtype=np.int64)])
            end = np.cumsum(size)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array((total[end] - total[end - size]) / np.maximum(size, 1))], ["raster_id", "score"])

    return rows.select("raster_id", "payload").mapInArrow(run, "raster_id long, score double")


@udtf(returnType=T.StructType([T.StructField("block", T.IntegerType()), T.StructField("mean", T.DoubleType())]))
class Blocks:
    """A payload's runs of 64 bytes, each with its mean."""

    def eval(self, payload: bytes):
        for i in range(0, len(payload or b""), 64):
            yield i // 64, brightness(payload[i : i + 64])


@arrow_udf(T.DoubleType())
def by_array(parts: pa.Array) -> pa.Array:
    return pa.array([brightness(x) for x in parts.to_pylist()], pa.float64())


@pandas_udf(T.DoubleType())
def jackknife(v: pd.Series) -> float:
    """Standard error of a group's mean by leaving out one value at a time."""
    v, n = v.dropna().to_numpy(float), int(v.notna().sum())
    if n < 2:
        return float("nan")
    left = (v.sum() - v) / (n - 1)
    return float(np.sqrt((n - 1) / n * ((left - left.mean()) ** 2).sum()))


IMPLEMENTATIONS = ("udf", "pandas_udf", "arrow_udf", "arrow")


def stack(rows: DataFrame, impl: str) -> DataFrame:
    """Rows (raster_id, score) by the named implementation."""
    if impl == "arrow":
        return by_batch(rows)
    f = {"udf": by_row, "pandas_udf": by_series, "arrow_udf": by_array}[impl]
    return rows.select("raster_id", f(F.col("payload")).alias("score"))


def compared(left: DataFrame, right: DataFrame) -> DataFrame:
    """Two renditions of the same item side by side (cogroup): bytes of each."""

    def both(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        key = a["raster_id"] if len(a) else b["item"]
        return pd.DataFrame({"raster_id": [int(key.iloc[0])], "left_bytes": [int(a["n_bytes"].sum()) if len(a) else 0], "right_bytes": [int(b["bytes"].sum()) if len(b) else 0]})

    a = left.select("raster_id", "n_bytes")
    b = right.select(F.col("raster_id").alias("item"), F.col("n_bytes").alias("bytes"))
    return a.groupBy("raster_id").cogroup(b.groupBy("item")).applyInPandas(both, "raster_id long, left_bytes long, right_bytes long")
