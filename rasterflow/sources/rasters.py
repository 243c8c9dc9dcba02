"""Rasters rendered from the given tables, as DataFrames.

Whole texts are rendered: bytes in rows of 32, the last row filled with zeros.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions import rasters as R
from ..operators import codec
from ..registry import table


def text_rasters(spark: SparkSession, sf_dir: str, source: str = "documents", width: int = R.WIDTH) -> DataFrame:
    """Rows (raster_id, pixels array<int>, height int, label)."""
    id_col, text, label = {"documents": ("doc_id", "text", "lang"), "pages": ("page_id", "html", "url")}[source]
    rows = table(spark, sf_dir, source).select(F.col(id_col).alias("raster_id"), R.byte_pixels(F.col(text), width).alias("pixels"), F.col(label).alias("label"))
    return rows.withColumn("height", (F.size("pixels") / width).cast("int"))


def text_blobs(spark: SparkSession, sf_dir: str, source: str = "documents") -> DataFrame:
    """Rows (raster_id, payload binary, label): the bytes that the Arrow stage takes; no pixel arrays are made."""
    id_col, text, label = {"documents": ("doc_id", "text", "lang"), "pages": ("page_id", "html", "url")}[source]
    return table(spark, sf_dir, source).select(F.col(id_col).alias("raster_id"), F.encode(F.coalesce(F.col(text), F.lit("")), "UTF-8").alias("payload"), F.col(label).alias("label"))


def text_images(docs: DataFrame, formats: Sequence[str] = ("full", "half_png", "quarter_png"), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (raster_id, format_id, height, width, n_bytes, payload): the 8 x 8 byte-class raster of each whole text, in every rendition.

    Pixel i is the share of the text's bytes among 4 i .. 4 i + 3, in 1/1020, at most 255; an empty text is black.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 512):
                part = b.slice(i, 512)
                out = []
                for x in part.column(1).cast(pa.binary()).to_pylist():
                    raw = np.frombuffer(x or b"", np.uint8)
                    r = np.minimum(255, np.bincount(raw >> 2, minlength=64) * 1020 // max(1, len(raw))).astype(np.uint8).reshape(8, 8)
                    out += [codec.encode(f, r)[0] for f in formats]
                n = part.num_rows
                side = [8 >> ("full", "half_png", "quarter_png").index(f) for f in formats] * n
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(np.repeat(np.arange(n), len(formats)))), pa.array(list(formats) * n), pa.array(side, pa.int32()), pa.array(side, pa.int32()), pa.array([len(p) for p in out], pa.int64()), pa.array(out, pa.binary())], ["raster_id", "format_id", "height", "width", "n_bytes", "payload"])

    return docs.select(F.col(id_col).cast("long").alias("raster_id"), text_col).mapInArrow(run, "raster_id long, format_id string, height int, width int, n_bytes long, payload binary")


def vector_rasters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows (raster_id, pixels array<int> of 64, label): one 8 x 8 block for each vector."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("raster_id"), R.vector_pixels(F.col("embedding")).alias("pixels"), "label")


def event_frames(spark: SparkSession, sf_dir: str, target: str = "click", every: str = "1 hour") -> DataFrame:
    """Rows (frame_id, y, x, weak): one frame for each bucket of `events`, empty ones too.

    y: events of the target kind.  x: sum of a 16 x 16 frame whose cell (user, minute) adds 40 for a target event and
    10 for another, at most 255.  weak: all events.
    """
    e = table(spark, sf_dir, "events").withColumn("frame_id", F.date_trunc("hour", "ts"))
    hit = F.when(F.col("event_type") == target, 1).otherwise(0)
    cells = e.groupBy("frame_id", (F.col("user_id") % 16).alias("r"), (F.minute("ts") % 16).alias("c")).agg(F.sum(hit).alias("hits"), F.count("*").alias("n"))
    cells = cells.withColumn("v", F.least(F.lit(255), F.col("hits") * 40 + (F.col("n") - F.col("hits")) * 10))
    frames = cells.groupBy("frame_id").agg(F.sum("hits").alias("y"), F.sum("v").alias("x"), F.sum("n").alias("weak"))
    spine = e.agg(F.min("frame_id").alias("a"), F.max("frame_id").alias("b")).select(F.explode(F.sequence("a", "b", F.expr(f"INTERVAL {every}"))).alias("frame_id"))
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("double").alias(c)
    return spine.join(frames, "frame_id", "left").select(F.col("frame_id").cast("timestamp_ntz").cast("string").alias("frame_id"), zero("y"), zero("x"), zero("weak"))


def order_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frames are orders: y lines, x quantity, weak lines of status F, none the order's price."""
    lines = table(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(F.count("*").alias("y"), F.sum("l_quantity").alias("x"), F.sum(F.when(F.col("l_linestatus") == "F", 1).otherwise(0)).alias("weak"))
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("double").alias(c)
    orders = table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_totalprice").alias("none"))
    return orders.join(lines, "o_orderkey", "left").select(F.col("o_orderkey").cast("string").alias("frame_id"), zero("y"), zero("x"), zero("weak"), "none")


def page_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frames are pages: y tags, x length, weak text outside of tags."""
    tags = F.regexp_count("html", F.lit("<[a-zA-Z/]")).cast("double")
    return table(spark, sf_dir, "pages").select(F.col("page_id").cast("string").alias("frame_id"), tags.alias("y"), F.length("html").cast("double").alias("x"), F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("double").alias("weak"))


def document_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frames are documents: y lines, x characters, weak commas."""
    d = table(spark, sf_dir, "documents")
    lines = (F.length("text") - F.length(F.replace("text", F.lit("\n"))) + 1).cast("double")
    return d.select(F.col("doc_id").cast("string").alias("frame_id"), lines.alias("y"), F.col("n_chars").cast("double").alias("x"), (F.length("text") - F.length(F.replace("text", F.lit(",")))).cast("double").alias("weak"))


STREAMS = {"v1_events": event_frames, "v2_orders": order_frames, "v3_pages": page_frames, "v4_documents": document_frames}

#: The same frames in SQL.
STREAM_SQL = {
    "v1_events": """(SELECT strftime(s.f, '%Y-%m-%d %H:%M:%S') AS frame_id, coalesce(y, 0)::DOUBLE AS y, coalesce(x, 0)::DOUBLE AS x, coalesce(weak, 0)::DOUBLE AS weak
 FROM (SELECT unnest(generate_series(date_trunc('hour', min(ts)), date_trunc('hour', max(ts)), INTERVAL 1 HOUR)) AS f FROM events) s LEFT JOIN
 (SELECT f, sum(hits) AS y, sum(least(255, hits * 40 + (n - hits) * 10)) AS x, sum(n) AS weak FROM (SELECT date_trunc('hour', ts) AS f, user_id % 16 AS r, minute(ts) % 16 AS c, sum((event_type = 'click')::INT) AS hits, count(*) AS n FROM events GROUP BY 1, 2, 3) GROUP BY f) e ON e.f = s.f)""",
    "v2_orders": "(SELECT o_orderkey::VARCHAR AS frame_id, coalesce(y, 0)::DOUBLE AS y, coalesce(x, 0)::DOUBLE AS x, coalesce(weak, 0)::DOUBLE AS weak, o_totalprice AS none FROM orders LEFT JOIN (SELECT l_orderkey, count(*) AS y, sum(l_quantity) AS x, sum((l_linestatus = 'F')::INT) AS weak FROM lineitem GROUP BY 1) l ON l.l_orderkey = o_orderkey)",
    "v3_pages": "(SELECT page_id::VARCHAR AS frame_id, len(regexp_extract_all(html, '<[a-zA-Z/]'))::DOUBLE AS y, length(html)::DOUBLE AS x, length(regexp_replace(html, '<[^>]*>', '', 'g'))::DOUBLE AS weak FROM pages)",
    "v4_documents": "(SELECT doc_id::VARCHAR AS frame_id, (length(text) - length(replace(text, chr(10), '')) + 1)::DOUBLE AS y, n_chars::DOUBLE AS x, (length(text) - length(replace(text, ',', '')))::DOUBLE AS weak FROM documents)",
}
