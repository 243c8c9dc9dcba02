"""The rendition store: one partition for each format, so that choosing a format prunes the others' bytes."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def write(renditions: DataFrame, path: str, buckets: int = 8) -> None:
    """Partitioned by format, clustered by id in files of `buckets` ranges, so that footers skip by id."""
    rows = renditions.repartitionByRange(buckets, "format_id", "raster_id").sortWithinPartitions("format_id", "raster_id")
    rows.write.mode("overwrite").partitionBy("format_id").option("maxRecordsPerFile", 1_000_000).parquet(path)


def read(spark: SparkSession, path: str, format_id: str | None = None, columns: Sequence[str] = ()) -> DataFrame:
    rows = spark.read.parquet(path)
    if format_id is not None:
        rows = rows.where(F.col("format_id") == format_id)
    return rows.select(*columns) if columns else rows


def catalogue(renditions: DataFrame) -> DataFrame:
    """Rows (format_id, n, bytes, mean_h, mean_w): what the cost model needs without reading payloads."""
    return renditions.groupBy("format_id").agg(F.count("*").alias("n"), F.sum("n_bytes").alias("bytes"), F.avg("height").alias("mean_h"), F.avg("width").alias("mean_w"))


class RangeOfRasters(InputPartition):
    def __init__(self, start: int, stop: int):
        super().__init__(start)
        self.start, self.stop = start, stop


class GradientSource(DataSource):
    """`rasterblob`: made rasters for calibration (a gradient with a step), read in parallel.

    Options: n (rows), parts, side.
    """

    @classmethod
    def name(cls) -> str:
        return "rasterblob"

    def schema(self) -> str:
        return "raster_id long, height int, width int, payload binary"

    def reader(self, schema) -> DataSourceReader:
        return GradientReader({k: int(v) for k, v in self.options.items() if str(v).isdigit()})


class GradientReader(DataSourceReader):
    def __init__(self, options: dict[str, int]):
        self.n, self.parts, self.side = options.get("n", 100), options.get("parts", 4), options.get("side", 16)

    def partitions(self) -> list[RangeOfRasters]:
        cut = [self.n * i // self.parts for i in range(self.parts + 1)]
        return [RangeOfRasters(a, b) for a, b in zip(cut, cut[1:], strict=False) if b > a]

    def read(self, partition: RangeOfRasters):
        for i in range(partition.start, partition.stop):
            yield i, self.side, self.side, bytes((i + x + (64 if y >= self.side // 2 else 0)) % 256 for y in range(self.side) for x in range(self.side))
