"""Streams of frames: windows over event files, running control-variate moments, dedup, joins; batch twins for each.

Every query runs over files that are already there and stops (availableNow), so batch and stream can be compared.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.streaming.listener import StreamingQueryListener
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    """A stream over parquet files of events (a folder, or one file)."""
    reader = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger)
    folder, _, name = path.rpartition("/")
    return reader.option("pathGlobFilter", name).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def batch(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(EVENTS).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def counts(e: DataFrame, width: str = "1 hour", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """Frames by tumbling or sliding windows: all events and clicks."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    g = (e.withWatermark("ts", late) if e.isStreaming else e).groupBy(w.alias("w"))
    return g.agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "click").alias("clicks")).select(F.col("w.start").alias("start"), "n", "clicks")


def sessions(e: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """Bursts of each user's events."""
    g = (e.withWatermark("ts", late) if e.isStreaming else e).groupBy(F.session_window("ts", gap).alias("w"), "user_id")
    return g.agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def moments(e: DataFrame) -> DataFrame:
    """Running sums for the control variate, one row for each event type: state of constant size."""
    x, y = F.col("value"), (F.col("user_id") % 16).cast("double")
    return e.groupBy("event_type").agg(F.count("*").alias("n"), F.sum(x).alias("sx"), F.sum(y).alias("sy"), F.sum(x * y).alias("sxy"), F.sum(x * x).alias("sxx"), F.sum(y * y).alias("syy"))


def distinct(e: DataFrame, late: str = "10 minutes") -> DataFrame:
    """Events without repeats of an id."""
    return e.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]) if e.isStreaming else e.dropDuplicates(["event_id"])


def scored_pairs(e: DataFrame, late: str = "10 minutes") -> DataFrame:
    """Proxy results joined with target results of the same user within ten minutes: purchases and earlier errors."""
    mark = (lambda d, c: d.withWatermark(c, late)) if e.isStreaming else (lambda d, c: d)
    proxy = mark(e.where("event_type = 'error'").select(F.col("user_id").alias("u"), F.col("ts").alias("t0")), "t0")
    target = mark(e.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("t1")), "t1")
    return target.join(proxy, F.expr("user_id = u AND t1 BETWEEN t0 AND t0 + INTERVAL 10 MINUTES")).select("user_id", "t0", "t1")


def finished(stream: DataFrame, mode: str, path: str) -> DataFrame:
    """Run over what is there, and read the result from the folder that the micro-batches were written to.

    append and update: all batches; complete: the last one, which holds everything.
    """
    last = [-1]

    def write(d: DataFrame, n: int) -> None:
        d.write.mode("overwrite").parquet(f"{path}/out/batch={n}")
        last[0] = max(last[0], n)

    stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{path}/out/batch={last[0]}" if mode == "complete" else f"{path}/out/batch=*")


def into(stream: DataFrame, path: str, checkpoint: str, plan: Callable[[DataFrame], DataFrame] = lambda d: d) -> None:
    """Each micro-batch through `plan`, into a folder of its own number: a batch that is run again replaces itself."""
    stream.writeStream.foreachBatch(lambda d, n: plan(d).write.mode("overwrite").parquet(f"{path}/batch={n}")).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


MOMENTS = "event_type string, n long, sx double, sy double, sxy double"


def running_moments(e: DataFrame) -> DataFrame:
    """The running sums by an operator with state of its own: five numbers for each key, however many events come."""

    def add(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, sx, sy, sxy = state.get if state.exists else (0, 0.0, 0.0, 0.0)
        for p in parts:
            x, y = p["value"].fillna(0.0), (p["user_id"] % 16).astype(float)
            n, sx, sy, sxy = n + len(p), sx + float(x.sum()), sy + float(y.sum()), sxy + float((x * y).sum())
        state.update((n, sx, sy, sxy))
        yield pd.DataFrame({"event_type": [key[0]], "n": [n], "sx": [sx], "sy": [sy], "sxy": [sxy]})

    keyed = e.select("event_type", "user_id", "value").groupBy("event_type")
    return keyed.applyInPandasWithState(add, MOMENTS, "n long, sx double, sy double, sxy double", "update", GroupStateTimeout.NoTimeout)


def enriched(e: DataFrame, plans: DataFrame) -> DataFrame:
    """A stream joined with a static plan table of checked size, which is broadcast."""
    return e.join(F.broadcast(plans), "event_type")


def late_rows(query) -> int:
    """Rows that a finished or running query dropped behind its watermark."""
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for op in p["stateOperators"])


def adaptive_plan(frontier: list[tuple[str, float, float]], arriving: float) -> str:
    """Of (plan, accuracy, throughput), the most accurate that keeps up with the arrival rate; else the fastest."""
    enough = [p for p in frontier if p[2] >= arriving]
    return max(enough, key=lambda p: (p[1], p[2]))[0] if enough else max(frontier, key=lambda p: p[2])[0]


class PlanChooser(StreamingQueryListener):
    """Keeps the plan that fits the arrival rate which the last progress report of a stream gave."""

    def __init__(self, frontier: list[tuple[str, float, float]]):
        self.frontier, self.plan, self.history = frontier, adaptive_plan(frontier, 0.0), []

    def arrived(self, rate: float) -> None:
        self.plan = adaptive_plan(self.frontier, rate)
        self.history.append((rate, self.plan))

    def onQueryStarted(self, event) -> None:  # noqa: N802
        pass

    def onQueryProgress(self, event) -> None:  # noqa: N802
        self.arrived(float(event.progress.inputRowsPerSecond or 0.0))

    def onQueryIdle(self, event) -> None:  # noqa: N802
        self.arrived(0.0)

    def onQueryTerminated(self, event) -> None:  # noqa: N802
        pass
