"""Joins that Spark has no operator for: bands of time and the latest row before."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window as W, functions as F


def band(left: DataFrame, right: DataFrame, a: str, b: str, seconds: int) -> DataFrame:
    """Pairs whose times differ by at most `seconds`: an equi-join on buckets of that width (the left looks at three), then the condition."""
    bucket = lambda c: F.floor(F.unix_micros(c) / (seconds * 1_000_000))
    micros = lambda c: F.unix_micros(c)
    wide = left.withColumn("_b", F.explode(F.array(*[bucket(F.to_timestamp(F.col(a))) + k for k in (-1, 0, 1)])))
    j = wide.join(right.withColumn("_b", bucket(F.to_timestamp(F.col(b)))), "_b")
    return j.where(F.abs(micros(F.to_timestamp(F.col(a))) - micros(F.to_timestamp(F.col(b)))) <= seconds * 1_000_000).drop("_b")


def asof(left: DataFrame, right: DataFrame, key: str, ts: str, value: str) -> DataFrame:
    """left with `value` of the latest right row of the same key at or before its time: one union, one sort, one window."""
    both = left.withColumn("_side", F.lit(1)).withColumn("_v", F.lit(None).cast(right.schema[value].dataType))
    other = right.select(key, ts, F.col(value).alias("_v")).withColumn("_side", F.lit(0))
    rows = both.unionByName(other, allowMissingColumns=True)
    w = W.partitionBy(key).orderBy(ts, "_side", "_v").rowsBetween(W.unboundedPreceding, W.currentRow)
    return rows.withColumn(value, F.last("_v", ignorenulls=True).over(w)).where("_side = 1").drop("_side", "_v")


def back_range(rows: DataFrame, key: str, at: str, width: int) -> DataFrame:
    """rows with n: how many of the same key lie in the `width` before each, itself and ties included.

    A row also goes to the stretch after its own, so a window over (key, stretch) sees all that a frame can reach and a
    key with most of the rows is spread over time.
    """
    own = F.floor(F.col(at) / F.lit(width))
    both = rows.withColumn("_own", own).withColumn("_s", F.explode(F.array(own, own + 1)))
    w = W.partitionBy(key, "_s").orderBy(at).rangeBetween(-width, 0)
    return both.withColumn("n", F.count("*").over(w)).where("_s = _own").drop("_own", "_s")
