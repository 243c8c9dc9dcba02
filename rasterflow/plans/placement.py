"""Where each operator of a chain runs: a prefix on the host, the rest beside the model."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window as W, functions as F


def splits(ops: DataFrame, by: Sequence[str] = ("plan_id",), cores: float = 1.0, speedup: float = 1.0) -> DataFrame:
    """Rates of each split point from rows (by..., exec, place, seconds, host_only): split s keeps ops 1..s on the host.

    host rate = cores over the host ops' seconds; the accelerator does the others `speedup` times as fast, after which
    the model.  Splits inside the ops that must stay on the host aren't offered.
    """
    w = W.partitionBy(*by).orderBy("place")
    whole = W.partitionBy(*by)
    upto = F.sum("seconds").over(w.rowsBetween(W.unboundedPreceding, 0))
    after = F.coalesce(F.sum("seconds").over(w.rowsBetween(1, W.unboundedFollowing)), F.lit(0.0))
    least = F.coalesce(F.max(F.when(F.col("host_only"), F.col("place"))).over(whole), F.lit(1))
    out = ops.select(*by, F.col("place").alias("split"), (F.lit(cores) / upto).alias("host_rate"), (1 / (1 / F.col("exec") + after / F.lit(speedup))).alias("accel_rate"), least.alias("least"))
    return out.where("split >= least").drop("least").withColumn("tput", F.least("host_rate", "accel_rate"))


def best_split(ops: DataFrame, by: Sequence[str] = ("plan_id",), cores: float = 1.0, speedup: float = 1.0) -> DataFrame:
    """The split with the largest end-to-end rate; ties keep work on the host."""
    order = W.partitionBy(*by).orderBy(F.desc(F.round("tput", 9)), F.desc("split"))
    return splits(ops, by, cores, speedup).withColumn("_n", F.row_number().over(order)).where("_n = 1").drop("_n")


def rule(pre: Column, ex: Column) -> Column:
    """Everything on the host if the model is the bottleneck, as much as possible off it otherwise."""
    return F.when(ex < pre, "host").otherwise("accel")
