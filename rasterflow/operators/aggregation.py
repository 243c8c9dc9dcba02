"""Aggregates of an expensive target under an error bound: exact, plain sampling, control variates, sample sizes.

Samples are the first n rows by md5(seed-id): nested as n grows, equal on every engine.  `sample` takes them by a
top-k; `drawn` takes those of many seeds in one scan, by a threshold on the hash before ranking.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window as W, functions as F

Z95 = 1.959964


def hash_key(seed: int, id_col: str = "frame_id") -> Column:
    return F.md5(F.concat(F.lit(f"{seed}-"), F.col(id_col).cast("string")))


def sample(frames: DataFrame, n: int, seed: int = 0, id_col: str = "frame_id") -> DataFrame:
    """The first n rows by hash (a top-k: each partition keeps n)."""
    return frames.orderBy(hash_key(seed, id_col), id_col).limit(n)


def exact(frames: DataFrame, y: str = "y") -> DataFrame:
    return frames.agg(F.avg(y).alias("estimate"), F.count(F.col(y)).alias("target_calls"))


def moments(rows: DataFrame, y: str, x: str) -> DataFrame:
    return rows.agg(F.count("*").alias("n"), F.avg(y).alias("my"), F.avg(x).alias("mx"), F.var_samp(y).alias("vy"), F.var_samp(x).alias("vx"), F.covar_samp(y, x).alias("cov"))


def control_variate(frames: DataFrame, n: int, y: str = "y", x: str = "x", seed: int = 0, coef: float | str = "optimal", z: float = Z95) -> DataFrame:
    """One row (estimate, half_width, target_calls, plain, plain_half_width): the target on n frames, the proxy on all.

    coef: 'optimal' (covariance over variance, 0 for a constant proxy) or a number; 0 is plain sampling.
    """
    everything = frames.agg(F.avg(x).alias("mu"), F.count("*").alias("total"))
    s = moments(sample(frames, n, seed), y, x).crossJoin(F.broadcast(everything))  # one row each
    c = F.when(F.coalesce(F.col("vx"), F.lit(0.0)) > 0, F.col("cov") / F.col("vx")).otherwise(0.0) if coef == "optimal" else F.lit(float(coef))
    s = s.withColumn("c", c).withColumn("fpc", 1 - F.col("n") / F.col("total"))
    residual = F.greatest(F.lit(0.0), F.col("vy") - 2 * F.col("c") * F.col("cov") + F.col("c") * F.col("c") * F.col("vx"))
    half = lambda v: F.lit(z) * F.sqrt(v / F.col("n") * F.col("fpc"))
    return s.select((F.col("my") - F.col("c") * (F.col("mx") - F.col("mu"))).alias("estimate"), half(residual).alias("half_width"), F.col("n").alias("target_calls"), F.col("my").alias("plain"), half(F.col("vy")).alias("plain_half_width"))


def required_n(variance: Column, eps: Column, z: float = Z95, population: Column | None = None) -> Column:
    n = F.lit(z * z) * variance / (eps * eps)
    return F.ceil(n / (1 + n / population)) if population is not None else F.ceil(n)


def total_time(frames: Column, pre: Column, proxy: Column, calls: Column, target: Column) -> Column:
    """Modelled seconds: the proxy over all frames at the pipelined rate, the target over the sample."""
    return frames / F.least(pre, proxy) + calls / target


def adaptive(frames: DataFrame, eps: float, y: str = "y", x: str = "x", pilot: int = 50, seed: int = 0, z: float = Z95, rounds: int = 8) -> tuple[DataFrame, list[int]]:
    """Grow the nested sample until the half width is at most eps; also the sizes tried.

    Each round's size comes from the variance seen so far; at most `rounds` rounds, the last of which takes what is
    needed with a margin.  One row of moments comes to the driver in each.
    """
    total = frames.count()
    n, tried = min(pilot, total), []
    while True:
        tried.append(n)
        out = control_variate(frames, n, y, x, seed, z=z)
        row = out.first()
        if row is None or row["half_width"] is None or row["half_width"] <= eps or n >= total or len(tried) > rounds:
            return out, tried
        need = n * (row["half_width"] / eps) ** 2
        n = min(total, max(n + 1, math.ceil(1.1 * need)))


def drawn(frames: DataFrame, n: int, seeds: Sequence[int]) -> DataFrame:
    """Rows (seed, frame_id, y, x): for each seed the first n frames by hash, from rows (frame_id, y, x).

    A threshold on the hash keeps a little more than n of them while scanning, so only these are shuffled and ranked; if
    it left any seed short (about never), it is doubled.
    """
    total, spark = frames.count(), frames.sparkSession
    trials = frames.crossJoin(F.broadcast(spark.createDataFrame([(int(s),) for s in seeds], "seed int")))
    key = F.md5(F.concat(F.col("seed").cast("string"), F.lit("-"), F.col("frame_id")))
    share = (n + 8 * math.sqrt(n) + 16) / max(1, total)
    while True:
        kept = trials if share >= 1 else trials.where(F.substring(key, 1, 8) < f"{int(share * 16**8):08x}")
        if share >= 1 or kept.groupBy("seed").count().where(F.col("count") >= min(n, total)).count() == len(set(seeds)):
            break
        share *= 2
    return kept.withColumn("r", F.row_number().over(W.partitionBy("seed").orderBy(key, "frame_id"))).where(F.col("r") <= n).drop("r")


def coverage(frames: DataFrame, n: int, seeds: Sequence[int], y: str = "y", x: str = "x", z: float = Z95) -> DataFrame:
    """Share of seeds whose interval holds the exact mean, and variance of both estimates: every seed in one plan."""
    rows = frames.select("frame_id", F.col(y).alias("y"), F.col(x).alias("x"))
    s = drawn(rows, n, seeds).groupBy("seed").agg(F.count("*").alias("n"), F.avg("y").alias("my"), F.avg("x").alias("mx"), F.var_samp("y").alias("vy"), F.var_samp("x").alias("vx"), F.covar_samp("y", "x").alias("cov"))
    s = s.crossJoin(F.broadcast(frames.agg(F.avg(x).alias("mu"), F.avg(y).alias("truth"), F.count("*").alias("total"))))
    c = F.when(F.col("vx") > 0, F.col("cov") / F.col("vx")).otherwise(0.0)
    est = F.col("my") - c * (F.col("mx") - F.col("mu"))
    var = F.greatest(F.lit(0.0), F.col("vy") - c * F.col("cov")) / F.col("n") * (1 - F.col("n") / F.col("total"))
    inside = F.abs(est - F.col("truth")) <= F.lit(z) * F.sqrt(var)
    return s.agg(F.avg(inside.cast("double")).alias("coverage"), F.var_samp(est).alias("cv_variance"), F.var_samp("my").alias("plain_variance"))
