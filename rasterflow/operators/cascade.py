"""The cascade baseline: a small net answers where it is sure, and only what it forwards reaches the deepest net.

24 small nets (nearest class means over few values of the full rendition), of which the most accurate ones on the
training fold are chained to the target at several thresholds of the margin between the two nearest classes.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from ..functions import cost
from ..plans.engine import Engine, Net

#: (values, first value) of the small nets, and the rate of one that takes a single value.
SMALL = tuple((v, f) for v in (1, 2, 3, 4, 6, 8) for f in (0, 2, 4, 8))
SMALL_RATE = 250000.0
USED = 8
THRESHOLDS = (0.2, 0.5, 0.8)


def name(values: int, first: int) -> str:
    return f"tiny{values}at{first}"


def stage(x: Column, classes: Column, values: int, first: int) -> Column:
    """struct(guess, margin): the nearest class, and by how much of its distance the second is farther (1 without a second)."""
    near = F.slice(Engine.nearest(x, classes, values, first), 1, 2)
    margin = F.transform(F.array(near), lambda n: F.struct(F.element_at(n, 1)["label"].alias("guess"), F.when(F.size(n) < 2, 1.0).otherwise((n[1]["d"] - n[0]["d"]) / F.greatest(n[1]["d"], F.lit(1e-9))).alias("margin")))
    return margin[0]


def small_nets(engine: Engine) -> DataFrame:
    """Rows (dataset, net, rate, acc, used): accuracy of every small net on the training fold; the best USED of a dataset are used."""
    rows = engine.labelled(("full",)).where("NOT held").join(F.broadcast(engine.means(("full",))), ["format_id", "dataset"])
    hits = [F.avg((stage(F.col("x"), F.col("classes"), v, f)["guess"] == F.col("label")).cast("double")).alias(name(v, f)) for v, f in SMALL]
    wide = rows.groupBy("dataset").agg(*hits)
    nets = F.explode(F.array(*[F.struct(F.lit(name(v, f)).alias("net"), F.lit(SMALL_RATE / v).alias("rate"), F.col(name(v, f)).alias("acc")) for v, f in SMALL])).alias("p")
    order = W.partitionBy("dataset").orderBy(F.desc(F.round("acc", 9)), F.desc("rate"), "net")
    return wide.select("dataset", nets).select("dataset", "p.*").withColumn("used", F.row_number().over(order) <= USED)


def plans(engine: Engine, thresholds: Sequence[float] = THRESHOLDS) -> DataFrame:
    """Rows (dataset, net, threshold, share, acc, exec, est_tput, true_tput) of the used nets chained to the deepest.

    share: what is forwarded, from held-out margins.  est_tput is the baseline's own additive estimate, which prepares
    once; true_tput is pipelined and prepares forwarded items again, as they are gathered for the second net.
    """
    deep = max(engine.nets, key=lambda n: n.values)
    rows = engine.labelled(("full",)).where("held").join(F.broadcast(engine.means(("full",))), ["format_id", "dataset"])
    rows = rows.withColumn("slow", Engine.nearest(F.col("x"), F.col("classes"), deep.values)[0]["label"])
    stages = F.explode(F.array(*[F.struct(F.lit(name(v, f)).alias("net"), stage(F.col("x"), F.col("classes"), v, f).alias("s")) for v, f in SMALL])).alias("p")
    rows = rows.select("dataset", "label", "slow", stages).select("dataset", "label", "slow", "p.net", "p.s.*")
    rows = rows.withColumn("threshold", F.explode(F.array(*map(F.lit, thresholds)))).withColumn("passed", F.round("margin", 9) < F.col("threshold"))
    answer = F.when(F.col("passed"), F.col("slow")).otherwise(F.col("guess"))
    out = rows.groupBy("dataset", "net", "threshold").agg(F.avg(F.col("passed").cast("double")).alias("share"), F.avg((answer == F.col("label")).cast("double")).alias("acc"))
    out = out.join(F.broadcast(small_nets(engine).where("used").select("dataset", "net", "rate")), ["dataset", "net"])
    full = engine.placed().where("format_id = 'full'").agg(F.max("pre").alias("pre"))
    out = out.crossJoin(F.broadcast(full)).withColumn("exec", 1 / (1 / F.col("rate") + F.col("share") / F.lit(deep.rate)))
    out = out.withColumn("est_tput", cost.est_additive(F.col("pre"), F.col("exec")))
    return out.withColumn("true_tput", cost.est_pipelined(cost.true_pre(F.col("pre"), F.col("pre"), F.col("share")), F.col("exec")))


def run(engine: Engine, dataset: str, values: int, first: int, threshold: float, deep: Net | None = None) -> DataFrame:
    """Rows (raster_id, guess, stage) of all items: the deepest net sees survivors only, gathered by a semi join on ids."""
    deep = deep or max(engine.nets, key=lambda n: n.values)
    classes = F.broadcast(engine.means(("full",)).where(F.col("dataset") == dataset).select("classes"))
    rows = engine.prepared("full")
    quick = rows.crossJoin(classes).select("raster_id", stage(F.col("x"), F.col("classes"), values, first).alias("s")).select("raster_id", "s.*")
    passed = F.round("margin", 9) < threshold
    survivors = rows.join(quick.where(passed).select("raster_id"), "raster_id", "left_semi")
    slow = survivors.crossJoin(classes).select("raster_id", Engine.nearest(F.col("x"), F.col("classes"), deep.values)[0]["label"].alias("guess"), F.lit(2).alias("stage"))
    return quick.where(~passed).select("raster_id", "guess", F.lit(1).alias("stage")).unionByName(slow)
