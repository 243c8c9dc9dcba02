"""Candidates, estimates, Pareto sets and choices.  Plan tables are small (hundreds of rows): one window each."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window as W, functions as F

from ..functions import cost

#: Plan tables larger than this aren't plan tables; the windows below have no partition key.
PLAN_ROWS = 100_000


def candidates(models: DataFrame, formats: DataFrame, compat: str | None = None) -> DataFrame:
    """Models x formats; compat='resolution' keeps pairs whose weights were trained for the format's resolution."""
    pairs = F.broadcast(models).crossJoin(formats)
    return pairs.where("train_side = short_side") if compat == "resolution" else pairs


def expand(plans: DataFrame, ops: Sequence[str], host_only: int = 1) -> DataFrame:
    """Each plan with every split point: ops up to `split` run on the host, the first `host_only` always."""
    return plans.withColumn("split", F.explode(F.sequence(F.lit(host_only), F.lit(len(ops))))).withColumn("host_ops", F.slice(F.array(*map(F.lit, ops)), 1, F.col("split")))


def estimate(plans: DataFrame, estimator: str = "pipelined", pre: str = "pre", ex: str = "exec", overhead: float = 0.0) -> DataFrame:
    f = cost.ESTIMATORS[estimator]
    value = f(F.col(pre), F.col(ex), overhead) if estimator == "pipelined" else f(F.col(pre), F.col(ex))
    return plans.withColumn("est_tput", value)


def frontier(plans: DataFrame, acc: str = "acc", tput: str = "est_tput", by: Sequence[str] = ()) -> DataFrame:
    """Plans that no other dominates (both axes rounded to 6 decimals first; equal plans stay): one sweep by falling accuracy."""
    a, t = F.round(F.col(acc), 6), F.round(F.col(tput), 6)
    strictly = W.partitionBy(*by).orderBy((-a)).rangeBetween(W.unboundedPreceding, W.currentRow)
    equal = W.partitionBy(*by, a)
    best_here = F.max(t).over(equal)
    best_upto = F.max(t).over(strictly)
    # of at least equal accuracy none is faster, and of greater accuracy none is as fast
    greater = F.max(F.struct(t.alias("t"), a.alias("a"))).over(strictly)
    return plans.withColumn("_keep", (t == best_here) & (t == best_upto) & (greater["a"] <= a)).where("_keep").drop("_keep")


def frontier_bruteforce(plans: DataFrame, acc: str = "acc", tput: str = "est_tput", by: Sequence[str] = ()) -> DataFrame:
    """The same by comparing every two plans."""
    a, b = plans.alias("a"), plans.alias("b")
    r = lambda t, c: F.round(F.col(f"{t}.{c}"), 6)
    dominated = (r("b", acc) >= r("a", acc)) & (r("b", tput) >= r("a", tput)) & ((r("b", acc) > r("a", acc)) | (r("b", tput) > r("a", tput)))
    for c in by:
        dominated = dominated & F.col(f"a.{c}").eqNullSafe(F.col(f"b.{c}"))
    return a.join(b, dominated, "left_anti")


def choose(plans: DataFrame, metric: str, resource: str | None = None, bound: float | None = None, sense: str = "ge", tie: Sequence[str] = ("plan_id",), by: Sequence[str] = (), on_infeasible: str = "empty") -> DataFrame:
    """The plan with the largest metric whose resource is within the bound (None: of all plans).

    on_infeasible: 'empty', 'raise', or 'closest' (the plan whose resource is nearest to the bound).
    """
    fits = plans
    if bound is not None and resource is not None:
        fits = plans.where(F.col(resource) >= bound if sense == "ge" else F.col(resource) <= bound)
        if on_infeasible != "empty" and fits.isEmpty():
            if on_infeasible == "raise":
                raise ValueError(f"no plan has {resource} {'>=' if sense == 'ge' else '<='} {bound}")
            order = W.partitionBy(*by).orderBy(F.abs(F.col(resource) - bound), *tie)
            return plans.withColumn("_n", F.row_number().over(order)).where("_n = 1").drop("_n")
    order = W.partitionBy(*by).orderBy(F.desc(metric), *tie)
    return fits.withColumn("_n", F.row_number().over(order)).where("_n = 1").drop("_n")


def matched_model(plans: DataFrame, pre: str = "pre", ex: str = "exec", acc: str = "acc") -> DataFrame:
    """For each format the most accurate model at least as fast as preparation; if none is, the fastest, flagged."""
    enough = F.col(ex) >= F.col(pre)
    order = W.partitionBy("format_id").orderBy(F.desc(enough), F.when(enough, -F.col(acc)).otherwise(-F.col(ex)), "model_id")
    return plans.withColumn("_n", F.row_number().over(order)).where("_n = 1").drop("_n").withColumn("exec_bound", ~enough)


def hypervolume(front: DataFrame, acc: str = "acc", tput: str = "est_tput", by: Sequence[str] = ()) -> DataFrame:
    """Area under the frontier's steps, from the origin."""
    w = W.partitionBy(*by).orderBy(F.desc(acc), F.desc(tput))
    below = F.coalesce(F.max(tput).over(w.rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0))
    steps = front.withColumn("_a", F.greatest(F.lit(0.0), F.col(tput) - below) * F.col(acc))
    return steps.groupBy(*by).agg(F.sum("_a").alias("hypervolume"))
