"""Cost measures as column functions: throughput of cascades, end-to-end estimates, price, power and regimes."""

from __future__ import annotations

from pyspark.sql import Column, functions as F


def cascade_exec(stages: Column, reach: str = "arriving") -> Column:
    """Rate of a chain of models from array<struct<rate, share>>.

    arriving: share is the part of all inputs that reaches a stage (1 for the first).
    literal: share is what a stage forwards; the reaching part is the product of those before it.
    """
    if reach == "arriving":
        return 1 / F.aggregate(stages, F.lit(0.0), lambda a, s: a + s["share"] / s["rate"])
    start = F.struct(F.lit(0.0).alias("t"), F.lit(1.0).alias("r"))
    return 1 / F.aggregate(stages, start, lambda a, s: F.struct((a["t"] + a["r"] / s["rate"]).alias("t"), (a["r"] * s["share"]).alias("r")))["t"]


def est_exec_only(pre: Column, ex: Column) -> Column:
    return ex


def est_additive(pre: Column, ex: Column) -> Column:
    return 1 / (1 / pre + 1 / ex)


def est_pipelined(pre: Column, ex: Column, overhead: float = 0.0) -> Column:
    return F.least(pre, ex) * (1 - overhead)


ESTIMATORS = {"pipelined": est_pipelined, "additive": est_additive, "exec_only": est_exec_only}


def true_pre(pre1: Column, pre2: Column, share: Column) -> Column:
    """Preparation rate when a share of the inputs is prepared again for the next model."""
    return 1 / (1 / pre1 + share / pre2)


def rel_error(estimate: Column, measured: Column) -> Column:
    return F.abs(estimate - measured) / measured


def regime(pre: Column, ex: Column, tolerance: float = 0.25) -> Column:
    gap = F.abs(pre - ex) / F.greatest(pre, ex)
    return F.when(gap <= tolerance, "balanced").when(pre < ex, "pre_bound").otherwise("exec_bound")


def effective_floor(bound: Column, pre: Column) -> Column:
    """A floor on throughput above the preparation rate buys nothing."""
    return F.least(bound, pre)


def sensitivity(pre: Column, ex: Column, d_exec: Column, d_pre: Column) -> Column:
    return F.least(pre * d_pre, ex * d_exec) / F.least(pre, ex)


def cents_per_million(price_hour: Column, tput: Column) -> Column:
    return price_hour * F.lit(1e8) / (F.lit(3600.0) * tput)


def match_cores(ex: Column, pre: Column, cores: float = 4.0) -> Column:
    """Cores whose preparation keeps up with the model, from the rate of `cores` of them."""
    return ex / (pre / F.lit(cores))


def cores_saved(before: Column, after: Column, cores: Column) -> Column:
    return cores - cores * before / after


def latency(batch: Column, pre: Column, ex: Column) -> Column:
    return batch / pre + batch / ex
