"""Accuracy and cost measures over a table of runs (view_id, method, M, L, seed, estimate, exact, ...)."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

BY = ("view_id", "method", "M", "L")


def accuracy(runs: DataFrame) -> DataFrame:
    """(..., exact, n_runs, rse, bias, p95_rel_err): the standard error is the deviation from the truth, not from the mean."""
    rel = F.abs(F.col("estimate") - F.col("exact")) / F.col("exact")
    return runs.where("estimate is not null").groupBy(*BY).agg(
        F.max("exact").alias("exact"), F.count("*").cast("int").alias("n_runs"),
        (F.sqrt(F.avg(F.pow(F.col("estimate") - F.col("exact"), 2.0))) / F.max("exact")).alias("rse"),
        (F.avg("estimate") / F.max("exact") - 1).alias("bias"), F.percentile(rel, 0.95).alias("p95_rel_err"),
    )


def errors(runs: DataFrame) -> DataFrame:
    """The relative error of each run."""
    return runs.withColumn("rel_err", F.abs(F.col("estimate") - F.col("exact")) / F.col("exact"))


def reliability(runs: DataFrame, eps: float) -> DataFrame:
    """(..., within): the share of runs with a relative error of eps at most."""
    return errors(runs).groupBy(*BY).agg(F.avg((F.col("rel_err") <= eps).cast("double")).alias("within"))


def slope(acc: DataFrame) -> DataFrame:
    """(view_id, method, L, slope, corr) of the logarithm of the standard error on that of M; -1/2 is the theory."""
    logs = acc.where("rse > 0").select("view_id", "method", "L", F.log2("rse").alias("e"), F.log2("M").alias("m"))
    return logs.groupBy("view_id", "method", "L").agg(F.regr_slope("e", "m").alias("slope"), F.corr("e", "m").alias("corr"))


def step_gain(acc: DataFrame) -> DataFrame:
    """The standard error beside that of the next smaller M."""
    return acc.withColumn("rse_before", F.lag("rse").over(Window.partitionBy("view_id", "method", "L").orderBy("M")))


def pivot(acc: DataFrame, ms: list[int]) -> DataFrame:
    """A row for each view and method, a column of percent for each M."""
    return acc.groupBy("view_id", "method", "exact").pivot("M", ms).agg(F.round(F.first("rse") * 100, 4))


def state_bytes(method: str, M: int, L: int, key_bytes: int = 0) -> float:
    """Bytes of a full state in the compact form: bit matrix, counters, or hashes (and levels) with tuples."""
    if method == "pc":
        return M * L / 8
    if method in ("ll", "ac", "linear"):
        return M * math.ceil(math.log2(L - int(math.log2(M)) + 2)) / 8
    if method == "gc":
        return M * (L / 8 + key_bytes)
    if method == "lps":
        return M * (1 + key_bytes)
    if method == "maxlevel":
        return 1.0
    raise ValueError(method)


def lookup_bytes(cardinalities: list[int], L: int) -> float:
    return sum(cardinalities) * L / 8
