"""The multifractal estimator: four numbers of a row sample, a fitted skew, an extrapolation to all facts.

Corrected form: a cell of probability q is hit by n draws with chance 1 - (1 - q)^n, and the fitted bias is kept for the extrapolation. The
forms that differ are switches, for ablations."""

from __future__ import annotations

import functools
import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import HashSpec, dim_hash, tuple_key, unsigned
from ..plans.views import ViewSpec
from ..session import ship


def sample_rows(df: DataFrame, ratio: float, seed: int, sampler: str = "bernoulli", row_key: list[str] | None = None) -> DataFrame:
    """'bernoulli': Spark's sample. 'hash': rows whose keyed hash of ``row_key`` (default: all columns) is below the ratio; the same rows in any engine and
    order, repeated rows together. 'exact': floor(ratio * n) rows by that hash (one more pass to count)."""
    if sampler == "bernoulli":
        return df.sample(False, ratio, seed)
    spec = HashSpec(L=32, mode="md5", mix="none", seed=seed)
    own = row_key or df.columns
    text = F.concat_ws("|", *[F.coalesce(F.col(c).cast("string"), F.lit("~")) for c in own])
    h = unsigned(dim_hash("row", text, spec), 32)
    if sampler == "hash":
        return df.where(h < F.lit(ratio * 2**32))
    if sampler != "exact":
        raise ValueError(f"unknown sampler {sampler}")
    total = df.count()
    n = math.floor(ratio * total)
    if not n:
        return df.limit(0)
    if n == total:
        return df
    # The n least hashes without a sort of all rows: a bound on the hash that surely leaves n, then the exact value of the n-th one among those.
    near = min(1.0, (n + 10 * math.sqrt(n) + 10) / total)
    rows = df.withColumn("sample_order", h)
    below = rows.where(F.col("sample_order") < near * 2**32) if near < 1 else rows
    counts = below.groupBy(F.floor(F.col("sample_order") / F.lit(2.0**12)).alias("b")).agg(F.count("*").alias("c"))
    if counts.agg(F.sum("c")).first()[0] < n:
        below, counts = rows, rows.groupBy(F.floor(F.col("sample_order") / F.lit(2.0**12)).alias("b")).agg(F.count("*").alias("c"))
    upto = counts.withColumn("upto", F.sum("c").over(Window.orderBy("b")))  # at most 2^20 bins
    last = upto.where(F.col("upto") >= n).orderBy("b").first()
    edge, missing = F.lit(float(last["b"]) * 2**12), n - (last["upto"] - last["c"])
    sure = below.where(F.col("sample_order") < edge)
    tied = below.where((F.col("sample_order") >= edge) & (F.col("sample_order") < edge + 2**12)).orderBy("sample_order", *own).limit(missing)  # one bin
    return sure.union(tied).drop("sample_order")


def mf_sample_stats(df: DataFrame, view: ViewSpec, ratio: float, seed: int = 0, sampler: str = "bernoulli", row_key: list[str] | None = None) -> DataFrame:
    """(view_id, ratio, seed, n_total, n_sample, f0, m_max): all the model needs."""
    df = df.where(view.where) if view.where else df
    plain = ViewSpec(view.name, view.dims, view.table)
    groups = plain.bind(sample_rows(df, ratio, seed, sampler, row_key)).groupBy(*view.names).agg(F.count("*").alias("c"))
    stats = groups.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n_sample"), F.count("*").alias("f0"), F.max("c").alias("m_max"))
    total = df.agg(F.count("*").alias("n_total"))
    return stats.crossJoin(total).select(F.lit(view.name).alias("view_id"), F.lit(float(ratio)).alias("ratio"), F.lit(seed).alias("seed"), "n_total", "n_sample", "f0", "m_max")


def mf_many(df: DataFrame, views: list[ViewSpec], ratios: list[float], n_seeds: int, row_key: list[str]) -> DataFrame:
    """mf_sample_stats() of many views, ratios and seeds with the 'hash' sampler in one scan: a fact takes part for the seeds that draw it, its row is kept for
    the ratios above its hash, and only then are views made of it. A sample that is empty gives zeros (m_max null)."""
    spec = HashSpec(L=32, mode="md5", mix="none", seed="seed")
    text = F.concat_ws("|", *[F.coalesce(F.col(c).cast("string"), F.lit("~")) for c in row_key])
    names = list(dict.fromkeys(n for v in views for n in v.names))
    raw = {n: c for v in views for n, c in v.raw().items()}
    seeds = F.explode(F.sequence(F.lit(0), F.lit(n_seeds - 1))).alias("seed")
    drawn = df.select(*[raw[n].alias(n) for n in names], text.alias("row"), seeds).withColumn("u", unsigned(dim_hash("row", F.col("row"), spec), 32) / F.lit(2.0**32)).where(F.col("u") < max(ratios))
    drawn = drawn.select("*", F.explode(F.filter(F.array(*[F.lit(float(r)) for r in ratios]), lambda r: F.col("u") < r)).alias("ratio"))
    own = F.explode(F.array(*[F.struct(F.lit(v.name).alias("view_id"), tuple_key({n: F.col(n) for n in v.names}).alias("key")) for v in views])).alias("x")
    groups = drawn.select("seed", "ratio", own).groupBy("x.view_id", "ratio", "seed", "x.key").agg(F.count("*").alias("c"))
    stats = groups.groupBy("view_id", "ratio", "seed").agg(F.sum("c").alias("n_sample"), F.count("*").alias("f0"), F.max("c").alias("m_max"))
    grid = df.sparkSession.createDataFrame([(v.name, float(r), k) for v in views for r in ratios for k in range(n_seeds)], "view_id string, ratio double, seed int")
    total = df.agg(F.count("*").alias("n_total"))
    zero = lambda c: F.coalesce(c, F.lit(0).cast("bigint")).alias(c)
    return grid.join(stats, ["view_id", "ratio", "seed"], "left").crossJoin(total).select("view_id", "ratio", "seed", "n_total", zero("n_sample"), zero("f0"), "m_max")


@functools.cache
def _log_factorials_to(n: int) -> np.ndarray:
    return np.array([math.lgamma(i + 1) for i in range(n + 1)])


def _log_factorials(k: int) -> np.ndarray:
    return _log_factorials_to(max(1023, k))


def occupied(k: int, bias: float, n: float, summand: str = "occupancy") -> float:
    """Expected number of hit cells of a k-fold binomial cascade after n draws, summed in logarithms."""
    a = np.arange(k + 1)
    log_c = _log_factorials(k)[k] - _log_factorials(k)[a] - _log_factorials(k)[k - a]
    with np.errstate(divide="ignore"):
        log_q = (k - a) * np.log(bias) + (a * np.log1p(-bias) if bias < 1 else np.where(a == 0, 0.0, -np.inf))
    if summand == "occupancy":
        q = np.exp(log_q)
        with np.errstate(divide="ignore"):
            hit = -np.expm1(n * np.log1p(-np.minimum(q, 1.0)))
    else:
        hit = -np.expm1(n * log_q)
    with np.errstate(divide="ignore", over="ignore"):
        return float(np.exp(np.minimum(700.0, log_c + np.log(hit))).sum())


def mf_fit(f0: int, n_sample: int, m_max: int, n_total: int, k_max: int = 512, bias: str = "sample", summand: str = "occupancy", fit: str = "first") -> dict:
    """k, bias, converged and estimate. fit='first': the least k whose expected sample size reaches f0; 'nearest': that or the k before it, whichever
    comes closer. bias='printed': taken anew from all facts before the extrapolation."""
    if not f0 or not n_sample:
        return {"k": None, "bias": None, "converged": False, "estimate": None}
    if f0 == 1:
        return {"k": 0, "bias": 1.0, "converged": True, "estimate": 1.0}
    top = m_max / n_sample
    k = max(1, math.ceil(math.log2(f0)))
    start, before = k, None
    while True:
        p = top ** (1.0 / k)
        f = occupied(k, p, n_sample, summand)
        if f >= f0 or k >= k_max:
            break
        before, k = f, k + 1
    converged = f >= f0
    if fit == "nearest" and converged:
        if before is None and start > 1:
            before = occupied(start - 1, top ** (1.0 / (start - 1)), n_sample, summand)
        if before is not None and f0 - before < f - f0 and k > 1:
            k -= 1
            p = top ** (1.0 / k)
    if bias == "printed":
        p = (m_max / n_total) ** (1.0 / k)
    return {"k": k, "bias": p, "converged": converged, "estimate": occupied(k, p, n_total, summand)}


def mf_from_stats(stats: DataFrame, **how) -> DataFrame:
    """stats rows with k, bias, converged and estimate added; fitted where they are, by a pandas function over batches of such small rows."""
    ship(stats.sparkSession)

    @F.pandas_udf("k int, bias double, converged boolean, estimate double")
    def fit(f0: pd.Series, n_sample: pd.Series, m_max: pd.Series, n_total: pd.Series) -> pd.DataFrame:
        rows = [mf_fit(int(a), int(b), int(c) if c == c and c is not None else 0, int(d), **how) for a, b, c, d in zip(f0, n_sample, m_max, n_total)]
        return pd.DataFrame(rows, columns=["k", "bias", "converged", "estimate"]).astype({"k": "Int32", "bias": "float64", "estimate": "float64"})

    return stats.withColumn("fit", fit("f0", "n_sample", F.coalesce("m_max", F.lit(0)), "n_total")).select(*stats.columns, "fit.*")


def mf_estimate(df: DataFrame, view: ViewSpec, ratio: float, seed: int = 0, sampler: str = "bernoulli", **how) -> DataFrame:
    return mf_from_stats(mf_sample_stats(df, view, ratio, seed, sampler), **how)
