"""Baselines: the uniformity assumption and Spark's own sketches."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.views import ViewSpec


def occupancy_estimate(df: DataFrame, view: ViewSpec, exact_cardinalities: bool = True, form: str = "stable") -> DataFrame:
    """(view_id, volume, facts, estimate): expected occupied cells if the facts fell uniformly into the product of the dimensions. form: 'stable', or 'plain',
    v (1 - exp(f ln(1 - 1 / v))) term by term as other engines write it, which loses digits as the volume grows."""
    if form not in ("stable", "plain"):
        raise ValueError(f"unknown form {form}")
    bound = view.bind(df)
    count = (lambda n: F.count_distinct(n) + F.max(F.col(n).isNull().cast("int"))) if exact_cardinalities else F.approx_count_distinct
    agg = bound.agg(F.count("*").alias("facts"), *[count(n).alias(f"c_{n}") for n in view.names])
    volume = F.lit(1.0)
    for n in view.names:
        volume = volume * F.col(f"c_{n}")
    volume_ = volume.cast("double")
    stable = -volume_ * F.expm1(F.col("facts") * F.log1p(F.lit(-1.0) / volume_))
    plain = volume_ * (F.lit(1.0) - F.exp(F.col("facts") * F.ln(F.lit(1.0) - F.lit(1.0) / volume_)))
    return agg.select(F.lit(view.name).alias("view_id"), volume_.alias("volume"), "facts", (stable if form == "stable" else plain).alias("estimate"))


def builtin_estimate(df: DataFrame, view: ViewSpec, sketch: str = "hllpp", rsd: float = 0.05, lgk: int = 12) -> DataFrame:
    """(view_id, method, estimate) by approx_count_distinct ('hllpp'), an HLL sketch ('hll') or a theta sketch ('theta')."""
    from ..functions.hashing import tuple_key

    key = tuple_key({n: F.col(n) for n in view.names})
    agg = {
        "hllpp": lambda: F.approx_count_distinct(key, rsd),
        "hll": lambda: F.hll_sketch_estimate(F.hll_sketch_agg(key, lgk)),
        "theta": lambda: F.theta_sketch_estimate(F.theta_sketch_agg(key, lgk)),
    }[sketch]()
    return view.bind(df).agg(agg.cast("double").alias("estimate")).select(F.lit(view.name).alias("view_id"), F.lit(sketch).alias("method"), "estimate")
