"""Iceberg views (HAVING count >= s): exact, and from level-pruned survivors with their counts. An extension."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import HashSpec
from ..plans.views import ViewSpec, hashed
from . import counting, levels


def exact(df: DataFrame, view: ViewSpec, min_count: int) -> DataFrame:
    groups = view.bind(df).groupBy(*view.names).agg(F.count("*").alias("c")).where(F.col("c") >= min_count)
    return groups.agg(F.count("*").alias("exact")).select(F.lit(view.name).alias("view_id"), F.lit(min_count).alias("min_count"), "exact")


def lps_estimate(df: DataFrame, view: ViewSpec, min_count: int, M: int, spec: HashSpec) -> DataFrame:
    """(view_id, min_count, level_floor, kept, estimate). The kept tuples are a uniform sample of the distinct ones and their counts are complete,
    so 2^floor times those that are frequent enough estimates the iceberg view."""
    rows = hashed(df, view, spec, key=True).select("view_id", "seed", counting.level(F.col("y"), spec.L).cast("bigint").alias("h"), "key")
    counted = rows.groupBy("view_id", "seed", "h", "key").agg(F.count("*").alias("c"))
    kept = counted.join(F.broadcast(levels.floors(counted, M)), ["view_id", "seed"]).where("h >= level_floor")
    agg = kept.groupBy("view_id").agg(F.max("level_floor").alias("level_floor"), F.count_if(F.col("c") >= min_count).alias("kept"))
    return agg.select("view_id", F.lit(min_count).alias("min_count"), "level_floor", "kept", (F.pow(F.lit(2.0), F.col("level_floor")) * F.col("kept")).alias("estimate"))
