"""Level-pruned sampling: the distinct tuples whose hash has at least ``floor`` trailing zeros, floor the least that leaves M at most.

The floor needs no loop: it is read off the level histogram. Plans as for Generalized Counting."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import ship
from . import counting, partial

KEYS = counting.KEYS


def _leveled(rows: DataFrame, L: int) -> DataFrame:
    return rows.select("view_id", "seed", counting.level(F.col("y"), L).cast("bigint").alias("h"), "key")


def floors(sample: DataFrame, M: int) -> DataFrame:
    """(view_id, seed, level_floor) from rows (view_id, seed, h, key) of distinct tuples with their levels: one past the highest level whose tail exceeds M."""
    histogram = sample.groupBy(*KEYS, "h").agg(F.count("*").alias("c"))
    tail = F.sum("c").over(Window.partitionBy(*KEYS).orderBy(F.desc("h")))  # at most L + 1 rows a view
    over = histogram.withColumn("tail", tail).groupBy(*KEYS).agg(F.max(F.when(F.col("tail") > M, F.col("h"))).alias("top"))
    return over.select(*KEYS, F.coalesce(F.col("top") + 1, F.lit(0)).cast("int").alias("level_floor"))


def _prune(sample: DataFrame, M: int, least: DataFrame | None = None) -> DataFrame:
    """``least``: (view_id, seed, least) below which the sample holds nothing."""
    floor = floors(sample, M)
    if least is not None:
        floor = floor.join(least, list(KEYS)).select(*KEYS, F.greatest("level_floor", "least").alias("level_floor"))
    kept = sample.join(F.broadcast(floor), list(KEYS))  # one row a view and seed
    return kept.select("view_id", "seed", "key", F.when(F.col("h") >= F.col("level_floor"), F.col("h")).cast("int").alias("level"), "level_floor").where("level is not null")


def lower_floors(rows: DataFrame, M: int, L: int) -> DataFrame:
    """(view_id, seed, least): the floor can't be below ``least``. The buckets, 4M by high bits, that hold a level of f or more are no more
    than the distinct tuples that have one; where they exceed M, the floor is higher than f. The highest level of each bucket is all that is kept."""
    buckets = 1 << (4 * M - 1).bit_length()
    bucket = F.shiftrightunsigned("y", L - buckets.bit_length() + 1)
    top = rows.select(*KEYS, bucket.alias("bucket"), counting.level(F.col("y"), L).cast("bigint").alias("h")).groupBy(*KEYS, "bucket").agg(F.max("h").alias("h"))
    return floors(top, M).withColumnRenamed("level_floor", "least")


def lps_state(rows: DataFrame, M: int, L: int, plan: str = "threshold", some: DataFrame | None = None) -> DataFrame:
    """rows (view_id, seed, y, key) -> (view_id, seed, key, level, level_floor). ``some``: a part of the rows for the first pass of ``threshold``. What a part holds the whole
    holds too, so its floors are lower bounds as well; views that it lacks get none. The state is made of all rows in any case."""
    if M < 1:
        raise ValueError("M must be positive")
    if plan == "native":
        return _prune(_leveled(rows, L).distinct(), M)
    if plan == "partial":
        ship(rows.sparkSession)
        return lps_merge(_leveled(rows, L).mapInArrow(partial.leveled(M), partial.LEVELED_SCHEMA), M=M)
    if plan != "threshold":
        raise ValueError(f"unknown plan {plan}")
    least = lower_floors(rows if some is None else some, M, L)
    if some is None:
        high = rows.join(F.broadcast(least), list(KEYS)).where(counting.level(F.col("y"), L) >= F.col("least"))
        return _prune(_leveled(high.drop("least"), L).distinct(), M, least)
    high = rows.join(F.broadcast(least), list(KEYS), "left").where(counting.level(F.col("y"), L) >= F.coalesce("least", F.lit(0)))
    kept = high.select("view_id", "seed", counting.level(F.col("y"), L).cast("bigint").alias("h"), "key", F.coalesce("least", F.lit(0)).alias("least")).distinct()
    return _prune(kept.drop("least"), M, kept.groupBy(*KEYS).agg(F.max("least").alias("least")))


def lps_merge(*states: DataFrame, M: int) -> DataFrame:
    """Exact: a part's floor never exceeds the floor of the whole, so what a part pruned is pruned anyway."""
    rows = counting._union(states)
    highest = rows.groupBy(*KEYS).agg(F.max("level_floor").alias("f"))
    own = rows.join(F.broadcast(highest), list(KEYS)).where("level >= f and key is not null").select("view_id", "seed", F.col("level").cast("bigint").alias("h"), "key", "f").distinct()
    floor = floors(own, M).join(highest, list(KEYS)).select(*KEYS, F.greatest("level_floor", "f").alias("level_floor"))
    return own.drop("f").join(F.broadcast(floor), list(KEYS)).where("h >= level_floor").select("view_id", "seed", "key", F.col("h").cast("int").alias("level"), "level_floor")


def lps_estimate(state: DataFrame, M: int | None = None) -> DataFrame:
    """(view_id, seed, level_floor, kept, branch, estimate): 2^floor times the kept tuples; floor 0 is an exact count."""
    agg = state.groupBy(*KEYS).agg(F.max("level_floor").alias("level_floor"), F.count("*").alias("kept"))
    return lps_scaled(agg)


def lps_scaled(agg: DataFrame) -> DataFrame:
    """lps_estimate() of (view_id, seed, level_floor, kept)."""
    return agg.select(*KEYS, "level_floor", "kept", F.when(F.col("level_floor") == 0, "exact").otherwise("scaled").alias("branch"), (F.pow(F.lit(2.0), F.col("level_floor")) * F.col("kept")).alias("estimate"))
