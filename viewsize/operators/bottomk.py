"""Generalized Counting: the M smallest hashes with their tuples.

Three plans give the same state. ``threshold`` (the default) first reads an upper bound of the M-th smallest hash off a register pass and makes and
compares the tuples of hashes within it alone; ``native`` removes duplicates and cuts by rank; ``partial`` lets each task keep M rows over Arrow first."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import order_key, unsigned
from ..session import ship
from . import counting, partial

KEYS = counting.KEYS


def _cut(rows: DataFrame, M: int) -> DataFrame:
    by = Window.partitionBy(*KEYS).orderBy("h", "key")
    return rows.withColumn("r", F.row_number().over(by)).where(F.col("r") <= M).drop("r")


def _keyed(rows: DataFrame, L: int, key: str) -> DataFrame:
    tuple_ = F.col("key") if key == "tuple" else F.lit(0).cast("bigint")
    return rows.select("view_id", "seed", order_key(F.col("y"), L).alias("h"), tuple_.alias("key"))


def upper_bounds(rows: DataFrame, M: int, L: int) -> DataFrame:
    """(view_id, seed, bound): at least M distinct hashes of the view are at most ``bound``; views without a row here may keep everything.

    The least hash of each of 4M buckets (by low bits) is a distinct hash of the view, so the M-th smallest of these can't be below the M-th smallest of all;
    about 1.15 M hashes are within it. One aggregate with map-side combine, at most 8M rows for each view and task."""
    buckets = 1 << (4 * M - 1).bit_length()
    least = rows.select(*KEYS, F.col("y").bitwiseAND(F.lit(buckets - 1).cast("bigint")).alias("bucket"), order_key(F.col("y"), L).alias("h")).groupBy(*KEYS, "bucket").agg(F.min("h").alias("h"))
    by = Window.partitionBy(*KEYS).orderBy("h")
    return least.withColumn("r", F.row_number().over(by)).where(F.col("r") == M).select(*KEYS, F.col("h").alias("bound"))


def gc_state(rows: DataFrame, M: int, L: int, plan: str = "threshold", key: str = "tuple") -> DataFrame:
    """rows (view_id, seed, y, key) -> (view_id, seed, h, key), h in the hash's unsigned order. key='hash': tuples of equal hash count once."""
    if M < 1:
        raise ValueError("M must be positive")
    if plan == "native":
        return _cut(_keyed(rows, L, key).distinct(), M)
    if plan == "partial":
        ship(rows.sparkSession)
        return _cut(_keyed(rows, L, key).mapInArrow(partial.bottom(M), partial.SCHEMA).distinct(), M)
    if plan != "threshold":
        raise ValueError(f"unknown plan {plan}")
    low = rows.join(F.broadcast(upper_bounds(rows, M, L)), list(KEYS), "left").where(F.col("bound").isNull() | (order_key(F.col("y"), L) <= F.col("bound")))
    return _cut(_keyed(low.drop("bound"), L, key).distinct(), M)  # one row a view and seed is broadcast


def gc_merge(*states: DataFrame, M: int) -> DataFrame:
    """Exact: a globally small element is small in every part that has it."""
    return _cut(counting._union(states).distinct(), M)


def gc_estimate(state: DataFrame, M: int, L: int, exact_when_small: bool = True) -> DataFrame:
    """(view_id, seed, kept, top, branch, estimate): 2^L * kept / largest hash; a state that isn't full is an exact count if so asked."""
    return gc_scaled(state.groupBy(*KEYS).agg(F.count("*").alias("kept"), F.max("h").alias("h")), M, L, exact_when_small)


def gc_scaled(agg: DataFrame, M: int, L: int, exact_when_small: bool = True) -> DataFrame:
    """gc_estimate() of (view_id, seed, kept, h), h the largest hash that is kept."""
    y = order_key(F.col("h"), L)
    top = unsigned(y, L)
    ratio = F.when(top > 0, F.lit(float(2**L)) * F.col("kept") / top).otherwise(F.col("kept").cast("double"))
    small = (F.col("kept") < M) if exact_when_small else F.lit(False)
    return agg.select(*KEYS, "kept", y.alias("top"), F.when(small, "exact").otherwise("ratio").alias("branch"), F.when(small, F.col("kept").cast("double")).otherwise(ratio).alias("estimate"))
