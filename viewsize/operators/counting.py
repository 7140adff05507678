"""Bitmap and register sketches: Probabilistic Counting, LogLog, Adaptive Counting, linear counting, the maximum-level counter.

State builders take hashed rows (view_id, seed, y); their aggregates combine on the map side, so at most M rows for each view and task
are shuffled. Finishers give one row for each (view_id, seed)."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import MIN_LONG

PHI = 0.77351
SWITCH = 0.051
KEYS = ("view_id", "seed")


def log2_exact(M: int) -> int:
    if M < 2 or M & (M - 1):
        raise ValueError(f"M must be a power of two from 2 on, not {M}")
    return M.bit_length() - 1


def _trailing_zeros(w: Column) -> Column:
    """Of a non-negative long; 64 for 0."""
    return F.bit_count(w.bitwiseAND(-w) - F.lit(1).cast("bigint"))


def bucket_rank(y: Column, M: int, L: int, bit_order: str = "low") -> tuple[Column, Column]:
    """(bucket, rank): the bucket from the low (or high) bits, the rank the position, from 1, of the first 1-bit of the others; all zero: one past the last."""
    k = log2_exact(M)
    if bit_order == "low":
        bucket, rest = y.bitwiseAND(F.lit(M - 1).cast("bigint")), F.shiftrightunsigned(y, k)
    else:
        bucket, rest = F.shiftrightunsigned(y, L - k), y.bitwiseAND(F.lit((1 << (L - k)) - 1).cast("bigint"))
    return bucket, F.least(_trailing_zeros(rest), F.lit(L - k)) + 1


def level(y: Column, L: int) -> Column:
    """Position, from 0, of the first 1-bit of the whole hash; L for 0."""
    lone = F.when((y == 0) | (y == F.lit(MIN_LONG)), F.lit(1).cast("bigint")).otherwise(y)  # neither can be negated or decremented safely
    return F.when(y == 0, F.lit(L)).when(y == F.lit(MIN_LONG), F.lit(63)).otherwise(_trailing_zeros(lone))


def pc_state(rows: DataFrame, M: int, L: int, bit_order: str = "low") -> DataFrame:
    """(view_id, seed, bucket, bits) of the touched buckets."""
    bucket, rank = bucket_rank(F.col("y"), M, L, bit_order)
    return rows.select(*KEYS, bucket.alias("bucket"), F.call_function("shiftleft", F.lit(1).cast("bigint"), (rank - 1).cast("int")).alias("bit")).groupBy(*KEYS, "bucket").agg(F.bit_or("bit").alias("bits"))


def ll_state(rows: DataFrame, M: int, L: int, bit_order: str = "low") -> DataFrame:
    """(view_id, seed, bucket, reg) of the touched buckets."""
    bucket, rank = bucket_rank(F.col("y"), M, L, bit_order)
    return rows.select(*KEYS, bucket.alias("bucket"), rank.alias("rank")).groupBy(*KEYS, "bucket").agg(F.max("rank").alias("reg"))


def pc_merge(*states: DataFrame) -> DataFrame:
    return _union(states).groupBy(*KEYS, "bucket").agg(F.bit_or("bits").alias("bits"))


def ll_merge(*states: DataFrame) -> DataFrame:
    return _union(states).groupBy(*KEYS, "bucket").agg(F.max("reg").alias("reg"))


def _union(states) -> DataFrame:
    out = states[0]
    for s in states[1:]:
        out = out.unionByName(s)
    return out


def first_zero(bits: Column) -> Column:
    """Position, from 0, of the first 0-bit of a long; 64 if there is none."""
    inverse = F.bitwise_not(bits)
    safe = F.when(inverse == F.lit(MIN_LONG), F.lit(0).cast("bigint")).otherwise(inverse)
    return F.when(inverse == F.lit(MIN_LONG), F.lit(63)).otherwise(_trailing_zeros(safe))


def _linear(beta: Column, M: int) -> Column:
    return F.when(beta > 0, -F.lit(float(M)) * F.ln(beta / F.lit(float(M))))


def alpha(M: int) -> float:
    return 0.39701 - (2 * math.pi**2 + math.log(2) ** 2) / (48 * M)


def pc_estimate(state: DataFrame, M: int, switch: float | None = None) -> DataFrame:
    """(view_id, seed, a, beta, branch, estimate). ``switch``: small views, by their share of empty buckets, get the linear count."""
    agg = state.groupBy(*KEYS).agg(F.sum(first_zero(F.col("bits"))).cast("bigint").alias("a"), (F.lit(M) - F.count("*")).alias("beta"))
    pc = F.lit(M / PHI) * F.pow(F.lit(2.0), F.col("a") / F.lit(float(M)))
    small = F.lit(False) if switch is None else F.col("beta") / F.lit(float(M)) >= F.lit(switch)
    return agg.select(*KEYS, "a", "beta", F.when(small, "linear").otherwise("counting").alias("branch"), F.when(small, _linear(F.col("beta"), M)).otherwise(pc).alias("estimate"))


def _registers(state: DataFrame, M: int) -> DataFrame:
    return state.groupBy(*KEYS).agg(F.sum("reg").cast("bigint").alias("a"), (F.lit(M) - F.count("*")).alias("beta"))


def _loglog(M: int) -> Column:
    return F.lit(alpha(M) * M) * F.pow(F.lit(2.0), F.col("a") / F.lit(float(M)))


def ll_estimate(state: DataFrame, M: int) -> DataFrame:
    return _registers(state, M).select(*KEYS, "a", "beta", F.lit("loglog").alias("branch"), _loglog(M).alias("estimate"))


def ac_estimate(state: DataFrame, M: int, switch: float = SWITCH) -> DataFrame:
    """LogLog, or the linear count where at least ``switch`` of the registers are unused."""
    small = F.col("beta") / F.lit(float(M)) >= F.lit(switch)
    return _registers(state, M).select(*KEYS, "a", "beta", F.when(small, "linear").otherwise("loglog").alias("branch"), F.when(small, _linear(F.col("beta"), M)).otherwise(_loglog(M)).alias("estimate"))


def linear_estimate(state: DataFrame, M: int) -> DataFrame:
    """Linear counting alone; null where no register is empty."""
    return _registers(state, M).select(*KEYS, "a", "beta", F.lit("linear").alias("branch"), _linear(F.col("beta"), M).alias("estimate"))


def max_level_state(rows: DataFrame, L: int) -> DataFrame:
    return rows.groupBy(*KEYS).agg(F.max(level(F.col("y"), L)).alias("top"))


def max_level_estimate(state: DataFrame) -> DataFrame:
    return state.select(*KEYS, F.col("top").cast("bigint").alias("a"), F.lit(None).cast("bigint").alias("beta"), F.lit("level").alias("branch"), F.pow(F.lit(2.0), F.col("top")).alias("estimate"))
