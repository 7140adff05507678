"""Stored states: Parquet partitioned by method and view, with what they were made with; states made differently aren't merged."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import HashSpec
from ..operators import bottomk, counting, levels


def meta(method: str, M: int, spec: HashSpec, dims: list[str]) -> str:
    return json.dumps({"method": method, "M": M, "L": spec.L, "mode": spec.mode, "mix": spec.mix, "seed": spec.seed, "dims": dims}, sort_keys=True)


def save(state: DataFrame, path: str, method: str, M: int, spec: HashSpec, dims: list[str], mode: str = "append") -> None:
    out = state.withColumns({"method": F.lit(method), "meta": F.lit(meta(method, M, spec, dims))})
    out.write.mode(mode).partitionBy("method", "view_id").parquet(path)


def load(spark: SparkSession, path: str, method: str, view_id: str) -> tuple[DataFrame, dict]:
    """The state of a view and how it was made; ValueError if the store holds states of that view that were made in different ways."""
    df = spark.read.parquet(path).where((F.col("method") == method) & (F.col("view_id") == view_id))
    found = [r["meta"] for r in df.select("meta").distinct().limit(2).collect()]
    if len(found) != 1:
        raise ValueError(f"{len(found) or 'no'} kinds of state for {method} of {view_id}")
    return df.drop("meta", "method"), json.loads(found[0])


def merge(method: str, metas: list[dict], *states: DataFrame) -> DataFrame:
    """One state of several; refused if M, L, hash or dimensions differ."""
    if any(m != metas[0] for m in metas[1:]):
        raise ValueError("states that were made differently can't be merged")
    M = metas[0]["M"]
    if method in ("pc", "pc_guarded"):
        return counting.pc_merge(*states)
    if method in ("ll", "ac", "linear"):
        return counting.ll_merge(*states)
    if method.startswith("gc"):
        return bottomk.gc_merge(*states, M=M)
    if method == "lps":
        return levels.lps_merge(*states, M=M)
    raise ValueError(f"{method} has no stored state")
