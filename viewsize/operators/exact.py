"""Exact view sizes, the ground truth."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.views import ViewSpec, tuples


def view_size(df: DataFrame, view: ViewSpec) -> DataFrame:
    """(view_id, exact). Tuples with nulls count, as in GROUP BY."""
    return tuples(df, view).agg(F.count("*").alias("exact")).select(F.lit(view.name).alias("view_id"), "exact")


def view_sizes(df: DataFrame, views: list[ViewSpec]) -> DataFrame:
    """(view_id, exact) of several views in one scan, by grouping sets."""
    names = list(dict.fromkeys(n for v in views for n in v.names))
    raw = {n: c for v in views for n, c in v.raw().items()}
    src = df.select(*[raw[n].alias(n) for n in names])
    at = {n: F.col(n) for n in names}
    grouped = src.groupingSets([[at[n] for n in v.names] for v in views], *at.values()).agg(F.grouping_id().alias("gid"))
    sizes = grouped.groupBy("gid").agg(F.count("*").alias("exact"))
    bit = {n: 1 << (len(names) - 1 - i) for i, n in enumerate(names)}
    ids = [(v.name, sum(b for n, b in bit.items() if n not in v.names)) for v in views]
    table = df.sparkSession.createDataFrame(ids, "view_id string, gid long")
    return table.join(sizes, "gid", "left").select("view_id", F.coalesce("exact", F.lit(0)).alias("exact"))


def lattice_sizes(df: DataFrame, dims: list[str], how: str = "cube") -> DataFrame:
    """(dims_mask, exact) for all 2^d views of the dimensions ('cube') or their prefixes ('rollup'); bit i of the mask is set if dims[i] is grouped by."""
    grouped = (df.cube if how == "cube" else df.rollup)(*dims).agg(F.grouping_id().alias("gid"))
    d = len(dims)
    mask = sum((F.shiftright(F.col("gid"), d - 1 - i).bitwiseAND(F.lit(1)).bitwiseXOR(F.lit(1)) * (1 << i) for i in range(d)), F.lit(0))
    return grouped.groupBy("gid").agg(F.count("*").alias("exact")).select(mask.cast("long").alias("dims_mask"), "exact")
