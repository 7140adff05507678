"""Greedy choice of views to materialise, from exact or estimated sizes. An extension; at most 2^d rows of sizes take part."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def smallest(sizes: DataFrame, k: int, by: str = "estimate") -> DataFrame:
    return sizes.orderBy(by, "view_id").limit(k)


def greedy(sizes: DataFrame, d: int, k: int, size: str = "exact") -> DataFrame:
    """sizes (dims_mask, <size>) of a lattice over d dimensions -> (step, dims_mask, benefit) of k views besides the full one. A view answers every view whose
    dimensions it has; the benefit of a choice is what it saves in rows read over all views."""
    if d > 20:
        raise ValueError("the lattice of more than 20 dimensions isn't enumerated")
    rows = {r["dims_mask"]: float(r[size]) for r in sizes.select("dims_mask", size).collect()}
    top = (1 << d) - 1
    cost = {v: rows[top] for v in rows}
    picks, chosen = [], {top}
    for step in range(1, k + 1):
        best = None
        for c in sorted(rows):
            if c not in chosen:
                gain = sum(max(0.0, cost[v] - rows[c]) for v in rows if v & c == v)
                if best is None or gain > best[1]:
                    best = (c, gain)
        if best is None:
            break
        chosen.add(best[0])
        picks.append((step, best[0], best[1]))
        for v in rows:
            if v & best[0] == v:
                cost[v] = min(cost[v], rows[best[0]])
    return sizes.sparkSession.createDataFrame(picks, "step int, dims_mask long, benefit double")


def answered_by(views: DataFrame) -> DataFrame:
    """(view_id, by): which views can answer which, by containment of their masks (a theta join over at most 2^d rows)."""
    a, b = views.select("view_id", "dims_mask"), views.select(F.col("view_id").alias("by"), F.col("dims_mask").alias("by_mask"))
    return a.join(b, F.col("dims_mask").bitwiseAND(F.col("by_mask")) == F.col("dims_mask")).where("view_id <> by").select("view_id", "by")
