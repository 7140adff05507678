"""Connected components of an edge table, by alternating large-star and small-star steps.

Every step is a min-aggregate (combined map-side) and one equi-join, so a vertex that touches a third of all edges is
aggregated before it is shuffled, and its side of the join is one that adaptive execution may split. Nothing goes to the
driver but two numbers a round. Edges that one task holds need no rounds: it joins them in memory, and the driver plans one step.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import settle, ship


#: Edges to a task; steps over few edges run in few tasks, whatever the session's number of shuffle partitions.
EDGES_A_TASK = 100_000


def _large(edges: DataFrame, tasks: int) -> DataFrame:
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    moved = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
    return moved.coalesce(tasks).distinct().coalesce(tasks)


def _small(edges: DataFrame, tasks: int) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    moved = down.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).where("u <> v").coalesce(tasks).distinct().coalesce(tasks)


def _in_one_task(batches):
    """Edges (u, v) to (node, root): trees of nodes whose roots are the least."""
    up: dict = {}

    def root(x):
        while (y := up[x]) != x:
            up[x] = x = up[y]
        return x

    kind = None
    for batch in batches:
        kind = batch.column(0).type
        for u, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            up.setdefault(u, u)
            up.setdefault(v, v)
            a, b = root(u), root(v)
            if a != b:
                up[max(a, b)] = min(a, b)
    if kind is not None:
        yield pa.RecordBatch.from_arrays([pa.array(up, kind), pa.array(map(root, up), kind)], names=["node", "root"])


def connected_components(edges: DataFrame) -> DataFrame:
    """(u, v) of any ordered type -> (node, root), root the least node of the component. Loops, repeated edges and nulls
    are ignored; nodes without an edge do not appear; no edges give no rows. Ends when a round leaves the edges as they were."""
    now = settle(edges.select("u", "v").where("u <> v").distinct(), "edges")
    kind = now.schema["u"].dataType
    if isinstance(kind, T.IntegralType) and now.count() <= EDGES_A_TASK:
        ship(now.sparkSession)
        return now.coalesce(1).mapInArrow(_in_one_task, T.StructType([T.StructField("node", kind), T.StructField("root", kind)]))
    seen = None
    while True:
        mark = now.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        tasks = -(-mark["n"] // EDGES_A_TASK) or 1
        if (mark["n"], mark["h"]) == seen or mark["n"] == 0:
            both = now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(now.select(F.col("v").alias("node"), F.col("v").alias("root")))
            return both.coalesce(tasks).distinct().coalesce(tasks)
        seen = (mark["n"], mark["h"])
        now = settle(_small(_large(now.coalesce(tasks), tasks), tasks), "edges")
