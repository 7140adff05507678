"""Exact top-k by inner product with a pivot-distance index.

One more component, sqrt(M - |x|^2) with M the largest squared norm, puts all candidates on a sphere; a query gets a zero there, and the
order of inner products is then the order of distances. A candidate is keyed by its nearest pivot and its distance from it; each
pivot's distances are cut into annuli, so that an annulus, with its exact least and greatest distance, bounds how near its
members can come to any query by the triangle inequality. Each query first expands the annuli nearest to it, which sets
a floor under its k-th score, and then just those others whose bound still reaches the floor.

Pivots (at most ``pivots``) come from a bounded sample (``sample`` rows), the index holds every row. The driver sees pivots and annuli
only, both bounded by parameters. A crowded annulus, even one of equal vectors, is dealt by id hash into blocks of about ``block``
candidates, and queries come in blocks too, so no task holds more than one block of either.
"""

from __future__ import annotations

import math
import sys

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import ship
from .common import settle

_EXACT = 2.0**53
#: Above this, components are shrunk by a power of two wherever squares are summed.
_LARGE = 2.0**400
_LONGEST, _LOWEST = 2**63 - 1, -(2**63)


def prepare(rows: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 256) -> DataFrame:
    """(vec_id, v) with v the components floor(scale * x) as doubles, which hold them exactly, of the rows that take part: with an id and a vector without null or
    non-finite components. A product beyond the largest double counts as that."""
    x = F.col(vector_col).cast("array<double>")
    sound = F.col(id_col).isNotNull() & x.isNotNull() & F.forall(x, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < F.lit(float("inf"))))

    def whole(c):
        y, most = c * F.lit(float(scale)), sys.float_info.max
        return F.when(F.abs(y) < F.lit(_EXACT), F.floor(y).cast("double")).otherwise(F.greatest(F.lit(-most), F.least(F.lit(most), y)))

    return rows.where(sound).select(F.col(id_col).cast("long").alias("vec_id"), F.transform(x, whole).alias("v"))


def _matrix(column: pa.Array | pa.ChunkedArray, dims: int) -> np.ndarray:
    """Lists of numbers as rows of float64, shorter ones padded with zeros."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        column = column.chunk(0) if isinstance(column, pa.ChunkedArray) else column
    lengths = np.diff(column.offsets.to_numpy())
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    if len(lengths) and (lengths == dims).all():
        return flat.reshape(len(lengths), dims)
    out = np.zeros((len(lengths), dims))
    at = np.concatenate([[0], np.cumsum(lengths)])
    for i, n in enumerate(lengths):
        out[i, :n] = flat[at[i] : at[i + 1]]
    return out


def _lift(x: np.ndarray, top: float) -> np.ndarray:
    return np.hstack([x, np.sqrt(np.maximum(0.0, top - (x * x).sum(axis=1)))[:, None]])


def _distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum(0.0, (a * a).sum(axis=1)[:, None] + (b * b).sum(axis=1)[None] - 2 * a @ b.T))


def choose_pivots(x: np.ndarray, n: int) -> np.ndarray:
    """n rows, each the farthest from those before it, the first the farthest from the mean."""
    if not len(x):
        return x
    far = ((x - x.mean(axis=0)) ** 2).sum(axis=1)
    out = []
    for _ in range(min(n, len(x))):
        i = int(far.argmax())
        if out and far[i] <= 0:
            break
        d = ((x - x[i]) ** 2).sum(axis=1)
        far = d if not out else np.minimum(far, d)
        out.append(i)
    return x[out]


class Index:
    """Pivots, annuli and bounds, as the tasks need them."""

    def __init__(self, dims: int, top: float, pivots: np.ndarray, shrink: float = 1.0):
        """top: the largest squared norm, and pivots, of components times ``shrink``."""
        self.dims, self.top, self.pivots, self.shrink = dims, top, pivots, shrink
        self.cuts: dict[int, np.ndarray] = {}
        self.cells = np.zeros((0, 4))  # number, pivot, least and greatest distance
        self.per = 64

    def key(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        d = _distances(_lift(x * self.shrink, self.top), self.pivots)
        p = d.argmin(axis=1)
        return p, d[np.arange(len(x)), p]

    def ceilings(self, q: np.ndarray) -> np.ndarray:
        """The highest score that each query (row) may meet in each cell (column)."""
        q = q * self.shrink
        flat = np.hstack([q, np.zeros((len(q), 1))])
        d = _distances(flat, self.pivots)[:, self.cells[:, 1].astype(int)]
        gap = np.maximum(0.0, np.maximum(d - self.cells[:, 3], self.cells[:, 2] - d))
        square = (q * q).sum(axis=1)[:, None] + self.top
        with np.errstate(over="ignore"):
            return ((square - gap * gap) / 2 + 1e-9 * square) / self.shrink / self.shrink + 1.0  # with room for rounding


def _best(q: np.ndarray, qid: np.ndarray, x: np.ndarray, ids: np.ndarray, k: int, floor: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query position, id, score) of each query's k best candidates that reach its floor, ties to smaller ids."""
    size = float(np.abs(q).max(initial=0)) * float(np.abs(x).max(initial=0)) * q.shape[1]
    if not size < 2.0**62:
        return _best_large(q, qid, x, ids, k, floor)
    s = (q @ x.T).astype(np.int64) if size < _EXACT else q.astype(np.int64) @ x.astype(np.int64).T
    order = np.argsort(ids, kind="stable")
    s, ids = s[:, order], ids[order]
    at, out, scores = [], [], []
    for i in range(len(q)):
        own = np.flatnonzero((s[i] >= floor[i]) & (ids != qid[i]))
        if len(own) > k:
            cut = np.partition(s[i, own], len(own) - k)[len(own) - k]
            own = own[s[i, own] >= cut]
        own = own[np.argsort(-s[i, own], kind="stable")][:k]
        at += [i] * len(own)
        out += ids[own].tolist()
        scores += s[i, own].tolist()
    return np.array(at, np.int64), np.array(out, np.int64), np.array(scores, np.int64)


def _best_large(q: np.ndarray, qid: np.ndarray, x: np.ndarray, ids: np.ndarray, k: int, floor: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """_best() where products may exceed 63 bits: scores in floating point with their errors leave few candidates, whose exact scores end at the limits of a long."""
    a, b = (math.frexp(float(np.abs(m).max(initial=0)))[1] for m in (q, x))
    qs, xs = np.ldexp(q, -a), np.ldexp(x, -b)
    about, error = qs @ xs.T, q.shape[1] * 2.0**-50 * (np.abs(qs) @ np.abs(xs).T) + 1e-290
    limit = math.ldexp(1.0, max(-1074, 63 - a - b))
    low, high = np.clip(about - error, -limit, limit), np.clip(about + error, -limit, limit)
    whole = lambda row: [int(c) for c in row.tolist()]
    xi: dict[int, list[int]] = {}
    at, out, scores = [], [], []
    for i in range(len(q)):
        own = np.flatnonzero(ids != qid[i])
        if len(own) > k:
            own = own[high[i, own] >= np.partition(low[i, own], len(own) - k)[len(own) - k]]
        own_q, found = whole(q[i]), []
        for j in own.tolist():
            if j not in xi:
                xi[j] = whole(x[j])
            s = max(_LOWEST, min(_LONGEST, sum(c * d for c, d in zip(own_q, xi[j]))))
            if s >= floor[i]:
                found.append((-s, int(ids[j])))
        for s, j in sorted(found)[:k]:
            at.append(i)
            out.append(j)
            scores.append(-s)
    return np.array(at, np.int64), np.array(out, np.int64), np.array(scores, np.int64)


def _search(blocks: DataFrame, asked: DataFrame, cells: DataFrame, dims: int, k: int) -> DataFrame:
    """blocks (cell, part, vec_id, v), asked (cell, batch, n, query_id, v, floor), cells (cell, parts) -> (n, query_id, vec_id, score)."""
    asked = asked.join(F.broadcast(cells), "cell").select("cell", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), "batch", "n", "query_id", "v", "floor")
    batches = settle(asked, "asked")
    wanted = batches.select("cell", "part", F.col("batch").alias("lot")).distinct()

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        names = ["n", "query_id", "vec_id", "score"]
        if not left.num_rows or not right.num_rows:
            return pa.table({c: pa.array([], pa.int64()) for c in names})
        qid = right.column("query_id").to_numpy()
        at, ids, scores = _best(_matrix(right.column("v"), dims), qid, _matrix(left.column("v"), dims), left.column("vec_id").to_numpy(), k, right.column("floor").to_numpy())
        return pa.table({"n": right.column("n").to_numpy()[at], "query_id": qid[at], "vec_id": ids, "score": scores})

    held = blocks.join(wanted, ["cell", "part"]).groupBy("cell", "part", "lot")
    return held.cogroup(batches.groupBy("cell", "part", "batch")).applyInArrow(run, "n long, query_id long, vec_id long, score long")


def top_k(rows: DataFrame, queries: DataFrame, k: int = 5, pivots: int = 64, sample: int = 4096, annuli: int = 64, block: int = 2048, first: int = 4, seed: int = 3) -> DataFrame:
    """rows and queries (vec_id, v), as prepare() makes them -> (query_id, rank, vec_id, score): each query's k highest inner products among the
    rows with another id, ties to smaller ids; all if there are fewer. Rows that share the query's id are its own. Repeated candidates count each,
    repeated queries answer each; vectors of different lengths are padded with zeros; no rows or no queries give no rows. Scores are exact; those beyond the
    limits of a long count as the limit, and tie."""
    spark = rows.sparkSession
    ship(spark)
    rows, queries = settle(rows.select("vec_id", "v"), "vectors"), settle(queries.select("vec_id", "v", F.monotonically_increasing_id().alias("n")), "queries")
    big = F.coalesce(F.max(F.array_max(F.transform("v", F.abs))), F.lit(0.0)).alias("big")

    def norms(shrink: float):
        return F.max(F.aggregate(F.transform("v", lambda c: c * F.lit(shrink)), F.lit(0.0), lambda s, c: s + c * c)).alias("top")

    about = rows.agg(F.count("*").alias("n"), big, F.max(F.size("v")).alias("dims"), norms(1.0)).first()
    longest = queries.agg(F.max(F.size("v")).alias("dims"), F.count("*").alias("n"), big).first()
    schema = "query_id long, rank int, vec_id long, score long"
    if not about["n"] or not longest["n"]:
        return spark.createDataFrame([], schema)
    dims, largest = max(about["dims"], longest["dims"]), max(about["big"], longest["big"])
    shrink = 1.0 if largest <= _LARGE else math.ldexp(1.0, 400 - math.frexp(largest)[1])
    top = float(about["top"] if shrink == 1.0 else rows.agg(norms(shrink)).first()["top"])
    few = rows.withColumn("o", F.xxhash64(F.lit(seed), "vec_id")).orderBy("o", "vec_id").limit(sample).select("v").collect()
    picked = shrink * np.array([list(r["v"]) + [0] * (dims - len(r["v"])) for r in few], np.float64).reshape(len(few), dims)
    index = Index(dims, top, choose_pivots(_lift(picked, top), max(1, min(pivots, int(about["n"] ** 0.5 / 8)))), shrink)
    keyed = spark.sparkContext.broadcast(index)

    def place(batches):
        ix = keyed.value
        for b in batches:
            p, d = ix.key(_matrix(b.column("v"), ix.dims))
            yield pa.RecordBatch.from_arrays([b.column("vec_id"), b.column("v"), pa.array(p.astype(np.int32)), pa.array(d)], names=["vec_id", "v", "pivot", "dist"])

    placed = settle(rows.select("vec_id", "v").mapInArrow(place, "vec_id long, v array<double>, pivot int, dist double"), "placed")
    shares = [i / annuli for i in range(1, annuli)]
    cuts = placed.groupBy("pivot").agg(F.percentile_approx("dist", shares, 1000).alias("cuts"), F.count("*").alias("c"))
    rings = []  # one row a pivot
    for r in cuts.collect():
        want = max(1, min(annuli, r["c"] // block))
        rings.append((r["pivot"], [r["cuts"][i * annuli // want - 1] for i in range(1, want)]))
    ring = F.broadcast(spark.createDataFrame(rings, "pivot int, cuts array<double>"))
    celled = placed.join(ring, "pivot").select("vec_id", "v", "pivot", "dist", (F.col("pivot") * annuli + F.size(F.filter("cuts", lambda c: c < F.col("dist")))).alias("cell"))
    cells = celled.groupBy("cell", "pivot").agg(F.min("dist").alias("lo"), F.max("dist").alias("hi"), F.count("*").alias("c")).orderBy("cell").collect()
    index.cells = np.array([(r["cell"], r["pivot"], r["lo"], r["hi"]) for r in cells], np.float64)
    parts = spark.createDataFrame([(r["cell"], -(-r["c"] // block)) for r in cells], "cell int, parts int")
    blocks = settle(celled.join(F.broadcast(parts), "cell").select("cell", F.pmod(F.xxhash64("vec_id", F.lit(5)), F.col("parts").cast("long")).cast("int").alias("part"), "vec_id", "v"), "blocks")
    shared = spark.sparkContext.broadcast(index)
    spread = F.pmod(F.xxhash64("n"), F.lit(-(-longest["n"] // block))).cast("int").alias("batch")

    def expand(start: bool):
        def run(batches):
            ix = shared.value
            for b in batches:
                ceil = ix.ceilings(_matrix(b.column("v"), ix.dims))
                nearest = np.argsort(-ceil, axis=1, kind="stable")
                floor = b.column("floor").to_numpy()
                for i in range(b.num_rows):
                    near = nearest[i, :first] if start else nearest[i, first:][ceil[i, nearest[i, first:]] >= floor[i]]
                    if len(near):
                        one = b.slice(i, 1).take(pa.array(np.zeros(len(near), np.int64)))
                        yield pa.RecordBatch.from_arrays([pa.array(ix.cells[near, 0].astype(np.int32)), *one.columns], names=["cell", *one.schema.names])

        return run

    out = "cell int, batch int, n long, query_id long, v array<double>, floor long"
    asked = queries.select(spread, "n", F.col("vec_id").alias("query_id"), "v")
    found = settle(_search(blocks, asked.withColumn("floor", F.lit(_LOWEST)).mapInArrow(expand(True), out), parts, dims, k), "first")
    by_query = Window.partitionBy("n").orderBy(F.desc("score"), "vec_id")
    floors = found.withColumn("r", F.row_number().over(by_query)).where(F.col("r") == k).select("n", F.col("score").alias("floor"))
    rest = asked.join(floors, "n", "left").select("batch", "n", "query_id", "v", F.coalesce("floor", F.lit(_LOWEST)).alias("floor"))
    more = _search(blocks, rest.mapInArrow(expand(False), out), parts, dims, k)
    ranked = found.union(more).withColumn("rank", F.row_number().over(by_query)).where(F.col("rank") <= k)
    return ranked.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
