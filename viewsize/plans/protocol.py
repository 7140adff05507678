"""The test protocol: query x memory x seed, with logs and timings."""

from __future__ import annotations

import math
import time
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from ..functions import md5
from ..functions.hashing import MIN_LONG, HashSpec, order_key
from ..operators import bottomk, counting, levels, multi
from ..session import settle, ship
from .views import ViewSpec, hashed, tuples

_KEYED = ("gc", "gc_printed", "lps")
_BITMAPS = ("pc", "pc_guarded", "ll", "ac", "linear")


def seeded(df: DataFrame, n_seeds: int) -> DataFrame:
    return df.withColumn("seed", F.explode(F.sequence(F.lit(0), F.lit(n_seeds - 1))))


#: Registers and samples of so many entries are handled for several seeds at once.
ENTRIES = 1 << 21


def run(df: DataFrame, views: list[ViewSpec], methods: list[str], ms: list[int], n_seeds: int = 20, spec: HashSpec = HashSpec(), plan: str = "threshold") -> DataFrame:
    """runs (view_id, method, M, L, seed, estimate, branch, diag, exact). All sketches depend on the set of tuples alone, so the facts are grouped once for a
    view, which also gives the exact size, and the tuples are written to the scratch folder, without hashes. One pass over them for all seeds then makes
    the state from which every method and M follows, by _whole_state(). Plans other than ``threshold`` build each method's own state from the hashed tuples."""
    states, sizes, seeds = None, [], list(range(n_seeds))
    for view in views:
        own = settle(tuples(df, view), "tuples")
        n = own.count()
        sizes.append((view.name, n))
        if plan == "threshold":
            one = _whole_state(own, view, methods, ms, seeds, spec, n)
        else:
            one = hashed(seeded(own, n_seeds), view, spec.with_seed("seed"), key=any(m in _KEYED for m in methods), bound=True)
        states = one if states is None else states.unionByName(one)
    out = None
    for method in methods:
        if plan == "threshold":
            one = reduce(DataFrame.unionByName, [_from_state(states, method, M, _top(methods, ms), spec.L) for M in ms])
        else:
            one = multi.finish_many(states if method in _KEYED else states.drop("key"), method, ms, spec.L, plan)
        out = one if out is None else out.unionByName(one)
    exact = df.sparkSession.createDataFrame(sizes, "view_id string, exact long")
    return out.join(F.broadcast(exact), "view_id").select(*out.columns, "exact")  # one row a view


def _top(methods: list[str], ms: list[int]) -> int:
    return max(ms) if any(m in _BITMAPS for m in methods) else 2


def _bound(M: int, n: int, L: int, margin: float) -> int | None:
    """A hash, in signed order, within which about M + margin sqrt(M) + 20 of n hashes are; none if that is all of them."""
    part = M + margin * math.sqrt(M) + 20
    return None if part >= n else int(part / n * 2**L) - (2**63 if L == 64 else 0)


#: A task's counts of buckets and ranks, for each seed; with more, each hash is a row.
COUNTS = 1 << 17
#: Tuples that are hashed at once.
_AT_ONCE = 32_768
_PARTIAL = "seed int, bucket long, first int, h long, c long, bits long"


def _counter(names: list[str], seeds: list[int], spec: HashSpec, top: int, limit: int | None, sampled: bool):
    """Distinct tuples to rows of a state, combined within a task: those of _whole_state(), by the same formulas, in numpy."""
    k, L = counting.log2_exact(top), spec.L
    width = L - k + 2  # ranks from 1

    def rows(seed, bucket, first, h, c, bits) -> pa.RecordBatch:
        n = len(bucket)
        no = pa.nulls(n, pa.int64()) if h is None else pa.array(h)
        cols = [pa.array(np.full(n, seed, np.int32)), pa.array(bucket), pa.array(first.astype(np.int32), mask=bucket != 0), no, pa.array(c), pa.array(bits.view(np.int64))]
        return pa.RecordBatch.from_arrays(cols, names=["seed", "bucket", "first", "h", "c", "bits"])

    def run(batches):
        hashes, held = md5.TupleHash(names, seeds, L, spec.mix), {}

        def dims(table: pa.Table) -> list:
            for col in table.columns:
                col = col.combine_chunks()
                yield col.to_pylist() if pa.types.is_string(col.type) else (col.fill_null(0).to_numpy(), col.is_null().to_numpy(zero_copy_only=False))

        def state(table: pa.Table):
            for seed, y in hashes.each(list(dims(table))):
                bucket, rest = y & np.int64(top - 1), y.view(np.uint64) >> np.uint64(k)
                zeros = np.bitwise_count((rest & (np.uint64(0) - rest)) - np.uint64(1))
                rank = np.minimum(zeros.astype(np.int64), L - k) + 1
                h = y ^ np.int64(MIN_LONG) if L == 64 else y
                low = np.full(len(y), sampled) if limit is None else (h <= limit) & sampled
                if top * width > COUNTS:
                    whole = np.ones(len(y), np.int64)
                    bits = np.uint64(1) << (rank - 1).astype(np.uint64)
                    for part, hs in ((low, h), (~low, None)):
                        if part.any():
                            yield rows(seed, bucket[part], rank[part], None if hs is None else hs[part], whole[part], bits[part])
                    continue
                if low.any():
                    yield rows(seed, bucket[low], rank[low], h[low], np.ones(low.sum(), np.int64), np.uint64(1) << (rank[low] - 1).astype(np.uint64))
                    bucket, rank = bucket[~low], rank[~low]
                found = np.bincount(bucket * width + rank, minlength=top * width)
                held[seed] = held[seed] + found if seed in held else found

        wait, n = [], 0
        for batch in batches:
            wait.append(batch)
            n += batch.num_rows
            if n >= _AT_ONCE:
                yield from state(pa.Table.from_batches(wait))
                wait, n = [], 0
        if n:
            yield from state(pa.Table.from_batches(wait))
        for seed, found in held.items():
            found = found.reshape(top, width)
            first = np.flatnonzero(found[0])
            bits = np.where(found > 0, np.uint64(1) << np.maximum(np.arange(width) - 1, 0).astype(np.uint64), np.uint64(0))
            yield rows(seed, np.zeros(len(first), np.int64), first, None, found[0, first], bits[0, first])
            other = np.flatnonzero(found[1:].any(axis=1)) + 1
            yield rows(seed, other, np.zeros(len(other), np.int64), None, found[other].sum(axis=1), np.bitwise_or.reduce(bits[other], axis=1))

    return run


def _whole_state(own: DataFrame, view: ViewSpec, methods: list[str], ms: list[int], seeds: list[int], spec: HashSpec, n: int) -> DataFrame:
    """(view_id, seed, bucket, first, h, c, bits) of distinct tuples, n of them: one row for each bucket of the largest M, for each rank in bucket 0, and for each hash
    h that the smallest M may hold; c counts tuples, bits has their ranks. The limit for h follows from n. It is checked, and widened until every seed has M hashes."""
    top, need, margin = _top(methods, ms), min(max(ms), n), 6.0
    sampled = [m for m in methods if m.startswith("gc")]
    many = max(1, ENTRIES // max(ms))
    chunks = [seeds[i : i + many] for i in range(0, len(seeds), many)]
    in_python = spec.mode == "md5"  # whose hashes cost far more than the way to Python and back
    if in_python:
        ship(own.sparkSession)
        kinds = dict(own.dtypes)
        texts = own.select(*[F.col(f"`{n}`").cast("long" if kinds[n] == "bigint" else "string").alias(f"d{i}") for i, n in enumerate(view.names)])
    if len(chunks) > 1 and not in_python:  # tasks so large that their buckets fill
        own = own.coalesce(own.sparkSession.sparkContext.defaultParallelism)
    while True:
        limit = _bound(max(ms), n, spec.L, margin)
        parts = []
        for chunk in chunks if not in_python or top * (spec.L - counting.log2_exact(top) + 2) > COUNTS else [seeds]:
            if in_python:
                some = texts.mapInArrow(_counter(view.names, chunk, spec, top, limit, bool(sampled)), _PARTIAL)
                parts.append(some.groupBy("seed", "bucket", "first", "h").agg(F.sum("c").alias("c"), F.bit_or("bits").alias("bits")).select(F.lit(view.name).alias("view_id"), "*"))
                continue
            rows = hashed(own.withColumn("seed", F.explode(F.array(*map(F.lit, chunk)))), view, spec.with_seed("seed"), bound=True)
            bucket, rank = counting.bucket_rank(F.col("y"), top, spec.L)
            h = order_key(F.col("y"), spec.L)
            low = (h if limit is None else F.when(h <= F.lit(limit), h)) if sampled else F.lit(None).cast("bigint")
            rows = rows.select("view_id", "seed", bucket.alias("bucket"), F.when(bucket == 0, rank).cast("int").alias("first"), low.alias("h"), F.call_function("shiftleft", F.lit(1).cast("bigint"), (rank - 1).cast("int")).alias("bit"))
            parts.append(rows.groupBy("view_id", "seed", "bucket", "first", "h").agg(F.count("*").alias("c"), F.bit_or("bit").alias("bits")))
        state = settle(reduce(DataFrame.unionByName, parts), "state")
        if not sampled or limit is None:
            return state
        held = F.count("*") if "gc_hashkey" in sampled else F.sum("c")
        if state.where("h is not null").groupBy("seed").agg(held.alias("held")).where(F.col("held") >= need).count() == len(seeds):
            return state
        margin = 4 * margin + 16


def _from_state(states: DataFrame, method: str, M: int, top: int, L: int) -> DataFrame:
    """The rows of multi.finish() from states of _whole_state() with ``top`` buckets."""
    keys, k = list(counting.KEYS), counting.log2_exact(top)
    if method in _BITMAPS:
        lost = k - counting.log2_exact(M)
        higher = F.shiftright("bucket", k - lost)  # these bits of the bucket are the first of the rest of the hash, for M buckets
        bits = F.when(higher > 0, higher.bitwiseAND(-higher)).otherwise(F.shiftleft("bits", lost)) if lost else F.col("bits")
        own = states.select(*keys, F.col("bucket").bitwiseAND(F.lit(M - 1).cast("bigint")).alias("bucket"), bits.alias("bits")).groupBy(*keys, "bucket").agg(F.bit_or("bits").alias("bits"))
        if method in ("pc", "pc_guarded"):
            est = counting.pc_estimate(own, M, counting.SWITCH if method == "pc_guarded" else None)
        else:
            est = getattr(counting, f"{method}_estimate")(own.select(*keys, "bucket", F.length(F.bin("bits")).alias("reg")), M)
        return multi._diag(est, method, M, L, a="a", beta="beta")
    level = F.when(F.col("bucket") == 0, k + F.col("first") - 1).otherwise(counting.level(F.col("bucket"), L))
    if method == "maxlevel":
        return multi._diag(counting.max_level_estimate(states.groupBy(*keys).agg(F.max(level).alias("top"))), method, M, L, a="a")
    if method == "lps":
        histogram = states.select(*keys, level.cast("int").alias("level"), "c").groupBy(*keys, "level").agg(F.sum("c").alias("c"))
        tails = histogram.withColumn("tail", F.sum("c").over(Window.partitionBy(*keys).orderBy(F.desc("level"))))  # at most L + 1 rows a view and seed
        floor = tails.groupBy(*keys).agg((F.coalesce(F.max(F.when(F.col("tail") > M, F.col("level"))) + 1, F.lit(0))).cast("int").alias("level_floor"))
        kept = tails.join(F.broadcast(floor), keys).groupBy(*keys).agg(F.max("level_floor").alias("level_floor"), F.coalesce(F.sum(F.when(F.col("level") >= F.col("level_floor"), F.col("c"))), F.lit(0)).alias("kept"))
        return multi._diag(levels.lps_scaled(kept.where("kept > 0")), method, M, L, floor="level_floor", kept="kept")
    own = states.where("h is not null").groupBy(*keys, "h").agg(F.lit(1).cast("bigint").alias("c") if method == "gc_hashkey" else F.sum("c").alias("c"))
    before = own.withColumn("before", F.sum("c").over(Window.partitionBy(*keys).orderBy("h")) - F.col("c")).where(F.col("before") < M)
    agg = before.groupBy(*keys).agg(F.least(F.lit(M).cast("bigint"), F.max(F.col("before") + F.col("c"))).alias("kept"), F.max("h").alias("h"))
    return multi._diag(bottomk.gc_scaled(agg, M, L, method != "gc_printed"), method, M, L, kept="kept", top="top")


def run_generated(df: DataFrame, view: ViewSpec, exact: int, methods: list[str], ms: list[int], n_seeds: int, spec: HashSpec = HashSpec()) -> DataFrame:
    """run() of one view whose tuples are distinct already and so many: nothing is grouped or written, every pass hashes them anew."""
    out = None
    for method in methods:
        rows = hashed(seeded(view.bind(df), n_seeds), view, spec.with_seed("seed"), key=method in _KEYED, bound=True)
        one = multi.finish_many(rows, method, ms, spec.L)
        out = one if out is None else out.unionByName(one)
    return out.withColumn("exact", F.lit(exact).cast("bigint"))


def append_log(runs: DataFrame, path: str) -> None:
    runs.write.mode("append").parquet(path)


def read_log(spark, path: str) -> DataFrame:
    """The runs, each beside the latest exact count logged before it for its view, where the log has a time ``at``."""
    return spark.read.parquet(path)


def as_of_exact(runs: DataFrame, exacts: DataFrame) -> DataFrame:
    """runs (view_id, at, ...) joined with the latest of exacts (view_id, at, exact) that isn't later."""
    r = runs.withColumn("run_no", F.monotonically_increasing_id())
    met = r.join(exacts.select(F.col("view_id").alias("v2"), F.col("at").alias("exact_at"), "exact"), (F.col("view_id") == F.col("v2")) & (F.col("exact_at") <= F.col("at")), "left")
    by = Window.partitionBy("run_no").orderBy(F.desc("exact_at"))
    return met.withColumn("r", F.row_number().over(by)).where("r = 1").drop("r", "v2", "run_no")


def _timed(df: DataFrame) -> float:
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def phase_times(df: DataFrame, view: ViewSpec, method: str, M: int, spec: HashSpec = HashSpec()) -> dict[str, float]:
    """Seconds of three nested jobs, as differences: loading (all dimensions of every fact consumed), hashing, counting. For 'mf': sampling and estimating."""
    if method == "mf":
        from ..operators import multifractal

        sample = _timed(multifractal.sample_rows(view.bind(df), 0.005, 0))
        total = _timed(multifractal.mf_estimate(df, view, 0.005))
        return {"sample_s": sample, "count_s": max(0.0, total - sample), "total_s": total}
    bound = view.bind(df)
    load = _timed(bound)
    key = method in _KEYED
    hashed_s = _timed(hashed(df, view, spec, key=key))
    total = _timed(multi.finish(hashed(df, view, spec, key=key), method, M, spec.L))
    return {"load_s": load, "hash_s": max(0.0, hashed_s - load), "count_s": max(0.0, total - hashed_s), "total_s": total}


def sweep(df: DataFrame, view: ViewSpec, methods: list[str], ms: list[int], spec: HashSpec = HashSpec()) -> DataFrame:
    """(view_id, method, M, total_s, ...) over the grid."""
    rows = []
    for method in methods:
        for m in ms:
            t = phase_times(df, view, method, m, spec)
            rows.append((view.name, method, m, t.get("load_s"), t.get("hash_s"), t["count_s"], t["total_s"]))
    return df.sparkSession.createDataFrame(rows, "view_id string, method string, M long, load_s double, hash_s double, count_s double, total_s double")


def state_rows(df: DataFrame, view: ViewSpec, M: int, spec: HashSpec = HashSpec()) -> DataFrame:
    """(view_id, method, rows): measured rows of each state."""
    rows = hashed(df, view, spec, key=True)
    states = {"pc": counting.pc_state(rows, M, spec.L), "ll": counting.ll_state(rows, M, spec.L), "gc": bottomk.gc_state(rows, M, spec.L), "lps": levels.lps_state(rows, M, spec.L)}
    out = None
    for name, state in states.items():
        one = state.groupBy("view_id").agg(F.count("*").alias("rows")).select("view_id", F.lit(name).alias("method"), "rows")
        out = one if out is None else out.union(one)
    return out


def observed(df: DataFrame, name: str = "scan") -> tuple[DataFrame, Observation]:
    """df with its row count observed as it passes."""
    o = Observation(name)
    return df.observe(o, F.count("*").alias("rows")), o
