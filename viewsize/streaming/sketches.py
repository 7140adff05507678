"""View sizes over streams. Sketches ignore order and repetition, so replays and at-least-once sources do no harm."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.hashing import HashSpec, canonical, dim_hash, order_key, prehashed, with_lookup, xor_all
from ..operators import counting, levels
from ..plans.views import ViewSpec, hashed
from ..session import settle, ship


def source(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def with_hash(df: DataFrame, view: ViewSpec, spec: HashSpec, keep: list[str]) -> DataFrame:
    """The stream's kept columns and the tuple hash y."""
    raw = view.raw()
    src = df.select(*keep, *[c.alias(f"d_{n}") for n, c in raw.items()])
    kinds = {f.name: f.dataType for f in src.schema.fields}
    y = xor_all([dim_hash(n, canonical(F.col(f"d_{n}"), kinds[f"d_{n}"]), spec) for n in raw], spec)
    return src.select(*keep, y.alias("y"))


def registers(df: DataFrame, view: ViewSpec, M: int, spec: HashSpec, kind: str = "ll") -> DataFrame:
    """The unbounded state of a whole stream, for update or complete mode: at most M rows, so no watermark is needed."""
    rows = hashed(df, view, spec)
    return counting.pc_state(rows, M, spec.L) if kind == "pc" else counting.ll_state(rows, M, spec.L)


def windowed_registers(df: DataFrame, view: ViewSpec, M: int, spec: HashSpec, ts: str, width: str, slide: str | None = None, late: str = "1 hour", kind: str = "ll") -> DataFrame:
    """(start, end, bucket, reg or bits) of event-time windows; rows later than the watermark are dropped."""
    timed = df.withColumn(ts, F.col(ts).cast("timestamp"))
    timed = timed.withWatermark(ts, late) if df.isStreaming else timed
    rows = with_hash(timed, view, spec, [ts])
    bucket, rank = counting.bucket_rank(F.col("y"), M, spec.L)
    bit = F.call_function("shiftleft", F.lit(1).cast("bigint"), (rank - 1).cast("int"))
    agg = F.bit_or(bit).alias("bits") if kind == "pc" else F.max(rank).alias("reg")
    win = F.window(ts, width, slide) if slide else F.window(ts, width)
    return rows.groupBy(win.alias("w"), bucket.alias("bucket")).agg(agg).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "bucket", "reg" if kind != "pc" else "bits")


def finish_windows(state: DataFrame, M: int, kind: str = "ac") -> DataFrame:
    """(start, end, a, beta, branch, estimate) of a table of windowed states, as a sink's foreachBatch or a later read has it."""
    rows = state.withColumns({"view_id": F.concat_ws("|", F.col("start").cast("string"), F.col("end").cast("string")), "seed": F.lit(0)})
    est = counting.pc_estimate(rows, M) if kind == "pc" else counting.ac_estimate(rows, M)
    ends = rows.select("view_id", "start", "end").distinct()
    return est.join(ends, "view_id").select("start", "end", "a", "beta", "branch", "estimate")


def session_sizes(df: DataFrame, view: ViewSpec, spec: HashSpec, key: str, ts: str, gap: str, late: str = "1 hour") -> DataFrame:
    """(key, start, end, exact) of sessions. The session's key must not hold the bucket, so the small set of a session's hashes is gathered and counted."""
    timed = df.withColumn(ts, F.col(ts).cast("timestamp"))
    timed = timed.withWatermark(ts, late) if df.isStreaming else timed
    rows = with_hash(timed, view, spec, [key, ts])
    grouped = rows.groupBy(key, F.session_window(ts, gap).alias("w")).agg(F.collect_set("y").alias("ys"))
    return grouped.select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), F.size("ys").cast("long").alias("exact"))


def session_linear(df: DataFrame, view: ViewSpec, spec: HashSpec, key: str, ts: str, gap: str, M: int = 512, late: str = "1 hour") -> DataFrame:
    """(key, start, end, beta, estimate) of sessions by linear counting: the state of a session is a bitmap of M bits in M / 64 longs, however long it lasts."""
    timed = df.withColumn(ts, F.col(ts).cast("timestamp"))
    timed = timed.withWatermark(ts, late) if df.isStreaming else timed
    rows = with_hash(timed, view, spec, [key, ts]).withColumn("bucket", F.col("y").bitwiseAND(F.lit(M - 1).cast("bigint")))
    bit = F.call_function("shiftleft", F.lit(1).cast("bigint"), (F.col("bucket") % 64).cast("int"))
    words = [F.coalesce(F.bit_or(F.when(F.floor(F.col("bucket") / 64) == i, bit)), F.lit(0).cast("bigint")).alias(f"b{i}") for i in range(M // 64)]
    grouped = rows.groupBy(key, F.session_window(ts, gap).alias("w")).agg(*words)
    beta = F.lit(M) - sum((F.bit_count(f"b{i}") for i in range(M // 64)), F.lit(0))
    out = grouped.select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), beta.cast("bigint").alias("beta"))
    return out.withColumn("estimate", F.when(F.col("beta") > 0, -F.lit(float(M)) * F.ln(F.col("beta") / F.lit(float(M)))))


def hashed_by_lookup(df: DataFrame, view: ViewSpec, tables: dict[str, DataFrame], spec: HashSpec) -> DataFrame:
    """(view_id, seed, y) of a stream from stored tables: stream-static joins; values that a table lacks yet are hashed on the fly."""
    bound = view.bind(df)
    met = with_lookup(bound, {n: F.col(n) for n in view.names}, tables, spec)
    return met.select(F.lit(view.name).alias("view_id"), spec.seed_column().cast("int").alias("seed"), prehashed(view.names, spec).alias("y"))


def level_sample(df: DataFrame, view: ViewSpec, M: int, spec: HashSpec, shards: int = 8) -> DataFrame:
    """(view_id, shard, keys, levels, floor) updates of a stateful level-pruned sample: each shard of the tuples keeps those of at least its floor, which rises while
    there are more than M."""
    ship(df.sparkSession)
    rows = hashed(df, view, spec, key=True).select("view_id", counting.level(F.col("y"), spec.L).alias("level"), "key", F.pmod("key", F.lit(shards)).cast("int").alias("shard"))

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        keys, tops, floor = state.get if state.exists else ([], [], 0)
        held = dict(zip(keys, tops))
        for pdf in batches:
            pdf = pdf[pdf["level"] >= floor]
            held.update(zip(pdf["key"].tolist(), pdf["level"].tolist()))
            while len(held) > M:
                floor += 1
                held = {t: v for t, v in held.items() if v >= floor}
        own = sorted(held)
        tops = [held[t] for t in own]
        state.update((own, tops, floor))
        yield pd.DataFrame({"view_id": [key[0]], "shard": [key[1]], "keys": [own], "levels": [tops], "floor": [floor]})

    return rows.groupBy("view_id", "shard").applyInPandasWithState(
        step, "view_id string, shard int, keys array<long>, levels array<int>, floor int", "keys array<long>, levels array<int>, floor int", "update", GroupStateTimeout.NoTimeout
    )


def finish_levels(updates: DataFrame, M: int) -> DataFrame:
    """The estimate from all updates: a shard's floor only rises, and its last update holds all tuples from its floor on."""
    base = updates.select("view_id", F.lit(0).alias("seed"), F.explode_outer(F.arrays_zip("keys", "levels")).alias("x"), F.col("floor").alias("level_floor"))
    rows = base.select("view_id", "seed", F.col("x.keys").alias("key"), F.col("x.levels").alias("level"), "level_floor")
    return levels.lps_estimate(levels.lps_merge(settle(rows, "levels"), M=M))


def exact_distinct(df: DataFrame, view: ViewSpec, ts: str, late: str = "1 hour") -> DataFrame:
    """The baseline: tuples without repetition inside the watermark."""
    timed = df.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, late)
    return timed.select(ts, *[c.alias(n) for n, c in view.raw().items()]).dropDuplicatesWithinWatermark(view.names)


def bottom_hashes(df: DataFrame, view: ViewSpec, M: int, spec: HashSpec, shards: int = 8) -> DataFrame:
    """(view_id, shard, kept, top) updates of a stateful Generalized Counting: each shard of the hash space keeps its M smallest hashes, so a shard is a task's work
    and the M smallest over all shards are the state of the stream."""
    ship(df.sparkSession)
    rows = hashed(df, view, spec).select("view_id", order_key(F.col("y"), spec.L).alias("h"), F.pmod(F.xxhash64("y"), F.lit(shards)).cast("int").alias("shard"))

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = set(state.get[0]) if state.exists else set()
        for pdf in batches:
            held.update(pdf["h"].tolist())
        own = sorted(held)[:M]
        state.update((own,))
        yield pd.DataFrame({"view_id": [key[0]], "shard": [key[1]], "hashes": [own]})

    return rows.groupBy("view_id", "shard").applyInPandasWithState(step, "view_id string, shard int, hashes array<long>", "hashes array<long>", "update", GroupStateTimeout.NoTimeout)


def finish_bottom(updates: DataFrame, M: int, L: int) -> DataFrame:
    """The estimate from the last update of each shard (the longest chain of updates wins: a shard's M-th hash only falls)."""
    from ..operators import bottomk

    rows = updates.select("view_id", F.lit(0).alias("seed"), F.explode("hashes").alias("h"), F.lit(0).cast("bigint").alias("key")).distinct()
    return bottomk.gc_estimate(bottomk._cut(rows, M), M, L)


def merge_into(path: str, kind: str = "ll"):
    """A foreachBatch function that keeps one merged register state at path, alternating between two folders so that a batch never reads what it writes."""

    def each(batch: DataFrame, epoch: int) -> None:
        spark = batch.sparkSession
        new, old = f"{path}/{epoch % 2}", f"{path}/{(epoch + 1) % 2}"
        merge = counting.pc_merge if kind == "pc" else counting.ll_merge
        (merge(batch, spark.read.parquet(old)) if epoch else batch).write.mode("overwrite").parquet(new)

    return each
