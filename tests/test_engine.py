import math
import shutil

import pytest
from pyspark.sql import functions as F

from viewsize import sqlapi
from viewsize.functions import hashing
from viewsize.functions.hashing import HashSpec
from viewsize.operators import baselines, counting, exact, iceberg, levels, multi, multifractal, selection
from viewsize.plans import metrics, protocol, theory
from viewsize.plans.views import CATALOGUE, CENSUS, ViewSpec, facts, hashed
from viewsize.sources import data, store
from viewsize.streaming import sketches as stream

SIZES = {"C01": 90, "C02": 210, "C08": 2807, "C20": 6000, "D1": 10, "D3": 200, "D7": 5939, "V1": 15, "V3": 75, "V6": 998}


@pytest.mark.parametrize("name", SIZES)
def test_exact_sizes(spark, sf, name):
    v = CATALOGUE[name]
    assert exact.view_size(facts(spark, sf, v), v).collect()[0]["exact"] == SIZES[name]


def test_grouping_sets_equal_single(spark, sf):
    got = {r["view_id"]: r["exact"] for r in exact.view_sizes(facts(spark, sf, *CENSUS), CENSUS).collect()}
    assert len(got) == 20 and all(got[n] == s for n, s in SIZES.items() if n in got)


# Theory.


def test_theory_values():
    assert [round(theory.gc_eps(1, k), 2) for k in (2, 3, 4, 8)] == [9.06, 6.74, 6.06, 5.89]
    assert [theory.lps_eps(2048, k) for k in (2, 3, 4, 8)] == pytest.approx([0.247, 0.137, 0.111, 0.098], abs=0.002)
    assert theory.gc_max_f0(64, 10_000, 0.1) >= 2e21
    assert theory.gc_min_bits(theory.gc_max_f0(64, 10_000, 0.1), 10_000, 0.1) == pytest.approx(64)
    assert theory.max_level_bound(40) == (39, 0.95)
    assert theory.gc_delta(4096, 4, 0.1, "tight") > theory.gc_delta(4096, 4, 0.1, "printed")
    assert theory.lps_eps_short(2500) == pytest.approx(0.1)
    assert round(100 * theory.rse_pc(64), 2) == 9.75 and round(100 * theory.rse_ll(64), 2) == 16.25
    assert theory.bits_original([100] * 10) > 3 * theory.bits_modified(10**6, 0.1, 10_000)
    assert HashSpec().independence(1) == "full" and HashSpec().independence(3) == "3-wise"
    with pytest.raises(ValueError):
        theory.gc_delta(4, 4, 0.1)


def test_curves(spark):
    got = {(r["curve"], r["k"], r["M"]): r["value"] for r in theory.curves(spark).collect()}
    assert got["lps_bound", 4, 256] < got["gc_bound", 4, 256]
    assert all(got["rse_pc", None, m] < got["rse_ll", None, m] for m in (16, 64, 2048))


# The published behaviour.


@pytest.fixture(scope="module")
def census(spark, sf):
    views = [CATALOGUE[n] for n in ("C01", "C03", "C08", "C20")]
    runs = protocol.run(facts(spark, sf, *views), views, ["pc", "ll", "ac", "gc", "lps", "maxlevel"], [16, 64, 256, 2048], 20).cache()
    return runs, {(r["view_id"], r["method"], r["M"]): r for r in metrics.accuracy(runs).collect()}


def test_small_views_break_counting_without_a_switch(census):
    _, acc = census
    assert acc["C01", "pc", 2048]["rse"] > 10 and acc["C01", "ll", 2048]["rse"] > 4
    assert acc["C01", "ac", 2048]["rse"] < 0.1
    assert all(acc["C01", m, 2048]["rse"] == 0 for m in ("gc", "lps"))


def test_error_falls_with_memory_and_stays_near_theory(census):
    _, acc = census
    for method in ("pc", "ll", "ac", "gc", "lps"):
        assert acc["C20", method, 256]["rse"] < acc["C20", method, 64]["rse"] * 1.2 < acc["C20", method, 16]["rse"] * 1.5
    for view in ("C08", "C20"):
        for M in (64, 256):
            assert acc[view, "ac", M]["rse"] < 2 * theory.rse_ll(M) and acc[view, "gc", M]["rse"] < 2 / math.sqrt(M) and acc[view, "lps", M]["rse"] < 3 / math.sqrt(M)
    assert acc["C20", "pc", 256]["rse"] < 1.6 * theory.rse_pc(256)


def test_bounds_hold_and_the_level_counter_is_wild(census):
    runs, acc = census
    for M in (64, 256):
        assert acc["C20", "gc", M]["p95_rel_err"] <= theory.gc_eps(M, 3) and acc["C20", "lps", M]["p95_rel_err"] <= max(theory.lps_eps(M, 3), 0.3)
    assert acc["C20", "maxlevel", 16]["rse"] > 0.5 and acc["C20", "maxlevel", 16]["rse"] == acc["C20", "maxlevel", 2048]["rse"]
    within = {(r["method"], r["M"]): r["within"] for r in metrics.reliability(runs.where("view_id = 'C20'"), 0.2).collect()}
    assert within["ac", 2048] == 1.0


def test_slope_is_about_minus_one_half(census, spark):
    _, acc = census
    df = spark.createDataFrame([(v, m, M, 64, float(r["rse"])) for (v, m, M), r in acc.items() if v == "C20" and m in ("pc", "gc", "lps") and M <= 256], "view_id string, method string, M long, L int, rse double")
    assert all(-0.9 < r["slope"] < -0.25 for r in metrics.slope(df).collect())


def test_estimates_do_not_see_the_distribution(spark):
    flat = spark.range(3000).selectExpr("id AS a")
    steep = flat.unionAll(spark.range(3000).selectExpr("id % 3 AS a")).unionAll(spark.range(5000).selectExpr("CAST(0 AS BIGINT) AS a"))
    for m in ("pc", "ac", "gc", "lps"):
        assert multi.estimate(flat, ["a"], m, 256).collect() == multi.estimate(steep, ["a"], m, 256).collect()


def test_skew_makes_the_uniform_assumption_overestimate(spark, sf):
    df = data.load(spark, sf, "lineitem").select(data.skewed("l_partkey", 200).alias("p"), data.skewed("l_suppkey", 10).alias("s"), "l_quantity")
    v = ViewSpec("s", ("p", "s", "l_quantity"), "facts")
    assert baselines.occupancy_estimate(df, v).collect()[0]["estimate"] > 1.2 * exact.view_size(df, v).collect()[0]["exact"]


# The multifractal model.


def test_multifractal_fit():
    assert multifractal.mf_fit(0, 0, 0, 10)["estimate"] is None
    assert multifractal.mf_fit(1, 10, 10, 1000)["estimate"] == 1.0
    printed = multifractal.mf_fit(1000, 3000, 9, 600_000, summand="printed")
    assert printed["estimate"] == pytest.approx(2.0 ** printed["k"], rel=0.01)
    f = multifractal.mf_fit(1000, 3000, 9, 600_000)
    assert f["converged"] and f["estimate"] > 1000
    skewed = [multifractal.mf_fit(1000, 3000, 150, 90_000, bias=b)["estimate"] for b in ("sample", "printed")]
    assert skewed[0] < skewed[1]
    assert not multifractal.mf_fit(3000, 3000, 1, 600_000, k_max=64)["converged"]
    for k, p, n in ((3, 0.6, 5), (1, 1.0, 4), (6, 0.5, 1000)):
        want = sum(math.comb(k, a) * (1 - (1 - p ** (k - a) * (1 - p) ** a) ** n) for a in range(k + 1))
        assert multifractal.occupied(k, p, n) == pytest.approx(want)


def test_multifractal_is_never_reliable(spark, sf):
    worst = 0
    for name in ("C01", "C08", "D3", "D7"):
        v = CATALOGUE[name]
        r = multifractal.mf_estimate(facts(spark, sf, v), v, 0.05, 1).collect()[0]
        worst = max(worst, abs((r["estimate"] or 0) / SIZES[name] - 1))
    assert worst > 0.1


def test_samplers(spark, sf):
    df = data.load(spark, sf, "lineitem")
    assert multifractal.sample_rows(df, 0.1, 1, "exact").count() == 600
    h = multifractal.sample_rows(df, 0.1, 1, "hash", ["l_orderkey", "l_partkey"])
    assert 400 < h.count() < 800 and h.count() == multifractal.sample_rows(df.repartition(9), 0.1, 1, "hash", ["l_orderkey", "l_partkey"]).count()
    r = multifractal.mf_sample_stats(df.limit(0), ViewSpec("v", ("l_partkey",)), 0.5).collect()[0]
    assert (r["f0"], r["n_sample"], r["m_max"]) == (0, 0, None)


# Measures, protocol, store, SQL, extensions.


def test_measures(spark):
    runs = spark.createDataFrame([("v", "ac", 16, 64, s, e, 100) for s, e in enumerate((90.0, 110.0, 100.0, 120.0))], "view_id string, method string, M long, L int, seed int, estimate double, exact long")
    r = metrics.accuracy(runs).collect()[0]
    assert r["rse"] == pytest.approx(math.sqrt(150) / 100) and r["bias"] == pytest.approx(0.05) and r["n_runs"] == 4
    assert metrics.reliability(runs, 0.1).collect()[0]["within"] == 0.75
    assert metrics.state_bytes("pc", 256, 64) == 2048 and metrics.state_bytes("ll", 256, 64) == 192 and metrics.state_bytes("gc", 10, 64, 4) == 120
    wide = metrics.pivot(metrics.accuracy(runs), [16]).collect()[0]
    assert wide["16"] == pytest.approx(12.2474)


def test_log_and_as_of(spark, tmp_path):
    runs = spark.createDataFrame([("v", 5), ("v", 15), ("w", 1)], "view_id string, at long")
    exacts = spark.createDataFrame([("v", 1, 10), ("v", 10, 20), ("w", 3, 7)], "view_id string, at long, exact long")
    assert sorted((r["view_id"], r["at"], r["exact"]) for r in protocol.as_of_exact(runs, exacts).select("view_id", "at", "exact").collect() if r["exact"]) == [("v", 5, 10), ("v", 15, 20)]
    protocol.append_log(runs, str(tmp_path / "log"))
    protocol.append_log(runs, str(tmp_path / "log"))
    assert protocol.read_log(spark, str(tmp_path / "log")).count() == 6


def test_phase_times(spark, sf):
    t = protocol.phase_times(facts(spark, sf, CATALOGUE["D3"]), CATALOGUE["D3"], "ac", 64)
    assert t["total_s"] > 0 and set(t) == {"load_s", "hash_s", "count_s", "total_s"}
    assert set(protocol.phase_times(facts(spark, sf, CATALOGUE["D3"]), CATALOGUE["D3"], "mf", 64)) == {"sample_s", "count_s", "total_s"}


def test_store(spark, sf, tmp_path):
    view, spec = CATALOGUE["C11"], HashSpec()
    rows = hashed(facts(spark, sf, view), view, spec, key=True)
    path = str(tmp_path / "states")
    parts = [rows.where("y % 2 = 0"), rows.where("y % 2 <> 0")]
    for p in parts:
        store.save(counting.ll_state(p, 256, 64), path, "ll", 256, spec, view.names)
    state, meta = store.load(spark, path, "ll", "C11")
    whole = counting.ac_estimate(counting.ll_state(rows, 256, 64), 256).collect()
    assert counting.ac_estimate(store.merge("ll", [meta], state.select("view_id", "seed", "bucket", "reg")), 256).collect() == whole
    store.save(levels.lps_state(rows, 64, 64), path, "lps", 64, spec, view.names)
    assert store.load(spark, path, "lps", "C11")[1]["M"] == 64
    with pytest.raises(ValueError):
        store.merge("ll", [meta, meta | {"seed": 1}], state, state)
    store.save(counting.ll_state(rows, 256, 64), path, "ll", 256, spec.with_seed(3), view.names)
    with pytest.raises(ValueError):
        store.load(spark, path, "ll", "C11")


def test_sql(spark, sf):
    sqlapi.register(spark, sf)
    r = spark.sql(sqlapi.ac_sql("lineitem", ["l_partkey", "l_suppkey"], 256)).collect()[0]
    truth = spark.sql("SELECT count(*) FROM (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem)").collect()[0][0]
    assert abs(r["estimate"] / truth - 1) < 0.3
    got = {r[0]: r[1] for r in spark.sql("SELECT vs_level(CAST(v AS BIGINT), 64), v FROM VALUES (0), (1), (8), (-9223372036854775808) AS t(v)").collect()}
    assert got == {64: 0, 0: 1, 3: 8, 63: -(2**63)}
    assert [r["m"] for r in spark.sql("SELECT * FROM vs_curve('rse_ll', 64)").collect()] == [16, 32, 64]


def test_sources(spark, tmp_path):
    df = spark.createDataFrame([(1, "a"), (2, None)], "i int, s string")
    df.write.option("sep", "|").csv(str(tmp_path / "p"))
    assert sorted(data.read_delimited(spark, str(tmp_path / "p"), "|", "i int, s string").collect()) == sorted(df.collect())
    for fmt in ("parquet", "orc", "json"):
        df.write.format(fmt).partitionBy("i").save(str(tmp_path / fmt))
        assert data.read(spark, str(tmp_path / fmt), fmt).count() == 2
    assert data.synthetic_keys(spark, 50, 3, 2).distinct().count() == 50


def test_star_joins_only_what_is_asked(spark, sf):
    assert data.tables_of(["l_tax", "cr"]) == {"lineitem", "customer_nation"}
    assert data.star(spark, sf).count() == data.load(spark, sf, "lineitem").count()
    assert "Join" not in data.star(spark, sf, ["l_tax", "sy"])._jdf.queryExecution().optimizedPlan().toString()


def test_iceberg_and_selection(spark, sf):
    df = data.load(spark, sf, "lineitem")
    v = ViewSpec("i", ("l_partkey", "l_linenumber"), "facts")
    truth = iceberg.exact(df, v, 5).collect()[0]["exact"]
    assert iceberg.lps_estimate(df, v, 5, 10**6, HashSpec()).collect()[0]["estimate"] == truth
    assert abs(iceberg.lps_estimate(df, v, 5, 256, HashSpec()).collect()[0]["estimate"] / truth - 1) < 0.5
    sizes = spark.createDataFrame([(3, 100), (1, 50), (2, 10), (0, 1)], "dims_mask long, exact long")
    assert [(r["dims_mask"], r["benefit"]) for r in selection.greedy(sizes, 2, 2).orderBy("step").collect()] == [(2, 180.0), (1, 50.0)]
    masks = spark.createDataFrame([("ab", 3), ("a", 1), ("b", 2)], "view_id string, dims_mask long")
    assert sorted(map(tuple, selection.answered_by(masks).collect())) == [("a", "ab"), ("b", "ab")]
    for k in ("hllpp", "hll", "theta"):
        assert abs(baselines.builtin_estimate(df, v, k).collect()[0]["estimate"] / exact.view_size(df, v).collect()[0]["exact"] - 1) < 0.2


# Streams.


@pytest.fixture
def event_files(spark, sf, tmp_path):
    df = data.load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")).orderBy("ts")
    path = tmp_path / "events"
    n = df.count()
    ranked = df.withColumn("r", F.expr("row_number() OVER (ORDER BY ts, event_id)"))
    for i in range(4):
        ranked.where(f"r > {n * i // 4} AND r <= {n * (i + 1) // 4}").drop("r").coalesce(1).write.parquet(str(tmp_path / f"p{i}"))
        path.mkdir(exist_ok=True)
        for f in (tmp_path / f"p{i}").glob("*.parquet"):
            shutil.copy(f, path / f"{i}.parquet")
    return str(path), df


def drain(q):
    try:
        q.processAllAvailable()
    finally:
        q.stop()


def test_stream_registers_equal_batch(spark, event_files, tmp_path):
    path, df = event_files
    view, spec = ViewSpec("u", ("user_id", "event_type"), "events"), HashSpec()
    src = stream.source(spark, path, df.schema)
    drain(stream.registers(src, view, 64, spec).writeStream.outputMode("complete").format("memory").queryName("regs").start())
    assert sorted(map(tuple, spark.table("regs").collect())) == sorted(map(tuple, counting.ll_state(hashed(df, view, spec), 64, 64).collect()))


def test_stream_windows_and_late_rows(spark, event_files):
    path, df = event_files
    view, spec = ViewSpec("u", ("user_id",), "events"), HashSpec()
    state = stream.windowed_registers(stream.source(spark, path, df.schema), view, 64, spec, "ts", "1 day")
    drain(state.writeStream.outputMode("append").format("memory").queryName("wins").start())
    batch = stream.finish_windows(stream.windowed_registers(df, view, 64, spec, "ts", "1 day"), 64)
    got = {r["start"]: r["estimate"] for r in stream.finish_windows(spark.table("wins"), 64).collect()}
    want = {r["start"]: r["estimate"] for r in batch.collect()}
    assert len(got) >= len(want) - 2 and all(want[k] == v for k, v in got.items())


def test_stream_bottom_hashes_and_merge(spark, event_files, tmp_path):
    path, df = event_files
    view, spec = ViewSpec("u", ("user_id", "value"), "events"), HashSpec()
    src = stream.source(spark, path, df.schema)
    drain(stream.bottom_hashes(src, view, 32, spec, 3).writeStream.outputMode("update").format("memory").queryName("low").start())
    got = stream.finish_bottom(spark.table("low"), 32, 64).collect()[0]["estimate"]
    assert got == multi.estimate(df, ["user_id", "value"], "gc_hashkey", 32).collect()[0]["estimate"]
    out = str(tmp_path / "merged")

    def each(batch, epoch, keep=stream.merge_into(out)):
        keep(counting.ll_state(hashed(batch, view, spec), 64, 64), epoch)

    q = stream.source(spark, path, df.schema).writeStream.foreachBatch(each).start()
    drain(q)
    states = [counting.ll_state(hashed(df, view, spec), 64, 64).groupBy().sum("reg").collect()[0][0], max(spark.read.parquet(f"{out}/{i}").groupBy().sum("reg").collect()[0][0] for i in (0, 1))]
    assert states[0] == states[1]


def test_stream_dedupe_baseline(spark, event_files):
    path, df = event_files
    view = ViewSpec("u", ("user_id", "event_type"), "events")
    drain(stream.exact_distinct(stream.source(spark, path, df.schema), view, "ts", "60 days").writeStream.outputMode("append").format("memory").queryName("dd").start())
    assert spark.table("dd").count() == exact.view_size(df, view).collect()[0]["exact"]


def test_stateful_level_sample_and_stream_static_lookup(spark, sf, tmp_path):
    """A stream in four files, with repetitions: the level-pruned sample equals that of the batch; hashes from a stored table that lacks values equal computed ones."""
    view, spec = ViewSpec("ue", ("user_id", "event_type", "value"), "events"), HashSpec(seed=3)
    events = data.load(spark, sf, "events")
    for i in range(4):
        events.where(f"event_id % 4 = {i} or event_id % 7 = 0").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    src = stream.source(spark, str(tmp_path / "in"), events.schema, 2)
    want = levels.lps_estimate(levels.lps_state(hashed(events, view, spec, key=True), 40, 64)).collect()[0]
    q = stream.level_sample(src, view, 40, spec).writeStream.format("memory").queryName("lps_updates").outputMode("update").option("checkpointLocation", str(tmp_path / "c1")).start()
    q.processAllAvailable()
    q.stop()
    got = stream.finish_levels(spark.table("lps_updates"), 40).collect()[0]
    assert (got["estimate"], got["level_floor"]) == (want["estimate"], want["level_floor"])
    one = ViewSpec("u", ("user_id",), "events")
    table = hashing.build_lookup(events.where("user_id % 3 <> 0").select(F.col("user_id")), "user_id", F.col("user_id"), spec)
    q = stream.hashed_by_lookup(src, one, {"user_id": table}, spec).writeStream.format("memory").queryName("looked_up").option("checkpointLocation", str(tmp_path / "c2")).start()
    q.processAllAvailable()
    q.stop()
    assert {r["y"] for r in spark.table("looked_up").collect()} == {r["y"] for r in hashed(events, one, spec).collect()}


def test_array_tables_and_refresh(spark, sf):
    df, spec = data.load(spark, sf, "lineitem").select(F.col("l_linenumber").cast("long").alias("l_linenumber")), HashSpec()
    cols = {"l_linenumber": F.col("l_linenumber")}
    same = hashing.with_array_lookup(df, cols, {"l_linenumber": 5}, spec).where(F.col("h_l_linenumber") != hashing.dim_hash("l_linenumber", F.col("l_linenumber"), spec))
    assert same.count() == 0
    old = hashing.build_lookup(df.where("l_linenumber < 4"), "l_linenumber", F.col("l_linenumber"), spec)
    assert {r["value_key"] for r in hashing.missing_values(df, "l_linenumber", F.col("l_linenumber"), old, spec).collect()} == {4, 5, 6, 7}


def test_table_function_of_estimates(spark, sf):
    sqlapi.register(spark, sf)
    r = spark.sql("SELECT * FROM viewsize_estimate(TABLE(SELECT l_partkey, l_suppkey FROM lineitem) WITH SINGLE PARTITION, 1024)").collect()[0]
    truth = spark.sql("SELECT count(*) FROM (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem)").collect()[0][0]
    assert r["facts"] == 6000 and abs(r["estimate"] - truth) / truth < 0.15


def test_scratch_tables_are_deleted(spark):
    import os

    from viewsize import session

    path = session.scratch(spark).removeprefix("file://")
    session.settle(spark.range(3)).count()
    os.makedirs(path, exist_ok=True)
    assert session.clean(spark) >= 2 and not os.path.exists(path) and session.clean(spark) == 0


def test_exact_sampler_keeps_the_least_hashes(spark, sf):
    df = data.load(spark, sf, "lineitem").select("l_orderkey", "l_linenumber")
    for ratio in (0.0, 0.001, 0.05, 0.9, 1.0):
        own = multifractal.sample_rows(df, ratio, 2, "exact", ["l_orderkey", "l_linenumber"])
        assert own.count() == int(ratio * 6000)
    few = {tuple(r) for r in multifractal.sample_rows(df, 0.02, 2, "exact", ["l_orderkey", "l_linenumber"]).collect()}
    more = {tuple(r) for r in multifractal.sample_rows(df, 0.03, 2, "exact", ["l_orderkey", "l_linenumber"]).collect()}
    assert few < more
