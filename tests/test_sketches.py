import random

import pytest
from pyspark.sql import functions as F

from viewsize.functions import hashing
from viewsize.functions.hashing import HashSpec
from viewsize.operators import bottomk, counting, exact, levels, multi
from viewsize.plans.views import CATALOGUE, CENSUS, ViewSpec, facts, hashed, hashed_many

from . import reference as R


def rows_of(spark, ys, L):
    signed = [y - 2**64 if y >= 2**63 else y for y in ys]
    return spark.createDataFrame([("v", 0, y, i) for i, y in enumerate(signed)], "view_id string, seed int, y long, key long")


@pytest.fixture(scope="module", params=[(32, 5000), (64, 3000), (64, 40)])
def sample(request, spark):
    L, n = request.param
    rng = random.Random(n)
    ys = [0, 1, 2**31, 2**L - 1, 2 ** (L - 1)] + [rng.getrandbits(L) for _ in range(n)]
    ys += ys[: n // 3]
    pairs = [(y, str(i)) for i, y in enumerate(ys)]
    return L, ys, pairs, rows_of(spark, ys, L).cache()


@pytest.mark.parametrize("M", [2, 16, 256])
def test_against_definitions(sample, M):
    L, ys, pairs, rows = sample
    one = lambda df: df.collect()[0]["estimate"]
    assert one(counting.pc_estimate(counting.pc_state(rows, M, L), M)) == pytest.approx(R.probabilistic_counting(ys, M, L))
    assert one(counting.ll_estimate(counting.ll_state(rows, M, L), M)) == pytest.approx(R.loglog(ys, M, L))
    assert one(counting.ac_estimate(counting.ll_state(rows, M, L), M)) == pytest.approx(R.adaptive(ys, M, L))
    assert one(counting.max_level_estimate(counting.max_level_state(rows, L))) == 2.0 ** max(R.zeros(y, L) for y in ys)
    for plan in ("native", "partial", "threshold"):
        assert one(bottomk.gc_estimate(bottomk.gc_state(rows, M, L, plan), M, L)) == pytest.approx(R.smallest_hashes(pairs, M, L))
        got = levels.lps_estimate(levels.lps_state(rows, M, L, plan)).collect()
        want, floor = R.level_pruned(pairs, M, L)
        assert (got[0]["estimate"], got[0]["level_floor"]) == (want, floor) if got else want == 0


@pytest.mark.parametrize("codegen", ["true", "false"])
def test_edge_hashes(spark, codegen):
    """Zero, the lowest and highest longs, all ones: no overflow under ANSI, with and without code generation."""
    spark.conf.set("spark.sql.codegen.wholeStage", codegen)
    try:
        ys = [0, 1, 2**31, 2**32 - 1, 2**63, 2**63 - 1, 2**64 - 1]
        rows = rows_of(spark, ys, 64)
        got = [r[0] for r in rows.select(counting.level(F.col("y"), 64)).collect()]
        assert got == [64, 0, 31, 0, 63, 0, 0]
        bits = spark.createDataFrame([(b,) for b in (0, 1, 2, 7, 2**63 - 1, -1, -(2**63))], "b long")
        assert [r[0] for r in bits.select(counting.first_zero(F.col("b"))).collect()] == [0, 1, 0, 3, 63, 64, 0]
        for order in ("low", "high"):
            b, r = counting.bucket_rank(F.col("y"), 16, 64, order)
            assert all(0 <= x[0] < 16 and 1 <= x[1] <= 61 for x in rows.select(b, r).collect())
        assert [r[0] for r in rows.select(hashing.unsigned(F.col("y"), 64)).collect()] == [float(y) for y in ys]
    finally:
        spark.conf.unset("spark.sql.codegen.wholeStage")


@pytest.mark.parametrize("n", [0, 1, 15, 16, 17])
def test_small_views_are_exact(spark, n):
    df = spark.range(n).unionAll(spark.range(n))
    for method, M in (("gc", 18), ("lps", 17)):  # a full state of hashes may hide more
        got = multi.estimate(df, ["id"], method, M).collect()
        assert [r["estimate"] for r in got] == ([float(n)] if n else [])


def test_order_repetition_and_partitions_do_not_matter(spark, sf):
    view = CATALOGUE["C11"]
    df = facts(spark, sf, view)
    for method in ("pc", "ac", "gc", "lps"):
        a = multi.estimate_many(df, [view], [method], 64).collect()
        b = multi.estimate_many(df.unionAll(df).repartition(7).orderBy("p_size"), [view], [method], 64).collect()
        assert a == b


def test_many_views_equal_single_views(spark, sf):
    views = CENSUS[:4]
    df = facts(spark, sf, *views)
    for method in ("ac", "gc", "lps", "pc"):
        many = {r["view_id"]: r for r in multi.estimate_many(df, views, [method], 64).collect()}
        for v in views:
            assert many[v.name] == multi.estimate_many(facts(spark, sf, v), [v], [method], 64).collect()[0]


def test_merge_equals_whole(spark, sf):
    view, spec, M = CATALOGUE["D7"], HashSpec(), 128
    rows = hashed(facts(spark, sf, view), view, spec, key=True).cache()
    parts = [rows.where(f"pmod(hash(key), 3) = {i}") for i in range(3)] + [rows.where("y % 5 = 0")]
    assert sorted(map(tuple, counting.pc_merge(*[counting.pc_state(p, M, 64) for p in parts]).collect())) == sorted(map(tuple, counting.pc_state(rows, M, 64).collect()))
    assert sorted(map(tuple, counting.ll_merge(*[counting.ll_state(p, M, 64) for p in parts]).collect())) == sorted(map(tuple, counting.ll_state(rows, M, 64).collect()))
    whole = bottomk.gc_state(rows, M, 64)
    assert sorted(map(tuple, bottomk.gc_merge(*[bottomk.gc_state(p, M, 64) for p in parts], M=M).collect())) == sorted(map(tuple, whole.collect()))
    whole = levels.lps_state(rows, M, 64)
    assert sorted(map(tuple, levels.lps_merge(*[levels.lps_state(p, M, 64) for p in parts], M=M).collect())) == sorted(map(tuple, whole.select(*levels.lps_merge(whole, M=M).columns).collect()))


def test_nulls_zeros_nans_and_keys(spark):
    nan = float("nan")
    rows = [("a", 0.0), ("a", -0.0), ("a", nan), ("a", -nan), (None, nan), (None, None), ("", None), ("n", None), ("a", None), ("x", 1.0)]
    df = spark.createDataFrame(rows, "a string, b double").withColumn("c", F.lit(None).cast("timestamp"))
    view = ViewSpec("v", ("a", "b", "c"), "facts")
    size = exact.view_size(df, view).collect()[0]["exact"]
    assert size == 8
    for method in ("gc", "lps"):
        assert multi.estimate_many(df, [view], [method], 64).collect()[0]["estimate"] == 8.0


def test_equal_values_of_two_dimensions_do_not_cancel(spark):
    df = spark.range(200).selectExpr("id AS a", "id AS b")
    assert multi.estimate(df, ["a", "b"], "gc", 4096, HashSpec(mix="none")).collect()[0]["estimate"] == 200.0


@pytest.mark.parametrize("d", [1, 2, 3, 6])
def test_error_within_theory(spark, d):
    df = spark.range(20_000).select(*[(F.col("id") * (i + 1)).alias(f"k{i}") for i in range(d)])
    for method, tolerance in (("pc", 0.1), ("ll", 0.15), ("ac", 0.15), ("gc", 0.13), ("lps", 0.25)):
        got = multi.estimate(df, [f"k{i}" for i in range(d)], method, 1024).collect()[0]["estimate"]
        assert abs(got / 20_000 - 1) < tolerance, method


def test_lookup_tables_equal_expressions(spark, sf):
    df = spark.read.parquet(f"{sf}/lineitem.parquet").select("l_returnflag", "l_partkey")
    dims = {c: F.col(c) for c in df.columns}
    for mode in ("xx", "md5"):
        spec = HashSpec(mode=mode, mix="none")
        tables = {n: hashing.build_lookup(df.where("l_partkey < 50"), n, c, spec) for n, c in dims.items()}
        met = hashing.with_lookup(df, dims, tables, spec)
        assert met.where(hashing.prehashed(list(dims), spec) != hashing.tuple_hash(dims, spec)).count() == 0 and met.count() == df.count()


def test_stored_hash_columns(spark, sf, tmp_path):
    view = CATALOGUE["C02"]
    df, spec = facts(spark, sf, view), HashSpec()
    bound = view.bind(df)
    stored = hashing.persist_hashed(bound, {n: F.col(n) for n in view.names}, spec, str(tmp_path / "h"), sort=True)
    rows = stored.select(F.lit("C02").alias("view_id"), F.lit(0).alias("seed"), hashing.prehashed(view.names, spec).alias("y"))
    assert counting.ac_estimate(counting.ll_state(rows, 256, 64), 256).collect() == counting.ac_estimate(counting.ll_state(hashed(df, view, spec), 256, 64), 256).collect()


def test_plans_are_native_and_narrow(spark, sf):
    view = CATALOGUE["C12"]
    df = multi.estimate_many(facts(spark, sf, view), [view], ["ac"], 256)
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "partial_max" in plan
    assert "l_comment" not in plan and "l_orderkey" not in plan and "Join" not in plan
    many = hashed_many(facts(spark, sf, *CENSUS), CENSUS, HashSpec())
    assert many._jdf.queryExecution().optimizedPlan().toString().count("Generate explode") == 1


def test_bad_arguments(spark, sf):
    with pytest.raises(ValueError):
        HashSpec(L=48)
    with pytest.raises(ValueError):
        counting.log2_exact(100)
    with pytest.raises(ValueError):
        multi.estimate(spark.range(3), ["id"], "unheard_of").collect()
    with pytest.raises(ValueError):
        ViewSpec("v", ("m",)).bind(spark.sql("SELECT map(1, 2) AS m"))
    with pytest.raises(ValueError):
        ViewSpec("v", ()).bind(spark.range(1))
