import pytest
from pyspark.sql import functions as F

from viewsize import queries
from viewsize.plans.views import CENSUS, SYNTHETIC


@pytest.mark.parametrize("name, views", [(n, CENSUS) for n in ("accuracy_w1", "rse_w1")] + [(n, SYNTHETIC) for n in ("accuracy_w3", "rse_w3")])
def test_workloads_run_on_every_view(monkeypatch, name, views):
    class Seen(Exception):
        pass

    def run(df, views, methods, *rest):
        raise Seen([v.name for v in views], methods)

    monkeypatch.setattr(queries, "facts", lambda *a: None)
    monkeypatch.setattr(queries.protocol, "run", run)
    with pytest.raises(Seen) as seen:
        queries.queries()[name](None, "")
    assert seen.value.args == ([v.name for v in views], ["pc", "ll", "ac", "gc", "lps"])


def test_t2_runs_all_seeds(spark, sf, monkeypatch):
    runs = []
    real = queries.protocol.run
    monkeypatch.setattr(queries.protocol, "run", lambda *a: runs.append(real(*a)) or runs[-1])
    queries.queries()["t2_pivot"](spark, sf)
    per = runs[0].groupBy("view_id", "method", "M").agg(F.count_distinct("seed").alias("seeds")).collect()
    assert len(per) == 4 * 2 * 3 and {r["seeds"] for r in per} == {20}


def test_many_views_are_all_views(spark, sf):
    got = queries.queries()["multi_pc"](spark, sf).collect()
    assert {r["view_id"] for r in got} == {v.name for v in CENSUS}


@pytest.mark.parametrize("L", [32, 64])
def test_protocol_writes_tuples_once_and_agrees_with_each_state(spark, sf, monkeypatch, L):
    from viewsize.functions.hashing import HashSpec
    from viewsize.plans import protocol
    from viewsize.plans.views import CATALOGUE, facts

    written = []
    settle = protocol.settle
    monkeypatch.setattr(protocol, "settle", lambda df, name: written.append((name, "seed" in df.columns)) or settle(df, name))
    views = [CATALOGUE["D1"], CATALOGUE["D5"]]
    methods, ms, spec = ["pc", "ll", "ac", "gc", "lps"], [4, 16, 1024], HashSpec(L=L)
    df = facts(spark, sf, *views)
    whole = protocol.run(df, views, methods, ms, 3, spec)
    got = sorted(map(repr, whole.collect()))
    assert written == [("tuples", False), ("state", True)] * 2  # no row for each tuple and seed
    monkeypatch.setattr(protocol, "ENTRIES", 1024)
    monkeypatch.setattr(protocol, "_bound", lambda M, n, L, margin, real=protocol._bound: real(M, n, L, -30.0 if margin == 6 else margin))  # short at first
    assert got == sorted(map(repr, protocol.run(df, views, methods, ms, 3, spec).collect()))
    assert got == sorted(map(repr, protocol.run(df, views, methods, ms, 3, spec, "native").collect()))


def test_level_sample_needs_only_a_part_for_its_bounds(spark, monkeypatch):
    from viewsize.functions.hashing import HashSpec
    from viewsize.operators import levels, multi
    from viewsize.plans.views import ViewSpec, hashed_many

    df = spark.range(3000).selectExpr("id", "id % 5 AS few").unionByName(spark.range(3000).selectExpr("id", "id % 5 AS few"))
    views, spec = [ViewSpec("a", ("id", "few"), "facts"), ViewSpec("b", ("few",), "facts")], HashSpec()
    bounds = []
    real = levels.lower_floors
    monkeypatch.setattr(levels, "lower_floors", lambda rows, M, L: bounds.append(rows.count()) or real(rows, M, L))
    est = lambda plan: sorted(map(repr, multi.estimate_many(df, views, ["lps"], 16, spec, plan).collect()))
    assert est("threshold") == est("native") and len(bounds) == 1 and 0 < bounds[0] < 12_000 / 4
    rows = hashed_many(df, views, spec, key=True)
    none = levels.lps_estimate(levels.lps_state(rows, 16, 64, some=rows.where("view_id = 'a' AND y % 7 = 0"))).collect()  # a part that lacks a view
    assert sorted(map(repr, none)) == sorted(map(repr, levels.lps_estimate(levels.lps_state(rows, 16, 64, "native")).collect()))


@pytest.mark.parametrize("L, most", [(32, 1024), (64, 1024), (32, 2**13), (64, 2**13)])
def test_md5_states_are_combined_in_tasks_and_agree(spark, monkeypatch, L, most):
    """Hashes of the numpy form, of numbers, negative ones, texts, fractions and nulls, give the estimates of the expressions; few rows leave a task where there are few buckets."""
    from viewsize.functions.hashing import HashSpec
    from viewsize.plans import protocol
    from viewsize.plans.views import ViewSpec

    made = []
    real = protocol._counter
    monkeypatch.setattr(protocol, "_counter", lambda *a: made.append(a) or real(*a))
    df = spark.range(4000).selectExpr("if(id % 41 = 0, null, (id - 2000) * 450359962737049) AS a", "if(id % 7 = 0, null, concat('é', id % 3)) AS b", "id % 5 / 4 AS c", "id")
    views, methods, ms, spec = [ViewSpec("v", ("a", "b", "c"), "f"), ViewSpec("w", ("id",), "f"), ViewSpec("x", ("b", "c"), "f")], ["pc", "ll", "ac", "gc", "lps"], [16, most], HashSpec(L=L, mode="md5", mix="final")
    got = sorted(map(repr, protocol.run(df, views, methods, ms, 2, spec).collect()))
    assert len(made) >= 3 and got == sorted(map(repr, protocol.run(df, views, methods, ms, 2, spec, "native").collect()))


def test_numbers_hash_as_their_texts():
    import hashlib

    import numpy as np

    from viewsize.functions import md5

    v = np.array([0, 1, -1, 9, 10, 99, 100, -10, 2**32 - 1, 2**63 - 1, -(2**63), 10**18, -(10**18), *range(-300, 300, 7)], np.int64)
    for prefix in (b"", b"3:l_orderkey:v:", b"12:" + b"x" * 60):
        assert md5.of_numbers(prefix, v).tolist() == [int(hashlib.md5(prefix + str(x).encode()).hexdigest()[:16], 16) for x in v.tolist()]
