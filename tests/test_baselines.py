import duckdb

from viewsize import queries
from viewsize.functions.hashing import tuple_hash
from viewsize.operators import baselines
from viewsize.plans.views import CATALOGUE, ViewSpec


def test_overlap_compares_hashes_not_tuples(spark, monkeypatch):
    from pyspark.sql import functions as F

    keys = spark.range(400_000).select((F.col("id") + 1).alias("o_custkey"), (F.col("id") % 3).alias("l_suppkey"))
    h = keys.select("*", tuple_hash({n: F.col(n) for n in CATALOGUE["D6"].names}, queries.SPEC).alias("y"))
    both = h.groupBy("y").agg(F.collect_list(F.struct("o_custkey", "l_suppkey")).alias("t"), F.collect_set("l_suppkey").alias("s")).where("size(t) = 2 and array_contains(s, 0L) and array_contains(s, 1L)")
    two = both.select(F.explode("t").alias("t")).select("t.*")
    n = both.count()
    assert n  # two tuples of one 32-bit hash, each in one part only
    monkeypatch.setattr(queries, "facts", lambda s, d, v: two.localCheckpoint())
    assert queries.sample_overlap(spark, "").first()["shared"] == n


def test_uniform_estimate_of_a_large_volume_equals_sql(spark):
    # 150,000 facts over a volume of 1.35e10: the plain formula is off by several cells there, and the SQL is the plain formula.
    ids = spark.range(150_000)
    df = ids.selectExpr("id % 110003 AS o_custkey", "id % 122777 AS l_suppkey")
    view = ViewSpec("D6", ("o_custkey", "l_suppkey"))
    got = baselines.occupancy_estimate(df, view, form="plain").first()
    volume = float(got["volume"])
    want = duckdb.sql(f"SELECT {volume!r}::DOUBLE AS volume, {got['facts']} AS facts, volume * (1 - exp(facts * ln(1 - 1 / volume))) AS estimate").fetchall()[0][2]
    exact = baselines.occupancy_estimate(df, view).first()["estimate"]
    assert round(got["estimate"]) == round(want) and abs(want - exact) > 0.01


def test_the_uniform_query_follows_its_sql(spark, monkeypatch):
    forms = []
    real = baselines.occupancy_estimate
    monkeypatch.setattr(queries.baselines, "occupancy_estimate", lambda df, v, form="stable": forms.append(form) or real(df, v, form=form))
    monkeypatch.setattr(queries, "facts", lambda s, d, v: s.range(9).selectExpr("id AS o_custkey", "id % 3 AS l_suppkey"))
    assert queries.queries()["uniform_D6"](spark, "").first()["volume"] == 27.0 and forms == ["plain"]
