import importlib

import duckdb
import pytest

import __spark_entry__ as entry_module

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = ["exact_C08", "exact_grouping_sets", "exact_cube_flags", "hash_tuple_final", "pc_C08", "ac_C20", "gc_D7", "gc_printed_D7", "lps_D7", "lps_partial_D7", "multi_lps", "merge_gc", "mf_stats_C08_p007", "uniform_C12", "iceberg_lps", "events_sliding_pc", "events_session_exact", "docs_words_ac"]


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, sf, duck, name):
    df = entry_module.queries()[name](spark, sf)
    cols = sorted(df.columns)
    rel = duck.sql(entry_module.oracle_sql()[name])
    assert sorted(rel.columns) == cols
    want = [tuple(r[rel.columns.index(c)] for c in cols) for r in rel.fetchall()]
    assert sorted(map(repr, want)) == sorted(repr(tuple(r[c] for c in cols)) for r in df.collect())


def test_entry(spark):
    rows = entry_module.entry(spark).collect()
    assert len(rows) == 20 and max(r["rel_err"] for r in rows) < 0.15


def test_every_sql_has_a_query():
    assert set(entry_module.oracle_sql()) <= set(entry_module.queries())
    assert importlib.import_module("viewsize.queries").queries().keys() <= entry_module.queries().keys()


@pytest.mark.parametrize("name", ["state_bytes", "theory_f3", "theory_gc", "theory_lps_short", "theory_lps", "theory_bits", "theory_max_level"])
def test_theory_reads_the_facts(spark, sf, duck, name):
    test_query_equals_sql(spark, sf, duck, name)
    assert any("lineitem" in f for f in entry_module.queries()[name](spark, sf).inputFiles())


def test_t2_reads_the_facts(spark, sf):
    # The tuples are in the scratch folder by then: the views' sizes are those of the table's parts.
    got = {r["view_id"]: r["exact"] for r in entry_module.queries()["t2_pivot"](spark, sf).collect()}
    lines = spark.read.parquet(f"{sf}/lineitem.parquet").select("l_orderkey", "l_linenumber").distinct()
    assert got == {f"keys_{n}": lines.where(f"l_orderkey % 6 < {n}").count() for n in (1, 2, 4, 6)}
