"""Every registered query of the engine against its SQL twin, on the smallest tables."""

import os

import duckdb
import pytest

import __spark_entry__ as entry
from distill_filter import queries

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for f in os.listdir(SF):
        c.sql(f"CREATE VIEW {f[:-8]} AS SELECT * FROM read_parquet('{SF}/{f}')")
    return c


def plain(x):
    if x is None or x != x:
        return "null"
    return f"{x:.6g}" if isinstance(x, float) else str(x)


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_equals_sql(spark, duck, name):
    got = queries.QUERIES[name](spark, SF)
    columns = sorted(got.columns)
    want = duck.sql(queries.ORACLES[name])
    assert columns == sorted(want.columns)
    rows = lambda source, cols: sorted(tuple(plain(r[cols.index(c)]) for c in columns) for r in source)
    assert rows([tuple(r) for r in got.collect()], got.columns) == rows(want.fetchall(), want.columns)


@pytest.mark.parametrize("name", ["st2_focal_linear", "st3_library", "st4_vectors", "b06_pool_eot", "a16_coverage", "w06_student_ablation", "w10_theory_check", "w12_vectors", "s09_decision_cut", "t04_watermark", "o02_formats"])
def test_query_without_twin_runs(spark, name):
    assert len(queries.QUERIES[name](spark, SF).collect()) > 0


def test_claims(spark):
    cover = queries.QUERIES["a16_coverage"](spark, SF).collect()
    assert sum(r.covered for r in cover) >= 0.9 * len(cover)
    assert all(r.bound is None or r.vacuous or r.bound <= r.balance + 1e-9 for r in queries.QUERIES["w10_theory_check"](spark, SF).collect())


def test_entry(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
