"""Hubs above the degrees that have steps of their own."""

import pytest
from pyspark.sql import functions as F

from streamcut.sources import zipf


def test_steps_cover_all_degrees_with_their_mass():
    n, exponent = 1_000_000, 2.0
    table = zipf.steps(exponent, n)
    assert table[0][0] == 1 and table[-1][0] + table[-1][1] == n + 1 and table[-1][3] == 2**32
    assert all(a + w == b and hi == lo for (a, w, _, hi), (b, _, lo, _) in zip(table, table[1:]))
    total = sum(k**-exponent for k in range(1, n + 1))
    for least in (5000, 50_000, 500_000):
        first = next(i for i, x in enumerate(table) if x[0] >= least)
        want = sum(k**-exponent for k in range(table[first][0], n + 1)) / total
        assert 1 - table[first][2] / 2**32 == pytest.approx(want, rel=2e-2)


def test_graph_has_its_hubs(spark):
    n = 20_000
    out = zipf.zipf_graph(spark, n, 1.9, 2.2).groupBy("src").agg(F.count("*").alias("d")).agg(F.max("d")).first()[0]
    assert 4096 < out < n


def test_twin_has_the_same_hubs(spark):
    duckdb = pytest.importorskip("duckdb")
    want = set(duckdb.sql(zipf.zipf_sql(6000, 1.9, 1.9)).fetchall())
    assert {tuple(r) for r in zipf.zipf_graph(spark, 6000, 1.9, 1.9).collect()} == want


def test_graph_over_the_keys_of_a_table(spark):
    """Keys with gaps, a null and a repeated one; the SQL gives the same edges, and the query's vertices are customers."""
    import duckdb

    keys = [(k * 7 - 50,) for k in range(90)] + [(None,), (-50,)]
    got = sorted(tuple(r) for r in zipf.zipf_on(spark.createDataFrame(keys, "k int"), 1.9, 2.2, 60).collect())
    values = ", ".join("(NULL)" if k is None else f"({k})" for (k,) in keys)
    assert got == sorted(duckdb.sql(zipf.zipf_on_sql(f"SELECT v FROM (VALUES {values}) t(v)", 1.9, 2.2, 60)).fetchall())
    assert {v for e in got for v in e} <= {k for (k,) in keys} and len(got) > 90
    assert not zipf.zipf_on(spark.createDataFrame([], "k int"), 2.0, 2.0, 60).count()
    from streamcut import registry

    d = "/root/testdata/sf0.001"
    customers = {r[0] for r in spark.read.parquet(f"{d}/customer.parquet").select("c_custkey").collect()}
    rows = registry.QUERIES["zipf_graph_22_22"](spark, d).collect()
    assert {v for r in rows for v in r} == customers
