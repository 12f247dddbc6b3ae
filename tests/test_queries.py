"""Every query with an oracle against DuckDB on the smallest tables, a sample of the rest."""

import duckdb
import pytest

from compare import TABLES, digest
from hetpart import registry

SLOW = ("exp_", "inv_", "st_", "refine_never_worse", "sssp_full")
NAMES = [n for n in registry.SQL if not n.startswith(SLOW)]


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    con.sql("set timezone='UTC'")
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return con


def check(spark, sf, duck, name):
    df = registry.QUERIES[name](spark, sf)
    r = duck.sql(registry.SQL[name])
    a, b = digest([tuple(x) for x in df.collect()], df.columns), digest(r.fetchall(), r.columns)
    assert a[1] == b[1] and a[2] == b[2]


@pytest.mark.parametrize("name", NAMES)
def test_query(spark, sf, duck, name):
    check(spark, sf, duck, name)


@pytest.mark.parametrize("name", ["inv_full_g1", "inv_naive_g1", "inv_grow_parallel", "st_tumbling", "st_place_inv", "exp_gap", "refine_never_worse"])
def test_slow_query(spark, sf, duck, name):
    check(spark, sf, duck, name)


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 30
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_ablation_and_sweep(spark, sf):
    rows = registry.QUERIES["exp_ablation_g9"](spark, sf).collect()
    assert {r["method"] for r in rows} == {"full", "plus", "star", "naive"} and all(r["over_memory"] == 0 for r in rows)
    tc = {r["method"]: r["tc"] for r in rows}
    assert tc["full"] <= tc["plus"]


def test_win_range_rounds_as_its_sql(spark, tmp_path):
    rows = [(k, 1, p) for k, p in enumerate([0.5, 1.5, 2.5, 50000.5, 50001.5, 50001.4, 50002.5, 50002.6, -0.5, -1.5, -49999.5])]
    spark.createDataFrame(rows, "o_orderkey long, o_custkey long, o_totalprice double").toPandas().to_parquet(tmp_path / "orders.parquet")
    con = duckdb.connect()
    con.sql(f"create view orders as select * from '{tmp_path}/orders.parquet'")
    assert {tuple(r) for r in registry.QUERIES["win_range"](spark, str(tmp_path)).collect()} == set(con.sql(registry.SQL["win_range"]).fetchall())
