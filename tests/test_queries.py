"""Every registered query with SQL against DuckDB on the smallest tables."""

import os

import pytest

import __spark_entry__
from slicegrad import registry

SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")


@pytest.fixture(scope="module")
def duck():
    duckdb = pytest.importorskip("duckdb")
    con = duckdb.connect()
    for name in os.listdir(SF):
        con.execute(f"create view {name.removesuffix('.parquet')} as select * from '{SF}/{name}'")
    return con


def rows(columns, found):
    order = sorted(range(len(columns)), key=lambda k: columns[k])
    return sorted(tuple(repr(r[k] + 0.0) if isinstance(r[k], float) else str(r[k]) for k in order) for r in found)


@pytest.mark.parametrize("key", sorted(registry.oracle_sql()))
def test_query(spark, duck, key):
    got = registry.queries()[key](spark, SF)
    want = duck.execute(registry.oracle_sql()[key])
    names = [d[0] for d in want.description]
    assert sorted(got.columns) == sorted(names)
    assert rows(got.columns, got.collect()) == rows(names, want.fetchall())


@pytest.mark.parametrize("key", sorted(set(registry.queries()) - set(registry.oracle_sql())))
def test_runs(spark, key):
    assert registry.queries()[key](spark, SF).count() > 0


def test_entry(spark):
    assert __spark_entry__.entry(spark).columns == ["slice", "j", "w"]
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


@pytest.mark.parametrize("key", ["m_cluster_cost", "m_model_roundtrip", "m_traffic_model", "x_udtf_slices"])
def test_reads_a_table(spark, tmp_path, key):
    """The rows come from a given table: another one gives others."""
    for name in ("orders", "lineitem"):
        whole = spark.read.parquet(f"{SF}/{name}.parquet")
        whole.limit(whole.count() // 3).write.parquet(f"{tmp_path}/{name}.parquet")
    one, other = (sorted(map(str, registry.queries()[key](spark, where).collect())) for where in (SF, str(tmp_path)))
    assert one != other


def test_price_band_of_odd_prices(spark, tmp_path):
    """Pairs by brute force, whatever the price; bands are narrow, so that few pairs meet in vain."""
    prices = [0.0, -0.5, -5.0, 4.999, 5.0, 5.001, 904.99, 900.0, 905.0, 900.0, 909.999, None, 1e9, 1e9 + 4.5]
    parts = [(k * 7 % 23, "AB"[k % 2] if k != 9 else None, v) for k, v in enumerate(prices + prices[:10])]
    spark.createDataFrame(parts, "p_partkey long, p_brand string, p_retailprice double").write.parquet(f"{tmp_path}/part.parquet")
    got = registry.queries()["j_theta_price_band"](spark, str(tmp_path))
    want = [(a, b) for a, m, v in parts for b, n, w in parts if m is not None and m == n and a < b and None not in (v, w) and abs(v - w) < 5]
    assert sorted(map(tuple, got.collect())) == sorted(want)
    met = [x for x in got._jdf.queryExecution().optimizedPlan().toString().splitlines() if "posexplode" in x]
    assert len(met) == 1 and "/ 5.0" not in got._jdf.queryExecution().optimizedPlan().toString()
