"""File formats keep odd rows, and filters and columns reach the scan."""

import pytest

from slicegrad.sources.files import scanned


@pytest.mark.parametrize("kind", ["csv", "json", "orc", "parquet"])
def test_odd_rows_survive(spark, kind):
    rows = [(1, 'a "quoted", one\nof two lines', 0.1), (2, None, None), (3, "", 1e-300), (None, "  blanks ", -0.5), (1, 'a "quoted", one\nof two lines', 0.1), (4, "back\\slash", 2.0)]
    df = spark.createDataFrame(rows, "id long, text string, x double")
    assert sorted(map(repr, scanned(df, kind).collect())) == sorted(map(repr, df.collect()))
    assert scanned(df.filter("false"), kind).count() == 0


def test_text_lines(spark):
    df = spark.createDataFrame([("one",), ("",), ("tw o ",)], "value string")
    assert sorted(r[0] for r in scanned(df, "text").collect()) == ["", "one", "tw o "]
    with pytest.raises(ValueError):
        scanned(df, "avro")


def test_orc_scan_is_pruned(spark):
    df = spark.range(100).selectExpr("id", "id * 2 as b", "cast(id as string) as c")
    plan = scanned(df, "orc").filter("b >= 50").select("id")._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(b,50)" in plan and "c:string" not in plan
