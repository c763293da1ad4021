"""Scans of files other than parquet, each over a whole table."""

from __future__ import annotations

from pyspark.sql import functions as F

from slicegrad.plans.kit import Book
from slicegrad.sources.files import scanned
from slicegrad.sources.tables import load

B = Book()
QUERIES, ORACLES = B.queries, B.oracles


@B.add("src_csv_orders", "SELECT o_orderkey, o_custkey, o_orderstatus, o_totalprice, o_orderdate FROM orders WHERE o_orderstatus = 'F'")
def src_csv_orders(spark, d):
    rows = load(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate")
    return scanned(rows, "csv").filter("o_orderstatus = 'F'")


@B.add("src_json_events", "SELECT event_type, count(*) AS n, count(props) AS n_props, max(ts) AS last_ts FROM events GROUP BY 1")
def src_json_events(spark, d):
    """The schema given prunes what the parser builds."""
    e = scanned(load(spark, d, "events").select("event_type", "ts", "props"), "json")
    return e.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.count("props").alias("n_props"), F.max("ts").alias("last_ts"))


@B.add("src_orc_lineitem", "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity >= 45")
def src_orc_lineitem(spark, d):
    """Columns and the filter reach the ORC scan."""
    return scanned(load(spark, d, "lineitem"), "orc").filter("l_quantity >= 45").select("l_orderkey", "l_linenumber", "l_quantity")


@B.add("src_text_urls", "SELECT split_part(url, '/', 3) AS host, count(*) AS n FROM pages WHERE url IS NOT NULL GROUP BY 1")
def src_text_urls(spark, d):
    lines = scanned(load(spark, d, "pages").filter("url is not null").select(F.col("url").alias("value")), "text")
    return lines.groupBy(F.split_part("value", F.lit("/"), F.lit(3)).alias("host")).agg(F.count(F.lit(1)).alias("n"))
