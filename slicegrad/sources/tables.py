"""Loaders of the given tables and the derived sample sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def instant(ntz: Column) -> Column:
    """A zone-less timestamp as an instant (sessions run in UTC), as watermarks need it."""
    return ntz.cast("timestamp")


def vec8(spark: SparkSession, sf_dir: str) -> DataFrame:
    """id, the first 8 dimensions times 8, and the planted linear target of the first three."""
    e = load(spark, sf_dir, "embeddings")
    x = F.transform(F.slice("embedding", 1, 8), lambda v: v.cast("double") * 8)
    return e.select(F.col("vec_id").alias("id"), x.alias("x")).withColumn("y", 3 * F.col("x")[0] - 2 * F.col("x")[1] + 0.5 * F.col("x")[2])


#: The same in DuckDB; queries put it in a WITH list.
VEC8_SQL = """s AS (SELECT id, x, 3 * x[1] - 2 * x[2] + 0.5 * x[3] AS y FROM (
  SELECT vec_id AS id, list_transform(embedding[1:8], lambda v: v::DOUBLE * 8) AS x FROM embeddings))"""


def interactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct (user, item) of orders and line items, with the last order date and how often."""
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    l = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    both = o.join(l, o.o_orderkey == l.l_orderkey)
    return both.groupBy(F.col("o_custkey").alias("u"), F.col("l_partkey").alias("i")).agg(F.max("o_orderdate").alias("ts"), F.count(F.lit(1)).alias("n"))


INTERACTIONS_SQL = """inter AS (SELECT o_custkey AS u, l_partkey AS i, max(o_orderdate) AS ts, count(*) AS n
  FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2)"""
