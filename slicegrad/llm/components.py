"""Connected components of links that live in tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slicegrad.llm.common import cut


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(a, b) to (node, root): root is the smallest node that the node can reach; nodes without a link are absent.

    Each round links every node's larger neighbours to its smallest one and then its smaller neighbours to that,
    until nothing changes: the stars that remain are the components. Rows never outnumber the links, rounds grow
    with the logarithm of a component's span, and each round's table is cut into the shared checkpoint folder.
    A star's centre gets one pre-aggregated minimum; only the star's rows themselves meet it.
    """
    edges = cut(links.filter(F.col("a") != F.col("b")).select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    for _ in range(most_rounds):
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("c"), F.least("u", "m").alias("m"))
        large = both.filter("v > u").join(least, F.col("u") == F.col("c")).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        lowest = large.groupBy("u").agg(F.min("v").alias("m")).withColumnRenamed("u", "c")
        joined = large.join(lowest, F.col("u") == F.col("c"))
        small = joined.select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.*").filter("u != v").distinct()
        following = cut(small)
        same = following.count() == edges.count() and following.exceptAll(edges).isEmpty()
        edges = following
        if same:
            break
    else:
        raise RuntimeError("components did not settle")
    rooted = edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return rooted.unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
