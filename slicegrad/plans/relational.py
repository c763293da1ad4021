"""Relational preparation around training: scans, joins, aggregates, windows, strings, arrays."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from slicegrad.functions.arrays import argmax, dot, norm, softmax, sums, text_bucket
from slicegrad.plans.kit import Book
from slicegrad.sources.tables import INTERACTIONS_SQL, interactions, load

B = Book()
QUERIES, ORACLES = B.queries, B.oracles


def n1():
    return F.count(F.lit(1))


@B.add("p_filter_project", """SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem
  WHERE l_shipdate >= TIMESTAMP '1997-01-01' AND l_shipdate < TIMESTAMP '1998-01-01' AND l_discount BETWEEN 0.03 AND 0.05""")
def p_filter_project(spark, d):
    l = load(spark, d, "lineitem").filter("l_shipdate >= timestamp_ntz'1997-01-01' and l_shipdate < timestamp_ntz'1998-01-01' and l_discount between 0.03D and 0.05D")
    return l.select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@B.add("p_case_bucket", """SELECT CASE WHEN p_size <= 10 THEN 'small' WHEN p_size <= 30 THEN 'medium' ELSE 'large' END AS band, count(*) AS n, min(p_retailprice) AS low, max(p_retailprice) AS high FROM part GROUP BY 1""")
def p_case_bucket(spark, d):
    band = F.when(F.col("p_size") <= 10, "small").when(F.col("p_size") <= 30, "medium").otherwise("large")
    return load(spark, d, "part").groupBy(band.alias("band")).agg(n1().alias("n"), F.min("p_retailprice").alias("low"), F.max("p_retailprice").alias("high"))


@B.add("j_docs_labels", "SELECT lang, count(l.doc_id) AS labelled, count(*) - count(l.doc_id) AS unlabelled FROM documents d LEFT JOIN labels l USING (doc_id) GROUP BY 1")
def j_docs_labels(spark, d):
    l = load(spark, d, "labels").select("doc_id", F.lit(1).alias("has"))
    return load(spark, d, "documents").select("doc_id", "lang").join(l, "doc_id", "left").groupBy("lang").agg(F.count("has").alias("labelled"), (n1() - F.count("has")).alias("unlabelled"))


@B.add("w2_interactions", f"WITH {INTERACTIONS_SQL} SELECT u, i, ts, n FROM inter")
def j_interactions(spark, d):
    return interactions(spark, d)


@B.add("j_star", """SELECT r_name, extract(year FROM o_orderdate)::BIGINT AS y, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2""")
def j_star(spark, d):
    geo = load(spark, d, "nation").join(load(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    c = load(spark, d, "customer").join(F.broadcast(geo), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "r_name")
    o = load(spark, d, "orders").select("o_orderkey", "o_custkey", F.year("o_orderdate").cast("long").alias("y")).join(c, F.col("o_custkey") == F.col("c_custkey"))
    l = load(spark, d, "lineitem").select("l_orderkey", "l_extendedprice", "l_discount")
    return l.join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("r_name", "y").agg(F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


@B.add("j_broadcast_nation", "SELECT n_name, count(*) AS n, round(sum(s_acctbal), 2) AS balance FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY 1")
def j_broadcast_nation(spark, d):
    return load(spark, d, "supplier").join(F.broadcast(load(spark, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(n1().alias("n"), F.round(F.sum("s_acctbal"), 2).alias("balance"))


@B.add("j_unlabelled_anti", "SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def j_unlabelled_anti(spark, d):
    return load(spark, d, "documents").select("doc_id", "lang").join(load(spark, d, "labels").select("doc_id"), "doc_id", "left_anti")


@B.add("j_purchased_semi", "SELECT p_partkey, p_brand FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = 'BUILDING')")
def j_purchased_semi(spark, d):
    c = load(spark, d, "customer").filter("c_mktsegment = 'BUILDING'").select("c_custkey")
    o = load(spark, d, "orders").select("o_orderkey", "o_custkey").join(c, F.col("o_custkey") == F.col("c_custkey"), "left_semi")
    l = load(spark, d, "lineitem").select("l_orderkey", "l_partkey").join(o, F.col("l_orderkey") == F.col("o_orderkey"), "left_semi")
    return load(spark, d, "part").select("p_partkey", "p_brand").join(l, F.col("p_partkey") == F.col("l_partkey"), "left_semi")


HOURS_SQL = "SELECT unnest(generate_series(TIMESTAMP '2024-01-01', (SELECT greatest(max(date_trunc('hour', ts)), TIMESTAMP '2024-01-30 23:00:00') FROM events), INTERVAL 1 HOUR)) AS h"


def hour_grid(events):
    """(hour) from the first of January 2024 to the last event, thirty days at least: one row, spread out."""
    last = events.agg(F.greatest(F.max(hour_of()), F.lit(719).cast("long")).alias("last"))
    return last.select(F.explode(F.sequence(F.lit(0).cast("long"), F.coalesce("last", F.lit(719).cast("long")))).alias("hour"))


@B.add("j_left_zero_fill", f"""WITH h AS ({HOURS_SQL}), c AS (SELECT unnest(range(0, 64)) AS cell), e AS (SELECT date_trunc('hour', ts) AS h, user_id % 64 AS cell, count(*) AS n FROM events GROUP BY 1, 2)
  SELECT date_diff('hour', TIMESTAMP '2024-01-01', h.h)::BIGINT AS hour, c.cell, coalesce(n, 0)::BIGINT AS n FROM h CROSS JOIN c LEFT JOIN e ON e.h = h.h AND e.cell = c.cell""")
def j_left_zero_fill(spark, d):
    grid = hour_grid(load(spark, d, "events")).crossJoin(F.broadcast(spark.range(64).withColumnRenamed("id", "cell")))
    e = load(spark, d, "events").select(hour_of().alias("hour"), (F.col("user_id") % 64).alias("cell")).groupBy("hour", "cell").agg(n1().alias("n"))
    return grid.join(e, ["hour", "cell"], "left").fillna(0, ["n"])


def hour_of():
    """Hours since the first of January 2024."""
    return F.floor((F.unix_timestamp(F.col("ts").cast("timestamp")) - 1704067200) / 3600)


@B.add("j_cross_anchor", """SELECT vec_id // 16 AS pic, a AS anchor, round(sum(embedding[d + 1]::DOUBLE ** 2) * (1 + a), 5) AS energy FROM embeddings, (SELECT unnest(range(0, 16)) AS a), (SELECT unnest(range(0, 64)) AS d)
  WHERE vec_id % 16 = a GROUP BY 1, 2""")
def j_cross_anchor(spark, d):
    anchors = spark.range(16).withColumnRenamed("id", "anchor")
    e = load(spark, d, "embeddings").select(F.floor(F.col("vec_id") / 16).alias("pic"), (F.col("vec_id") % 16).alias("tile"), F.aggregate("embedding", F.lit(0.0), lambda a, v: a + v.cast("double") * v.cast("double")).alias("e"))
    return e.join(F.broadcast(anchors), F.col("tile") == F.col("anchor")).groupBy("pic", "anchor").agg(F.round(F.sum("e") * (1 + F.col("anchor")), 5).alias("energy"))


@B.add("j_theta_price_band", "SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_partkey < b.p_partkey AND abs(a.p_retailprice - b.p_retailprice) < 5")
def j_theta_price_band(spark, d):
    """Brand and a price band of one are the join key: a part looks into its own band and the five above, so that a pair meets once and few in vain."""
    p = load(spark, d, "part").select("p_partkey", "p_brand", "p_retailprice")
    low = p.select(F.col("p_partkey").alias("x"), "p_brand", F.col("p_retailprice").alias("px"), F.posexplode(F.array(*[F.floor("p_retailprice") + k for k in range(6)])).alias("up", "band"))
    high = p.select(F.col("p_partkey").alias("y"), "p_brand", F.col("p_retailprice").alias("py"), F.floor("p_retailprice").alias("band"))
    # within a band both orders of a pair meet, and one is kept; the bands above bring it once
    met = low.join(high, ["p_brand", "band"]).filter("case when up = 0 then x < y else x <> y end and abs(px - py) < 5")
    return met.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))


@B.add("j_interval_events", """SELECT p.event_id AS purchase, c.event_id AS click FROM events p JOIN events c ON p.user_id = c.user_id AND c.ts >= p.ts - INTERVAL 30 MINUTE AND c.ts < p.ts WHERE p.event_type = 'purchase' AND c.event_type = 'click'""")
def j_interval_events(spark, d):
    """Half-hour buckets make the interval an equality: a purchase looks into its own and the one before."""
    e = load(spark, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    span = 1_800_000_000
    p = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("at").alias("pa"), F.explode(F.array(F.floor(F.col("at") / span), F.floor(F.col("at") / span) - 1)).alias("slot"))
    c = e.filter("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("at").alias("ca"), F.floor(F.col("at") / span).alias("slot"))
    return p.join(c, ["user_id", "slot"]).filter(f"ca >= pa - {span} and ca < pa").select("purchase", "click")


@B.add("j_asof_version", """WITH v AS (SELECT k AS version, TIMESTAMP '2024-01-01' + to_days(k::INTEGER) * 3 AS start FROM (SELECT unnest(range(0, 10)) AS k)) SELECT event_id, version::BIGINT AS version FROM events ASOF LEFT JOIN v ON ts >= start""")
def j_asof_version(spark, d):
    """Few versions: a broadcast of their starts, and the last one not after the event."""
    starts = F.array(*[F.lit(1704067200_000_000 + k * 3 * 86_400_000_000) for k in range(10)])
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    n = F.size(F.filter(starts, lambda s: s <= at))
    return load(spark, d, "events").select("event_id", F.when(n > 0, n - 1).cast("long").alias("version"))


@B.add("j_copurchase", "SELECT a.l_partkey AS a, b.l_partkey AS b, count(*) AS n FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) a JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1, 2 HAVING count(*) >= 2")
def j_copurchase(spark, d):
    l = load(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    a, b = l.withColumnRenamed("l_partkey", "a"), l.withColumnRenamed("l_partkey", "b")
    return a.join(b, "l_orderkey").filter("a < b").groupBy("a", "b").agg(n1().alias("n")).filter("n >= 2")


@B.add("a_feature_stats", "SELECT j::BIGINT AS dim, count(*) AS n, round(avg(embedding[j + 1]::DOUBLE), 6) AS mean, round(stddev(embedding[j + 1]::DOUBLE), 6) AS sd, round(min(embedding[j + 1]::DOUBLE), 6) AS low, round(max(embedding[j + 1]::DOUBLE), 6) AS high FROM embeddings, (SELECT unnest(range(0, 8)) AS j) GROUP BY 1")
def a_feature_stats(spark, d):
    e = load(spark, d, "embeddings").select(F.posexplode(F.slice("embedding", 1, 8)).alias("dim", "v")).select(F.col("dim").cast("long").alias("dim"), F.col("v").cast("double").alias("v"))
    return e.groupBy("dim").agg(n1().alias("n"), F.round(F.avg("v"), 6).alias("mean"), F.round(F.stddev("v"), 6).alias("sd"), F.round(F.min("v"), 6).alias("low"), F.round(F.max("v"), 6).alias("high"))


@B.add("a_returnflag", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS qty, round(sum(l_extendedprice), 2) AS gross, round(sum(l_extendedprice * (1 - l_discount)), 2) AS net, round(avg(l_discount), 6) AS discount, count(*) AS n FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY 1, 2")
def a_returnflag(spark, d):
    l = load(spark, d, "lineitem").filter("l_shipdate <= timestamp_ntz'1998-09-02'")
    return l.groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.sum("l_extendedprice"), 2).alias("gross"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("net"), F.round(F.avg("l_discount"), 6).alias("discount"), n1().alias("n"))


@B.add("a_distinct_items", "SELECT c_mktsegment, count(DISTINCT l_partkey) AS items FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def a_distinct_items(spark, d):
    c = load(spark, d, "customer").select("c_custkey", "c_mktsegment")
    return interactions(spark, d).join(c, F.col("u") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.countDistinct("i").alias("items"))


@B.add("a_approx_users")
def a_approx_users(spark, d):
    return load(spark, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"))


@B.add("a_rollup_lang_source", "SELECT lang, source, grouping(lang)::BIGINT AS gl, grouping(source)::BIGINT AS gs, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY ROLLUP (lang, source)")
def a_rollup_lang_source(spark, d):
    return load(spark, d, "documents").rollup("lang", "source").agg(F.grouping("lang").cast("long").alias("gl"), F.grouping("source").cast("long").alias("gs"), n1().alias("n"), F.sum("n_chars").alias("chars"))


@B.add("a_cube_flags", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def a_cube_flags(spark, d):
    return load(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(n1().alias("n"))


@B.add("a_unpivot_features", "SELECT vec_id, 'd' || j AS dim, round(embedding[j + 1]::DOUBLE, 6) AS v FROM embeddings, (SELECT unnest(range(0, 8)) AS j)")
def a_unpivot_features(spark, d):
    e = load(spark, d, "embeddings").select("vec_id", *[F.round(F.col("embedding")[j].cast("double"), 6).alias(f"d{j}") for j in range(8)])
    return e.unpivot("vec_id", [f"d{j}" for j in range(8)], "dim", "v")


def _vec(op, key, sql):
    @B.add(key, sql)
    def run(spark, d):
        e = load(spark, d, "embeddings").select("label", F.transform("embedding", lambda v: v.cast("double")).alias("x"))
        total = e.groupBy("label").agg(sums(F.col("x"), 64).alias("s"), n1().alias("n"))
        value = F.col("v") if op == "sum" else F.col("v") / F.col("n")
        return total.select("label", "n", F.posexplode("s").alias("pos", "v")).select("label", F.col("pos").cast("long").alias("pos"), F.round(value, 5).alias("v"))


_vec("sum", "a_vec_sum_by_label", "SELECT label, j::BIGINT AS pos, round(sum(embedding[j + 1]::DOUBLE), 5) AS v FROM embeddings, (SELECT unnest(range(0, 64)) AS j) GROUP BY 1, 2")
_CENTROID_SQL = "SELECT label, j::BIGINT AS pos, round(avg(embedding[j + 1]::DOUBLE), 5) AS v FROM embeddings, (SELECT unnest(range(0, 64)) AS j) GROUP BY 1, 2"
_vec("avg", "a_centroids", _CENTROID_SQL)


@B.add("x_udaf_vec_mean", _CENTROID_SQL)
def x_udaf_vec_mean(spark, d):
    """The same mean as a grouped Arrow function that adds batch by batch, for vectors too wide for k sums."""
    import numpy as np
    import pandas as pd

    def mean(key, pdf):
        m = np.stack([np.asarray(v, dtype=np.float64) for v in pdf["x"]]).mean(0)
        return pd.DataFrame({"label": key[0], "pos": np.arange(len(m), dtype=np.int64), "v": m})

    e = load(spark, d, "embeddings").select("label", F.transform("embedding", lambda v: v.cast("double")).alias("x"))
    return e.groupBy("label").applyInPandas(mean, "label int, pos long, v double").withColumn("v", F.round("v", 5))


@B.add("a_hash_split", "SELECT lang, doc_id % 5 = 0 AS test, count(*) AS n FROM documents GROUP BY 1, 2")
def a_hash_split(spark, d):
    return load(spark, d, "documents").groupBy("lang", (F.col("doc_id") % 5 == 0).alias("test")).agg(n1().alias("n"))


@B.add("wdw_rank_items", """WITH r AS (SELECT c_mktsegment, l_partkey, round(sum(l_extendedprice), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2)
  SELECT *, rank() OVER w AS rk, dense_rank() OVER w AS drk, row_number() OVER (PARTITION BY c_mktsegment ORDER BY revenue DESC, l_partkey) AS rn FROM r WINDOW w AS (PARTITION BY c_mktsegment ORDER BY revenue DESC) QUALIFY rn <= 20""")
def wdw_rank_items(spark, d):
    c = load(spark, d, "customer").select("c_custkey", "c_mktsegment")
    o = load(spark, d, "orders").select("o_orderkey", "o_custkey").join(c, F.col("o_custkey") == F.col("c_custkey"))
    l = load(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_extendedprice").join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    r = l.groupBy("c_mktsegment", "l_partkey").agg(F.round(F.sum("l_extendedprice"), 2).alias("revenue"))
    w = Window.partitionBy("c_mktsegment").orderBy(F.desc("revenue"))
    ranked = r.withColumn("rk", F.rank().over(w).cast("long")).withColumn("drk", F.dense_rank().over(w).cast("long")).withColumn("rn", F.row_number().over(Window.partitionBy("c_mktsegment").orderBy(F.desc("revenue"), "l_partkey")).cast("long"))
    return ranked.filter("rn <= 20")


@B.add("wdw_lag_lead", "SELECT event_id, lag(event_id) OVER w AS prev_id, lead(event_id) OVER w AS next_id, date_diff('second', lag(ts) OVER w, ts)::BIGINT AS gap FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def wdw_lag_lead(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    s = F.unix_timestamp(F.col("ts").cast("timestamp"))
    e = load(spark, d, "events").select("event_id", "user_id", "ts", s.alias("s"))
    return e.select("event_id", F.lag("event_id").over(w).alias("prev_id"), F.lead("event_id").over(w).alias("next_id"), (F.col("s") - F.lag("s").over(w)).alias("gap"))


@B.add("wdw_range_frame", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW), 4) AS hour_sum FROM events")
def wdw_range_frame(spark, d):
    e = load(spark, d, "events").select("event_id", "user_id", "value", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    return e.select("event_id", F.round(F.sum("value").over(Window.partitionBy("user_id").orderBy("at").rangeBetween(-3_600_000_000, 0)), 4).alias("hour_sum"))


@B.add("wdw_ntile", "SELECT c_custkey, ntile(4) OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey) AS quarter, round(percent_rank() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal), 6) AS pr, round(cume_dist() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal), 6) AS cd FROM customer")
def wdw_ntile(spark, d):
    w = Window.partitionBy("c_mktsegment").orderBy("c_acctbal")
    return load(spark, d, "customer").select("c_custkey", F.ntile(4).over(Window.partitionBy("c_mktsegment").orderBy("c_acctbal", "c_custkey")).cast("long").alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@B.add("o_topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def o_topk_global(spark, d):
    return load(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@B.add("o_topk_group", "SELECT p_brand, p_partkey, p_retailprice FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) <= 3")
def o_topk_group(spark, d):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return load(spark, d, "part").select("p_brand", "p_partkey", "p_retailprice").withColumn("rn", F.row_number().over(w)).filter("rn <= 3").drop("rn")


@B.add("o_best_by", "SELECT p_brand, p_partkey FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) = 1")
def o_best_by(spark, d):
    best = F.max(F.struct("p_retailprice", (-F.col("p_partkey")).alias("k")))
    return load(spark, d, "part").groupBy("p_brand").agg((-best["k"]).alias("p_partkey"))


@B.add("u_train_test_disjoint", "SELECT count(*) AS n FROM (SELECT doc_id FROM documents WHERE doc_id % 5 = 0 INTERSECT SELECT doc_id FROM documents WHERE doc_id % 5 <> 0)")
def u_train_test_disjoint(spark, d):
    x = load(spark, d, "documents").select("doc_id")
    return x.filter("doc_id % 5 = 0").intersect(x.filter("doc_id % 5 != 0")).agg(n1().alias("n"))


@B.add("u_union_streams", "SELECT user_id AS u FROM events UNION SELECT o_custkey FROM orders")
def u_union_streams(spark, d):
    return load(spark, d, "events").select(F.col("user_id").alias("u")).union(load(spark, d, "orders").select("o_custkey")).distinct()


@B.add("u_except_unlabelled", "SELECT doc_id FROM documents EXCEPT SELECT doc_id FROM labels")
def u_except_unlabelled(spark, d):
    return load(spark, d, "documents").select("doc_id").exceptAll(load(spark, d, "labels").select("doc_id"))


@B.add("f_tokenise", "SELECT w, count(*) AS n FROM (SELECT lower(unnest(regexp_extract_all(text, '[A-Za-z]+'))) AS w FROM documents) GROUP BY 1 ORDER BY n DESC, w LIMIT 50")
def f_tokenise(spark, d):
    w = load(spark, d, "documents").select(F.explode(F.regexp_extract_all("text", F.lit("[A-Za-z]+"), F.lit(0))).alias("w")).select(F.lower("w").alias("w"))
    return w.groupBy("w").agg(n1().alias("n")).orderBy(F.desc("n"), "w").limit(50)


@B.add("f_ngrams", """WITH t AS (SELECT item_id, regexp_extract_all(lower(text), '[a-z]+') AS w FROM benchmark)
  SELECT item_id, w[k] || ' ' || w[k + 1] AS gram, count(*) AS n FROM (SELECT item_id, w, unnest(range(1, len(w))) AS k FROM t) GROUP BY 1, 2""")
def f_ngrams(spark, d):
    t = load(spark, d, "benchmark").select("item_id", F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0)).alias("w")).filter(F.size("w") > 1)
    grams = F.zip_with(F.slice("w", 1, F.size("w") - 1), F.slice("w", 2, F.size("w") - 1), lambda a, b: F.concat_ws(" ", a, b))
    return t.select("item_id", F.explode(grams).alias("gram")).groupBy("item_id", "gram").agg(n1().alias("n"))


@B.add("f_html_title", "SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title FROM pages")
def f_html_title(spark, d):
    return load(spark, d, "pages").select("page_id", F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"))


@B.add("f_url_parts", "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '://([^/?#]*)', 1) AS host, regexp_extract(url, '://[^/?#]*([^?#]*)', 1) AS path, regexp_extract(url, '[?]([^#]*)', 1) AS query FROM pages")
def f_url_parts(spark, d):
    u = lambda p: F.regexp_extract("url", p, 1)
    return load(spark, d, "pages").select("page_id", u("^([a-z]+)://").alias("scheme"), u("://([^/?#]*)").alias("host"), u("://[^/?#]*([^?#]*)").alias("path"), u("[?]([^#]*)").alias("query"))


@B.add("f_hash_bucket", "SELECT ('0x' || substr(md5(source), 1, 8))::BIGINT % 512 AS bucket, count(*) AS n FROM documents GROUP BY 1")
def f_hash_bucket(spark, d):
    return load(spark, d, "documents").groupBy(text_bucket(F.col("source"), 512).alias("bucket")).agg(n1().alias("n"))


@B.add("f_date_features", "SELECT o_orderkey, extract(year FROM o_orderdate)::BIGINT AS y, extract(month FROM o_orderdate)::BIGINT AS m, extract(isodow FROM o_orderdate)::BIGINT AS dow, round(sin(2 * pi() * extract(month FROM o_orderdate) / 12), 6) + 0.0 AS s, round(cos(2 * pi() * extract(month FROM o_orderdate) / 12), 6) + 0.0 AS c FROM orders")
def f_date_features(spark, d):
    m = F.month("o_orderdate")
    angle = 2 * F.pi() * m / 12
    return load(spark, d, "orders").select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), m.cast("long").alias("m"), (F.weekday("o_orderdate") + 1).cast("long").alias("dow"), (F.round(F.sin(angle), 6) + 0.0).alias("s"), (F.round(F.cos(angle), 6) + 0.0).alias("c"))


@B.add("f_activations", "SELECT vec_id, round(tanh(v), 6) AS th, round(1 / (1 + exp(-v)), 6) AS sg, round(greatest(v, 0), 6) + 0.0 AS rl, round(0.5 * (1 + v / (1 + abs(v))), 6) AS rational FROM (SELECT vec_id, embedding[1]::DOUBLE * 8 AS v FROM embeddings)")
def f_activations(spark, d):
    v = F.col("v")
    e = load(spark, d, "embeddings").select("vec_id", (F.col("embedding")[0].cast("double") * 8).alias("v"))
    return e.select("vec_id", F.round(F.tanh(v), 6).alias("th"), F.round(1 / (1 + F.exp(-v)), 6).alias("sg"), (F.round(F.greatest(v, F.lit(0.0)), 6) + 0.0).alias("rl"), F.round(0.5 * (1 + v / (1 + F.abs(v))), 6).alias("rational"))


def _first8():
    return F.transform(F.slice("embedding", 1, 8), lambda v: v.cast("double"))


_X8 = "list_transform(embedding[1:8], lambda v: v::DOUBLE)"


@B.add("f_softmax", f"SELECT vec_id, j::BIGINT AS pos, round(exp(x[j + 1]) / list_sum(list_transform(x, lambda v: exp(v))), 6) AS p FROM (SELECT vec_id, {_X8} AS x FROM embeddings), (SELECT unnest(range(0, 8)) AS j)")
def f_softmax(spark, d):
    e = load(spark, d, "embeddings").select("vec_id", _first8().alias("x"))
    return e.select("vec_id", F.posexplode(softmax(F.col("x"))).alias("pos", "p")).select("vec_id", F.col("pos").cast("long").alias("pos"), F.round("p", 6).alias("p"))


@B.add("f_dot", f"SELECT vec_id, round(list_inner_product(x, x), 6) AS dot FROM (SELECT vec_id, {_X8} AS x FROM embeddings)")
def f_dot(spark, d):
    return load(spark, d, "embeddings").select("vec_id", F.round(dot(_first8(), _first8()), 6).alias("dot"))


@B.add("f_l2_normalise", f"SELECT vec_id, j::BIGINT AS pos, round(x[j + 1] / sqrt(list_inner_product(x, x)), 6) AS v FROM (SELECT vec_id, {_X8} AS x FROM embeddings), (SELECT unnest(range(0, 8)) AS j)")
def f_l2_normalise(spark, d):
    e = load(spark, d, "embeddings").select("vec_id", _first8().alias("x")).withColumn("l", norm(F.col("x")))
    return e.select("vec_id", "l", F.posexplode("x").alias("pos", "v")).select("vec_id", F.col("pos").cast("long").alias("pos"), F.round(F.col("v") / F.col("l"), 6).alias("v"))


@B.add("f_argmax", f"SELECT vec_id, (list_position(x, list_max(x)) - 1)::BIGINT AS best FROM (SELECT vec_id, {_X8} AS x FROM embeddings)")
def f_argmax(spark, d):
    return load(spark, d, "embeddings").select("vec_id", argmax(_first8()).alias("best"))


@B.add("f_conv1d_sql", f"SELECT vec_id, j::BIGINT AS pos, round(0.5 * x[j + 1] - x[j + 2] + 0.25 * x[j + 3], 6) + 0.0 AS v FROM (SELECT vec_id, {_X8} AS x FROM embeddings), (SELECT unnest(range(0, 6)) AS j)")
def f_conv1d_sql(spark, d):
    e = load(spark, d, "embeddings").select("vec_id", _first8().alias("x"))
    out = F.transform(F.sequence(F.lit(0), F.lit(5)), lambda j: 0.5 * F.get("x", j) - F.get("x", j + 1) + 0.25 * F.get("x", j + 2))
    return e.select("vec_id", F.posexplode(out).alias("pos", "v")).select("vec_id", F.col("pos").cast("long").alias("pos"), (F.round("v", 6) + 0.0).alias("v"))


@B.add("f_props_k", "SELECT event_type, sum((props->>'$.k')::BIGINT)::BIGINT AS total, min((props->>'$.k')::BIGINT) AS low, max((props->>'$.k')::BIGINT) AS high FROM events GROUP BY 1")
def f_props_k(spark, d):
    k = F.from_json("props", "k long")["k"]
    return load(spark, d, "events").select("event_type", k.alias("k")).groupBy("event_type").agg(F.sum("k").alias("total"), F.min("k").alias("low"), F.max("k").alias("high"))


def _pixels(e, out):
    return e.select("vec_id", F.posexplode(out).alias("pos", "v")).select("vec_id", F.col("pos").cast("long").alias("pos"), F.round(F.col("v").cast("double"), 6).alias("v"))


@B.add("f_crop", "SELECT vec_id, j::BIGINT AS pos, round(embedding[(j // 4 + 2) * 8 + j % 4 + 2 + 1]::DOUBLE, 6) AS v FROM embeddings, (SELECT unnest(range(0, 16)) AS j)")
def f_crop(spark, d):
    return _pixels(load(spark, d, "embeddings"), F.transform(F.sequence(F.lit(0), F.lit(15)), lambda j: F.get("embedding", ((F.floor(j / 4) + 2) * 8 + j % 4 + 2).cast("int"))))


@B.add("f_flip", "SELECT vec_id, j::BIGINT AS pos, round(embedding[(j // 8) * 8 + 7 - j % 8 + 1]::DOUBLE, 6) AS v FROM embeddings, (SELECT unnest(range(0, 64)) AS j)")
def f_flip(spark, d):
    return _pixels(load(spark, d, "embeddings"), F.transform(F.sequence(F.lit(0), F.lit(63)), lambda j: F.get("embedding", (F.floor(j / 8) * 8 + 7 - j % 8).cast("int"))))


@B.add("f_resize_nearest", "SELECT vec_id, j::BIGINT AS pos, round(embedding[(j // 4 * 2) * 8 + j % 4 * 2 + 1]::DOUBLE, 6) AS v FROM embeddings, (SELECT unnest(range(0, 16)) AS j)")
def f_resize_nearest(spark, d):
    return _pixels(load(spark, d, "embeddings"), F.transform(F.sequence(F.lit(0), F.lit(15)), lambda j: F.get("embedding", (F.floor(j / 4) * 2 * 8 + j % 4 * 2).cast("int"))))


@B.add("x_predict_sql", """SELECT vec_id, round(list_sum(list_transform(range(1, 65), lambda j: embedding[j]::DOUBLE * (((j - 1) * 37 + 11) % 101 - 50) / 100.0)), 6) AS score FROM embeddings""")
def x_predict_sql(spark, d):
    """Scoring by a SQL function that is registered from expressions, so it stays in the JVM."""
    load(spark, d, "embeddings").createOrReplaceTempView("sg_embeddings")
    w = ", ".join(f"{((j * 37 + 11) % 101 - 50) / 100}D" for j in range(64))
    spark.sql("create or replace temporary function sg_predict(x array<float>) returns double return aggregate(zip_with(x, array(" + w + "), (a, b) -> cast(a as double) * b), 0D, (s, v) -> s + v)")
    return spark.sql("select vec_id, round(sg_predict(embedding), 6) as score from sg_embeddings")


@B.add("x_udtf_slices", "SELECT l_suppkey, s::BIGINT AS slice, (s * k // 4)::BIGINT AS low, ((s + 1) * k // 4)::BIGINT AS high FROM (SELECT l_suppkey, count(*) AS k FROM lineitem GROUP BY 1), (SELECT unnest(range(0, 4)) AS s)")
def x_udtf_slices(spark, d):
    """Where each supplier's line items are cut into four slices: a table function joined laterally to their counts."""
    from pyspark.sql.functions import lit, udtf

    @udtf(returnType="slice long, low long, high long")
    class Cuts:
        def eval(self, k: int, n: int):
            for s in range(n):
                yield s, s * k // n, (s + 1) * k // n

    items = load(spark, d, "lineitem").groupBy("l_suppkey").agg(n1().alias("k"))
    return items.lateralJoin(Cuts(F.col("k").outer(), lit(4))).select("l_suppkey", "slice", "low", "high")
