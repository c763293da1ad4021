"""Streams: windows, sessions, state, joins and routed classification over files that arrive.

Each query runs all that is available into files of the shared folder and returns them. Append mode leaves windows out that the
last watermark has not closed.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slicegrad.functions.arrays import dot
from slicegrad.plans.core import _LANG_S, LANGS, lang_samples, softmax_rounds, softmax_sql, word_counts
from slicegrad.plans.kit import Book
from slicegrad.sources.store import shared_folder
from slicegrad.sources.tables import load

B = Book()
QUERIES, ORACLES = B.queries, B.oracles
EPOCH = "TIMESTAMP '2024-01-01'"


def stream(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """The table as a stream of files; a bus would differ in format and options only."""
    schema = load(spark, sf_dir, table).schema
    pattern = f"{sf_dir}/{table[:-1]}[{table[-1]}].parquet"  # a pattern takes a single file as well as a folder
    return spark.readStream.schema(schema).parquet(pattern)


def timed(spark, sf_dir, delay: str = "1 hour") -> DataFrame:
    return stream(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run all that is available and return what came out, from files in the shared folder.

    An appending stream writes files itself; one that updates or completes writes each batch's rows, and the last row or
    table counts: an update keeps every batch's, a complete one the last only.
    """
    spark = df.sparkSession
    where = shared_folder(spark, "stream")
    out = df.writeStream.outputMode(mode).option("checkpointLocation", f"{where}/check").trigger(availableNow=True)
    if mode == "append":
        out.format("parquet").start(f"{where}/out").awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{where}/out")

    def write(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{where}/out/{epoch if mode == 'update' else 0}")

    out.foreachBatch(write).start().awaitTermination()
    return spark.read.schema(df.schema).option("recursiveFileLookup", True).parquet(f"{where}/out")


def hours(c):
    return F.floor((F.unix_timestamp(c) - 1704067200) / 3600)


CLOSED = "(SELECT max(ts) - INTERVAL 1 HOUR FROM events)"


@B.add("st_tumbling", f"SELECT date_diff('hour', {EPOCH}, date_trunc('hour', ts))::BIGINT AS hour, count(*) AS n FROM events GROUP BY date_trunc('hour', ts) HAVING date_trunc('hour', ts) + INTERVAL 1 HOUR <= {CLOSED}")
def st_tumbling(spark, d):
    out = drained(timed(spark, d).groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n")))
    return out.select(hours(F.col("window.start")).alias("hour"), "n")


@B.add("st_sliding", f"""SELECT date_diff('hour', {EPOCH}, w)::BIGINT AS hour, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts) - INTERVAL 1 HOUR, date_trunc('hour', ts)]) AS w FROM events) GROUP BY w HAVING w + INTERVAL 2 HOUR <= {CLOSED}""")
def st_sliding(spark, d):
    out = drained(timed(spark, d).groupBy(F.window("ts", "2 hours", "1 hour")).agg(F.count(F.lit(1)).alias("n")))
    return out.select(hours(F.col("window.start")).alias("hour"), "n")


SESSION_SQL = f"""WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) >= INTERVAL 2 HOUR THEN 1 ELSE 0 END AS fresh FROM events),
  s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
  SELECT user_id, count(*) AS n FROM s GROUP BY user_id, k HAVING max(ts) + INTERVAL 2 HOUR <= {CLOSED}"""


@B.add("st_session", SESSION_SQL)
def st_session(spark, d):
    out = drained(timed(spark, d).groupBy("user_id", F.session_window("ts", "2 hours")).agg(F.count(F.lit(1)).alias("n")))
    return out.select("user_id", "n")


@B.add("st_dedup", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def st_dedup(spark, d):
    """Every event twice; the copies within the watermark go."""
    twice = timed(spark, d).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return drained(twice.dropDuplicatesWithinWatermark(["event_id"])).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@B.add("st_late_rows", "SELECT count(*) AS kept FROM events")
def st_late_rows(spark, d):
    """In order, nothing is late."""
    out = drained(timed(spark, d).groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n")), "update")
    return out.agg(F.sum("n").alias("kept"))


@B.add("st_stream_static", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def st_stream_static(spark, d):
    c = load(spark, d, "customer").select("c_custkey", "c_mktsegment")
    return drained(stream(spark, d, "events").join(c, F.col("user_id") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")), "complete")


@B.add("st_stream_stream", "SELECT p.event_id AS purchase, c.event_id AS click FROM events p JOIN events c ON p.user_id = c.user_id AND c.ts >= p.ts - INTERVAL 30 MINUTE AND c.ts <= p.ts WHERE p.event_type = 'purchase' AND c.event_type = 'click'")
def st_stream_stream(spark, d):
    p = timed(spark, d).filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("pu"), F.col("ts").alias("pt"))
    c = timed(spark, d).filter("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("cu"), F.col("ts").alias("ct"))
    return drained(p.join(c, F.expr("pu = cu and ct >= pt - interval 30 minutes and ct <= pt")).select("purchase", "click"))


@B.add("st_running_user", "SELECT user_id, count(*) AS n, sum(round(value * 100)::BIGINT)::BIGINT AS cents FROM events GROUP BY 1")
def st_running_user(spark, d):
    """Per-user count and sum as state; the last row of each user is its state."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(key, frames, state):
        n, cents = state.get if state.exists else (0, 0)
        for f in frames:
            n, cents = n + len(f), cents + int(f["cents"].sum())
        state.update((n, cents))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "cents": [cents]})

    rows = stream(spark, d, "events").select("user_id", F.round(F.col("value") * 100).cast("long").alias("cents"))
    out = rows.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, cents long", "n long, cents long", "update", GroupStateTimeout.NoTimeout)
    return drained(out, "update").groupBy("user_id").agg(F.max("n").alias("n"), F.max_by("cents", "n").alias("cents"))


@B.add("st_online_weights")
def st_online_weights(spark, d):
    """Online regression of the value on the hour, one state for each event type."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(key, frames, state):
        w0, w1, n = state.get if state.exists else (0.0, 0.0, 0)
        for f in frames:
            for x, y in zip(f["x"], f["y"]):
                e = w0 + w1 * x - y
                w0, w1, n = w0 - 0.05 * e, w1 - 0.05 * e * x, n + 1
        state.update((w0, w1, n))
        yield pd.DataFrame({"event_type": [key[0]], "w0": [w0], "w1": [w1], "n": [n]})

    rows = stream(spark, d, "events").select("event_type", (F.hour(F.col("ts").cast("timestamp")) / 24.0).alias("x"), (F.col("value") / 100).alias("y"))
    return drained(rows.groupBy("event_type").applyInPandasWithState(step, "event_type string, w0 double, w1 double, n long", "w0 double, w1 double, n long", "update", GroupStateTimeout.NoTimeout), "update")


def trained_routes(spark, sf_dir) -> DataFrame:
    """One row: the weights that the text pipeline learns, to go with every call."""
    w = softmax_rounds(lang_samples(spark, sf_dir), 4, 3)
    return spark.createDataFrame([([[float(v) for v in r] for r in w],)], "w array<array<double>>")


def routed(calls: DataFrame, weights: DataFrame) -> DataFrame:
    """Calls of users, each to the language that the trained model gives it; calls without a word go to the first."""
    said = calls.filter("role = 'user'").select("conv_id", "turn", word_counts(F.col("text")).alias("c")).crossJoin(F.broadcast(weights))
    z = said.withColumn("z", F.transform("w", lambda r: dot(r, F.col("c"))))
    best = F.when(F.aggregate("c", F.lit(0.0), lambda a, v: a + v) > 0, F.array_position("z", F.array_max("z")) - 1).otherwise(0).cast("int")
    return z.select("conv_id", "turn", F.get(F.array(*map(F.lit, LANGS)), best).alias("route"))


_ROUTE_SQL = softmax_sql(_LANG_S, 4, """SELECT conv_id, turn, ['de', 'en', 'es', 'fr'][CASE WHEN list_sum(n) > 0 THEN list_position(z, list_max(z)) ELSE 1 END] AS route FROM (
    SELECT conv_id, turn, n, list_transform(range(0, 4), lambda c: list_inner_product(t.w[c * 16 + 1:c * 16 + 16], n)) AS z FROM t, (
      SELECT conv_id, turn, list_transform(range(0, 16), lambda b: len(list_filter(own, lambda v: v = b))::DOUBLE) AS n FROM (
        SELECT conv_id, turn, list_transform(regexp_extract_all(text, '[A-Za-z]+'), lambda w: ('0x' || substr(md5(lower(w)), 1, 8))::BIGINT % 16) AS own FROM conversations WHERE role = 'user')) WHERE it = 3)""")


@B.add("w12_stream_classify", _ROUTE_SQL)
def w12_stream_classify(spark, d):
    """No state and no shuffle: what the trained model says in a batch, as calls arrive."""
    return drained(routed(stream(spark, d, "conversations"), trained_routes(spark, d)))


@B.add("w12_route_counts", f"SELECT route, count(*) AS n FROM ({_ROUTE_SQL}) GROUP BY 1")
def w12_route_counts(spark, d):
    return drained(routed(stream(spark, d, "conversations"), trained_routes(spark, d)).groupBy("route").agg(F.count(F.lit(1)).alias("n")), "complete")


@B.add("w12_stream_rates")
def w12_stream_rates(spark, d):
    """Rows, rows a second, seconds a batch and late rows that went, as the stream's own progress tells."""
    where = shared_folder(spark, "stream")
    counted = timed(spark, d).groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    query = counted.writeStream.outputMode("append").format("parquet").option("checkpointLocation", f"{where}/check").trigger(availableNow=True).start(f"{where}/out")
    query.awaitTermination()
    seen = [p for p in query.recentProgress]
    late = [sum(int(o["numRowsDroppedByWatermark"]) for o in p["stateOperators"]) for p in seen]
    rows = [(int(p["batchId"]), int(p["numInputRows"]), float(p["processedRowsPerSecond"] or 0.0), p["durationMs"].get("triggerExecution", 0) / 1000, n) for p, n in zip(seen, late)]
    return spark.createDataFrame(rows, "batch long, n_rows long, rows_per_s double, seconds double, late long")


def route_sink(spark: SparkSession, sf_dir: str, folder: str, checkpoint: str, weights: DataFrame) -> None:
    """Calls to one folder a route; a batch that is tried again writes over its own files."""
    def write(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").partitionBy("route").parquet(f"{folder}/epoch={epoch}")

    query = routed(stream(spark, sf_dir, "conversations"), weights).writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
