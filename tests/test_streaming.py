"""Late rows, restarts, routes and the limited source."""

import os
import time

from pyspark.sql import functions as F

from slicegrad.sources.limited import LimitedPictures
from slicegrad.sources.store import WeightStore, one_version
from slicegrad.streaming import queries as streams

SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")


def files(spark, folder, parts):
    for k, rows in enumerate(parts):
        spark.createDataFrame(rows, "event_id long, at long").selectExpr("event_id", "timestamp_seconds(at) as ts").coalesce(1).write.parquet(f"{folder}/{k}")
        time.sleep(1.1)  # files are taken in the order of their times


def counted(spark, folder, check):
    s = spark.readStream.schema("event_id long, ts timestamp").option("maxFilesPerTrigger", 1).parquet(f"{folder}/*")
    agg = s.withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    name = f"late_{os.path.basename(folder)}"
    agg.writeStream.outputMode("update").format("memory").queryName(name).option("checkpointLocation", check).trigger(availableNow=True).start().awaitTermination()
    return spark.table(name).groupBy("window").agg(F.max("n").alias("n")).agg(F.sum("n")).first()[0]


def test_late_rows_go(spark, tmp_path):
    early, late = [(k, 1000 + k) for k in range(10)], [(100 + k, 200_000 + k) for k in range(10)]
    files(spark, str(tmp_path / "ordered"), [early, late])
    # a batch filters by the watermark that the batch before it began with, so one file stands between
    files(spark, str(tmp_path / "swapped"), [late, [(300, 200_500)], early])
    assert counted(spark, str(tmp_path / "ordered"), str(tmp_path / "c1")) == 20
    assert counted(spark, str(tmp_path / "swapped"), str(tmp_path / "c2")) == 11


def test_routes_are_stored_once(spark, tmp_path):
    weights = streams.trained_routes(spark, SF)
    for _ in range(2):  # the second start finds nothing new
        streams.route_sink(spark, SF, str(tmp_path / "out"), str(tmp_path / "check"), weights)
    stored = spark.read.parquet(str(tmp_path / "out"))
    batch = streams.routed(spark.read.parquet(f"{SF}/conversations.parquet"), weights)
    assert stored.count() == batch.count()
    assert stored.select("conv_id", "turn", "route").exceptAll(batch.select("conv_id", "turn", "route")).isEmpty()


def test_versions_do_not_mix(spark, tmp_path):
    store = WeightStore(spark, str(tmp_path))
    for v in (1, 2, 3):
        store.publish(spark.createDataFrame([(0, [float(v)])], "slice int, w array<double>"), v)
    assert store.latest().first()["w"] == [3.0] and store.latest(2).first()["w"] == [2.0]
    try:
        one_version(spark.read.parquet(str(tmp_path)))
    except ValueError:
        return
    raise AssertionError("mixed versions were taken")


def test_limited_source(spark):
    spark.dataSource.register(LimitedPictures)
    df = spark.read.format("limited_pictures").options(rows=10, readers=3).load()
    assert df.rdd.getNumPartitions() == 3 and sorted(r["pic"] for r in df.select("pic").collect()) == list(range(10))
