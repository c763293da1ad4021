"""The paper's measurements re-run: python -m slicegrad.plans.experiments NAME SF_DIR, or all.

Each prints one JSON line. Absolute times are this machine's; the trends are what is compared.
"""

from __future__ import annotations

import json
import sys
import time

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from slicegrad.nn import models
from slicegrad.operators import optim
from slicegrad.operators import measures
from slicegrad.operators.kernel import local_train, predict, train_net
from slicegrad.operators.train import Glm, to_samples, train, unrolled
from slicegrad.plans.apps import frame_samples, frames_of, images, rating_samples, token_length, token_samples
from slicegrad.sources.tables import load, vec8


def clock(f):
    began = time.time()
    out = f()
    return time.time() - began, out


def sync_overhead(spark, sf_dir):
    """Synchronisation time over compute time of recorded rounds, by width of the network and number of tasks."""
    out = []
    for width in (4, 16):
        net = models.Inception(8, width, 4)
        for parts in (1, 2, 4, 8, 16, 32):
            run = train_net(images(spark, sf_dir), net, optim.Sgd(0.1), 3, parts=parts, measure=True)
            share = measures.sync_share(measures.ledger_frame(spark, run.ledger[1:])).first()
            out.append({"k": net.k, "tasks": parts, "sync_share": round(share["sync_share"], 3), "dispatch_share": round(share["dispatch_share"], 3)})
    return out


def dispatch(spark, sf_dir):
    """Time to launch tasks that do nothing, by how many there are, and rounds handed over together."""
    out = []
    for tasks in (4, 32, 100, 200, 300, 400, 500):
        job = spark.range(0, tasks, 1, tasks)
        job.write.format("noop").mode("overwrite").save()
        out.append({"tasks": tasks, "s": round(clock(lambda j=job: j.write.format("noop").mode("overwrite").save())[0], 3)})
    net = models.Mlp(64, 8, 4)
    for tasks in (4, 16, 64):
        for group in (1, 5, 10):
            s, _ = clock(lambda t=tasks, g=group: train_net(images(spark, sf_dir), net, optim.Sgd(0.1), 10, parts=t, publish="replicate", group=g))
            out.append({"tasks": tasks, "network_group": group, "ten_rounds_s": round(s, 3)})
    samples = to_samples(vec8(spark, sf_dir), 4).persist()
    samples.count()
    for group in (1, 3, 6):
        s, _ = clock(lambda g=group: [unrolled(samples, Glm(8), optim.Sgd(0.1), g).collect() for _ in range(6 // g)])
        out.append({"group": group, "six_rounds_s": round(s, 3)})
    samples.unpersist()
    return out


def scaling(spark, sf_dir):
    """Samples a second of recorded rounds on replicated data, and the fitted model of a round carried to 256 nodes."""
    net = models.Inception(8, 8, 4)
    rows = []
    for copies in (2, 8):
        data = images(spark, sf_dir).crossJoin(F.broadcast(spark.range(copies).withColumnRenamed("id", "copy"))).withColumn("id", F.col("id") * copies + F.col("copy")).drop("copy").persist()
        data.count()
        for tasks in (1, 2, 4, 8):
            run = train_net(data, net, optim.Sgd(0.1), 3, parts=tasks, measure=True)
            rows += [r | {"nodes": tasks} for r in run.ledger[1:]]
        data.unpersist()
    frame = measures.ledger_frame(spark, rows)
    fit = measures.fit_cost_model(frame)
    said = {n: measures.predict_nodes(fit, n, samples=1e6) for n in (1, 4, 16, 96, 256)}
    return {"measured": [r.asDict() for r in measures.speedup(frame).collect()], "fit": fit, "speedup_96_over_16": round(said[16] / said[96], 2), "speedup_256_over_16": round(said[16] / said[256], 2)}


def volume(spark, sf_dir):
    """Frames of events replicated up to thirty times: windows a second by how many rows are read."""
    out = []
    for copies in (1, 10, 30):
        e = load(spark, sf_dir, "events").crossJoin(F.broadcast(spark.range(copies).withColumnRenamed("id", "copy"))).withColumn("user_id", F.col("user_id") + F.col("copy"))
        s, n = clock(lambda x=e: frames_of(spark, x).count())
        out.append({"copies": copies, "cells": n, "s": round(s, 2)})
    return out


def ncf(spark, sf_dir):
    """Time for the same rounds of the recommender in Spark and in one process, and the losses of both."""
    data = rating_samples(spark, sf_dir).persist()
    data.count()
    net = models.NeuMf(32, 32, 4, 8)
    spark_s, result = clock(lambda: train_net(data, net, optim.Adam(0.05), 8))
    rows = data.orderBy("id").collect()
    x, y = np.array([r["x"] for r in rows]), np.array([r["y"] for r in rows])
    alone_s, (_, losses) = clock(lambda: local_train(x, y, net, optim.Adam(0.05), 8))
    data.unpersist()
    return {"rows": len(rows), "spark_s": round(spark_s, 2), "one_process_s": round(alone_s, 2), "last_loss": [round(result.ledger[-1]["loss"] / len(rows), 5), round(losses[-1] / len(rows), 5)]}


def nets(spark, sf_dir):
    """Gradient bytes a sample-second of compute: convolutional against recurrent networks."""
    out = []
    for name, data, net in (("cnn", images, models.Inception(8, 8, 4)), ("factored", images, models.Inception(8, 8, 4, "factored")), ("residual", images, models.Inception(8, 8, 4, "residual")), ("lstm", token_samples, models.Recurrent(64, token_length(spark, sf_dir), 6, 16, 2))):
        own = data(spark, sf_dir).limit(500).toPandas()
        x, y = net.filled(net.gathered(own["x"].to_numpy())), np.stack(own["y"])
        theta = net.init(0)
        net.loss_grad(theta, x, y)
        s, _ = clock(lambda: net.loss_grad(theta, x, y))
        out.append({"net": name, "k": net.k, "compute_s": round(s, 4), "bytes_per_compute_s": round(16 * net.k / s)})
    return out


def detect_pipeline(spark, sf_dir):
    """Rows a second of read, detect, describe by how many readers there are; share of time spent reading."""
    from slicegrad.sources.limited import LimitedPictures

    spark.dataSource.register(LimitedPictures)
    net = models.BitDescriptor(8, 16)
    theta, out = net.init(0), []
    for readers in (1, 2, 4):
        source = spark.read.format("limited_pictures").options(rows=400, readers=readers, pauseMs=2).load()
        read, _ = clock(lambda: source.write.format("noop").mode("overwrite").save())
        whole, _ = clock(lambda: predict(source.repartition(4), net, theta, "px").write.format("noop").mode("overwrite").save())
        out.append({"readers": readers, "rows_per_s": round(400 / whole), "read_share": round(min(read / whole, 1), 2)})
    return out


def connector(spark, sf_dir):
    """Scoring in the plan against export, another process and import."""
    from slicegrad.plans.core import m_predict_glm
    from slicegrad.sources.connector import score_outside
    from slicegrad.sources.store import shared_folder

    df = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda v: v.cast("double")).alias("x"))
    inside, _ = clock(lambda: m_predict_glm(spark, sf_dir).write.format("noop").mode("overwrite").save())
    outside, _ = clock(lambda: score_outside(df, shared_folder(spark, "connector"), 64).write.format("noop").mode("overwrite").save())
    return {"in_plan_s": round(inside, 3), "connector_s": round(outside, 3)}


def frames(spark, sf_dir):
    """Windows of frames a second."""
    s, n = clock(lambda: frame_samples(spark, sf_dir, every=1).count())
    return {"windows": n, "per_s": round(n / s)}


def jobs(spark, sf_dir):
    """One action a round against two."""
    samples = to_samples(vec8(spark, sf_dir), 4).persist()
    samples.count()
    fused, a = clock(lambda: train(samples, Glm(8), optim.Sgd(0.1), 5))
    split, b = clock(lambda: train(samples, Glm(8), optim.Sgd(0.1), 5, split_jobs=True))
    samples.unpersist()
    return {"fused_s": round(fused, 3), "split_s": round(split, 3), "jobs": [sum(r["jobs"] for r in x.ledger) for x in (a, b)], "equal": bool(np.allclose(a.weights, b.weights))}


EXPERIMENTS = {f.__name__: f for f in (sync_overhead, dispatch, scaling, volume, ncf, nets, detect_pipeline, connector, frames, jobs)}


def main(names: list[str], sf_dir: str) -> None:
    spark = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in names:
        print(json.dumps({name: EXPERIMENTS[name](spark, sf_dir)}), flush=True)


if __name__ == "__main__":
    chosen = sys.argv[1] if len(sys.argv) > 1 else "all"
    main(list(EXPERIMENTS) if chosen == "all" else [chosen], sys.argv[2] if len(sys.argv) > 2 else "/root/testdata/sf0.1")
