"""Measures of recorded rounds: shares, throughput, speed-up, time to a quality, counters, recovery, a model of a round.

A ledger has a row a round: ``iter``, ``nodes``, ``tasks``, ``jobs``, ``compute_ms``, ``sync_ms``, ``dispatch_ms``, ``wall_ms``,
``samples``, ``loss``, bytes. The functions take any frame with the columns they name, recorded or made up.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

LEDGER = "iter long, nodes long, tasks long, jobs long, compute_ms double, sync_ms double, dispatch_ms double, wall_ms double, samples double, loss double, gradient_bytes long, weight_bytes long"


def ledger_frame(spark: SparkSession, rows: list[dict]) -> DataFrame:
    """The ledgers of ``TrainResult``; a round without a number of nodes counts its tasks."""
    names = [c.split()[0] for c in LEDGER.split(", ")]
    kinds = [float if c.endswith("double") else int for c in LEDGER.split(", ")]
    full = [r if "nodes" in r else r | {"nodes": r.get("tasks")} for r in rows]
    return spark.createDataFrame([tuple(None if r.get(k) is None else kind(r[k]) for k, kind in zip(names, kinds)) for r in full], LEDGER)


def shares() -> list[Column]:
    return [F.round(F.avg("sync_ms") / F.avg("compute_ms"), 6).alias("sync_share"), F.round(F.avg("dispatch_ms") / F.avg("compute_ms"), 6).alias("dispatch_share")]


def sync_share(ledger: DataFrame, *by: Column | str) -> DataFrame:
    """Synchronisation and launching in parts of mean compute time, with the number of rounds."""
    return ledger.groupBy(*by).agg(F.count(F.lit(1)).alias("rounds"), *shares())


def speedup(ledger: DataFrame) -> DataFrame:
    """Samples a second by nodes, against the fewest nodes; efficiency against the ideal."""
    t = ledger.groupBy("nodes").agg((F.sum("samples") * 1000.0 / F.sum("wall_ms")).alias("thr"))
    w = Window.orderBy("nodes")  # one row a cluster size
    up = F.col("thr") / F.first("thr").over(w)
    return t.select("nodes", F.round("thr", 6).alias("samples_per_s"), F.round(up, 6).alias("speedup"), F.round(up / (F.col("nodes") / F.first("nodes").over(w)), 6).alias("efficiency"))


def time_to_quality(ledger: DataFrame, goals: list[float]) -> DataFrame:
    """The time until the loss first is at each goal or below; null, if it never is."""
    r = ledger.groupBy("iter").agg(F.sum("wall_ms").alias("wall_ms"), F.min("loss").alias("loss"))
    c = r.withColumn("at_ms", F.sum("wall_ms").over(Window.orderBy("iter")))  # one row a round
    g = ledger.sparkSession.createDataFrame([(float(v),) for v in goals], "goal double")
    return F.broadcast(g).join(c, F.col("loss") <= F.col("goal"), "left").groupBy("goal").agg(F.min("at_ms").alias("ms"))


def throughput_ratio(ledger: DataFrame, over: int, under: int) -> DataFrame:
    def thr(n):
        own = F.col("nodes") == n
        return F.sum(F.when(own, F.col("samples"))) * 1.0 / F.sum(F.when(own, F.col("wall_ms")))

    return ledger.agg(F.round(thr(over) / thr(under), 6).alias("ratio"))


def counters(ledger: DataFrame) -> DataFrame:
    """Rounds, jobs a round, tasks a round, kernel seconds, bytes a round."""
    return ledger.agg(
        F.countDistinct("iter").alias("rounds"), (F.sum("jobs") / F.countDistinct("iter")).alias("jobs_per_round"), F.avg("tasks").alias("tasks_per_round"),
        (F.sum("compute_ms") / 1000).alias("compute_s"), F.avg("gradient_bytes").alias("gradient_bytes"), F.avg("weight_bytes").alias("weight_bytes"))


def recovery_cost(ledger: DataFrame, every: int) -> DataFrame:
    """Tasks that run again if a round fails: the failed one, or all since the last snapshot."""
    own = ledger.groupBy((F.col("iter") % every).alias("failed_at"))
    return own.agg(F.count(F.lit(1)).alias("rounds"), F.max(F.lit(1).cast("long")).alias("tasks_rerun_fine"), (F.sum("tasks") - F.count(F.lit(1))).alias("spared"), F.sum("tasks").alias("tasks_rerun_snapshot"))


def fit_cost_model(ledger: DataFrame) -> dict[str, float]:
    """Least squares of a round's time: seconds a sample and node, fixed seconds, seconds a task; none below 0.

    The normal equations are one aggregate over the ledger, so only a few numbers reach the driver.
    """
    terms = [F.col("samples") / F.col("nodes"), F.lit(1.0), F.col("tasks").cast("double")]
    y = F.col("wall_ms") / 1000
    sums = [F.sum(a * b) for a in terms for b in terms] + [F.sum(a * y) for a in terms]
    got = ledger.agg(F.array(*sums).alias("s")).first()["s"]
    gram, right = np.array(got[:9]).reshape(3, 3), np.array(got[9:])
    active = [0, 1, 2]
    while active:
        fit = np.linalg.lstsq(gram[np.ix_(active, active)], right[active], rcond=None)[0]
        if (fit >= 0).all():
            break
        active.pop(int(fit.argmin()))
    out = np.zeros(3)
    out[active] = fit if active else 0
    return dict(zip(("per_sample_s", "fixed_s", "per_task_s"), map(float, out)))


def predict_nodes(fit: dict[str, float], nodes: int, samples: float, weight_bytes: float = 0.0, bandwidth: float = 1.25e9) -> float:
    """Seconds of a round on so many nodes: compute, 2 K over the bandwidth, and the fixed and by-task parts of the fit."""
    return fit["per_sample_s"] * samples / nodes + 2 * weight_bytes / bandwidth + fit["fixed_s"] + fit["per_task_s"] * 2 * nodes
