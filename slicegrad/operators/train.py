"""Synchronous data-parallel training as ordinary Spark plans.

A round is one plan of two stages: local gradients beside the samples, one exchange that brings slice n of every
gradient and of the weights to task n, and there the sum and the update. The driver only sequences rounds.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slicegrad.functions.arrays import bucket_of, dot, folded, sums
from slicegrad.operators import slices
from slicegrad.operators.optim import Optimizer


def to_samples(df: DataFrame, parts: int, buckets: int = 1, seed: int = 0, wt: Column | None = None) -> DataFrame:
    """(id, x, y) to samples: ``part`` says which task trains on a row, ``bucket`` in which mini-batch it is."""
    return df.select(
        F.col("id").cast("long").alias("sample_id"), F.pmod("id", F.lit(parts)).cast("int").alias("part"),
        bucket_of(F.col("id"), buckets, seed).cast("int").alias("bucket"), "x", "y", (F.lit(1.0) if wt is None else wt).alias("wt"),
    )


def minibatch(samples: DataFrame, it: int, buckets: int, mode: str = "bucket", fraction: float = 0.1, seed: int = 0) -> DataFrame:
    """The rows of round ``it``.

    bucket: one bucket after another, so a bucketed or partitioned store reads that batch only. epoch: the same in an
    order that changes with the epoch. bernoulli: an independent draw, which scans everything.
    """
    if mode == "bernoulli":
        return samples.sample(False, fraction, seed + it)
    turn = it % buckets
    if mode == "epoch":
        step = next(s for s in range(1 + (seed + it // buckets) * 2 % max(buckets, 1), 10 * buckets) if _coprime(s, buckets))
        turn = (turn * step + seed + it // buckets) % buckets
    return samples.filter(F.col("bucket") == turn)


def _coprime(a: int, b: int) -> bool:
    while b:
        a, b = b, a % b
    return a == 1


@dataclass(frozen=True)
class Glm:
    """Linear model with a link; the gradient of every link here is (prediction - y) x."""

    k: int
    link: str = "linear"

    def predict(self, w: Column, x: Column) -> Column:
        z = dot(w, x)
        if self.link == "linear":
            return z
        if self.link == "logistic":
            return 1 / (1 + F.exp(-z))
        return 0.5 * (1 + z / (1 + F.abs(z)))  # rational surrogate: the same bits in every engine

    def gradients(self, batch: DataFrame, w: Column | list) -> DataFrame:
        """One row a producer: k sums, combined before any exchange. A list of weights travels as one broadcast row, so
        that every round has the same plan and the same code."""
        if isinstance(w, list):
            row = batch.sparkSession.createDataFrame([(w,)], "_v array<double>")
            batch, w = batch.crossJoin(F.broadcast(row)), F.col("_v")
        p = self.predict(F.col("_w"), F.col("x"))
        rows = batch.withColumn("_w", w).withColumn("_e", (p - F.col("y")) * F.col("wt"))
        g = F.array(*[F.sum(F.col("_e") * F.get("x", j)) for j in range(self.k)])
        return rows.groupBy(F.col("part").alias("producer")).agg(F.sum("wt").alias("n"), F.sum(F.col("_e") * F.col("_e") / 2).alias("loss"), g.alias("g"))


def weight_rows(spark, layout: slices.ParamLayout, w: list[float], slots: dict[str, list[float]]) -> DataFrame:
    cut = {k: dict(layout.pieces(v)) for k, v in slots.items()}
    rows = [(s, piece, *[cut[k][s] for k in slots]) for s, piece in layout.pieces(w)]
    return spark.createDataFrame(rows, "slice int, w array<double>" + "".join(f", `{k}` array<double>" for k in slots))


def update(cut: DataFrame, weights: DataFrame, optim: Optimizer, it: int, n: int, reduce: str = "mean") -> DataFrame:
    """Sum and update in one exchange: gradient and weight rows travel as one tagged union to the slice's owner."""
    slots = list(optim.slots)
    left = cut.select("slice", F.col("n").alias("_n"), F.col("loss").alias("_loss"), "g", *[F.lit(None).cast("array<double>").alias(c) for c in ("w", *slots)])
    right = weights.select("slice", F.lit(None).cast("double").alias("_n"), F.lit(None).cast("double").alias("_loss"), F.lit(None).cast("array<double>").alias("g"), "w", *slots)
    return _owned(left.unionByName(right), optim, it, n, reduce)


def _owned(rows: DataFrame, optim: Optimizer, it: int, n: int, reduce: str) -> DataFrame:
    """What the owner of a slice does with all its rows."""
    slots = list(optim.slots)
    owned = rows.repartitionById(n, "slice").groupBy("slice").agg(
        F.sum("_n").alias("_n"), F.sum("_loss").alias("_loss"), folded(F.collect_list("g")).alias("g"), *[F.max(c).alias(c) for c in ("w", *slots)])
    by = F.col("_n") if reduce == "mean" else F.lit(1.0)
    owned = owned.withColumn("g", F.transform(F.coalesce("g", F.transform("w", lambda v: v * 0.0)), lambda v: v / F.coalesce(by, F.lit(1.0))))
    moved = owned.withColumn("p", F.transform(F.arrays_zip("w", "g", *slots), lambda p: optim.step(p, it)))
    return moved.select("slice", "_n", "_loss", *[F.col(f"p.{c}").alias(c) for c in ("w", *slots)])


@dataclass
class TrainResult:
    weights: list[float]
    slots: dict[str, list[float]]
    rounds: int
    ledger: list[dict] = field(default_factory=list)


def train(samples: DataFrame, model: Glm, optim: Optimizer, rounds: int, n: int = 4, buckets: int = 1, mode: str = "bucket", reduce: str = "mean", split_jobs: bool = False, init: TrainResult | None = None, stop=None, cache: bool = True) -> TrainResult:
    """Rounds until ``rounds`` or until ``stop(weights)``.

    ``split_jobs`` runs the two jobs of a round as two actions; otherwise they are two stages of one. ``init``
    continues from an earlier result, slots and round count included. Samples are kept in memory or on disk for the
    rounds (``cache``); a store that is bucketed by mini-batch is read bucket by bucket instead and needs no keeping.
    """
    own = cache and not samples.is_cached
    if own:
        samples = samples.persist()
    try:
        return _rounds(samples, model, optim, rounds, n, buckets, mode, reduce, split_jobs, init, stop)
    finally:
        if own:
            samples.unpersist()


def _rounds(samples, model, optim, rounds, n, buckets, mode, reduce, split_jobs, init, stop) -> TrainResult:
    spark = samples.sparkSession
    layout = slices.ParamLayout(model.k, n)
    state = init or TrainResult([0.0] * model.k, {s: [0.0] * model.k for s in optim.slots}, 0)
    w, slots, ledger = list(state.weights), {k: list(v) for k, v in state.slots.items()}, list(state.ledger)
    for it in range(state.rounds + 1, state.rounds + rounds + 1):
        began = time.time()
        batch = samples if buckets == 1 else minibatch(samples, it - 1, buckets, mode)
        cut = layout.cut(model.gradients(batch, w))
        if split_jobs:
            cut = cut.persist()
            cut.count()
        after = update(cut, weight_rows(spark, layout, w, slots), optim, it, n, reduce).collect()
        if split_jobs:
            cut.unpersist()
        parts = {r["slice"]: r for r in after}
        w = [v for s in range(n) for v in parts[s]["w"]]
        slots = {k: [v for s in range(n) for v in parts[s][k]] for k in slots}
        ledger.append({"iter": it, "jobs": 2 if split_jobs else 1, "wall_ms": int(1000 * (time.time() - began)), "samples": parts[0]["_n"], "loss": parts[0]["_loss"]})
        if stop is not None and stop(w):
            break
    return TrainResult(w, slots, ledger[-1]["iter"] if ledger else state.rounds, ledger)


def unrolled(samples: DataFrame, model: Glm, optim: Optimizer, rounds: int, n: int = 4, reduce: str = "mean", start: list[float] | None = None) -> DataFrame:
    """Several rounds in one plan: weights go from stage to stage and never to the driver.

    The one row that tasks read is the assembled state, broadcast: k numbers and their slots, bounded by the model.
    Gradient rows carry their slice of it on, so a round reads the one before once and the plan grows in line.
    """
    spark = samples.sparkSession
    layout = slices.ParamLayout(model.k, n)
    names = ["w", *optim.slots]
    weights = weight_rows(spark, layout, start or [0.0] * model.k, {s: [0.0] * model.k for s in optim.slots})
    edges = F.array(*[F.lit(e) for e in layout.edges])
    low, high = F.get(edges, F.col("slice")), F.get(edges, F.col("slice") + 1)
    for it in range(1, rounds + 1):
        batch = samples.crossJoin(F.broadcast(assemble(weights, names)))
        p = model.predict(F.col("_w"), F.col("x"))
        e = batch.withColumn("_e", (p - F.col("y")) * F.col("wt"))
        g = F.array(*[F.sum(F.col("_e") * F.get("x", j)) for j in range(model.k)])
        grads = e.groupBy(F.col("part").alias("producer")).agg(F.sum("wt").alias("_n"), F.sum(F.col("_e") * F.col("_e") / 2).alias("_loss"), g.alias("g"), *[F.first(f"_{c}").alias(c) for c in names])
        cut = grads.withColumn("slice", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).select("slice", "_n", "_loss", *[F.slice(c, low + 1, high - low).alias(c) for c in ("g", *names)])
        weights = _owned(cut, optim, it, n, reduce)
    return weights


def assemble(weights: DataFrame, names=("w",)) -> DataFrame:
    """The whole vectors from their slices, in order, as one row: ``_whole``, or ``_`` and the name for several."""
    rows = F.array_sort(F.collect_list(F.struct("slice", *names)))
    whole = lambda c: F.flatten(F.transform(rows, lambda p: p[c]))
    return weights.agg(whole("w").alias("_whole")) if names == ("w",) else weights.agg(*[whole(c).alias(f"_{c}") for c in names])


def train_stale(samples: DataFrame, model: Glm, lr: float, rounds: int, lag, bound: int | None = None) -> list[float]:
    """Producer p computes its gradient at the weights of ``lag(p)`` rounds ago; what a missing barrier amounts to.

    ``lag`` may look at the producer and, as a second argument, at the round. With a ``bound`` no producer falls further
    behind. All versions that may be asked for travel as one broadcast table of (version, weights).
    """
    spark = samples.sparkSession
    history = [[0.0] * model.k]
    late = lag if lag.__code__.co_argcount > 1 else lambda part, it: lag(part)
    for it in range(rounds):
        behind = late(F.col("part"), it)
        behind = behind if bound is None else F.least(behind, F.lit(bound))
        own = samples.withColumn("_version", F.greatest(F.lit(0), F.lit(it) - behind).cast("int"))
        kept = history if bound is None else history[max(0, it - bound) :]
        table = spark.createDataFrame([(it - len(kept) + 1 + k, w) for k, w in enumerate(kept)], "_version int, _at array<double>")
        total = model.gradients(own.join(F.broadcast(table), "_version"), F.col("_at")).agg(F.sum("n").alias("n"), sums(F.col("g"), model.k).alias("g")).first()
        if total["n"]:
            history.append([a - lr * b / total["n"] for a, b in zip(history[-1], total["g"])])
    return history[-1]


def weights_frame(spark, w: list[float], n: int = 4) -> DataFrame:
    """(slice, j, w), rounded to 6 places."""
    layout = slices.ParamLayout(len(w), n)
    rows = [(s, layout.bounds(s)[0] + i, float(v)) for s, piece in layout.pieces(w) for i, v in enumerate(piece)]
    return spark.createDataFrame(rows, "slice long, j long, w double").select("slice", "j", F.round("w", 6).alias("w"))
