"""Gradient slicing, and the ways to bring slices together.

Strategies take ``(producer, slice, n, loss, g)`` rows and return ``(slice, n, loss, g)``, the element-wise sums.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slicegrad.functions.arrays import folded


class ParamLayout:
    """k parameters in N slices; slice n is [n k / N, (n + 1) k / N) in whole numbers."""

    def __init__(self, k: int, n: int):
        self.k, self.n = k, n
        self.edges = [k * s // n for s in range(n + 1)]

    def bounds(self, s: int) -> tuple[int, int]:
        return self.edges[s], self.edges[s + 1]

    def cut(self, grads: DataFrame) -> DataFrame:
        """One row for each producer and slice; slices may be empty."""
        edges = F.array(*[F.lit(e) for e in self.edges])
        rows = grads.withColumn("slice", F.explode(F.sequence(F.lit(0), F.lit(self.n - 1))))
        low, high = F.get(edges, F.col("slice")), F.get(edges, F.col("slice") + 1)
        return rows.select("producer", "slice", "n", "loss", F.slice("g", low + 1, high - low).alias("g"))

    def pieces(self, vector: list) -> list[tuple[int, list]]:
        return [(s, list(vector[a:b])) for s in range(self.n) for a, b in [self.bounds(s)]]


def sliced(rows: DataFrame, n: int) -> DataFrame:
    """Slice s goes to partition s exactly, so its owner sums it without another exchange."""
    return _summed(rows.repartitionById(n, "slice"))


def _summed(rows: DataFrame) -> DataFrame:
    return rows.groupBy("slice").agg(F.sum("n").alias("n"), F.sum("loss").alias("loss"), folded(F.collect_list("g")).alias("g"))


def central(rows: DataFrame, n: int, servers: int = 1) -> DataFrame:
    """Few owners: slice s goes to server s mod servers."""
    return _summed(rows.withColumn("server", F.pmod("slice", F.lit(servers)).cast("int")).repartitionById(servers, "server"))


def tree(rows: DataFrame, n: int, fan_in: int = 2) -> DataFrame:
    """Level by level: each takes the sums of ``fan_in`` producers."""
    level = rows.withColumn("node", F.col("producer").cast("long"))
    most = level.agg(F.max("node")).first()[0] or 0
    while most > 0:
        level = level.withColumn("node", F.floor(F.col("node") / fan_in)).groupBy("node", "slice").agg(F.sum("n").alias("n"), F.sum("loss").alias("loss"), folded(F.collect_list("g")).alias("g"))
        most //= fan_in
    return level.select("slice", "n", "loss", "g")


def driver(rows: DataFrame, n: int) -> DataFrame:
    """All to the driver: the control that the sliced way avoids. Bounded by producers times parameters."""
    out: dict[int, list] = {}
    for r in rows.collect():
        own = out.setdefault(r["slice"], [r["slice"], 0, r["loss"] * 0, [v * 0 for v in r["g"]]])
        own[1] += r["n"]
        own[2] += r["loss"]
        own[3] = [a + b for a, b in zip(own[3], r["g"])]
    return rows.sparkSession.createDataFrame([tuple(v) for v in out.values()], rows.select("slice", "n", "loss", "g").schema)


def ring(rows: DataFrame, n: int, producers: int) -> DataFrame:
    """Reduce-scatter along a ring: producers - 1 hops, each adding what the next node has of the same slice.

    At hop h, the sum of slice s has visited nodes s, s + 1, ... s + h (modulo the ring); a hop is an exchange by the
    node that the sum moves to, where that node's own slice waits.
    """
    local = rows.groupBy(F.pmod(F.col("producer"), F.lit(producers)).cast("int").alias("node"), "slice").agg(F.sum("n").alias("n"), F.sum("loss").alias("loss"), folded(F.collect_list("g")).alias("g"))
    begin = F.pmod(F.col("slice"), F.lit(producers)).cast("int")
    moving = local.filter(F.col("node") == begin)
    for hop in range(1, producers):
        own = local.filter(F.col("node") == F.pmod(F.col("slice") + hop, F.lit(producers)).cast("int"))
        moved = moving.withColumn("node", F.pmod(F.col("node") + 1, F.lit(producers)).cast("int"))
        moving = moved.unionByName(own).repartitionById(producers, "node").groupBy("node", "slice").agg(F.sum("n").alias("n"), F.sum("loss").alias("loss"), folded(F.collect_list("g")).alias("g"))
    return moving.select("slice", "n", "loss", "g")


def ring_all(rows: DataFrame, producers: int) -> tuple[DataFrame, DataFrame]:
    """The whole ring with as many slices as nodes: (node, slice, g) of every sum at every node, and (half, hop, node, bytes) moved.

    After the first half, node s - 1 has the sum of slice s; each hop of the second half sends what a node got last to
    the next one, which keeps it.
    """
    size = 8 * F.size("g")
    local = rows.groupBy(F.pmod(F.col("producer"), F.lit(producers)).cast("int").alias("node"), "slice").agg(folded(F.collect_list("g")).alias("g"))
    moving = local.filter(F.col("node") == F.pmod(F.col("slice"), F.lit(producers)))
    hops = []

    def pass_on(held: DataFrame, hop: int) -> DataFrame:
        moved = held.withColumn("node", F.pmod(F.col("node") + 1, F.lit(producers)).cast("int")).repartitionById(producers, "node")
        hops.append(moved.select(F.lit(hop).cast("long").alias("hop"), F.col("node").cast("long").alias("node"), size.cast("long").alias("bytes")))
        return moved

    for hop in range(1, producers):
        own = local.filter(F.col("node") == F.pmod(F.col("slice") + hop, F.lit(producers)).cast("int"))
        both = pass_on(moving, hop).unionByName(own).repartitionById(producers, "node")
        moving = both.groupBy("node", "slice").agg(folded(F.collect_list("g")).alias("g"))
    held = moving
    for hop in range(producers, 2 * producers - 1):
        moving = pass_on(moving, hop)
        held = held.unionByName(moving)
    every = hops[0]
    for h in hops[1:]:
        every = every.unionByName(h)
    return held.select("node", "slice", "g"), every


def barrier_train(samples: DataFrame, k: int, lr: float, rounds: int, tasks: int) -> list[float]:
    """Long-running peers, without the driver between rounds: (id, x, y) least squares, all rounds in one gang.

    Each peer adds up its own samples' gradient, gathers the others' sums (k numbers a peer and round) and moves its copy of the
    weights. If a peer is lost, the whole gang starts again. Spark refuses a gang that finds too few slots (by default after 40 looks in 10 minutes).
    """
    import json

    from pyspark import BarrierTaskContext

    def gang(part):
        import numpy as np

        held = [(list(r["x"]), r["y"]) for r in part]
        x, y = np.array([h[0] for h in held]).reshape(-1, k), np.array([h[1] for h in held])
        context, w = BarrierTaskContext.get(), np.zeros(k)
        for _ in range(rounds):
            own = [len(y), *(x.T @ (x @ w - y)).tolist()]
            total = np.sum([json.loads(m) for m in context.allGather(json.dumps(own))], axis=0)
            if total[0]:
                w = w - lr * total[1:] / total[0]
        return iter([w.tolist()] if context.partitionId() == 0 else [])

    return samples.select("x", "y").repartition(tasks).rdd.barrier().mapPartitions(gang).collect()[0]


def barrier(rows: DataFrame, n: int, tasks: int) -> DataFrame:
    """A gang of tasks that exchange their slices among themselves, without the driver between.

    Needs as many free slots as tasks; Spark refuses the stage otherwise.
    """
    import json

    from pyspark import BarrierTaskContext

    def gang(part):
        held = [[r["slice"], r["n"], r["loss"], list(r["g"])] for r in part]
        context = BarrierTaskContext.get()
        everyone = [x for message in context.allGather(json.dumps(held)) for x in json.loads(message)]
        own: dict = {}
        for s, count, loss, g in everyone:
            if s % tasks == context.partitionId():
                old = own.get(s)
                own[s] = [s, count, loss, g] if old is None else [s, old[1] + count, old[2] + loss, [a + b for a, b in zip(old[3], g)]]
        return iter([tuple(v) for v in own.values()])

    schema = rows.select("slice", "n", "loss", "g").schema
    return rows.sparkSession.createDataFrame(rows.repartition(tasks).rdd.barrier().mapPartitions(gang), schema)


def long_sum(rows: DataFrame) -> DataFrame:
    """One row an element: partial sums before the exchange, for large k."""
    return rows.select("slice", F.posexplode("g").alias("pos", "v")).groupBy("slice", "pos").agg(F.sum("v").alias("v"))
