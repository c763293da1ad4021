"""Networks trained by kernels: one Arrow pass a round computes each task's gradient, already cut into slices.

State and gradients travel as packed bytes. The owner of a slice adds the gradients up as they come, one after another,
and applies the optimizer in NumPy, so it holds two copies of its slice and never all producers' rows.

Three ways bring new weights to the next round's tasks (``publish``). ``driver``: collected and broadcast, K numbers a
round through the driver. ``replicate``: every task is sent every slice by an exchange and meets its samples in a cogroup;
the driver sees counts and losses only. ``store``: the same from a versioned table in the shared folder. With the last
two, ``group`` rounds are one plan and one action.
"""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slicegrad.functions.ship import ship_by_value
from slicegrad.operators.optim import LayerWise, Optimizer
from slicegrad.operators.slices import ParamLayout
from slicegrad.operators.train import TrainResult, minibatch
from slicegrad.sources.store import WeightStore, kept

ship_by_value(__name__)

WIRE = {"f64": np.float64, "f32": np.float32, "f16": np.float16}
GRADIENT = "producer int, slice int, n double, loss double, ms double, v binary"
TAGGED = "slice int, kind int, n double, loss double, ms double, v binary"
TAGGED_COLUMNS = [c.split()[0] for c in TAGGED.split(", ")]
#: Samples of a batch in a cogroup, as many as an Arrow batch has.
BATCH = 10_000
STATE = "slice int, n double, loss double, ms double, bytes long, v binary"


def trainable(net) -> np.ndarray:
    """Places of the parameters that are trained; those of frozen layers are in no slice."""
    out, at = [], 0
    for name, shape in net.shapes.items():
        n = int(np.prod(shape))
        if name not in net.frozen:
            out.append(np.arange(at, at + n))
        at += n
    return np.concatenate(out) if out else np.zeros(0, dtype=np.int64)


def layers(net) -> np.ndarray:
    """The number of the layer of every trained parameter."""
    return np.concatenate([np.full(int(np.prod(s)), k) for k, (name, s) in enumerate(net.shapes.items()) if name not in net.frozen])


def matrix(column) -> np.ndarray:
    """Arrays of one length in an Arrow column, as rows, without an object for each."""
    return column.combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)


class Worker:
    """What a task does with its batch: the summed gradient of the trained parameters, cut and packed.

    ``base`` has the parameters that are not trained; None, if all are.
    """

    def __init__(self, net, base, places, edges, wire: str, threads: int, fault):
        self.net, self.base, self.places, self.edges, self.wire, self.threads, self.fault = net, base, places, edges, wire, threads, fault

    def gradient(self, batches, w: np.ndarray, it: int, part: int, attempt: int):
        """``batches``: (x, y) matrices."""
        from concurrent.futures import ThreadPoolExecutor

        if self.fault is not None:
            self.fault(part, attempt)
        theta = w
        if self.base is not None:
            theta = self.base.copy()
            theta[self.places] = w
        began = time.time()

        def one(job):
            k, (x, y) = job
            return len(x), *self.net.loss_grad(theta, x, y, (it, part, k))

        n, loss, g = 0, 0.0, np.zeros(len(theta))
        jobs = ((k, batch) for k, batch in enumerate(batches) if len(batch[0]))
        if self.threads > 1:
            with ThreadPoolExecutor(self.threads) as pool:
                results = list(pool.map(one, jobs))
        else:
            results = map(one, jobs)
        for rows, part_loss, part_g in results:
            n, loss, g = n + rows, loss + part_loss, g + part_g
        if n:
            own, kind = g[self.places], WIRE[self.wire]
            if self.wire == "f16":
                own = own / n  # a mean keeps to what two bytes can hold; the owner multiplies again
            cut = [own[a:b].astype(kind).tobytes() for a, b in zip(self.edges[:-1], self.edges[1:])]
            yield pd.DataFrame({"producer": part, "slice": list(range(len(cut))), "n": float(n), "loss": loss, "ms": 1000 * (time.time() - began), "v": cut})


def forward_backward(samples: DataFrame, worker: Worker, w: np.ndarray, it: int) -> DataFrame:
    """``samples``: (x, y arrays). One gradient a task; weights are one broadcast of k numbers.

    ``threads`` of the worker split the task's batches, as one task per server does; its ``fault(partition, attempt)``
    may raise, to show that a rerun task gives the same gradient.
    """
    held = samples.sparkSession.sparkContext.broadcast(np.asarray(w, dtype=np.float64))

    def run(frames):
        from pyspark import TaskContext

        context = TaskContext.get()
        batches = ((worker.net.gathered(f["x"].to_numpy()), np.stack(f["y"].to_numpy())) if len(f) else ((), ()) for f in frames)
        yield from worker.gradient(batches, held.value, it, context.partitionId(), context.attemptNumber())

    return samples.select("x", "y").mapInPandas(run, GRADIENT)


def paired_gradients(samples: DataFrame, state: DataFrame, worker: Worker, parts: int, slots: int, it: int) -> DataFrame:
    """The same with weights from ``state``: a replica of each slice goes to every task and meets the samples that are there.

    Each slice's slots go along to one of the tasks, which hands the slice's state on beside its gradient, so that a
    round reads the one before once and a plan of several rounds grows in line. Returns ``tagged`` rows.
    """
    owner = F.pmod("slice", F.lit(parts)) == F.col("part")
    weights = F.expr(f"substring(v, 1, cast(length(v) / {1 + slots} as int))")
    replicas = state.select("slice", "v").withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
    replicas = replicas.select("part", "slice", owner.alias("own"), F.when(owner, F.col("v")).otherwise(weights).alias("v")).repartitionById(parts, "part")

    def run(key, rows, pieces):
        import pyarrow as pa
        from pyspark import TaskContext

        pieces = pieces.to_pandas().sort_values("slice")
        own = pieces[pieces["own"].astype(bool)]
        out = [pd.DataFrame({"slice": own["slice"], "kind": 0, "n": 0.0, "loss": 0.0, "ms": 0.0, "v": own["v"]})]
        if len(rows):
            w = np.concatenate([np.frombuffer(v).reshape(1 + slots if mine else 1, -1)[0] for v, mine in zip(pieces["v"], pieces["own"])])
            x, y = matrix(rows["x"]) if worker.net.length is None else rows["x"].to_pandas().to_numpy(), matrix(rows["y"])
            size = max(BATCH, worker.net.rows or 0)  # larger where no row depends on another, as every batch costs a gradient of all weights
            batches = ((x[a : a + size], y[a : a + size]) for a in range(0, len(x), size))
            out += [g.drop(columns="producer").assign(kind=1) for g in worker.gradient(batches, w, it, key[0].as_py(), TaskContext.get().attemptNumber())]
        said = pd.concat(out, ignore_index=True)[TAGGED_COLUMNS]
        return pa.Table.from_pandas(said, schema=pa.schema([("slice", pa.int32()), ("kind", pa.int32()), ("n", pa.float64()), ("loss", pa.float64()), ("ms", pa.float64()), ("v", pa.binary())]), preserve_index=False)

    return samples.select("part", "x", "y").groupBy("part").cogroup(replicas.groupBy("part")).applyInArrow(run, TAGGED)


class Owner:
    """What the owner of a slice does: adds up, regularises, clips, applies the optimizer."""

    def __init__(self, optim: Optimizer, wire: str, l1: float, l2: float, clip: float | None):
        self.optim, self.wire, self.l1, self.l2, self.clip = optim, wire, l1, l2, clip

    def mean(self, total, n, w):
        g = total / n if n else np.zeros_like(w)
        g = g + self.l2 * w + self.l1 * np.sign(w)
        return g if self.clip is None else np.clip(g, -self.clip, self.clip)

    def moved(self, held, total, n, it, scale=None):
        w, slots = held[0], dict(zip(self.optim.slots, held[1:]))
        g = self.mean(total, n, w)
        w, slots = self.optim.step_np(w, g, slots, it) if scale is None else self.optim.scaled_np(w, g, slots, it, scale)
        return np.stack([w, *[slots[k] for k in self.optim.slots]])

    def settle(self, frames, finish):
        """Rows come by slice, the state's first; ``finish`` gets (slice, state, sum, n, loss, ms, bytes)."""
        now = None
        for f in frames:
            for s, kind, n, loss, ms, v in zip(f["slice"], f["kind"], f["n"], f["loss"], f["ms"], f["v"]):
                if kind == 0:
                    if now is not None:
                        yield finish(*now)
                    held = np.frombuffer(v).reshape(1 + len(self.optim.slots), -1)
                    now = [s, held, np.zeros(held.shape[1]), 0.0, 0.0, 0.0, 0]
                else:
                    part = np.frombuffer(v, dtype=WIRE[self.wire]).astype(np.float64)
                    now[2] = now[2] + (part * n if self.wire == "f16" else part)
                    now[3], now[4], now[5], now[6] = now[3] + n, now[4] + loss, max(now[5], ms), now[6] + len(v)
        if now is not None:
            yield finish(*now)


def tagged(grads: DataFrame, state: DataFrame) -> DataFrame:
    """Gradient and state rows as one union, so that one exchange brings both to the slice's owner."""
    zero = F.lit(0.0)
    own = state.select("slice", F.lit(0).alias("kind"), zero.alias("n"), zero.alias("loss"), zero.alias("ms"), "v")
    return own.unionByName(grads.select("slice", F.lit(1).alias("kind"), "n", "loss", "ms", "v"))


def at_owner(rows: DataFrame, n: int) -> DataFrame:
    return rows.repartitionById(n, "slice").sortWithinPartitions("slice", "kind")


def update_packed(rows: DataFrame, owner: Owner, it: int, n: int) -> DataFrame:
    def run(frames):
        def finish(s, held, total, count, loss, ms, size):
            return pd.DataFrame({"slice": [s], "n": [count], "loss": [loss], "ms": [ms], "bytes": [size], "v": [owner.moved(held, total, count, it).tobytes()]})

        yield from owner.settle(frames, finish)

    return at_owner(rows, n).mapInPandas(run, STATE)


def update_scaled(rows: DataFrame, owner: Owner, it: int, n: int, layer_of: np.ndarray, edges: list[int], clip_norm: float | None) -> DataFrame:
    """For what needs norms across slices: sums first, then norms (a few numbers a slice) at the driver, then the step."""
    count_layers = int(layer_of.max()) + 1 if len(layer_of) else 1
    wise = isinstance(owner.optim, LayerWise)

    def add(frames):
        def finish(s, held, total, count, loss, ms, size):
            w, slots = held[0], dict(zip(owner.optim.slots, held[1:]))
            g = owner.mean(total, count, w)
            u = owner.optim.direction_np(w, g, slots, it) if wise else g
            own = layer_of[edges[s] : edges[s + 1]]
            norms = np.bincount(own, w * w, count_layers).tolist() + np.bincount(own, u * u, count_layers).tolist()
            return pd.DataFrame({"slice": [s], "n": [count], "loss": [loss], "ms": [ms], "bytes": [size], "v": [held.tobytes()], "g": [total.tobytes()], "norms": [norms]})

        yield from owner.settle(frames, finish)

    added = kept(at_owner(rows, n).mapInPandas(add, STATE + ", g binary, norms array<double>"))
    norms = np.sum([r["norms"] for r in added.select("norms").collect()], axis=0)
    w_norm, u_norm = np.sqrt(norms[:count_layers]), np.sqrt(norms[count_layers:])
    shrink = 1.0 if clip_norm is None else min(1.0, clip_norm / max(float(np.sqrt((u_norm**2).sum())), 1e-300))
    trust = owner.optim.trust(w_norm, u_norm) if wise else None

    def step(frames):
        for f in frames:
            for s, count, loss, ms, size, v, g in zip(f["slice"], f["n"], f["loss"], f["ms"], f["bytes"], f["v"], f["g"]):
                held = np.frombuffer(v).reshape(1 + len(owner.optim.slots), -1)
                scale = None if trust is None else trust[layer_of[edges[s] : edges[s + 1]]]
                yield pd.DataFrame({"slice": [s], "n": [count], "loss": [loss], "ms": [ms], "bytes": [size], "v": [owner.moved(held, np.frombuffer(g) * shrink, count, it, scale).tobytes()]})

    return added.drop("norms").mapInPandas(step, STATE)


def packed_state(spark, layout: ParamLayout, w: np.ndarray, slots: dict, names) -> DataFrame:
    whole = np.stack([w, *[np.asarray(slots[k], dtype=np.float64) for k in names]])
    rows = [(s, 0.0, 0.0, 0.0, 0, np.ascontiguousarray(whole[:, a:b]).tobytes()) for s in range(layout.n) for a, b in [layout.bounds(s)]]
    return spark.createDataFrame(rows, STATE)


def unpacked_state(rows, names) -> tuple[np.ndarray, dict]:
    whole = np.concatenate([np.frombuffer(r["v"]).reshape(1 + len(names), -1) for r in sorted(rows, key=lambda r: r["slice"])], axis=1)
    return whole[0], dict(zip(names, whole[1:]))


def train_net(samples: DataFrame, net, optim: Optimizer, rounds: int, parts: int = 4, n: int = 4, seed: int = 0, threads: int = 1, fault=None, init: TrainResult | None = None, stop=None, publish: str = "driver", group: int = 1, buckets: int = 1, accumulate: int = 1, wire: str = "f64", l1: float = 0.0, l2: float = 0.0, clip: float | None = None, clip_norm: float | None = None, measure: bool = False) -> TrainResult:
    """``samples``: (id, x, y). The samples are dealt to ``parts`` tasks once and kept there.

    A round takes ``accumulate`` of the ``buckets`` mini-batches, added up in the tasks before anything is sent. ``wire``
    is the form of gradients on their way. ``measure`` runs a round as two actions and notes the time of both, of the
    slowest kernel, and what launching took. ``stop`` is asked after each group with the weights.
    """
    if publish not in ("driver", "replicate", "store"):
        raise ValueError(f"no way to publish: {publish}")
    across = isinstance(optim, LayerWise) or clip_norm is not None
    if group > 1 and (publish == "driver" or across or measure):
        raise ValueError("rounds in one plan need weights that stay in the cluster and no norms across slices or times of single rounds")
    spark = samples.sparkSession
    places, names = trainable(net), list(optim.slots)
    layout = ParamLayout(len(places), n)
    base = np.array(net.init(seed) if init is None else init.weights, dtype=np.float64)
    slots = {k: np.zeros(len(places)) if init is None else np.asarray(init.slots[k])[places] for k in names}
    bucket = F.pmod(F.col("id") * 7919, F.lit(buckets)).cast("int").alias("bucket")
    held = samples.select(F.pmod("id", F.lit(parts)).cast("int").alias("part"), bucket, "id", "x", "y").repartitionById(parts, "part").sortWithinPartitions("id").persist()
    worker, owner = Worker(net, base.copy() if len(places) < net.k else None, places, layout.edges, wire, threads, fault), Owner(optim, wire, l1, l2, clip)
    layer_of = layers(net) if across else np.zeros(0, dtype=np.int64)
    first = init.rounds if init is not None else 0
    ledger, it = list(init.ledger) if init is not None else [], first
    store = WeightStore.temporary(spark) if publish == "store" else None
    state, w = packed_state(spark, layout, base[places], slots, names), base[places]
    try:
        while it < first + rounds:
            began, noted, gradient_s, pending = time.time(), [], 0.0, state
            for it in range(it + 1, min(it + group, first + rounds) + 1):
                batch = held
                if buckets > 1:
                    turns = {((it - 1) * accumulate + j) % buckets for j in range(accumulate)}
                    batch = held.filter(F.col("bucket").isin(*turns))
                if publish == "driver":
                    sent = tagged(forward_backward(batch, worker, w, it), pending)
                else:
                    sent = paired_gradients(batch, pending, worker, parts, len(names), it)
                if measure:
                    sent = sent.persist()
                    sent.count()
                    gradient_s = time.time() - began
                pending = update_scaled(sent, owner, it, n, layer_of, layout.edges, clip_norm) if across else update_packed(sent, owner, it, n)
                noted.append(it)
            if publish == "store":
                store.publish(pending, it)
                state = store.read(it)
            elif publish == "replicate":
                state = kept(pending)
            rows = (pending if publish == "driver" else state.drop("v")).collect()  # counts and losses, unless the driver publishes
            if publish == "driver":
                w, slots = unpacked_state(rows, names)
                state = packed_state(spark, layout, w, slots, names)
            wall = 1000 * (time.time() - began)
            if measure:
                sent.unpersist()
            said = next(iter(rows))
            for k in noted:
                last = k == noted[-1]
                compute = said["ms"] if last else None
                ledger.append({
                    "iter": k, "jobs": 2 if measure else 1, "grouped": len(noted), "tasks": parts + n, "wall_ms": wall / len(noted), "samples": said["n"] if last else None, "loss": said["loss"] if last else None, "compute_ms": compute,
                    "sync_ms": wall - 1000 * gradient_s if measure else None, "dispatch_ms": max(0.0, 1000 * gradient_s - compute) if measure else None,
                    "gradient_bytes": sum(r["bytes"] for r in rows), "weight_bytes": 8 * len(places) * parts,
                })
            seen = getattr(optim.schedule, "seen", None)
            if seen is not None and said["n"]:
                seen(said["loss"] / said["n"])
            if stop is not None:
                if publish != "driver":
                    w, slots = unpacked_state(state.collect(), names)
                base[places] = w
                if stop(base):
                    break
    finally:
        held.unpersist()
    if publish != "driver":
        w, slots = unpacked_state(state.collect(), names)  # the trained model, once
    base[places] = w
    full = {}
    for k in names:
        full[k] = np.zeros(len(base))
        full[k][places] = slots[k]
    return TrainResult(base.tolist(), {k: v.tolist() for k, v in full.items()}, it, ledger)


def predict(df: DataFrame, net, theta, x: str = "x", out: str = "scores") -> DataFrame:
    """Outputs of the network for each row, in one Arrow pass; filters on other columns still reach the scan."""
    held = df.sparkSession.sparkContext.broadcast(np.asarray(theta, dtype=np.float64))

    @F.pandas_udf("array<double>")
    def scored(batches: pd.Series) -> pd.Series:
        if not len(batches):
            return pd.Series([], dtype=object)
        return pd.Series(list(net.outputs(held.value, net.gathered(batches.to_numpy())).reshape(len(batches), -1)))

    return df.withColumn(out, scored(F.col(x)))


def local_train(x: np.ndarray, y: np.ndarray, net, optim: Optimizer, rounds: int, seed: int = 0, l1: float = 0.0, l2: float = 0.0, clip: float | None = None, clip_norm: float | None = None) -> tuple[np.ndarray, list[float]]:
    """The same rounds in one process: the reference that the distributed ones must equal."""
    places = trainable(net)
    whole, losses = net.init(seed), []
    slots = {s: np.zeros(len(places)) for s in optim.slots}
    owner = Owner(optim, "f64", l1, l2, clip)
    for it in range(1, rounds + 1):
        loss, g = net.loss_grad(whole, x, y, (it, 0, 0))
        losses.append(loss)
        w = whole[places]
        g = owner.mean(g[places], len(x), w)
        if clip_norm is not None:
            g = g * min(1.0, clip_norm / max(float(np.linalg.norm(g)), 1e-300))
        if isinstance(optim, LayerWise):
            own = layers(net)
            u = optim.direction_np(w, g, slots, it)
            trust = optim.trust(np.sqrt(np.bincount(own, w * w)), np.sqrt(np.bincount(own, u * u)))
            w, slots = optim.scaled_np(w, g, slots, it, trust[own])
        else:
            w, slots = optim.step_np(w, g, slots, it)
        whole = whole.copy()
        whole[places] = w
    return whole, losses
