"""Training, synchronisation, traffic and ledger queries."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import Window

from slicegrad.functions.arrays import bucket_of, dot
from slicegrad.operators import measures, optim, slices
from slicegrad.operators.train import Glm, TrainResult, assemble, to_samples, train, train_stale, unrolled, weight_rows, weights_frame
from slicegrad.plans.kit import Book
from slicegrad.sources.tables import INTERACTIONS_SQL, VEC8_SQL, interactions, load, vec8

B = Book()
QUERIES, ORACLES = B.queries, B.oracles
K, N, P = 8, 4, 4

GRAD = """(SELECT list(q.g ORDER BY q.j) FROM (SELECT d.j, sum((list_inner_product({w}, s.x) - s.y) * s.x[d.j]) / count(*) AS g
      FROM s, (SELECT unnest(range(1, 9)) AS j) d {where} GROUP BY d.j) q)"""
ZERO = "[0, 0, 0, 0, 0, 0, 0, 0]::DOUBLE[]"


def each(expr: str) -> str:
    return f"list_transform(range(1, 9), lambda j: {expr})"


def descent_sql(rounds: int, new_a: str = "q.a[j]", new_b: str = "q.b[j]", new_w: str = "r.w[j] - 0.1 * r.g[j]", where: str = "") -> str:
    """Gradient descent with up to two slots; element expressions see q (before) and r (with the new slots)."""
    return f"""WITH RECURSIVE {VEC8_SQL}, t AS (
    SELECT 0 AS it, {ZERO} AS w, {ZERO} AS a, {ZERO} AS b
    UNION ALL
    SELECT r.it, {each(new_w)}, r.a, r.b FROM (
      SELECT q.it, q.w, q.g, q.a AS olda, q.b AS oldb, {each(new_a)} AS a, {each(new_b)} AS b FROM (
        SELECT t.it + 1 AS it, t.w, t.a, t.b, {GRAD.format(w="t.w", where=where)} AS g FROM t WHERE t.it < {rounds}) q) r)
  SELECT (j // 2)::BIGINT AS slice, j::BIGINT AS j, round(w[j + 1], 6) AS w FROM t, (SELECT unnest(range(0, 8)) AS j) WHERE it = {rounds}"""


def _trained(key: str, opt, sql: str, rounds: int = 3):
    @B.add(key, sql)
    def run(spark, sf_dir):
        samples = to_samples(vec8(spark, sf_dir), P)
        return weights_frame(spark, train(samples, Glm(K), opt, rounds, N).weights)


_trained("m_lsq_train", optim.Sgd(0.1), descent_sql(3))
_trained("m_momentum", optim.Momentum(0.1), descent_sql(3, "0.9 * q.a[j] + q.g[j]", new_w="r.w[j] - 0.1 * r.a[j]"))
_trained("m_nesterov", optim.Momentum(0.1, nesterov=True), descent_sql(3, "0.9 * q.a[j] + q.g[j]", new_w="r.w[j] - 0.1 * (r.g[j] + 0.9 * r.a[j])"))
_trained("m_adagrad", optim.Adagrad(0.1), descent_sql(3, "q.a[j] + q.g[j] * q.g[j]", new_w="r.w[j] - 0.1 * r.g[j] / (sqrt(r.a[j]) + 1e-8)"))
_trained("m_rmsprop", optim.RmsProp(0.1), descent_sql(3, "0.9 * q.a[j] + 0.1 * q.g[j] * q.g[j]", new_w="r.w[j] - 0.1 * r.g[j] / (sqrt(r.a[j]) + 1e-8)"))
_trained("m_adadelta", optim.Adadelta(1.0), descent_sql(3, "0.9 * q.a[j] + 0.1 * q.g[j] * q.g[j]", "0.9 * q.b[j] + 0.1 * (q.g[j] * sqrt(q.b[j] + 1e-3) / sqrt(0.9 * q.a[j] + 0.1 * q.g[j] * q.g[j] + 1e-3)) ** 2", "r.w[j] - r.g[j] * sqrt(r.oldb[j] + 1e-3) / sqrt(r.a[j] + 1e-3)"))
_ADAM = ("0.9 * q.a[j] + 0.1 * q.g[j]", "0.999 * q.b[j] + 0.001 * q.g[j] * q.g[j]")
_MOVE = "r.a[j] / (1 - 0.9 ** r.it) / (sqrt(r.b[j] / (1 - 0.999 ** r.it)) + 1e-8)"
_trained("m_adam", optim.Adam(0.1), descent_sql(3, *_ADAM, f"r.w[j] - 0.1 * ({_MOVE})"))
_trained("m_adamw", optim.Adam(0.1, decay=0.05), descent_sql(3, *_ADAM, f"r.w[j] - 0.1 * ({_MOVE} + 0.05 * r.w[j])"))
_trained("m_adamax", optim.Adamax(0.1), descent_sql(3, _ADAM[0], "greatest(0.999 * q.b[j], abs(q.g[j]) + 1e-8)", "r.w[j] - 0.1 / (1 - 0.9 ** r.it) * r.a[j] / r.b[j]"))
_trained("m_ftrl", optim.Ftrl(0.1), descent_sql(3, "q.a[j] + q.g[j] - (sqrt(q.b[j] + q.g[j] * q.g[j]) - sqrt(q.b[j])) / 0.1 * q.w[j]", "q.b[j] + q.g[j] * q.g[j]", "CASE WHEN abs(r.a[j]) <= 0.01 THEN 0 ELSE -(CASE WHEN r.a[j] > 0 THEN r.a[j] - 0.01 ELSE r.a[j] + 0.01 END) / ((sqrt(r.b[j]) + 1) / 0.1 + 0.1) END"))
_trained("m_weight_decay", optim.Sgd(0.1, decay=0.2), descent_sql(3, new_w="r.w[j] - 0.1 * (r.g[j] + 0.2 * r.w[j])"))
_trained("m_schedule_step", optim.Sgd(0.1, schedule=optim.step_schedule(2, 0.5)), descent_sql(4, new_w="r.w[j] - 0.1 * 0.5 ** ((r.it - 1) // 2) * r.g[j]"), 4)
_trained("m_schedule_warmup", optim.Sgd(0.1, schedule=optim.warmup_schedule(3)), descent_sql(4, new_w="r.w[j] - (CASE WHEN r.it <= 3 THEN 0.1 * r.it / 3 ELSE 0.1 END) * r.g[j]"), 4)
_trained("m_schedule_poly", optim.Sgd(0.1, schedule=optim.poly_schedule(4, 2.0)), descent_sql(3, new_w="r.w[j] - 0.1 * (1 - (r.it - 1) / 4.0) ** 2 * r.g[j]"))


@B.add("m_split_jobs", descent_sql(2))
def m_split_jobs(spark, sf_dir):
    """The literal two jobs a round."""
    return weights_frame(spark, train(to_samples(vec8(spark, sf_dir), P), Glm(K), optim.Sgd(0.1), 2, N, split_jobs=True).weights)


@B.add("m_one_task_per_server", descent_sql(2))
def m_one_task_per_server(spark, sf_dir):
    """Two servers with a task each; partial sums inside the task stand for its threads."""
    return weights_frame(spark, train(to_samples(vec8(spark, sf_dir), 2), Glm(K), optim.Sgd(0.1), 2, N).weights)


@B.add("m_minibatch_train", descent_sql(3, where="WHERE (s.id * 7919) % 5 = t.it % 5"))
def m_minibatch_train(spark, sf_dir):
    return weights_frame(spark, train(to_samples(vec8(spark, sf_dir), P, buckets=5), Glm(K), optim.Sgd(0.1), 3, N, buckets=5).weights)


@B.add("m_group_rounds", descent_sql(3))
def m_group_rounds(spark, sf_dir):
    """Three rounds in one plan and one action."""
    whole = assemble(unrolled(to_samples(vec8(spark, sf_dir), P), Glm(K), optim.Sgd(0.1), 3, N))
    return whole.select(F.posexplode("_whole").alias("j", "w")).select(F.floor(F.col("j") * N / K).cast("long").alias("slice"), F.col("j").cast("long").alias("j"), F.round("w", 6).alias("w"))


@B.add("w6_group_equals_single", "SELECT 0::BIGINT AS differing")
def w6_group_equals_single(spark, sf_dir):
    grouped = m_group_rounds(spark, sf_dir)
    single = QUERIES["m_lsq_train"](spark, sf_dir)
    return grouped.exceptAll(single).agg(F.count(F.lit(1)).alias("differing"))


@B.add("m_resume", descent_sql(5, "0.9 * q.a[j] + q.g[j]", new_w="r.w[j] - 0.1 * r.a[j]"))
def m_resume(spark, sf_dir):
    """Two rounds, then three more from the stored result."""
    samples = to_samples(vec8(spark, sf_dir), P)
    first = train(samples, Glm(K), optim.Momentum(0.1), 2, N)
    return weights_frame(spark, train(samples, Glm(K), optim.Momentum(0.1), 3, N, init=TrainResult(first.weights, first.slots, first.rounds)).weights)


@B.add("w14_incremental", descent_sql(4, where="WHERE CASE WHEN t.it < 2 THEN s.id % 2 = 0 ELSE true END"))
def w14_incremental(spark, sf_dir):
    """A model trained on a first part of the data goes on when the rest has come."""
    samples = to_samples(vec8(spark, sf_dir), P)
    first = train(samples.filter("sample_id % 2 = 0"), Glm(K), optim.Sgd(0.1), 2, N)
    return weights_frame(spark, train(samples, Glm(K), optim.Sgd(0.1), 2, N, init=first).weights)


STALE_SQL = f"""WITH RECURSIVE {VEC8_SQL}, t AS (
    SELECT 0 AS it, {ZERO} AS w, {ZERO} AS old
    UNION ALL
    SELECT q.it + 1, {each("q.w[j] - 0.1 * q.g[j]")}, q.w FROM (
      SELECT t.*, {GRAD.format(w="(CASE WHEN s.id % 4 % 2 = 1 THEN t.old ELSE t.w END)", where="")} AS g FROM t WHERE t.it < 4) q)
  SELECT (j // 2)::BIGINT AS slice, j::BIGINT AS j, round(w[j + 1], 6) AS w FROM t, (SELECT unnest(range(0, 8)) AS j) WHERE it = 4"""


@B.add("m_stale_train", STALE_SQL)
def m_stale_train(spark, sf_dir):
    """Odd producers are a round behind."""
    return weights_frame(spark, train_stale(to_samples(vec8(spark, sf_dir), P), Glm(K), 0.1, 4, lambda part: F.pmod(part, F.lit(2))))


def _link_sql(link: str, rounds: int) -> str:
    p = {"logistic": "1 / (1 + exp(-z))", "rational": "0.5 * (1 + z / (1 + abs(z)))"}[link]
    return f"""WITH RECURSIVE s AS (SELECT vec_id AS id, list_transform(embedding[1:8], lambda v: v::DOUBLE * 8) AS x,
      CASE WHEN embedding[1]::DOUBLE + embedding[2]::DOUBLE - embedding[3]::DOUBLE > 0 THEN 1 ELSE 0 END AS y FROM embeddings), t AS (
    SELECT 0 AS it, {ZERO} AS w
    UNION ALL
    SELECT q.it + 1, {each("q.w[j] - 0.5 * q.g[j]")} FROM (SELECT t.*, (SELECT list(h.g ORDER BY h.j) FROM (
      SELECT d.j, sum(({p} - y) * x[d.j]) / count(*) AS g FROM (SELECT s.x, s.y, list_inner_product(t.w, s.x) AS z FROM s) e, (SELECT unnest(range(1, 9)) AS j) d GROUP BY d.j) h) AS g FROM t WHERE t.it < {rounds}) q)
  SELECT (j // 2)::BIGINT AS slice, j::BIGINT AS j, round(w[j + 1], 6) AS w FROM t, (SELECT unnest(range(0, 8)) AS j) WHERE it = {rounds}"""


def binary8(spark, sf_dir):
    e = F.col("embedding")
    y = F.when(e[0].cast("double") + e[1].cast("double") - e[2].cast("double") > 0, 1).otherwise(0)
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.transform(F.slice("embedding", 1, 8), lambda v: v.cast("double") * 8).alias("x"), y.alias("y"))


def _linked(key, link):
    @B.add(key, _link_sql(link, 3))
    def run(spark, sf_dir):
        return weights_frame(spark, train(to_samples(binary8(spark, sf_dir), P), Glm(K, link), optim.Sgd(0.5), 3, N).weights)


_linked("m_logistic_sql", "logistic")
_linked("m_logistic_rational", "rational")


@B.add("m_minibatch_bucket", "SELECT ((o_orderkey * 7919 + 3 * 104729) % 16)::BIGINT AS bucket, count(*) AS n, min(o_orderkey) AS first_key, max(o_orderkey) AS last_key FROM orders GROUP BY 1")
def m_minibatch_bucket(spark, sf_dir):
    o = load(spark, sf_dir, "orders").select("o_orderkey")
    return o.groupBy(bucket_of(F.col("o_orderkey"), 16, 3).alias("bucket")).agg(F.count(F.lit(1)).alias("n"), F.min("o_orderkey").alias("first_key"), F.max("o_orderkey").alias("last_key"))


@B.add("m_samples", "SELECT vec_id % 4 AS part, (vec_id * 7919) % 5 AS bucket, count(*) AS n FROM embeddings GROUP BY 1, 2")
def m_samples(spark, sf_dir):
    s = to_samples(vec8(spark, sf_dir), P, buckets=5)
    return s.groupBy(F.col("part").cast("long").alias("part"), F.col("bucket").cast("long").alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


@B.add("m_grad_slices", f"""WITH {VEC8_SQL} SELECT id % 4 AS producer, (j // 2)::BIGINT AS slice, (j % 2)::BIGINT AS pos, round(sum((0.1 * list_sum(x) - y) * x[j + 1]), 6) AS g
  FROM s, (SELECT unnest(range(0, 8)) AS j) GROUP BY 1, 2, 3""")
def m_grad_slices(spark, sf_dir):
    grads = Glm(K).gradients(to_samples(vec8(spark, sf_dir), P), F.array(*[F.lit(0.1)] * K))
    cut = slices.ParamLayout(K, N).cut(grads)
    return cut.select(F.col("producer").cast("long").alias("producer"), F.col("slice").cast("long").alias("slice"), F.posexplode("g").alias("pos", "g")).select("producer", "slice", F.col("pos").cast("long").alias("pos"), F.round("g", 6).alias("g"))


def fixed_gradients(spark, sf_dir, parts: int = P, k: int = 64):
    """Exact integer gradients: floor(v 2^20 + 1/2) of every dimension, summed by producer."""
    e = load(spark, sf_dir, "embeddings").select((F.col("vec_id") % parts).cast("int").alias("producer"), F.transform("embedding", lambda v: F.floor(v.cast("double") * (1 << 20) + 0.5)).alias("x"))
    g = F.array(*[F.sum(F.get("x", j)) for j in range(k)])
    return e.groupBy("producer").agg(F.count(F.lit(1)).alias("n"), F.sum(F.lit(0)).alias("loss"), g.alias("g"))


FIXED_SQL = """SELECT j * 8 // 64 AS slice, j % 8 AS pos, sum(floor(embedding[j + 1]::DOUBLE * 1048576 + 0.5)::BIGINT)::BIGINT AS g
  FROM embeddings, (SELECT unnest(range(0, 64)) AS j) GROUP BY 1, 2"""


def _strategy(key, way):
    @B.add(key, FIXED_SQL)
    def run(spark, sf_dir):
        cut = slices.ParamLayout(64, 8).cut(fixed_gradients(spark, sf_dir))
        out = way(cut)
        return out.select(F.col("slice").cast("long").alias("slice"), F.posexplode("g").alias("pos", "g")).select("slice", F.col("pos").cast("long").alias("pos"), "g")


_strategy("m_slice_sum_exact", lambda c: slices.sliced(c, 8))
_strategy("m_sync_central", lambda c: slices.central(c, 8, 2))
_strategy("m_sync_tree", lambda c: slices.tree(c, 8, 2))
_strategy("m_sync_driver", lambda c: slices.driver(c, 8))
_strategy("m_sync_ring", lambda c: slices.ring(c, 8, P))
_strategy("m_sync_barrier", lambda c: slices.barrier(c, 8, 2))


@B.add("m_ring_traffic", "SELECT node::BIGINT AS node, (2 * 3 * 8 * 64 // 4)::BIGINT AS bytes_in, (2 * 3)::BIGINT AS hops FROM (SELECT unnest(range(0, 4)) AS node)")
def m_ring_traffic(spark, sf_dir):
    """Bytes that reach each of four nodes, counted hop by hop in both halves of the ring: 2 K (N - 1) / N."""
    _, hops = slices.ring_all(slices.ParamLayout(64, 4).cut(fixed_gradients(spark, sf_dir)), 4)
    return hops.groupBy("node").agg(F.sum("bytes").alias("bytes_in"), F.countDistinct("hop").alias("hops"))


@B.add("m_ring_all_gather", FIXED_SQL.replace("j * 8 // 64", "j * 4 // 64").replace("j % 8", "j % 16").replace("SELECT", "SELECT n.node::BIGINT AS node,", 1).replace("GROUP BY 1, 2", ", (SELECT unnest(range(0, 4)) AS node) n GROUP BY 1, 2, 3"))
def m_ring_all_gather(spark, sf_dir):
    """After the second half every node has every slice's sum."""
    held, _ = slices.ring_all(slices.ParamLayout(64, 4).cut(fixed_gradients(spark, sf_dir)), 4)
    return held.select(F.col("node").cast("long").alias("node"), F.col("slice").cast("long").alias("slice"), F.posexplode("g").alias("pos", "g")).select("node", "slice", F.col("pos").cast("long").alias("pos"), "g")


@B.add("m_barrier_loop", descent_sql(3))
def m_barrier_loop(spark, sf_dir):
    """One barrier stage runs all rounds: peers keep their samples and weights and exchange sums among themselves."""
    w = slices.barrier_train(vec8(spark, sf_dir), K, 0.1, 3, 2)
    return weights_frame(spark, w)


@B.add("m_sync_long", FIXED_SQL)
def m_sync_long(spark, sf_dir):
    cut = slices.ParamLayout(64, 8).cut(fixed_gradients(spark, sf_dir))
    return slices.long_sum(cut).select(F.col("slice").cast("long").alias("slice"), F.col("pos").cast("long").alias("pos"), F.col("v").alias("g"))


@B.add("m_weight_publish", "SELECT unnest(['driver', 'replicate', 'store', 'store in one plan']) AS via, 0::BIGINT AS differing")
def m_weight_publish(spark, sf_dir):
    """A network trained with each way to publish: how many weights differ from the ones that the driver published."""
    from slicegrad.nn import models
    from slicegrad.operators.kernel import train_net
    from slicegrad.plans.apps import images

    samples = images(spark, sf_dir)
    ways = {"driver": {}, "replicate": {"publish": "replicate"}, "store": {"publish": "store"}, "store in one plan": {"publish": "store", "group": 3}}
    got = {k: train_net(samples, models.Mlp(64, 8, 4), optim.Adam(0.02), 3, **v).weights for k, v in ways.items()}
    return spark.createDataFrame([(k, sum(abs(a - b) > 1e-9 for a, b in zip(w, got["driver"]))) for k, w in got.items()], "via string, differing long")


SEED_FACTOR = "(({id} * 37 + {d} * 11 + {o}) % 101 - 50) / 100.0"


def factor(id_, d, o):
    return F.array(*[(F.pmod(id_ * 37 + k * 11 + o, F.lit(101)) - 50) / 100.0 for k in range(d)])


def _factor_sql(id_, o, d=4):
    return "[" + ", ".join("(" + SEED_FACTOR.format(id=id_, d=k, o=o) + ")::DOUBLE" for k in range(d)) + "]"


def _whole_sql(id_, o, d=4):
    return "[" + ", ".join(f"({id_} * 37 + {k} * 11 + {o}) % 101 - 50" for k in range(d)) + "]::BIGINT[]"


@B.add("m_sparse_embedding_grad", f"""WITH {INTERACTIONS_SQL}, e AS (SELECT u, i, {_whole_sql('u', 3)} AS p, {_whole_sql('i', 7)} AS q FROM inter),
  r AS (SELECT *, list_sum(list_transform(range(1, 5), lambda k: p[k] * q[k]))::BIGINT - 10000 AS err FROM e)
  SELECT 'item' AS tbl, i AS row_id, j::BIGINT AS pos, sum(err * p[j + 1])::BIGINT AS g FROM r, (SELECT unnest(range(0, 4)) AS j) GROUP BY 1, 2, 3
  UNION ALL SELECT 'user', u, j::BIGINT, sum(err * q[j + 1])::BIGINT FROM r, (SELECT unnest(range(0, 4)) AS j) GROUP BY 1, 2, 3""")
def m_sparse_embedding_grad(spark, sf_dir):
    """Gradients (in millionths, so that sums are exact) of the touched rows only; two aggregates, one by user and one by item."""
    whole = lambda id_, o: F.array(*[F.pmod(id_ * 37 + k * 11 + o, F.lit(101)) - 50 for k in range(4)])
    e = interactions(spark, sf_dir).select("u", "i", whole(F.col("u"), 3).alias("p"), whole(F.col("i"), 7).alias("q"))
    r = e.withColumn("err", sum((F.get("p", k) * F.get("q", k) for k in range(4)), F.lit(-10000)))

    def side(name, key, other):
        g = F.array(*[F.sum(F.col("err") * F.get(other, k)) for k in range(4)])
        return r.groupBy(F.col(key).alias("row_id")).agg(g.alias("g")).select(F.lit(name).alias("tbl"), "row_id", F.posexplode("g").alias("pos", "g"))

    return side("item", "i", "p").unionByName(side("user", "u", "q")).select("tbl", "row_id", F.col("pos").cast("long").alias("pos"), "g")


@B.add("m_traffic_model", """WITH g AS (SELECT n, kb, rounds FROM (SELECT 1 + o_orderkey % 500 AS n, count(*) AS rounds FROM orders GROUP BY 1), (SELECT unnest([4096, 1048576, 1073741824])::BIGINT AS kb))
  SELECT n, kb, rounds, strategy, round(bytes::DOUBLE, 3) AS bytes FROM (
    SELECT n, kb, rounds, 'sliced' AS strategy, 2.0 * kb AS bytes FROM g UNION ALL SELECT n, kb, rounds, 'sliced_remote', 2.0 * kb * (n - 1)::DOUBLE / n FROM g
    UNION ALL SELECT n, kb, rounds, 'ring', 2.0 * kb * (n - 1)::DOUBLE / n FROM g UNION ALL SELECT n, kb, rounds, 'central', 1.0 * n * kb FROM g UNION ALL SELECT n, kb, rounds, 'driver', 1.0 * n * kb FROM g)""")
def m_traffic_model(spark, sf_dir):
    """Bytes in to (and, alike, out of) the busiest node in a round, for the recorded numbers of tasks, a node each. central and driver: one owner of all slices."""
    rounds = ledger(spark, sf_dir).groupBy(F.col("tasks").alias("n")).agg(F.count(F.lit(1)).alias("rounds"))
    g = rounds.withColumn("kb", F.explode(F.array(*[F.lit(k).cast("long") for k in (4096, 1 << 20, 1 << 30)])))
    n, kb = F.col("n"), F.col("kb")
    forms = {"sliced": kb * 2.0, "sliced_remote": 2.0 * kb * (n - 1) / n, "ring": 2.0 * kb * (n - 1) / n, "central": 1.0 * n * kb, "driver": 1.0 * n * kb}
    named = F.explode(F.array(*[F.struct(F.lit(k).alias("strategy"), v.cast("double").alias("bytes")) for k, v in forms.items()])).alias("f")
    return g.select("n", "kb", "rounds", named).select("n", "kb", "rounds", F.col("f.strategy").alias("strategy"), F.round("f.bytes", 3).alias("bytes"))


@B.add("m_traffic_measured", "SELECT node::BIGINT AS node, (8 * 64)::BIGINT AS gradient_in, (8 * 16 * 3)::BIGINT AS remote_in, (8 * 64)::BIGINT AS publish_in FROM (SELECT unnest(range(0, 4)) AS node)")
def m_traffic_measured(spark, sf_dir):
    """Counted from the slice rows: with four producers, four owners and eight bytes an element, K = 512 bytes in for gradients and K for weights."""
    cut = slices.ParamLayout(64, 4).cut(fixed_gradients(spark, sf_dir)).withColumn("bytes", 8 * F.size("g"))
    got = cut.groupBy(F.col("slice").cast("long").alias("node")).agg(F.sum("bytes").cast("long").alias("gradient_in"), F.sum(F.when(F.col("slice") != F.col("producer"), F.col("bytes")).otherwise(0)).cast("long").alias("remote_in"))
    whole = cut.filter("producer = 0").agg(F.sum("bytes").cast("long").alias("publish_in"))
    return got.crossJoin(F.broadcast(whole)).select("node", "gradient_in", "remote_in", "publish_in")


LEDGER_SQL = """ledger AS (SELECT o_orderkey // 100 AS iter, 1 + o_orderkey % 500 AS tasks, 100 + o_orderkey % 37 AS compute_ms, 3 + o_orderkey % 5 AS sync_ms,
    (1 + o_orderkey % 500) // 40 AS dispatch_ms, 120 + o_orderkey % 53 AS wall_ms, 32 + o_orderkey % 8 AS samples, [4, 16, 32, 96, 256][1 + o_orderkey % 5]::BIGINT AS nodes, 1000.0 / (1 + o_orderkey // 100) AS loss FROM orders)"""


def ledger(spark, sf_dir):
    k = F.col("o_orderkey")
    nodes = F.get(F.array(*[F.lit(v) for v in (4, 16, 32, 96, 256)]), (k % 5).cast("int")).cast("long")
    return load(spark, sf_dir, "orders").select(
        F.floor(k / 100).alias("iter"), (1 + k % 500).alias("tasks"), (100 + k % 37).alias("compute_ms"), (3 + k % 5).alias("sync_ms"),
        F.floor((1 + k % 500) / 40).alias("dispatch_ms"), (120 + k % 53).alias("wall_ms"), (32 + k % 8).alias("samples"), nodes.alias("nodes"), (1000.0 / (1 + F.floor(k / 100))).alias("loss"))


@B.add("m_ledger_overheads", f"""WITH {LEDGER_SQL} SELECT (tasks // 100)::BIGINT AS tasks_hundreds, count(*) AS rounds, round(avg(sync_ms) / avg(compute_ms), 6) AS sync_share, round(avg(dispatch_ms) / avg(compute_ms), 6) AS dispatch_share FROM ledger GROUP BY 1""")
def m_ledger_overheads(spark, sf_dir):
    return measures.sync_share(ledger(spark, sf_dir), F.floor(F.col("tasks") / 100).alias("tasks_hundreds"))


SPEEDUP_SQL = f"""WITH {LEDGER_SQL}, t AS (SELECT nodes, sum(samples) * 1000.0 / sum(wall_ms) AS thr FROM ledger GROUP BY 1)
  SELECT nodes, round(thr, 6) AS samples_per_s, round(thr / first_value(thr) OVER (ORDER BY nodes), 6) AS speedup, round(thr / first_value(thr) OVER (ORDER BY nodes) / (nodes / first_value(nodes) OVER (ORDER BY nodes)), 6) AS efficiency FROM t"""


@B.add("m_ledger_speedup", SPEEDUP_SQL)
def m_ledger_speedup(spark, sf_dir):
    return measures.speedup(ledger(spark, sf_dir))


@B.add("m_time_to_quality", f"""WITH {LEDGER_SQL}, r AS (SELECT iter, sum(wall_ms)::BIGINT AS wall_ms, min(loss) AS loss FROM ledger GROUP BY 1), c AS (SELECT *, sum(wall_ms) OVER (ORDER BY iter) AS at_ms FROM r)
  SELECT g AS goal, min(at_ms)::BIGINT AS ms FROM (SELECT unnest([500.0, 100.0, 50.0])::DOUBLE AS g) LEFT JOIN c ON loss <= g GROUP BY 1""")
def m_time_to_quality(spark, sf_dir):
    return measures.time_to_quality(ledger(spark, sf_dir), [500.0, 100.0, 50.0])


@B.add("m_cost_model_fit", f"""WITH {LEDGER_SQL} SELECT round(regr_slope(dispatch_ms, tasks), 6) AS ms_per_task, round(regr_intercept(dispatch_ms, tasks), 6) AS ms_fixed, round(regr_r2(dispatch_ms, tasks), 6) AS r2 FROM ledger""")
def m_cost_model_fit(spark, sf_dir):
    return ledger(spark, sf_dir).agg(F.round(F.regr_slope("dispatch_ms", "tasks"), 6).alias("ms_per_task"), F.round(F.regr_intercept("dispatch_ms", "tasks"), 6).alias("ms_fixed"), F.round(F.regr_r2("dispatch_ms", "tasks"), 6).alias("r2"))


@B.add("m_ledger_ratio", f"""WITH {LEDGER_SQL} SELECT round((SELECT sum(samples) * 1.0 / sum(wall_ms) FROM ledger WHERE nodes = 96) / (SELECT sum(samples) * 1.0 / sum(wall_ms) FROM ledger WHERE nodes = 16), 6) AS ratio""")
def m_ledger_ratio(spark, sf_dir):
    return measures.throughput_ratio(ledger(spark, sf_dir), 96, 16)


@B.add("m_recovery_cost", f"""WITH {LEDGER_SQL} SELECT iter % 10 AS failed_at, count(*) AS rounds, 1::BIGINT AS tasks_rerun_fine, (sum(tasks) - count(*))::BIGINT AS spared, sum(tasks)::BIGINT AS tasks_rerun_snapshot FROM ledger GROUP BY 1""")
def m_recovery_cost(spark, sf_dir):
    """A failed task alone against going back to a snapshot that is up to ten rounds old."""
    return measures.recovery_cost(ledger(spark, sf_dir), 10)


def _recorded(spark, sf_dir, **options):
    """The ledger of a real run: a network over all images, rounds as two actions with their times."""
    from slicegrad.nn import models
    from slicegrad.operators.kernel import train_net
    from slicegrad.plans.apps import images

    runs = [train_net(images(spark, sf_dir), models.Mlp(64, 16, 4), optim.Momentum(0.1), 4, parts=p, measure=True, **options).ledger for p in (1, 2, 4)]
    return measures.ledger_frame(spark, [r | {"nodes": p} for p, run in zip((1, 2, 4), runs) for r in run])


@B.add("w4_recorded_shares")
def w4_recorded_shares(spark, sf_dir):
    """Synchronisation and launching over compute, of a recorded run."""
    return measures.sync_share(_recorded(spark, sf_dir), "nodes")


@B.add("w5_recorded_speedup")
def w5_recorded_speedup(spark, sf_dir):
    return measures.speedup(_recorded(spark, sf_dir))


@B.add("w6_recorded_counters")
def w6_recorded_counters(spark, sf_dir):
    return measures.counters(_recorded(spark, sf_dir).filter("nodes = 4"))


@B.add("w2_recorded_time_to_quality")
def w2_recorded_time_to_quality(spark, sf_dir):
    """When the summed loss of a recorded run is first under the untrained one, a hundredth and a third below it."""
    run = _recorded(spark, sf_dir).filter("nodes = 4")
    first = run.agg(F.max("loss").alias("l")).first()["l"] or 0.0
    return measures.time_to_quality(run, [0.999999 * first, 0.99 * first, 0.67 * first])


@B.add("m_recorded_cost_model")
def m_recorded_cost_model(spark, sf_dir):
    """The fitted model of a round, and what it says of up to 256 nodes."""
    fit = measures.fit_cost_model(_recorded(spark, sf_dir))
    return spark.createDataFrame([(n, measures.predict_nodes(fit, n, 1e6)) for n in (1, 4, 16, 96, 256)], "nodes long, seconds double")


@B.add("m_predict_glm", """SELECT vec_id, round(list_sum(list_transform(range(1, 65), lambda j: embedding[j]::DOUBLE * (((j - 1) * 37 + 11) % 101 - 50) / 100.0)), 6) AS score FROM embeddings""")
def m_predict_glm(spark, sf_dir):
    w = F.array(*[F.lit(((j * 37 + 11) % 101 - 50) / 100) for j in range(64)])
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(dot(F.transform("embedding", lambda v: v.cast("double")), w), 6).alias("score"))


@B.add("m_mlp_forward", """WITH h AS (SELECT vec_id, o, greatest(0, sum(embedding[j + 1]::DOUBLE * (((o * 64 + j) * 37 + 11) % 101 - 50) / 100.0)) AS v
    FROM embeddings, (SELECT unnest(range(0, 64)) AS j), (SELECT unnest(range(0, 8)) AS o) GROUP BY 1, 2)
  SELECT vec_id, round(sum(v * ((o * 37 + 11) % 101 - 50) / 100.0), 6) AS score FROM h GROUP BY 1""")
def m_mlp_forward(spark, sf_dir):
    """dense 64 to 8, ReLU, dense to 1, inside one projection."""
    x = F.transform("embedding", lambda v: v.cast("double"))
    hidden = [F.greatest(F.lit(0.0), dot(x, F.array(*[F.lit((((o * 64 + j) * 37 + 11) % 101 - 50) / 100) for j in range(64)]))) for o in range(8)]
    score = sum((h * (((o * 37 + 11) % 101 - 50) / 100) for o, h in enumerate(hidden)), F.lit(0.0))
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(score, 6).alias("score"))


@B.add("m_conv_forward", """SELECT vec_id, (r * 6 + c)::BIGINT AS cell, round(sum(embedding[(r + a) * 8 + c + b + 1]::DOUBLE * (((a * 3 + b) * 37 + 11) % 101 - 50) / 100.0), 6) AS v
  FROM embeddings, (SELECT unnest(range(0, 6)) AS r), (SELECT unnest(range(0, 6)) AS c), (SELECT unnest(range(0, 3)) AS a), (SELECT unnest(range(0, 3)) AS b) GROUP BY 1, 2""")
def m_conv_forward(spark, sf_dir):
    """3 by 3 convolution of the 8 by 8 image, valid cells."""
    def cell(at):
        r, c = F.floor(at / 6).cast("int"), (at % 6).cast("int")
        return sum((F.get("embedding", (r + a) * 8 + c + b).cast("double") * (((a * 3 + b) * 37 + 11) % 101 - 50) / 100.0 for a in range(3) for b in range(3)), F.lit(0.0))

    e = load(spark, sf_dir, "embeddings")
    return e.select("vec_id", F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(35)), cell)).alias("cell", "v")).select("vec_id", F.col("cell").cast("long").alias("cell"), F.round("v", 6).alias("v"))


_FEATURES_SQL = """tok AS (SELECT doc_id, lang, lower(unnest(regexp_extract_all(text, '[A-Za-z]+'))) AS w FROM documents),
  cnt AS (SELECT doc_id, ('0x' || substr(md5(w), 1, 8))::BIGINT % 16 AS b, count(*) AS c FROM tok GROUP BY 1, 2),
  nrm AS (SELECT doc_id, sqrt(sum(c * c)) AS l FROM cnt GROUP BY 1)"""


def word_counts(text, buckets: int = 16):
    """How many ASCII words of a text fall into each bucket: a fold inside the row, so nothing moves.

    One Arrow pass: lambdas of the engine are interpreted, and took seven times as long as an explode and two shuffles.
    """
    @F.pandas_udf("array<double>")
    def folded(texts: pd.Series) -> pd.Series:
        import re
        from hashlib import md5

        known: dict[str, int] = {}
        out = []
        for text in texts:
            counts = [0.0] * buckets
            for word in re.findall("[A-Za-z]+", text or ""):
                b = known.get(word)
                if b is None:
                    if len(known) > 100_000:
                        known.clear()
                    b = known[word] = int(md5(word.lower().encode()).hexdigest()[:8], 16) % buckets
                counts[b] += 1
            out.append(counts)
        return pd.Series(out, dtype=object)

    return folded(text)


def dense_text(spark, sf_dir, *carry):
    """(doc_id, x, ...): L2-normalised counts of documents that have a word."""
    d = load(spark, sf_dir, "documents").select("doc_id", *carry, word_counts(F.col("text")).alias("c"))
    total = F.sqrt(F.aggregate("c", F.lit(0.0), lambda a, v: a + v * v))
    return d.withColumn("l", total).filter("l > 0").select("doc_id", *carry, F.transform("c", lambda v: v / F.col("l")).alias("x"))


@B.add("w1_text_features", f"WITH {_FEATURES_SQL} SELECT doc_id, b AS bucket, c, round(c / l, 6) AS v FROM cnt JOIN nrm USING (doc_id)")
def w1_text_features(spark, sf_dir):
    d = load(spark, sf_dir, "documents").select("doc_id", word_counts(F.col("text")).alias("c"))
    total = F.sqrt(F.aggregate("c", F.lit(0.0), lambda a, v: a + v * v))
    f = d.withColumn("l", total).select("doc_id", "l", F.posexplode("c").alias("bucket", "c")).filter("c > 0")
    return f.select("doc_id", F.col("bucket").cast("long").alias("bucket"), F.col("c").cast("long").alias("c"), F.round(F.col("c") / F.col("l"), 6).alias("v"))


LANGS = ["de", "en", "es", "fr"]
_DENSE_SQL = f"""{_FEATURES_SQL}, dense AS (SELECT doc_id, list(coalesce(v, 0) ORDER BY j) AS x FROM (
    SELECT d.doc_id, j, c / l AS v FROM (SELECT DISTINCT doc_id FROM cnt) d CROSS JOIN (SELECT unnest(range(0, 16)) AS j) LEFT JOIN cnt ON cnt.doc_id = d.doc_id AND cnt.b = j JOIN nrm ON nrm.doc_id = d.doc_id) GROUP BY 1)"""
_SOFT_STEP = """SELECT t.it + 1, (SELECT list(h.w ORDER BY h.c, h.j) FROM (
      SELECT cc.c, jj.j, t.w[cc.c * 16 + jj.j] - 1.0 * sum((p[cc.c + 1] - CASE WHEN y = cc.c THEN 1 ELSE 0 END) * x[jj.j]) / count(*) AS w
      FROM (SELECT x, y, list_transform(e, lambda v: v / list_sum(e)) AS p FROM (SELECT x, y, list_transform(range(0, {c}), lambda c: exp(list_inner_product(t.w[c * 16 + 1:c * 16 + 16], x))) AS e FROM s)) q,
        (SELECT unnest(range(0, {c})) AS c) cc, (SELECT unnest(range(1, 17)) AS j) jj GROUP BY 1, 2) h) FROM t WHERE t.it < 3"""


def softmax_sql(samples: str, classes: int, final: str) -> str:
    zero = "list_transform(range(0, {}), lambda j: 0.0::DOUBLE)".format(16 * classes)
    return f"WITH RECURSIVE {_DENSE_SQL}, s AS MATERIALIZED ({samples}), t AS (SELECT 0 AS it, {zero} AS w UNION ALL {_SOFT_STEP.format(c=classes)}) {final}"


_WEIGHTS = "SELECT c::BIGINT AS c, (j - 1)::BIGINT AS j, round(w[c * 16 + j], 5) AS w FROM t, (SELECT unnest(range(0, {})) AS c), (SELECT unnest(range(1, 17)) AS j) WHERE it = 3"
_LANG_S = "SELECT doc_id, x, list_position(['de', 'en', 'es', 'fr'], lang) - 1 AS y FROM dense JOIN documents USING (doc_id)"
_QUALITY_S = "SELECT doc_id, x, quality AS y FROM dense JOIN labels USING (doc_id)"


def softmax_rounds(samples, classes: int, rounds: int, lr: float = 1.0, k: int = 16):
    """Full-batch softmax regression; ``samples`` (x, y) is kept, the gradient is k x classes sums in one aggregate."""
    w = [[0.0] * k for _ in range(classes)]
    samples = samples.persist()
    try:
        for _ in range(rounds):
            z = [dot(F.col("x"), F.array(*[F.lit(v) for v in row])) for row in w]
            e = samples.withColumn("e", F.array(*[F.exp(v) for v in z])).withColumn("p", F.transform("e", lambda v: v / F.aggregate("e", F.lit(0.0), lambda a, b: a + b)))
            g = [F.sum((F.get("p", c) - F.when(F.col("y") == c, 1).otherwise(0)) * F.get("x", j)) / F.count(F.lit(1)) for c in range(classes) for j in range(k)]
            got = e.agg(F.array(*g).alias("g")).first()["g"]
            if got[0] is None:
                break
            w = [[v - lr * got[c * k + j] for j, v in enumerate(row)] for c, row in enumerate(w)]
    finally:
        samples.unpersist()
    return w


def _matrix_frame(spark, w):
    return spark.createDataFrame([(c, j, float(v)) for c, row in enumerate(w) for j, v in enumerate(row)], "c long, j long, w double").withColumn("w", F.round("w", 5))


def lang_samples(spark, sf_dir):
    return dense_text(spark, sf_dir, "lang").select("doc_id", "x", (F.array_position(F.array(*map(F.lit, LANGS)), F.col("lang")) - 1).alias("y"))


def quality_samples(spark, sf_dir):
    return dense_text(spark, sf_dir).join(load(spark, sf_dir, "labels"), "doc_id").select("doc_id", "x", F.col("quality").alias("y"))


@B.add("w1_lang_train", softmax_sql(_LANG_S, 4, _WEIGHTS.format(4)))
def w1_lang_train(spark, sf_dir):
    return _matrix_frame(spark, softmax_rounds(lang_samples(spark, sf_dir), 4, 3))


@B.add("w1_quality_train", softmax_sql(_QUALITY_S, 2, _WEIGHTS.format(2)))
def w1_quality_train(spark, sf_dir):
    return _matrix_frame(spark, softmax_rounds(quality_samples(spark, sf_dir), 2, 3))


#: The learned weights after three rounds, and each document's best class; documents without a word get the first.
_PREDICTED = softmax_sql(_LANG_S, 4, f"""SELECT documents.doc_id, lang, ['de', 'en', 'es', 'fr'][coalesce(1 + list_position(z, list_max(z)) - 1, 1)] AS predicted FROM documents LEFT JOIN (
    SELECT doc_id AS d, list_transform(range(0, 4), lambda c: list_inner_product(t.w[c * 16 + 1:c * 16 + 16], x)) AS z FROM dense, t WHERE it = 3) ON d = documents.doc_id""")


def predicted_langs(spark, sf_dir):
    """The pipeline: load, features, train, predict with what was learned."""
    w = softmax_rounds(lang_samples(spark, sf_dir), 4, 3)
    row = spark.createDataFrame([([[float(v) for v in r] for r in w],)], "w array<array<double>>")  # 64 numbers
    d = load(spark, sf_dir, "documents").select("doc_id", "lang", word_counts(F.col("text")).alias("c")).crossJoin(F.broadcast(row))
    z = F.transform("w", lambda r: dot(r, F.col("c")))  # the norm of a text changes no order
    best = F.coalesce(F.array_position(z, F.array_max(z)) - 1, F.lit(0)).cast("int")
    some = F.aggregate("c", F.lit(0.0), lambda a, v: a + v) > 0
    return d.select("doc_id", "lang", F.get(F.array(*map(F.lit, LANGS)), F.when(some, best).otherwise(0)).alias("predicted"))


@B.add("w1_predict", _PREDICTED)
def w1_predict(spark, sf_dir):
    return predicted_langs(spark, sf_dir)


@B.add("w1_metrics", f"WITH best AS ({_PREDICTED}) SELECT lang, count(*) AS n, round(avg(CASE WHEN lang = predicted THEN 1.0 ELSE 0 END), 6) AS recall, sum(CASE WHEN lang = predicted THEN 1 ELSE 0 END)::BIGINT AS hits FROM best GROUP BY 1")
def w1_metrics(spark, sf_dir):
    hit = (F.col("lang") == F.col("predicted")).cast("int")
    return predicted_langs(spark, sf_dir).groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(hit), 6).alias("recall"), F.sum(hit).alias("hits"))


@B.add("a_confusion_pivot", f"WITH best AS ({_PREDICTED}) SELECT lang, " + ", ".join(f"count(*) FILTER (predicted = '{x}') AS {x}" for x in LANGS) + " FROM best GROUP BY 1")
def a_confusion_pivot(spark, sf_dir):
    return predicted_langs(spark, sf_dir).groupBy("lang").pivot("predicted", LANGS).agg(F.count(F.lit(1))).fillna(0)
