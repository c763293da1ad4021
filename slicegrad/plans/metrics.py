"""Quality measures, and the steps that need more than their own slice."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from slicegrad.operators import slices
from slicegrad.operators.train import Glm, to_samples
from slicegrad.plans.core import _PREDICTED, LEDGER_SQL, K, P, ledger, predicted_langs
from slicegrad.plans.apps import _BITS_SQL, descriptors
from slicegrad.plans.kit import Book
from slicegrad.sources.tables import VEC8_SQL, load, vec8

B = Book()
QUERIES, ORACLES = B.queries, B.oracles

_SCORED = "SELECT quality AS y, (doc_id * 37) % 101 AS s FROM labels"


@B.add("m_auc", f"""WITH d AS ({_SCORED}), g AS (SELECT s, sum(y) AS pos, sum(1 - y) AS neg FROM d GROUP BY 1), c AS (SELECT *, coalesce(sum(neg) OVER (ORDER BY s ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM g)
  SELECT round(sum(pos * (below + neg / 2.0)) / (sum(pos) * sum(neg)), 6) AS auc FROM c""")
def m_auc(spark, d):
    """Ties count half. Rows are combined by score first, so the running sum is over distinct scores."""
    g = load(spark, d, "labels").groupBy(((F.col("doc_id") * 37) % 101).alias("s")).agg(F.sum("quality").alias("pos"), F.sum(1 - F.col("quality")).alias("neg"))
    below = F.coalesce(F.sum("neg").over(Window.orderBy("s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    c = g.withColumn("below", below)
    return c.agg(F.round(F.sum(F.col("pos") * (F.col("below") + F.col("neg") / 2.0)) / (F.sum("pos") * F.sum("neg")), 6).alias("auc"))


@B.add("m_log_loss", "SELECT round(-avg(quality * ln(p) + (1 - quality) * ln(1 - p)), 6) AS log_loss FROM (SELECT quality, (1 + (doc_id * 37) % 99) / 100.0::DOUBLE AS p FROM labels)")
def m_log_loss(spark, d):
    p = (1 + (F.col("doc_id") * 37) % 99) / 100.0
    return load(spark, d, "labels").agg(F.round(-F.avg(F.col("quality") * F.log(p) + (1 - F.col("quality")) * F.log(1 - p)), 6).alias("log_loss"))


@B.add("m_class_metrics", f"""WITH best AS ({_PREDICTED}), c AS (SELECT l AS class, sum(CASE WHEN lang = l AND predicted = l THEN 1 ELSE 0 END) AS tp, sum(CASE WHEN lang <> l AND predicted = l THEN 1 ELSE 0 END) AS fp, sum(CASE WHEN lang = l AND predicted <> l THEN 1 ELSE 0 END) AS fn
    FROM best, (SELECT unnest(['de', 'en', 'es', 'fr']) AS l) GROUP BY 1)
  SELECT class, tp::BIGINT AS tp, fp::BIGINT AS fp, fn::BIGINT AS fn, round(2.0 * tp / greatest(2 * tp + fp + fn, 1), 6) AS f1, round(2.0 * sum(tp) OVER () / (2 * sum(tp) OVER () + sum(fp) OVER () + sum(fn) OVER ()), 6) AS micro_f1, round(avg(2.0 * tp / greatest(2 * tp + fp + fn, 1)) OVER (), 6) AS macro_f1 FROM c""")
def m_class_metrics(spark, d):
    p = predicted_langs(spark, d).groupBy("lang", "predicted").agg(F.count(F.lit(1)).alias("n"))
    per = p.withColumn("class", F.explode(F.array(*map(F.lit, ["de", "en", "es", "fr"]))))
    t, g = F.col("lang") == F.col("class"), F.col("predicted") == F.col("class")
    c = per.groupBy("class").agg(*[F.sum(F.when(x, F.col("n")).otherwise(0)).alias(k) for k, x in (("tp", t & g), ("fp", ~t & g), ("fn", t & ~g))])
    all_ = Window.partitionBy(F.lit(0))  # one row a class
    f1 = 2.0 * F.col("tp") / F.greatest(2 * F.col("tp") + F.col("fp") + F.col("fn"), F.lit(1))
    s = lambda k: F.sum(k).over(all_)
    return c.select("class", "tp", "fp", "fn", F.round(f1, 6).alias("f1"), F.round(2.0 * s("tp") / (2 * s("tp") + s("fp") + s("fn")), 6).alias("micro_f1"), F.round(F.avg(f1).over(all_), 6).alias("macro_f1"))


@B.add("m_average_precision", """WITH r AS (SELECT label, vec_id % 4 = 0 AS hit, row_number() OVER w AS rk, sum(CASE WHEN vec_id % 4 = 0 THEN 1 ELSE 0 END) OVER w AS hits FROM embeddings WINDOW w AS (PARTITION BY label ORDER BY (vec_id * 37) % 101 DESC, vec_id ROWS UNBOUNDED PRECEDING))
  SELECT label, round(avg(hits * 1.0 / rk), 6) AS ap, sum(CASE WHEN rk <= 10 THEN 1 ELSE 0 END)::BIGINT AS hits10 FROM r WHERE hit GROUP BY 1""")
def m_average_precision(spark, d):
    """Of each query (here: each label), precision at every hit, averaged."""
    w = Window.partitionBy("label").orderBy(F.desc("s"), "vec_id")
    e = load(spark, d, "embeddings").select("label", "vec_id", ((F.col("vec_id") * 37) % 101).alias("s"), (F.col("vec_id") % 4 == 0).alias("hit"))
    r = e.select("label", "hit", F.row_number().over(w).alias("rk"), F.sum(F.col("hit").cast("int")).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("hits")).filter("hit")
    return r.groupBy("label").agg(F.round(F.avg(F.col("hits") * 1.0 / F.col("rk")), 6).alias("ap"), F.sum((F.col("rk") <= 10).cast("int")).alias("hits10"))


def first_gradients(spark, d, w: float = 0.1):
    """(pos, w, g): the mean gradient at equal weights, an element a row."""
    grads = Glm(K).gradients(to_samples(vec8(spark, d), P), F.array(*[F.lit(w)] * K))
    total = slices.sliced(slices.ParamLayout(K, 4).cut(grads), 4).select("slice", "n", F.posexplode("g").alias("at", "g"))
    return total.select((F.col("slice") * 2 + F.col("at")).cast("long").alias("pos"), F.lit(w).alias("w"), (F.col("g") / F.col("n")).alias("g"))


_G = f"WITH {VEC8_SQL}, g AS (SELECT j AS pos, 0.1::DOUBLE AS w, sum((0.1 * list_sum(x) - y) * x[j + 1]) / count(*) AS g FROM s, (SELECT unnest(range(0, 8)) AS j) GROUP BY 1)"


@B.add("m_lars_step", f"""{_G}, n AS (SELECT pos // 4 AS layer, sqrt(sum(w * w)) AS wn, sqrt(sum(g * g)) AS gn FROM g GROUP BY 1)
  SELECT pos::BIGINT AS pos, round(w - 0.1 * wn / (gn + 0.01 * wn) * (g + 0.01 * w), 6) AS w FROM g JOIN n ON pos // 4 = layer""")
def m_lars_step(spark, d):
    """Layer-wise scaling crosses slices: one small aggregate by layer, broadcast (a row a layer), then the update."""
    g = first_gradients(spark, d).withColumn("layer", F.floor(F.col("pos") / 4))
    n = F.broadcast(g.groupBy("layer").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("wn"), F.sqrt(F.sum(F.col("g") * F.col("g"))).alias("gn")))
    new = F.col("w") - 0.1 * F.col("wn") / (F.col("gn") + 0.01 * F.col("wn")) * (F.col("g") + 0.01 * F.col("w"))
    return g.join(n, "layer").select("pos", F.round(new, 6).alias("w"))


@B.add("m_lamb_step", f"""{_G}, u AS (SELECT pos, w, g / (abs(g) + 1e-6) + 0.01 * w AS u FROM g), n AS (SELECT pos // 4 AS layer, sqrt(sum(w * w)) AS wn, sqrt(sum(u * u)) AS un FROM u GROUP BY 1)
  SELECT pos::BIGINT AS pos, round(w - 0.1 * wn / un * u, 6) AS w FROM u JOIN n ON pos // 4 = layer""")
def m_lamb_step(spark, d):
    """The first round of the Adam-like form: bias correction makes the moments the gradient and its square."""
    u = first_gradients(spark, d).select("pos", "w", (F.col("g") / (F.abs("g") + 1e-6) + 0.01 * F.col("w")).alias("u")).withColumn("layer", F.floor(F.col("pos") / 4))
    n = F.broadcast(u.groupBy("layer").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("wn"), F.sqrt(F.sum(F.col("u") * F.col("u"))).alias("un")))
    return u.join(n, "layer").select("pos", F.round(F.col("w") - 0.1 * F.col("wn") / F.col("un") * F.col("u"), 6).alias("w"))


@B.add("m_clip_norm_step", f"{_G}, n AS (SELECT sqrt(sum(g * g)) AS gn FROM g) SELECT pos::BIGINT AS pos, round(w - 0.1 * g * least(1, 0.5 / gn), 6) AS w FROM g, n")
def m_clip_norm_step(spark, d):
    g = first_gradients(spark, d)
    n = F.broadcast(g.agg(F.sqrt(F.sum(F.col("g") * F.col("g"))).alias("gn")))  # one row
    return g.crossJoin(n).select("pos", F.round(F.col("w") - 0.1 * F.col("g") * F.least(F.lit(1.0), 0.5 / F.col("gn")), 6).alias("w"))


@B.add("m_weighted_gradient", f"WITH {VEC8_SQL} SELECT j::BIGINT AS pos, round(sum((1 + id % 3) * (0.1 * list_sum(x) - y) * x[j + 1]) / sum(1 + id % 3), 6) AS g FROM s, (SELECT unnest(range(0, 8)) AS j) GROUP BY 1")
def m_weighted_gradient(spark, d):
    """Sample weights go into the sum and into the count that divides it."""
    samples = to_samples(vec8(spark, d), P, wt=(1 + F.col("id") % 3).cast("double"))
    grads = Glm(K).gradients(samples, F.array(*[F.lit(0.1)] * K))
    total = grads.agg(F.sum("n").alias("n"), F.array(*[F.sum(F.get("g", j)) for j in range(K)]).alias("g"))
    return total.select("n", F.posexplode("g").alias("pos", "g")).select(F.col("pos").cast("long").alias("pos"), F.round(F.col("g") / F.col("n"), 6).alias("g"))


@B.add("m_accumulated_gradient", f"WITH {VEC8_SQL} SELECT j::BIGINT AS pos, round(sum((0.1 * list_sum(x) - y) * x[j + 1]), 5) AS g FROM s, (SELECT unnest(range(0, 8)) AS j) WHERE (id * 7919) % 5 < 3 GROUP BY 1")
def m_accumulated_gradient(spark, d):
    """Three micro-batches are added up in their tasks before anything is sent."""
    samples = to_samples(vec8(spark, d), P, buckets=5).filter("bucket < 3")
    grads = Glm(K).gradients(samples, F.array(*[F.lit(0.1)] * K))
    total = grads.agg(F.array(*[F.sum(F.get("g", j)) for j in range(K)]).alias("g"))
    return total.select(F.posexplode("g").alias("pos", "g")).select(F.col("pos").cast("long").alias("pos"), F.round("g", 5).alias("g"))


@B.add("m_replica_pairing", "SELECT vec_id % 4 AS part, count(*) AS n, 1::BIGINT AS replicas FROM embeddings GROUP BY 1")
def m_replica_pairing(spark, d):
    """Samples and one replica a partition, both by id: a cogroup that moves nothing more."""
    s = to_samples(vec8(spark, d), P).select("part", "sample_id").repartitionById(P, "part")
    r = spark.range(P).select(F.col("id").cast("int").alias("part"), F.lit("net").alias("replica")).repartitionById(P, "part")

    def pair(key, samples: pd.DataFrame, replicas: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"part": [key[0]], "n": [len(samples)], "replicas": [len(replicas)]})

    return s.groupBy("part").cogroup(r.groupBy("part")).applyInPandas(pair, "part long, n long, replicas long")


@B.add("m_cluster_cost", f"""WITH {LEDGER_SQL}, t AS (SELECT sum(wall_ms) / 1000.0::DOUBLE AS s FROM ledger)
  SELECT cards::BIGINT AS cards, round(s * (0.5 * 20 / cards + 0.5 * 20 / cards), 3) AS tied, round(s * (0.5 * 20 / 1200 + 0.5 * 20 / cards), 3) AS free_reading FROM t, (SELECT unnest([5, 10, 20, 40]) AS cards)""")
def m_cluster_cost(spark, d):
    """Seconds of all recorded rounds, taken as those of a 20-card cluster that reads for half of them: reading tied to the cards, or to 1,200 cores."""
    t = ledger(spark, d).agg((F.sum("wall_ms") / 1000.0).alias("s"))
    n = F.col("cards")
    c = t.select("s", F.explode(F.array(*[F.lit(k).cast("long") for k in (5, 10, 20, 40)])).alias("cards"))
    return c.select("cards", F.round(F.col("s") * (0.5 * 20 / n + 0.5 * 20 / n), 3).alias("tied"), F.round(F.col("s") * (0.5 * 20 / 1200 + 0.5 * 20 / n), 3).alias("free_reading"))


@B.add("m_descriptor_retrieval", f"""WITH {_BITS_SQL}, r AS (SELECT q.pic AS q, x.pic, x.pic % 16 = q.pic % 16 AS hit, row_number() OVER (PARTITION BY q.pic ORDER BY bit_count(xor(q.bits, x.bits)), x.pic) AS rk FROM bits q JOIN bits x ON x.pic <> q.pic WHERE q.pic % 10 = 0),
  h AS (SELECT *, sum(hit::INTEGER) OVER (PARTITION BY q ORDER BY rk) AS hits FROM r)
  SELECT q, count(*) FILTER (hit AND rk <= 10) AS hits10, round(coalesce(avg(hits * 1.0 / rk) FILTER (hit), 0), 6) AS ap FROM h GROUP BY 1""")
def m_descriptor_retrieval(spark, d):
    """Pictures whose number is divisible by ten ask for those with the same planted tile, by Hamming distance: average precision, hits in ten."""
    x = descriptors(spark, d)
    q = F.broadcast(x.filter("pic % 10 = 0").select(F.col("pic").alias("q"), F.col("bits").alias("qb")))
    pairs = x.join(q, F.col("pic") != F.col("q")).select("q", "pic", F.bit_count(F.col("bits").bitwiseXOR(F.col("qb"))).alias("d"), (F.col("pic") % 16 == F.col("q") % 16).alias("hit"))
    w = Window.partitionBy("q").orderBy("d", "pic")
    r = pairs.select("q", "hit", F.row_number().over(w).alias("rk"), F.sum(F.col("hit").cast("int")).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("hits"))
    return r.groupBy("q").agg(F.count(F.when(F.col("hit") & (F.col("rk") <= 10), 1)).alias("hits10"), F.round(F.coalesce(F.avg(F.when(F.col("hit"), F.col("hits") * 1.0 / F.col("rk"))), F.lit(0.0)), 6).alias("ap"))
