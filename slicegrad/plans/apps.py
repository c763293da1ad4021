"""The experiment workloads: recommender, vision pipeline, nowcasting, networks trained by kernels."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from slicegrad.functions.arrays import dot
from slicegrad.nn import models
from slicegrad.operators import optim
from slicegrad.operators.kernel import predict, train_net
from slicegrad.plans.core import _factor_sql, factor
from slicegrad.plans.kit import Book
from slicegrad.plans.relational import HOURS_SQL, hour_grid, hour_of
from slicegrad.sources.store import WeightStore
from slicegrad.sources.tables import INTERACTIONS_SQL, interactions, load

B = Book()
QUERIES, ORACLES = B.queries, B.oracles

TASTE_SQL = f"{INTERACTIONS_SQL}, taste AS (SELECT * FROM inter WHERE u % 4 = i % 4)"
HOLD_SQL = f"{TASTE_SQL}, hold AS (SELECT u, i FROM taste QUALIFY count(*) OVER (PARTITION BY u) >= 2 AND row_number() OVER (PARTITION BY u ORDER BY ts DESC, i DESC) = 1)"


def taste(spark, d):
    return interactions(spark, d).filter("u % 4 = i % 4")


def holdout(spark, d):
    """Each user's last item, by date and then number; a maximum, so it combines before moving."""
    g = taste(spark, d).groupBy("u").agg(F.max(F.struct("ts", "i")).alias("last"), F.count(F.lit(1)).alias("n"))
    return g.filter("n >= 2").select("u", F.col("last.i").alias("i"))


@B.add("w2_holdout", f"WITH {HOLD_SQL} SELECT u, i FROM hold")
def w2_holdout(spark, d):
    return holdout(spark, d)


@B.add("w2_negatives", f"""WITH {HOLD_SQL} SELECT h.u, k::BIGINT AS k, (h.u * 31 + h.i * 17 + k * 101) % (SELECT count(*) FROM part) AS i FROM hold h, (SELECT unnest(range(0, 8)) AS k)
  WHERE NOT EXISTS (SELECT 1 FROM inter x WHERE x.u = h.u AND x.i = (h.u * 31 + h.i * 17 + k * 101) % (SELECT count(*) FROM part))""")
def w2_negatives(spark, d):
    return negatives(spark, d, 8)


def negatives(spark, d, n: int):
    """Seeded items a user never had: an anti-join by (user, item), no draw per task."""
    items = F.broadcast(load(spark, d, "part").agg(F.count(F.lit(1)).alias("items")))  # one row
    c = holdout(spark, d).withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).crossJoin(items)
    drawn = c.select("u", F.col("k").cast("long").alias("k"), ((F.col("u") * 31 + F.col("i") * 17 + F.col("k") * 101) % F.col("items")).alias("i"))
    return drawn.join(interactions(spark, d).select("u", "i"), ["u", "i"], "left_anti").select("u", "k", "i")


_STEP_SQL = """SELECT u, j::BIGINT AS pos, round(avg(err * {part}), 5) AS g FROM r, (SELECT unnest(range(0, 4)) AS j) GROUP BY 1, 2"""


def _rows(spark, d):
    return taste(spark, d).select("u", "i", factor(F.col("u"), 4, 3).alias("p"), factor(F.col("i"), 4, 7).alias("q"))


def _mean_grad(r, part):
    g = r.groupBy("u").agg(F.array(*[F.avg(F.col("err") * part(k)) for k in range(4)]).alias("g"))
    return g.select("u", F.posexplode("g").alias("pos", "g")).select("u", F.col("pos").cast("long").alias("pos"), F.round("g", 5).alias("g"))


@B.add("w2_mf_step", f"WITH {TASTE_SQL}, e AS (SELECT u, {_factor_sql('u', 3)} AS p, {_factor_sql('i', 7)} AS q FROM taste), r AS (SELECT *, 1 / (1 + exp(-list_inner_product(p, q))) - 1 AS err FROM e) {_STEP_SQL.format(part='q[j + 1]')}")
def w2_mf_step(spark, d):
    """Logistic error of a matrix factorisation, gradient of the users' vectors."""
    r = _rows(spark, d).withColumn("err", 1 / (1 + F.exp(-dot(F.col("p"), F.col("q")))) - 1)
    return _mean_grad(r, lambda k: F.get("q", k))


_H = [0.5, -0.25, 1.0, 0.75]


@B.add("w2_gmf_step", f"WITH {TASTE_SQL}, e AS (SELECT u, {_factor_sql('u', 3)} AS p, {_factor_sql('i', 7)} AS q, {_H}::DOUBLE[] AS h FROM taste), r AS (SELECT *, 1 / (1 + exp(-list_inner_product(list_transform(range(1, 5), lambda k: p[k] * q[k]), h))) - 1 AS err FROM e) {_STEP_SQL.format(part='h[j + 1] * q[j + 1]')}")
def w2_gmf_step(spark, d):
    """The same for a weighed product of the vectors."""
    h = F.array(*map(F.lit, _H))
    r = _rows(spark, d).withColumn("err", 1 / (1 + F.exp(-dot(F.zip_with("p", "q", lambda a, b: a * b), h))) - 1)
    return _mean_grad(r, lambda k: F.get("q", k) * _H[k])


@B.add("w2_rank_metrics", f"""WITH {HOLD_SQL}, sc AS (SELECT h.u, (h.u * 7 + h.i * 13) % 1009 AS s, (SELECT count(*) FROM (SELECT unnest(range(0, 99)) AS k) n WHERE (h.u * 11 + n.k * 29) % 1009 > (h.u * 7 + h.i * 13) % 1009) AS above FROM hold h)
  SELECT count(*) AS users, round(avg(CASE WHEN above < 10 THEN 1.0 ELSE 0 END), 6) AS hr10, round(avg(CASE WHEN above < 10 THEN 1 / log2(above + 2) ELSE 0 END), 6) AS ndcg10 FROM sc""")
def w2_rank_metrics(spark, d):
    """HR@10 and NDCG@10 of the held-out item among 99 others, by formula scores; no pair is written out."""
    h = holdout(spark, d)
    own = (F.col("u") * 7 + F.col("i") * 13) % 1009
    above = F.size(F.filter(F.sequence(F.lit(0), F.lit(98)), lambda k: (F.col("u") * 11 + k * 29) % 1009 > own))
    hit = above < 10
    return h.agg(F.count(F.lit(1)).alias("users"), F.round(F.avg(F.when(hit, 1.0).otherwise(0.0)), 6).alias("hr10"), F.round(F.avg(F.when(hit, 1 / F.log2(above + 2.0)).otherwise(0.0)), 6).alias("ndcg10"))


# ---- pictures: 16 vectors as the 4 by 4 tiles of a 32 by 32 picture; one tile is five times as bright

PIC_SQL = """full_pic AS (SELECT vec_id // 16 AS pic FROM embeddings GROUP BY 1 HAVING count(*) = 16),
  tiles AS (SELECT vec_id // 16 AS pic, vec_id % 16 AS tile, CASE WHEN vec_id % 16 = (vec_id // 16) % 16 THEN 5.0 ELSE 1.0 END AS gain, embedding FROM embeddings WHERE vec_id // 16 IN (SELECT pic FROM full_pic))"""


def tiles(spark, d):
    """(pic, tile, px): the tiles of whole pictures, counted by a window on the picture."""
    e = load(spark, d, "embeddings").select(F.floor(F.col("vec_id") / 16).alias("pic"), (F.col("vec_id") % 16).alias("tile"), "embedding")
    n = F.count(F.lit(1)).over(Window.partitionBy("pic"))
    gain = F.when(F.col("tile") == F.col("pic") % 16, 5.0).otherwise(1.0)
    return e.withColumn("n", n).filter("n = 16").select("pic", "tile", F.transform("embedding", lambda v: v.cast("double") * gain).alias("px"))


def pictures(spark, d):
    """(pic, px): 1,024 pixels by rows."""
    g = tiles(spark, d).groupBy("pic").agg(F.transform(F.array_sort(F.collect_list(F.struct("tile", "px"))), lambda t: t["px"]).alias("t"))  # 16 tiles a picture
    pixel = F.transform(F.sequence(F.lit(0), F.lit(1023)), lambda j: F.get(F.get("t", (F.floor(j / 256) * 4 + F.floor(j % 32 / 8)).cast("int")), (F.floor(j / 32) % 8 * 8 + j % 8).cast("int")))
    return g.select("pic", pixel.alias("px"))


@B.add("w8_pictures", f"""WITH {PIC_SQL} SELECT pic, 1024::BIGINT AS pixels, round(sum(gain * embedding[j + 1]::DOUBLE), 5) AS total, round(sum(gain * embedding[j + 1]::DOUBLE * ((tile // 4) * 8 + j // 8)), 4) AS by_row, round(sum(gain * embedding[j + 1]::DOUBLE * ((tile % 4) * 8 + j % 8)), 4) AS by_column
  FROM tiles, (SELECT unnest(range(0, 64)) AS j) GROUP BY 1""")
def w8_pictures(spark, d):
    p = pictures(spark, d).select("pic", F.posexplode("px").alias("j", "v"))
    return p.groupBy("pic").agg(F.count(F.lit(1)).alias("pixels"), F.round(F.sum("v"), 5).alias("total"), F.round(F.sum(F.col("v") * F.floor(F.col("j") / 32)), 4).alias("by_row"), F.round(F.sum(F.col("v") * (F.col("j") % 32)), 4).alias("by_column"))


def scores(spark, d):
    """A filter bank of one box a tile: its energy is the score, so detection can be checked."""
    energy = F.aggregate("px", F.lit(0.0), lambda a, v: a + v * v)
    return tiles(spark, d).withColumn("score", energy)


_SCORE_SQL = f"{PIC_SQL}, sc AS (SELECT pic, tile, gain, embedding, gain * gain * list_sum(list_transform(embedding, lambda v: v::DOUBLE * v::DOUBLE)) AS score FROM tiles)"
_BEST_SQL = f"{_SCORE_SQL}, best AS (SELECT * FROM sc QUALIFY row_number() OVER (PARTITION BY pic ORDER BY score DESC, tile) = 1)"


@B.add("w8_detect_scores", f"WITH {_SCORE_SQL} SELECT pic, tile, round(score, 4) AS score FROM sc")
def w8_detect_scores(spark, d):
    return scores(spark, d).select("pic", "tile", F.round("score", 4).alias("score"))


def best_box(spark, d):
    """The best box before any crop: one crop a picture goes on."""
    top = scores(spark, d).groupBy("pic").agg(F.max(F.struct("score", (-F.col("tile")).alias("t"), "px")).alias("b"))
    return top.select("pic", (-F.col("b.t")).alias("tile"), F.col("b.px").alias("px"))


@B.add("w8_best_box", f"WITH {_BEST_SQL} SELECT pic, tile, (tile % 4 * 8)::BIGINT AS x0, (tile // 4 * 8)::BIGINT AS y0, tile = pic % 16 AS found FROM best")
def w8_best_box(spark, d):
    return best_box(spark, d).select("pic", "tile", (F.col("tile") % 4 * 8).alias("x0"), (F.floor(F.col("tile") / 4) * 8).alias("y0"), (F.col("tile") == F.col("pic") % 16).alias("found"))


@B.add("w8_crop", f"WITH {_BEST_SQL} SELECT pic, j::BIGINT AS pos, round(gain * embedding[j + 1]::DOUBLE, 5) AS v FROM best, (SELECT unnest(range(0, 64)) AS j)")
def w8_crop(spark, d):
    return best_box(spark, d).select("pic", F.posexplode("px").alias("pos", "v")).select("pic", F.col("pos").cast("long").alias("pos"), F.round("v", 5).alias("v"))


_BITS_SQL = f"""{_BEST_SQL}, z AS (SELECT pic, b, sum(floor(gain * embedding[j + 1]::DOUBLE * 1048576 + 0.5)::BIGINT * (((b * 64 + j) * 37 + 11) % 101 - 50)) AS z FROM best, (SELECT unnest(range(0, 16)) AS b), (SELECT unnest(range(0, 64)) AS j) GROUP BY 1, 2),
  bits AS (SELECT pic, sum(CASE WHEN z > 0 THEN 1 << b ELSE 0 END)::BIGINT AS bits FROM z GROUP BY 1)"""


def descriptors(spark, d):
    fixed = F.transform("px", lambda v: F.floor(v * 1048576 + 0.5))
    crop = best_box(spark, d).select("pic", fixed.alias("x"))

    def z(b):
        w = F.array(*[F.lit(((b * 64 + j) * 37 + 11) % 101 - 50).cast("long") for j in range(64)])
        return F.aggregate(F.zip_with("x", w, lambda p, q: p * q), F.lit(0).cast("long"), lambda a, v: a + v)

    return crop.select("pic", sum((F.when(z(b) > 0, 1 << b).otherwise(0) for b in range(16)), F.lit(0)).cast("long").alias("bits"))


@B.add("w8_descriptor", f"WITH {_BITS_SQL} SELECT pic, bits FROM bits")
def w8_descriptor(spark, d):
    return descriptors(spark, d)


@B.add("w8_store_roundtrip", f"WITH {_BITS_SQL} SELECT count(*) AS n, sum(bits)::BIGINT AS total FROM bits")
def w8_store_roundtrip(spark, d):
    store = WeightStore.temporary(spark)
    descriptors(spark, d).write.mode("overwrite").parquet(f"{store.folder}/descriptors")
    return spark.read.parquet(f"{store.folder}/descriptors").agg(F.count(F.lit(1)).alias("n"), F.sum("bits").alias("total"))


@B.add("m_descriptor_quality", f"WITH {_BITS_SQL} SELECT b::BIGINT AS bit, round(avg(((bits >> b) & 1)::DOUBLE), 6) AS balance FROM bits, (SELECT unnest(range(0, 16)) AS b) GROUP BY 1")
def m_descriptor_quality(spark, d):
    e = descriptors(spark, d).withColumn("bit", F.explode(F.sequence(F.lit(0), F.lit(15))))
    return e.groupBy(F.col("bit").cast("long").alias("bit")).agg(F.round(F.avg(F.expr("cast((shiftright(bits, bit) & 1) as double)")), 6).alias("balance"))


@B.add("m_hamming", f"WITH {_BITS_SQL} SELECT a.pic AS a, b.pic AS b, bit_count(xor(a.bits, b.bits))::BIGINT AS d FROM bits a JOIN bits b ON b.pic = a.pic + 1")
def m_hamming(spark, d):
    """Distance of each picture's bits to the next picture's."""
    x = descriptors(spark, d)
    a, b = x.select(F.col("pic").alias("a"), F.col("bits").alias("x")), x.select(F.col("pic").alias("b"), F.col("bits").alias("y"))
    return a.join(b, F.col("b") == F.col("a") + 1).select("a", "b", F.bit_count(F.col("x").bitwiseXOR(F.col("y"))).cast("long").alias("d"))


@B.add("m_detection_iou", f"""WITH {_BEST_SQL}, o AS (SELECT pic, greatest(0, 8 - abs(tile % 4 * 8 - pic % 16 % 4 * 8 + 2)) * greatest(0, 8 - abs(tile // 4 * 8 - pic % 16 // 4 * 8 + 2)) AS inter FROM best)
  SELECT count(*) AS n, round(avg(inter / (128.0 - inter)), 6) AS mean_iou, round(avg(CASE WHEN inter / (128.0 - inter) >= 0.3 THEN 1.0 ELSE 0 END), 6) AS found FROM o""")
def m_detection_iou(spark, d):
    """Overlap of the best box, moved by two pixels each way, with the true one."""
    b = best_box(spark, d).select("pic", "tile")
    side = lambda got, true: F.greatest(F.lit(0), 8 - F.abs(got * 8 - true * 8 + 2))
    inter = side(F.col("tile") % 4, F.col("pic") % 16 % 4) * side(F.floor(F.col("tile") / 4), F.floor(F.col("pic") % 16 / 4))
    iou = inter / (128.0 - inter)
    return b.agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(iou), 6).alias("mean_iou"), F.round(F.avg(F.when(iou >= 0.3, 1.0).otherwise(0.0)), 6).alias("found"))


# ---- frames: hourly sums on an 8 by 8 grid, zero-filled, summed over the last 24 hours

FRAME_SQL = f"""h AS ({HOURS_SQL}), c AS (SELECT unnest(range(0, 64)) AS cell), e AS (SELECT date_trunc('hour', ts) AS h, user_id % 64 AS cell, sum(round(value * 10000)::BIGINT)::BIGINT AS v FROM events GROUP BY 1, 2),
  frames AS (SELECT date_diff('hour', TIMESTAMP '2024-01-01', h.h)::BIGINT AS hour, c.cell, sum(coalesce(v, 0)) OVER (PARTITION BY c.cell ORDER BY h.h ROWS 23 PRECEDING)::BIGINT AS v FROM h CROSS JOIN c LEFT JOIN e ON e.h = h.h AND e.cell = c.cell)"""


def frames(spark, d):
    return frames_of(spark, load(spark, d, "events"))


def frames_of(spark, events):
    """(hour, cell, v) for every hour up to the last event's, v in ten-thousandths so that sums are exact in any order."""
    grid = hour_grid(events).crossJoin(F.broadcast(spark.range(64).withColumnRenamed("id", "cell")))
    e = events.select(hour_of().alias("hour"), (F.col("user_id") % 64).alias("cell"), F.round(F.col("value") * 10000).cast("long").alias("v")).groupBy("hour", "cell").agg(F.sum("v").alias("v"))
    filled = grid.join(e, ["hour", "cell"], "left").fillna(0, ["v"])
    return filled.withColumn("v", F.sum("v").over(Window.partitionBy("cell").orderBy("hour").rowsBetween(-23, 0)))


@B.add("w10_frames", f"WITH {FRAME_SQL} SELECT hour, cell, v FROM frames")
def w10_frames(spark, d):
    return frames(spark, d)


@B.add("w10_sequences", f"""WITH {FRAME_SQL} SELECT hour, cell, lag(v, 5) OVER w AS past5, lag(v, 1) OVER w AS past1, v AS now, lead(v, 1) OVER w AS next1, lead(v, 3) OVER w AS next3 FROM frames WINDOW w AS (PARTITION BY cell ORDER BY hour) QUALIFY past5 IS NOT NULL AND next3 IS NOT NULL""")
def w10_sequences(spark, d):
    w = Window.partitionBy("cell").orderBy("hour")
    s = frames(spark, d).select("hour", "cell", F.lag("v", 5).over(w).alias("past5"), F.lag("v", 1).over(w).alias("past1"), F.col("v").alias("now"), F.lead("v", 1).over(w).alias("next1"), F.lead("v", 3).over(w).alias("next3"))
    return s.filter("past5 is not null and next3 is not null")


@B.add("w10_persistence", f"""WITH {FRAME_SQL}, l AS (SELECT k AS lead, v, lead(v, k::INTEGER) OVER (PARTITION BY k, cell ORDER BY hour) AS later FROM frames, (SELECT unnest([1, 2, 3]) AS k))
  SELECT lead::BIGINT AS lead, count(*) AS n, round(avg((v - later)::DOUBLE / 10000 * ((v - later)::DOUBLE / 10000)), 3) AS mse, round(avg(abs(v - later)::DOUBLE / 10000), 3) AS mae FROM l WHERE later IS NOT NULL GROUP BY 1""")
def w10_persistence(spark, d):
    """Error of saying that the last frame stays, by lead."""
    w = Window.partitionBy("cell").orderBy("hour")
    errors = frames(spark, d).select(*[((F.lead("v", k).over(w) - F.col("v")) / 10000).alias(f"e{k}") for k in (1, 2, 3)])
    leads = F.array(*[F.struct(F.lit(k).cast("long").alias("lead"), F.col(f"e{k}").alias("e")) for k in (1, 2, 3)])
    e = errors.select(F.explode(leads).alias("x")).select("x.*").filter("e is not null")
    return e.groupBy("lead").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(F.col("e") * F.col("e")), 3).alias("mse"), F.round(F.avg(F.abs("e")), 3).alias("mae"))


@B.add("w10_linear_ar_train", f"""WITH {FRAME_SQL}, l AS (SELECT cell, v::DOUBLE / 10000 AS x, lead(v) OVER (PARTITION BY cell ORDER BY hour)::DOUBLE / 10000 AS y FROM frames)
  SELECT cell, round(regr_slope(y, x), 4) AS slope, round(regr_intercept(y, x), 2) AS intercept FROM l WHERE y IS NOT NULL GROUP BY 1 HAVING regr_sxx(y, x) > 0""")
def w10_linear_ar_train(spark, d):
    """One autoregression a cell, by its normal equations in one aggregate."""
    w = Window.partitionBy("cell").orderBy("hour")
    l = frames(spark, d).select("cell", (F.col("v") / 10000).alias("x"), (F.lead("v").over(w) / 10000).alias("y")).filter("y is not null")
    return l.groupBy("cell").agg(F.round(F.regr_slope("y", "x"), 4).alias("slope"), F.round(F.regr_intercept("y", "x"), 2).alias("intercept"), F.regr_sxx("y", "x").alias("sxx")).filter("sxx > 0").drop("sxx")


@B.add("m_nowcast_csi", f"""WITH {FRAME_SQL}, l AS (SELECT v, lead(v) OVER (PARTITION BY cell ORDER BY hour) AS later FROM frames), t AS (SELECT (SELECT quantile_disc(v, 0.9) FROM frames) AS t)
  SELECT sum(CASE WHEN v >= t AND later >= t THEN 1 ELSE 0 END)::BIGINT AS hits, sum(CASE WHEN v < t AND later >= t THEN 1 ELSE 0 END)::BIGINT AS misses, sum(CASE WHEN v >= t AND later < t THEN 1 ELSE 0 END)::BIGINT AS false_alarms FROM l, t WHERE later IS NOT NULL""")
def m_nowcast_csi(spark, d):
    """Hits, misses and false alarms of persistence over the ninth decile."""
    f = frames(spark, d)
    t = F.broadcast(f.agg(F.expr("percentile_disc(0.9) within group (order by v)").cast("long").alias("t")))  # one row
    l = f.select("v", F.lead("v").over(Window.partitionBy("cell").orderBy("hour")).alias("later")).filter("later is not null").crossJoin(t)
    n = lambda c: F.sum(F.when(c, 1).otherwise(0))
    a, b = F.col("v") >= F.col("t"), F.col("later") >= F.col("t")
    return l.agg(n(a & b).alias("hits"), n(~a & b).alias("misses"), n(a & ~b).alias("false_alarms"))


# ---- networks trained by kernels: the ledger of a few rounds


def images(spark, d):
    """8 by 8 images and the planted class: the quadrant of most energy."""
    e = load(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda v: v.cast("double") * 8).alias("x"))
    quadrant = [sum((F.get("x", r * 8 + c) * F.get("x", r * 8 + c) for r in range(a * 4, a * 4 + 4) for c in range(b * 4, b * 4 + 4)), F.lit(0.0)) for a in (0, 1) for b in (0, 1)]
    best = F.array_max(F.array(*[F.struct(q.alias("q"), F.lit(-k).alias("k")) for k, q in enumerate(quadrant)]))["k"]
    return e.select("id", "x", F.array((-best).cast("double")).alias("y"))


def _turns(spark, d):
    return load(spark, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0)).alias("w"))


def token_length(spark, d):
    """Words of the longest turn."""
    return max(_turns(spark, d).agg(F.max(F.size("w"))).first()[0] or 0, 1)


def token_samples(spark, d, vocabulary: int = 64):
    """Whole turns as hashed word ids, each of its own length, with the role-free target: does the turn have more than twelve words."""
    ids = F.transform("w", lambda w: (F.pmod(F.crc32(w.cast("binary")), F.lit(vocabulary - 1)) + 1).cast("double"))
    return _turns(spark, d).select("id", F.coalesce(ids, F.array().cast("array<double>")).alias("x"), F.array(F.when(F.size("w") > 12, 1.0).otherwise(0.0)).alias("y"))


def rating_samples(spark, d, users: int = 32, items: int = 32):
    """Every interaction, and whether its groups agree."""
    p = interactions(spark, d)
    return p.select((F.col("u") * 100003 + F.col("i")).alias("id"), F.array((F.col("u") % users).cast("double"), (F.col("i") % items).cast("double")).alias("x"), F.array((F.col("u") % 4 == F.col("i") % 4).cast("double")).alias("y"))


def frame_samples(spark, d, past: int = 6, future: int = 3, every: int = 1):
    """Past and future frames as flat arrays; a frame is 64 cells, gathered by hour."""
    f = frames(spark, d).groupBy("hour").agg(F.transform(F.array_sort(F.collect_list(F.struct("cell", "v"))), lambda p: p["v"] / 1e6).alias("f"))
    windows = f.select(F.explode(F.sequence(F.col("hour") - past - future + 1, F.col("hour"))).alias("id"), "hour", "f")
    s = windows.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("hour", "f"))).alias("s")).filter((F.size("s") == past + future) & (F.pmod("id", F.lit(every)) == 0))
    flat = lambda a, n: F.flatten(F.transform(F.slice("s", a, n), lambda p: p["f"]))
    return s.select("id", flat(1, past).alias("x"), flat(past + 1, future).alias("y"))


def _ledger(spark, result):
    return spark.createDataFrame([(r["iter"], float(r["samples"]), float(r["loss"]) / max(r["samples"], 1)) for r in result.ledger], "iter long, samples double, mean_loss double")


def _kernel(key, samples, net, opt, rounds=3):
    @B.add(key)
    def run(spark, d):
        return _ledger(spark, train_net(samples(spark, d), net(spark, d) if callable(net) else net, opt, rounds))


_kernel("m_mlp_train_kernel", images, models.Mlp(64, 16, 4), optim.Momentum(0.1))
_kernel("m_cnn_train_kernel", images, models.Inception(8, 4, 4), optim.Sgd(0.1))
_kernel("w4_fb_step", images, models.Inception(8, 4, 4), optim.Sgd(0.1), 1)
_kernel("w7_factored_train", images, models.Inception(8, 4, 4, "factored"), optim.Sgd(0.1))
_kernel("w7_residual_train", images, models.Inception(8, 4, 4, "residual"), optim.Sgd(0.1))
_kernel("m_lstm_train_kernel", token_samples, lambda s, d: models.Recurrent(64, token_length(s, d), 6, 8, 2, "lstm"), optim.Adam(0.02))
_kernel("w7_gru_train", token_samples, lambda s, d: models.Recurrent(64, token_length(s, d), 6, 8, 2, "gru"), optim.Adam(0.02))
_kernel("w7_rnn_train", token_samples, lambda s, d: models.Recurrent(64, token_length(s, d), 6, 8, 2, "rnn"), optim.Adam(0.02))
_kernel("w1_textconv_train", token_samples, lambda s, d: models.TextConv(64, token_length(s, d), 6, 8, 3, 2), optim.Adam(0.02))
_kernel("m_convlstm_train_kernel", frame_samples, models.ConvLstm(8, 2, 6, 3), optim.Adam(0.01), 2)
_kernel("m_neumf_train_kernel", rating_samples, models.NeuMf(32, 32, 4, 8), optim.Adam(0.02))
_kernel("m_gmf_train_kernel", rating_samples, models.NeuMf(32, 32, 4, 8, "gmf"), optim.Adam(0.02))
_kernel("m_mlpcf_train_kernel", rating_samples, models.NeuMf(32, 32, 4, 8, "mlp"), optim.Adam(0.02))
_kernel("m_mf_train_kernel", rating_samples, models.NeuMf(32, 32, 4, 8, "mf"), optim.Adam(0.02))
_kernel("w8_bit_descriptor_train", lambda s, d: images(s, d).withColumn("y", F.array(F.lit(0.0))), models.BitDescriptor(8, 16), optim.Sgd(0.01), 2)


@B.add("w10_nowcast")
def w10_nowcast(spark, d):
    """Trained for two rounds, then one forecast a window: mean squared error by lead."""
    samples = frame_samples(spark, d)
    net = models.ConvLstm(8, 2, 6, 3)
    model = train_net(samples, net, optim.Adam(0.01), 2)
    said = predict(samples, net, model.weights)
    e = said.select(F.posexplode(F.zip_with("scores", "y", lambda a, b: (a - b) * (a - b))).alias("pos", "e"))
    return e.groupBy((F.floor(F.col("pos") / 64) + 1).alias("lead")).agg(F.avg("e").alias("mse"))


def _binary64(spark, d):
    e = load(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda v: v.cast("double")).alias("v"))
    y = F.when(F.get("v", 0) + F.get("v", 9) - F.get("v", 18) > 0, 1.0).otherwise(0.0)
    features = F.array(*[F.greatest(F.lit(0.0), sum((F.get("v", j) * (((o * 64 + j) * 37 + 11) % 101 - 50) / 50.0 for j in range(64)), F.lit(0.0))) for o in range(4)])
    return e.select("id", features.alias("x"), y.alias("y"))


_HEAD_SQL = """WITH RECURSIVE f AS (SELECT vec_id, o, greatest(0, sum(embedding[j + 1]::DOUBLE * (((o * 64 + j) * 37 + 11) % 101 - 50) / 50.0)) AS v FROM embeddings, (SELECT unnest(range(0, 64)) AS j), (SELECT unnest(range(0, 4)) AS o) GROUP BY 1, 2),
  s AS MATERIALIZED (SELECT vec_id, list(v ORDER BY o) AS x, any_value((SELECT CASE WHEN e.embedding[1]::DOUBLE + e.embedding[10]::DOUBLE - e.embedding[19]::DOUBLE > 0 THEN 1 ELSE 0 END FROM embeddings e WHERE e.vec_id = f.vec_id)) AS y FROM f GROUP BY 1),
  t AS (SELECT 0 AS it, [0, 0, 0, 0]::DOUBLE[] AS w UNION ALL
    SELECT q.it + 1, list_transform(range(1, 5), lambda j: q.w[j] - 0.5 * q.g[j]) FROM (SELECT t.*, (SELECT list(h.g ORDER BY h.j) FROM (SELECT k.j, sum((1 / (1 + exp(-z)) - y) * x[k.j]) / count(*) AS g FROM (SELECT s.x, s.y, list_inner_product(t.w, s.x) AS z FROM s) e, (SELECT unnest(range(1, 5)) AS j) k GROUP BY k.j) h) AS g FROM t WHERE t.it < 3) q)
  SELECT j::BIGINT AS slice, j::BIGINT AS j, round(w[j + 1], 5) AS w FROM t, (SELECT unnest(range(0, 4)) AS j) WHERE it = 3"""


@B.add("w13_transfer_head", _HEAD_SQL)
def w13_transfer_head(spark, d):
    """A logistic head on frozen features: only the head's slices are ever sent."""
    from slicegrad.operators.train import Glm, to_samples, train, weights_frame

    w = train(to_samples(_binary64(spark, d), 4), Glm(4, "logistic"), optim.Sgd(0.5), 3, 4).weights
    return weights_frame(spark, w, 4).withColumn("w", F.round("w", 5))




@B.add("m_model_roundtrip", "SELECT j::BIGINT AS j, coalesce(s::DOUBLE / n / 100, 0) AS w FROM (SELECT unnest(range(0, 26)) AS j) LEFT JOIN (SELECT l_orderkey % 26 AS j, sum(floor(l_quantity)::BIGINT) AS s, count(l_quantity) AS n FROM lineitem GROUP BY 1) USING (j)")
def m_model_roundtrip(spark, d):
    """A network whose weights are mean quantities of line items (in hundreds, by order number), saved in slices and loaded again."""
    from slicegrad.operators.persist import load as load_model
    from slicegrad.operators.persist import save

    where = WeightStore.temporary(spark).folder
    net = models.Mlp(3, 4, 2)
    of = load(spark, d, "lineitem").groupBy((F.col("l_orderkey") % net.k).alias("j")).agg((F.sum(F.floor("l_quantity")).cast("double") / F.count("l_quantity") / 100).alias("w"))
    means = {r["j"]: r["w"] for r in of.collect()}  # one a weight
    theta = [means.get(j) or 0.0 for j in range(net.k)]
    save(spark, net, theta, where, d=3, hidden=4, classes=2)
    _, back = load_model(spark, where)
    return spark.createDataFrame([(j, float(v)) for j, v in enumerate(back)], "j long, w double")


@B.add("w15_connector", """SELECT vec_id AS id, round(list_sum(list_transform(range(1, 65), lambda j: embedding[j]::DOUBLE * (((j - 1) * 37 + 11) % 101 - 50) / 100.0)), 6) AS score FROM embeddings""")
def w15_connector(spark, d):
    """Export, a process without Spark, import: the same scores as in the plan."""
    from slicegrad.sources.connector import score_outside

    df = load(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda v: v.cast("double")).alias("x"))
    return score_outside(df, WeightStore.temporary(spark).folder, 64).select("id", F.round("score", 6).alias("score"))


# ---- the recommender to a goal: true ids, drawn negatives, the trained model ranked


SHRINK = 1e-5  # of the recommender's weights, a round


def taste_samples(spark, d, drawn: int = 4):
    """Every taste but each user's held-out one as 1, and ``drawn`` seeded items a taste that the user never had as 0.

    Drawn by a hash of user, item and number, so that every item is as likely: items that are only ever drawn, or never, would teach their number.
    """
    own = taste(spark, d).select("u", "i").join(holdout(spark, d), ["u", "i"], "left_anti")
    items = F.broadcast(load(spark, d, "part").agg(F.count(F.lit(1)).alias("items")))  # one row
    other = own.withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(drawn)))).crossJoin(items)
    other = other.select("u", F.pmod(F.xxhash64("u", "i", "k"), F.col("items")).alias("i")).distinct()
    other = other.join(interactions(spark, d).select("u", "i"), ["u", "i"], "left_anti")
    both = own.withColumn("y", F.lit(1.0)).unionByName(other.withColumn("y", F.lit(0.0)))
    return both.select((F.col("u") * 1_000_003 + F.col("i")).alias("id"), F.array(F.col("u").cast("double"), F.col("i").cast("double")).alias("x"), F.array("y").alias("y"))


def ranked(spark, d, net, *thetas, k: int = 10):
    """Where each of the trained models puts each user's held-out item among 99 seeded ones that the user never had: a row a model, by number.

    The items are drawn once for all models, and one pass scores and ranks them.
    """
    h = holdout(spark, d)
    every = h.select("u", "i", F.lit(True).alias("own")).unionByName(negatives(spark, d, 99).select("u", "i").distinct().withColumn("own", F.lit(False)))
    scored = every.withColumn("x", F.array(F.col("u").cast("double"), F.col("i").cast("double")))
    per_model, rows = [], []
    for m, theta in enumerate(thetas):
        scored = predict(scored, net, theta, out=f"s{m}")
        s, above = F.get(f"s{m}", 0), F.col(f"above{m}")
        per_model += [F.max(F.when(F.col("own"), s)).alias(f"mine{m}"), F.collect_list(F.when(~F.col("own"), s)).alias(f"others{m}")]  # 99 numbers a user
        hr, ndcg = F.avg((above < k).cast("double")), F.avg(F.when(above < k, 1 / F.log2(above + 2.0)).otherwise(0.0))
        rows.append(F.struct(F.lit(m).alias("model"), F.count(F.lit(1)).alias("users"), hr.alias("hr"), ndcg.alias("ndcg")))
    per_user = scored.groupBy("u").agg(*per_model)
    above = per_user.select(*[F.expr(f"size(filter(others{m}, v -> v >= mine{m}))").alias(f"above{m}") for m in range(len(thetas))])
    return above.agg(F.array(*rows).alias("r")).select(F.inline("r"))


def recommender(spark, d, kind: str = "neumf", width: int = 8):
    users = load(spark, d, "customer").agg(F.max("c_custkey")).first()[0] or 0
    items = load(spark, d, "part").agg(F.max("p_partkey")).first()[0] or 0
    return models.NeuMf(users + 1, items + 1, width, 8, kind, start=0.1)


@B.add("w2_trained_ranking")
def w2_trained_ranking(spark, d):
    """The joint model over all tastes with true ids, its weights published by tasks; hits and gain of the held-out items before and after."""
    net = recommender(spark, d)
    samples = taste_samples(spark, d)
    parts = max(4, spark.sparkContext.defaultParallelism)
    out = train_net(samples, net, optim.Adam(0.05), 40, parts, publish="replicate", group=5, l2=SHRINK)
    rounds = F.when(F.col("model") == 0, 0).otherwise(out.rounds).cast("long").alias("rounds")
    return ranked(spark, d, net, net.init(0), out.weights).select("users", "hr", "ndcg", rounds)


def train_to_goal(spark, d, goal: float, most: int = 60, every: int = 5, **options):
    """Rounds until HR@10 of the held-out items reaches the goal: (result, history)."""
    net = recommender(spark, d)
    stop = optim.TargetMetric(lambda w: ranked(spark, d, net, w).first()["hr"], goal, patience=4)
    return train_net(taste_samples(spark, d), net, optim.Adam(0.05), most, publish="replicate", group=every, stop=stop, l2=SHRINK, **options), stop.history


# ---- the detector and the descriptor as networks


def boxed_pictures(spark, d):
    """Whole pictures, and the true box of the bright tile."""
    tile = F.col("pic") % 16
    corner = [tile % 4 * 8, F.floor(tile / 4) * 8, tile % 4 * 8 + 8, F.floor(tile / 4) * 8 + 8]
    return pictures(spark, d).select(F.col("pic").alias("id"), F.col("px").alias("x"), F.array(*[c.cast("double") for c in corner]).alias("y"))


def mean_iou(found):
    """(id, y, scores: x0, y0, x1, y1, score) to the mean overlap and the share at a half or more."""
    g = lambda c, k: F.get(c, k)
    side = lambda k: F.greatest(F.lit(0.0), F.least(g("y", k + 2), g("scores", k + 2)) - F.greatest(g("y", k), g("scores", k)))
    area = lambda c: (g(c, 2) - g(c, 0)) * (g(c, 3) - g(c, 1))
    inter = side(0) * side(1)
    iou = inter / (area("y") + area("scores") - inter)
    return found.agg(F.count(F.lit(1)).alias("pictures"), F.avg(iou).alias("mean_iou"), F.avg((iou >= 0.5).cast("double")).alias("found"))


@B.add("w8_detector_trained")
def w8_detector_trained(spark, d):
    """The detector trained on the boxes: overlap of its best box with the true one, before and after."""
    net, data = models.Detector(32, 4), boxed_pictures(spark, d)
    out = train_net(data, net, optim.Adam(0.05), 30, publish="replicate", group=10)
    rows = [mean_iou(predict(data, net, w)).withColumn("rounds", F.lit(k).cast("long")) for k, w in ((0, net.init(0)), (out.rounds, out.weights))]
    return rows[0].unionByName(rows[1])


@B.add("w8_network_pipeline")
def w8_network_pipeline(spark, d):
    """Detect, best box, crop to eight by eight, describe in bits: two trained networks, one pass over the pictures."""
    data = boxed_pictures(spark, d)
    detector, describer = models.Detector(32, 4), models.BitDescriptor(8, 16)
    found = train_net(data, detector, optim.Adam(0.05), 30, publish="replicate", group=10).weights
    told = train_net(images(spark, d).withColumn("y", F.array(F.lit(0.0))), describer, optim.Adam(0.01), 6, publish="replicate", group=3).weights
    boxes = predict(data, detector, found)
    at = lambda k: F.greatest(F.lit(0), F.least(F.lit(24), F.round(F.get("scores", k)))).cast("int")
    crop = F.transform(F.sequence(F.lit(0), F.lit(63)), lambda j: F.get("x", ((F.col("y0") + F.floor(j / 8)) * 32 + F.col("x0") + j % 8).cast("int")))
    crops = boxes.withColumn("x0", at(0)).withColumn("y0", at(1)).select(F.col("id").alias("pic"), "x0", "y0", crop.alias("px"))
    bits = F.aggregate(F.transform("scores", lambda v: (v > 0).cast("long")), F.lit(0).cast("long"), lambda a, v: a * 2 + v)
    return predict(crops, describer, told, "px").select("pic", F.col("x0").cast("long").alias("x0"), F.col("y0").cast("long").alias("y0"), bits.alias("bits"))


@B.add("f_resize_bilinear", """WITH p AS (SELECT vec_id, embedding, r, c, r * 7.0 / 3 AS y, c * 7.0 / 3 AS x FROM embeddings, (SELECT unnest(range(0, 4)) AS r), (SELECT unnest(range(0, 4)) AS c)),
  q AS (SELECT *, least(floor(y), 6)::INTEGER AS i, least(floor(x), 6)::INTEGER AS j FROM p)
  SELECT vec_id, (r * 4 + c)::BIGINT AS cell, round((1 - (y - i)) * ((1 - (x - j)) * embedding[i * 8 + j + 1]::DOUBLE + (x - j) * embedding[i * 8 + j + 2]::DOUBLE) + (y - i) * ((1 - (x - j)) * embedding[i * 8 + j + 9]::DOUBLE + (x - j) * embedding[i * 8 + j + 10]::DOUBLE), 5) AS v FROM q""")
def f_resize_bilinear(spark, d):
    """Eight by eight to four by four, corners on corners, each pixel from its four neighbours."""
    def pixel(at):
        y, x = F.floor(at / 4) * 7.0 / 3, (at % 4) * 7.0 / 3
        i, j = F.least(F.floor(y), F.lit(6)).cast("int"), F.least(F.floor(x), F.lit(6)).cast("int")
        e = lambda a, b: F.get("embedding", (i + a) * 8 + j + b).cast("double")
        dy, dx = y - i, x - j
        return (1 - dy) * ((1 - dx) * e(0, 0) + dx * e(0, 1)) + dy * ((1 - dx) * e(1, 0) + dx * e(1, 1))

    p = load(spark, d, "embeddings").select("vec_id", F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(15)), pixel)).alias("cell", "v"))
    return p.select("vec_id", F.col("cell").cast("long").alias("cell"), F.round("v", 5).alias("v"))


@B.add("f_normalize", """WITH s AS (SELECT vec_id, list_transform(embedding, lambda v: v::DOUBLE) AS x FROM embeddings), m AS (SELECT vec_id, x, list_sum(x) / 64 AS mean FROM s), d AS (SELECT *, sqrt(list_sum(list_transform(x, lambda v: (v - mean) * (v - mean))) / 64) AS dev FROM m)
  SELECT vec_id, j::BIGINT AS pos, round((x[j + 1] - mean) / dev, 5) AS v FROM d, (SELECT unnest(range(0, 64)) AS j)""")
def f_normalize(spark, d):
    """A channel brought to mean 0 and spread 1, picture by picture."""
    e = load(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda v: v.cast("double")).alias("x"))
    m = e.withColumn("mean", F.aggregate("x", F.lit(0.0), lambda a, v: a + v) / 64)
    s = m.withColumn("dev", F.sqrt(F.aggregate("x", F.lit(0.0), lambda a, v: a + (v - F.col("mean")) * (v - F.col("mean"))) / 64))
    p = s.select("vec_id", F.posexplode(F.transform("x", lambda v: (v - F.col("mean")) / F.col("dev"))).alias("pos", "v"))
    return p.select("vec_id", F.col("pos").cast("long").alias("pos"), F.round("v", 5).alias("v"))


@B.add("j_asof_click", """WITH p AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase'), c AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'click')
  SELECT p.event_id AS purchase, c.event_id AS click FROM p ASOF LEFT JOIN c ON p.user_id = c.user_id AND p.ts >= c.ts""")
def j_asof_click(spark, d):
    """Each purchase with its user's last click not after it: one union, one window by user, no pairs."""
    e = load(spark, d, "events").filter("event_type in ('purchase', 'click')").select("event_id", "user_id", "ts", (F.col("event_type") == "click").alias("seen"))
    last = Window.partitionBy("user_id").orderBy("ts", F.desc("seen"), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("click", F.last(F.when(F.col("seen"), F.col("event_id")), ignorenulls=True).over(last)).filter("not seen").select(F.col("event_id").alias("purchase"), "click")
