"""Mixing sources to target weights by systematic sampling.

``source_targets`` shares a budget of words among sources by weight, none above a multiple of its own size.
``mix_copies`` gives each document a number of copies: inside a source the expected copies (target / size)
are summed along the documents, one offset is added, and a document is emitted once for each integer that
its stretch of the sum crosses. The sum runs over chunks that are numbered in parallel and then chained by
the chunks' totals, so no task holds a source. Inside a chunk, documents stand by size, which spreads every
size evenly over the sample.

Null texts have size 0; null sources form one source, the last; repeated rows are rows of their own; a source
without words has ratio 0 and is never taken; an empty table gives an empty result; other columns stay.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from slicegrad.llm.common import count_words, cut, whole_rows

CHUNK_ROWS = 4_000
#: Up to so many rows, the tables by source and by chunk are broadcast; beyond, they are joined by key.
BROADCAST_ROWS = 50_000


def small(table: DataFrame) -> DataFrame:
    """Marked for broadcast if its rows, counted now, are few enough."""
    return F.broadcast(table) if table.count() <= BROADCAST_ROWS else table


def spread(text):
    """0 to 2 ** 32 - 1, from the first digits of the MD5, which other engines have too."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def source_targets(sizes: DataFrame, weights=(3, 1, 2), share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """(source, source_size, n_rows) to the same with ``target``.

    The shares that are capped give their excess to the others by weight until none is above its cap. With
    sources ordered by cap / weight, those capped are a prefix: the level is what is left over what the rest
    weighs, and a source is capped if the level at its place reaches its cap. After the first that isn't, levels
    only fall, so its level is the largest of theirs. One row a source is ordered.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    every = Window.partitionBy(F.lit(0))
    cycle = F.array(*[F.lit(float(w)) for w in weights])
    ranked = sizes.withColumn("weight", F.element_at(cycle, ((F.row_number().over(order) - 1) % len(weights) + 1).cast("int"))).withColumn("most", F.col("source_size") * F.lit(float(cap)))
    fill = Window.partitionBy(F.lit(0)).orderBy(F.col("most") / F.col("weight"), F.col("source").asc_nulls_last())
    before = fill.rowsBetween(Window.unboundedPreceding, -1)
    onward = fill.rowsBetween(0, Window.unboundedFollowing)
    leveled = ranked.withColumn("level", (F.sum("source_size").over(every) * F.lit(float(share)) - F.coalesce(F.sum("most").over(before), F.lit(0.0))) / F.sum("weight").over(onward))
    marked = leveled.withColumn("capped", F.col("level") * F.col("weight") >= F.col("most"))
    final = F.max(F.when(~F.col("capped"), F.col("level"))).over(every)
    return marked.withColumn("final", final).select("source", "source_size", "n_rows", F.when(F.col("capped"), F.col("most")).otherwise(F.col("final") * F.col("weight")).alias("target"))


def mix_copies(docs: DataFrame, text: str = "text", source: str = "source", doc_id: str = "doc_id", weights=(3, 1, 2), share: float = 1.5, cap: float = 2.0, seed: int = 17, keep: bool = True) -> DataFrame:
    """``_row`` (if ``keep``), ``doc_id``, ``size``, ``source_size``, ``target``, ``copies`` for every row."""
    rows = whole_rows(docs, text, source=source, doc_id=doc_id)
    sized = rows.select(*(["_row"] if keep else []), "doc_id", "source", count_words(F.col("_text")).alias("size"), F.xxhash64("_text").alias("tie"))
    narrow = cut(sized.select("doc_id", "source", "size", "tie"))  # words are counted once for all that follows
    per_source = narrow.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n_rows"))
    targets = small(cut(source_targets(per_source, weights, share, cap).withColumn("chunks", F.ceil(F.col("n_rows") / CHUNK_ROWS))))
    targets = targets.withColumnRenamed("source", "_of")
    chunk = F.pmod(spread(F.concat_ws(":", F.lit(str(seed)), F.coalesce(F.col("doc_id").cast("string"), F.col("tie").cast("string")), F.col("size").cast("string"))), F.col("chunks"))

    def deal(rows: DataFrame) -> DataFrame:
        return rows.join(targets, rows["source"].eqNullSafe(targets["_of"]), "left").drop("_of").withColumn("chunk", chunk)

    placed = deal(sized if keep else narrow).withColumn("place", F.row_number().over(Window.partitionBy("source", "chunk").orderBy("size", F.col("doc_id").asc_nulls_last(), "tie")))
    counts = deal(narrow).groupBy("source", "chunk").agg(F.count(F.lit(1)).alias("n"))
    starts = small(cut(counts.select(F.col("source").alias("_s"), F.col("chunk").alias("_c"), (F.sum("n").over(Window.partitionBy("source").orderBy("chunk")) - F.col("n")).alias("start"))))
    k = F.col("start") + F.col("place")
    ratio = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    offset = spread(F.concat(F.lit(f"{seed}:"), F.coalesce("source", F.lit("\0null")))) / F.lit(float(1 << 32))
    crossed = F.floor(offset + ratio * k) - F.floor(offset + ratio * (k - 1))
    out = placed.join(starts, placed.source.eqNullSafe(starts._s) & (placed.chunk == starts._c), "left")
    return out.select(*(["_row"] if keep else []), "doc_id", "size", "source_size", "target", crossed.cast("long").alias("copies"))


def mix(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: each row as often as its copies, with the columns of ``docs``."""
    copies = mix_copies(docs, **options)
    repeated = copies.filter(F.col("copies") > 0).select("_row", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))).alias("_copy"))
    return repeated.select(*[F.col("_row").getField(c).alias(c) for c in docs.columns])
