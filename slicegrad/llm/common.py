"""Pieces that the text operators share."""

from __future__ import annotations

import sys
import tempfile
import types

from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Characters that part words in contracts on white space.
SPACE_CLASS = r"[\x20\x09-\x0D]"
WORD_PATTERN = r"[^\x20\x09-\x0D]+"


def ship_by_value(name: str) -> None:
    """Kernels of the module travel inside the task, so executors need no copy of the repository."""
    cloudpickle.register_pickle_by_value(sys.modules[name])


def process_cache(name: str) -> dict:
    """A dictionary that lives as long as the Python worker does, whatever task uses it."""
    holder = sys.modules.setdefault("_slicegrad_worker_cache", types.ModuleType("_slicegrad_worker_cache"))
    return holder.__dict__.setdefault(name, {})


def cut(df: DataFrame) -> DataFrame:
    """Materialise ``df`` in the shared checkpoint folder; lost executors lose nothing of it."""
    spark = df.sparkSession
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        where = spark.conf.get("spark.checkpoint.dir", None)
        if where is None:
            if not context.master.startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
            where = tempfile.mkdtemp(prefix="slicegrad-checkpoint-")
        context.setCheckpointDir(where)
    return df.checkpoint()


def text_or_empty(text: Column) -> Column:
    return F.coalesce(text, F.lit(""))


def lower_ascii(text: Column) -> Column:
    """A-Z to a-z and nothing else."""
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def single_spaced(text: Column) -> Column:
    """Words joined by one blank, no blank at the ends; null counts as empty."""
    out = text_or_empty(text)
    for c in "\t\n\x0b\f\r":
        out = F.replace(out, F.lit(c), F.lit(" "))
    return F.trim(F.regexp_replace(out, "  +", " "))


def words_of(text: Column) -> Column:
    spaced = single_spaced(text)
    return F.when(spaced == "", F.array().cast("array<string>")).otherwise(F.split(spaced, " "))


def count_words(text: Column) -> Column:
    """How many words a text has, without building them."""
    spaced = single_spaced(text)
    return F.when(spaced == "", F.lit(0).cast("long")).otherwise((F.length(spaced) - F.length(F.replace(spaced, F.lit(" "), F.lit(""))) + 1).cast("long"))


def whole_rows(df: DataFrame, text: str, **more: str) -> DataFrame:
    """``_row`` holds every given column, so that working columns clash with none of them."""
    return df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("_row"), F.col(f"`{text}`").alias("_text"), *[F.col(f"`{c}`").alias(k) for k, c in more.items()])


def unpacked(df: DataFrame, columns: list[str]) -> DataFrame:
    return df.select(*[F.col("_row").getField(c).alias(c) for c in columns])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
