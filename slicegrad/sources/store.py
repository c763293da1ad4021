"""Versioned weights in a shared folder: tasks read the version they were launched with."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


class WeightStore:
    def __init__(self, spark: SparkSession, folder: str):
        self.spark, self.folder = spark, folder

    @classmethod
    def temporary(cls, spark: SparkSession) -> WeightStore:
        return cls(spark, shared_folder(spark, "weights"))

    def publish(self, weights: DataFrame, version: int) -> None:
        weights.write.mode("overwrite").parquet(f"{self.folder}/version={version}")

    def read(self, version: int) -> DataFrame:
        return self.spark.read.parquet(f"{self.folder}/version={version}")

    def latest(self, at_most: int | None = None) -> DataFrame:
        """The newest version (not above ``at_most``), with its number."""
        every = self.spark.read.parquet(self.folder)
        if at_most is not None:
            every = every.filter(F.col("version") <= at_most)
        newest = every.agg(F.max("version")).first()[0]
        return every.filter(F.col("version") == newest)


def kept(df: DataFrame) -> DataFrame:
    """Materialised in the shared checkpoint folder, its lineage cut."""
    context = df.sparkSession.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(shared_folder(df.sparkSession, "checkpoint"))
    return df.checkpoint()


def shared_folder(spark: SparkSession, what: str) -> str:
    """A new folder where all executors can write; machine-local only under a local master."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if where is None:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        where = tempfile.mkdtemp(prefix="slicegrad-")
    return f"{where.rstrip('/')}/{what}-{uuid.uuid4().hex}"


def one_version(rows: DataFrame) -> DataFrame:
    """Refuses weights of more than one version."""
    if rows.select("version").distinct().limit(2).count() > 1:
        raise ValueError("weights of several versions")
    return rows
