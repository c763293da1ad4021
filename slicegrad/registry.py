"""All queries of the library outside the text operators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from slicegrad.plans import apps, core, files, metrics, relational
from slicegrad.streaming import queries as streams

_MODULES: list = [core, relational, apps, metrics, files, streams]


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return queries()["m_lsq_train"](spark, sf_dir)


def queries() -> dict:
    return {key: q for m in _MODULES for key, q in m.QUERIES.items()}


def oracle_sql() -> dict:
    return {key: q for m in _MODULES for key, q in m.ORACLES.items()}
