"""Saving, loading and importing of models: structure as JSON, weights as slices in Parquet or named arrays."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slicegrad.nn import models
from slicegrad.operators.slices import ParamLayout
from slicegrad.operators.train import assemble, weight_rows


def save(spark: SparkSession, net, theta, path: str, n: int = 4, **build) -> None:
    """``build``: the constructor's arguments, so that ``load`` can make the network again."""
    spec = [(type(net).__name__, repr(sorted(build.items())), list(net.shapes), [list(map(int, s)) for s in net.shapes.values()])]
    spark.createDataFrame(spec, "kind string, build string, names array<string>, shapes array<array<int>>").coalesce(1).write.mode("overwrite").json(f"{path}/spec")
    weight_rows(spark, ParamLayout(net.k, n), list(map(float, theta)), {}).write.mode("overwrite").parquet(f"{path}/weights")


def load(spark: SparkSession, path: str):
    """(network, weights)."""
    from ast import literal_eval

    spec = spark.read.json(f"{path}/spec").first()
    net = getattr(models, spec["kind"])(**dict(literal_eval(spec["build"])))
    if list(net.shapes) != list(spec["names"]):
        raise ValueError("the stored parameters are not this network's")
    return net, np.array(assemble(spark.read.parquet(f"{path}/weights")).first()[0])


def import_weights(net, arrays: dict) -> np.ndarray:
    """Weights that another program named; every parameter must be there in its shape."""
    missing = [k for k in net.shapes if k not in arrays]
    if missing:
        raise KeyError(f"no weights for {missing}")
    for k, shape in net.shapes.items():
        if tuple(arrays[k].shape) != tuple(shape):
            raise ValueError(f"{k} is {arrays[k].shape}, not {tuple(shape)}")
    return np.concatenate([np.asarray(arrays[k], dtype=np.float64).ravel() for k in net.shapes])


def import_npz(net, raw: bytes) -> np.ndarray:
    import io

    with np.load(io.BytesIO(raw)) as arrays:
        return import_weights(net, {k: arrays[k] for k in arrays.files})


def read_npz(spark: SparkSession, net, path: str) -> np.ndarray:
    """A named-array file of any store that Spark reads."""
    return import_npz(net, bytes(spark.read.format("binaryFile").load(path).first()["content"]))


def to_half(rows: DataFrame, column: str = "g") -> DataFrame:
    """Slices as two-byte floats for the wire: half the bytes, three digits."""
    @F.pandas_udf("binary")
    def pack(v: pd.Series) -> pd.Series:
        return v.map(lambda x: np.asarray(x, dtype=np.float16).tobytes())

    return rows.withColumn(column, pack(column))


def from_half(rows: DataFrame, column: str = "g") -> DataFrame:
    @F.pandas_udf("array<double>")
    def unpack(v: pd.Series) -> pd.Series:
        return v.map(lambda x: np.frombuffer(x, dtype=np.float16).astype(np.float64))

    return rows.withColumn(column, unpack(column))
