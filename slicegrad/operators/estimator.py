"""Networks as stages of a pyspark.ml pipeline."""

from __future__ import annotations

from pyspark.ml import Estimator, Model
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slicegrad.functions.arrays import argmax
from slicegrad.operators.kernel import predict, train_net


class NetworkModel(Model):
    def __init__(self, net, weights, features: str = "x", scores: str = "scores", prediction: str = "prediction", ledger=()):
        super().__init__()
        self.net, self.weights, self.features, self.scores, self.prediction, self.ledger = net, weights, features, scores, prediction, list(ledger)

    def _transform(self, df: DataFrame) -> DataFrame:
        return predict(df, self.net, self.weights, self.features, self.scores).withColumn(self.prediction, argmax(F.col(self.scores)))


class NetworkEstimator(Estimator):
    def __init__(self, net, optimizer, rounds: int, parts: int = 4, key: str = "id", features: str = "x", label: str = "y", seed: int = 0):
        super().__init__()
        self.net, self.optimizer, self.rounds, self.parts, self.key, self.features, self.label, self.seed = net, optimizer, rounds, parts, key, features, label, seed

    def _fit(self, df: DataFrame) -> NetworkModel:
        label = F.col(self.label)
        target = label if dict(df.dtypes)[self.label].startswith("array") else F.array(label.cast("double"))
        samples = df.select(F.col(self.key).alias("id"), F.col(self.features).alias("x"), target.alias("y"))
        out = train_net(samples, self.net, self.optimizer, self.rounds, self.parts, seed=self.seed)
        return NetworkModel(self.net, out.weights, self.features, ledger=out.ledger)
