"""Scorers: the key rate of feature cells, MLlib classifiers, a logistic scorer with a choice of training loss, or a
given score column."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.ml import Pipeline, PipelineModel
from pyspark.ml.classification import GBTClassifier, LogisticRegression, RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schemas import require
from ..sources.io import shared_folder

KINDS = ("cells", "logit", "forest", "gbt", "steps", "given")
LOSSES = ("squared", "divergence")
#: bits that a stored cell takes in the size of a cells model: its key and its rate
CELL_BITS = 128


@dataclass
class Scorer:
    kind: str
    features: tuple[str, ...]
    cells: DataFrame | None = None
    prior: float = 0.5
    model: PipelineModel | None = None
    #: of kind 'steps': (mean, scale, weight) of each feature, and the constant
    weights: tuple[tuple[float, float, float], ...] = ()
    constant: float = 0.0

    def score(self, df: DataFrame) -> DataFrame:
        """df with score in [0, 1]; narrow."""
        if self.kind == "given":
            return require(df, "score")
        if self.kind == "cells":
            # cells are at most the distinct binned features, which the caller bounds; larger tables are joined by shuffle
            return df.join(self.cells, list(self.features), "left").withColumn("score", F.coalesce("cell_rate", F.lit(self.prior))).drop("cell_rate")
        if self.kind == "steps":
            return df.withColumn("score", _logistic(self.features, self.weights, self.constant))
        return self.model.transform(df).withColumn("score", vector_to_array("probability")[1]).drop("__features", "rawPrediction", "probability", "prediction")

    def model_bits(self) -> int:
        """Size of the stored scorer: the files of a saved model, or the cells."""
        if self.kind == "given":
            return 0
        if self.kind == "cells":
            return CELL_BITS * self.cells.count()
        if self.kind == "steps":
            return 64 * (3 * len(self.features) + 1)
        spark = SparkSession.active()
        at = f"{shared_folder(spark, 'model')}/m"
        self.model.write().save(at)
        return 8 * int(spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(at).agg(F.sum("length")).first()[0])


def _scaled(feature: str, mean: float, scale: float):
    return (F.coalesce(F.nanvl(F.col(feature).cast("double"), F.lit(mean)), F.lit(mean)) - mean) / scale


def _logistic(features, weights, constant: float):
    z = F.lit(float(constant))
    for f, (mean, scale, w) in zip(features, weights, strict=True):
        z = z + _scaled(f, mean, scale) * w
    return 1 / (1 + F.exp(-z))


def _by_steps(df: DataFrame, features: tuple[str, ...], label: str, loss: str, steps: int, rate: float) -> Scorer:
    """A logistic scorer by gradient steps, one aggregation each. 'squared' lowers the mean squared error, both classes
    weighing alike; 'divergence' raises the divergence of the mean scores of keys and non-keys, taken as the shares of
    a soft upper region."""
    if loss not in LOSSES:
        raise ValueError(f"loss {loss!r} is none of {LOSSES}")
    key = F.col(label) == 1
    first = df.agg(F.count_if(key), F.count_if(~key), *(x for f in features for x in (F.avg(F.nanvl(F.col(f).cast("double"), F.lit(None))), F.stddev(F.nanvl(F.col(f).cast("double"), F.lit(None)))))).first()
    n1, n0 = max(1, first[0]), max(1, first[1])
    scales = [(first[2 + 2 * i] or 0.0, first[3 + 2 * i] or 1.0) for i in range(len(features))]
    w, velocity = np.zeros(len(features) + 1), np.zeros(len(features) + 1)
    for _ in range(steps):
        s = _logistic(features, [(m, d, float(x)) for (m, d), x in zip(scales, w)], w[-1])
        rows = df.select(key.alias("k"), s.alias("s"), *(_scaled(f, m, d).alias(f"x{i}") for i, (f, (m, d)) in enumerate(zip(features, scales))))
        slope = F.col("s") * (1 - F.col("s"))
        parts = [F.lit(1.0), *(F.col(f"x{i}") for i in range(len(features)))]
        sums = [F.sum(F.when(c, slope * e * x).otherwise(0.0)) for c in (F.col("k"), ~F.col("k")) for e in (F.lit(1.0), F.col("s")) for x in parts]
        got = rows.agg(F.avg(F.when(F.col("k"), F.col("s"))), F.avg(F.when(~F.col("k"), F.col("s"))), *sums).first()
        a, b, g = got[0] or 0.5, got[1] or 0.5, np.array([x or 0.0 for x in got[2:]]).reshape(2, 2, len(parts))
        (key_1, key_s), (non_1, non_s) = g / np.array([n1, n0])[:, None, None]
        if loss == "squared":
            up = 2 * (key_1 - key_s) - 2 * non_s  # against the gradient of (1 - s)^2 over keys and s^2 over non-keys
        else:
            a, b = (min(1 - 1e-6, max(1e-6, x)) for x in (a, b))
            up = (math.log(a / b) - math.log((1 - a) / (1 - b))) * key_1 + ((1 - a) / (1 - b) - a / b) * non_1
            if a == b:
                up = key_1 - non_1  # the divergence is flat where both classes score alike
            up = up / max(1.0, float(np.abs(up).max()))
        velocity = 0.8 * velocity + rate * np.concatenate([up[1:], up[:1]])
        w = w + velocity
    return Scorer("steps", features, weights=tuple((m, d, float(x)) for (m, d), x in zip(scales, w)), constant=float(w[-1]))


def fit(df: DataFrame, kind: str, features: tuple[str, ...] = (), label: str = "is_key", seed: int = 7, **options) -> Scorer:
    """A scorer from training rows (keys and the train part of non-keys)."""
    if kind == "given":
        return Scorer(kind, tuple(features))
    require(df, label, *features)
    if kind == "cells":
        key = F.sum(label).cast("double")
        cells = df.groupBy(*features).agg(((key + 0.5) / (F.count("*") + 1)).alias("cell_rate"))
        keys, rows = df.agg(F.sum(label), F.count("*")).first()
        return Scorer(kind, tuple(features), cells=cells, prior=((keys or 0) + 0.5) / (rows + 1))
    if kind == "steps":
        return _by_steps(df, tuple(features), label, options.get("loss", "squared"), options.get("steps", 25), options.get("rate", 1.0))
    learner = {
        "logit": lambda: LogisticRegression(labelCol=label, featuresCol="__features", **options),
        "forest": lambda: RandomForestClassifier(labelCol=label, featuresCol="__features", seed=seed, **{"numTrees": 20, "maxDepth": 8, **options}),
        "gbt": lambda: GBTClassifier(labelCol=label, featuresCol="__features", seed=seed, **{"maxIter": 20, **options}),
    }[kind]()
    return Scorer(kind, tuple(features), model=Pipeline(stages=[VectorAssembler(inputCols=list(features), outputCol="__features", handleInvalid="keep"), learner]).fit(df))
