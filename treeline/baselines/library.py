"""Spark's own forest on the same bins."""

from __future__ import annotations

from pyspark.ml.classification import RandomForestClassifier
from pyspark.ml.functions import array_to_vector
from pyspark.ml.regression import RandomForestRegressor
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.spec import ForestSpec


def _vectors(rows: DataFrame) -> DataFrame:
    features = array_to_vector(F.transform("bins", lambda b: b.cast("double"))).alias("features")
    return rows.select("row_id", F.col("target").cast("double").alias("label"), features)


def fit(rows: DataFrame, n_classes: int, spec: ForestSpec):
    kind = RandomForestClassifier if spec.task == "classification" else RandomForestRegressor
    forest = kind(numTrees=spec.n_trees, maxDepth=spec.max_depth, maxBins=max(32, spec.n_bins + 1), featureSubsetStrategy="sqrt", minInstancesPerNode=max(1, int(spec.min_rows)), seed=spec.seed)
    return forest.fit(_vectors(rows))


def predict(model, rows: DataFrame) -> DataFrame:
    """row_id, target, prediction."""
    return model.transform(_vectors(rows)).select("row_id", F.col("label").alias("target"), "prediction")
