"""Dimension reduction: the most important features of a tree and random ones of the rest."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import mix


def reduce_features(scored: DataFrame, n_principal: int, n_selected: int, seed: int = 42) -> DataFrame:
    """tree, rank, feature_id, origin: n_principal features by importance, then n_selected - n_principal by hash of
    (feature, tree, seed) among the others; ties by feature_id. scored: tree, feature_id, importance."""
    by_value = Window.partitionBy("tree").orderBy(F.round("importance", 10).desc(), "feature_id")
    x = scored.select("tree", "feature_id", "importance").withColumn("r", F.row_number().over(by_value))
    key = mix(F.col("feature_id"), F.col("tree"), seed + 1)
    first = F.col("r") <= n_principal
    by_hash = Window.partitionBy("tree").orderBy((~first).cast("int"), F.when(first, F.col("r")), key, "feature_id")
    x = x.withColumn("rank", F.row_number().over(by_hash)).where(F.col("rank") <= n_selected)
    return x.select("tree", "rank", "feature_id", F.when(first, "principal").otherwise("random").alias("origin"))


def selected_arrays(selected: DataFrame, names: list[str]) -> DataFrame:
    """tree and its features' names in rank order."""
    lookup = F.array(*[F.lit(n) for n in names])
    ordered = F.sort_array(F.collect_list(F.struct("rank", lookup[F.col("feature_id")].alias("name"))))
    return selected.groupBy("tree").agg(F.transform(ordered, lambda x: x["name"]).alias("features"))
