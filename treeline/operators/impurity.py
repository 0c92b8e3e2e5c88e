"""Histograms and split scores. A histogram row is (tree, node, feature_id, bin, s0, s1, ...): for a classifier s_k is
the weight of class k, for a regressor s0, s1, s2 are the sums of w, w*y and w*y*y."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.math import xlog2x

NODE = ["tree", "node"]
CELL = ["tree", "node", "feature_id", "bin"]


def n_stats(task: str, n_classes: int) -> int:
    return n_classes if task == "classification" else 3


def stat_names(k: int) -> list[str]:
    return [f"s{i}" for i in range(k)]


def stat_sums(task: str, n_classes: int, w: Column, y: Column) -> list[Column]:
    if task == "classification":
        return [F.sum(F.when(y == i, w).otherwise(0)).cast("double").alias(f"s{i}") for i in range(n_classes)]
    y = y.cast("double")
    return [F.sum(x).cast("double").alias(f"s{i}") for i, x in enumerate((w, w * y, w * y * y))]


def histogram(cells: DataFrame, task: str, n_classes: int) -> DataFrame:
    """From cells (tree, node, feature_id, bin, target, w): one aggregate for all trees, nodes and features."""
    return cells.groupBy(*CELL).agg(*stat_sums(task, n_classes, F.col("w"), F.col("target")))


def _plus(cols: list[Column]) -> Column:
    return reduce(lambda a, b: a + b, cols)


def gains(hist: DataFrame, task: str, n_classes: int) -> DataFrame:
    """tree, node, feature_id, n and the scores of a split with one child per bin, from one aggregate.

    Classifier: h_target, h_cond, split_info, gain (not below 0), gain_ratio (0 where split_info is 0), gini.
    Regressor: variance (of the target), gain (its reduction, not below 0), split_info, gain_ratio = gain.
    """
    key = ["tree", "node", "feature_id"]
    s = [F.col(x) for x in stat_names(n_stats(task, n_classes))]
    if task == "classification":
        nb = _plus(s)
        x = hist.groupBy(*key).agg(
            F.sum(nb).alias("n"),
            F.sum(xlog2x(nb)).alias("sx"),
            F.sum(_plus([xlog2x(c) for c in s])).alias("sb"),
            F.sum(F.when(nb > 0, _plus([c * c for c in s]) / nb).otherwise(0.0)).alias("sg"),
            *[F.sum(c).alias(f"t{i}") for i, c in enumerate(s)],
        ).where("n > 0")
        t = [F.col(f"t{i}") for i in range(len(s))]
        h = F.log2("n") - _plus([xlog2x(c) for c in t]) / F.col("n")
        x = x.withColumn("h_target", h).withColumn("h_cond", (F.col("sx") - F.col("sb")) / F.col("n"))
        x = x.withColumn("split_info", F.log2("n") - F.col("sx") / F.col("n"))
        x = x.withColumn("gain", F.greatest(F.col("h_target") - F.col("h_cond"), F.lit(0.0)))
        x = x.withColumn("gini", F.greatest(F.col("sg") / F.col("n") - _plus([c * c for c in t]) / (F.col("n") * F.col("n")), F.lit(0.0)))
        x = x.withColumn("gain_ratio", F.when(F.col("split_info") > 1e-12, F.col("gain") / F.col("split_info")).otherwise(0.0))
        return x.select(*key, "n", "h_target", "h_cond", "split_info", "gain", "gain_ratio", "gini")
    x = hist.groupBy(*key).agg(
        F.sum("s0").alias("n"), F.sum("s1").alias("a"), F.sum("s2").alias("b"), F.sum(xlog2x(F.col("s0"))).alias("sx"), F.sum(F.when(F.col("s0") > 0, F.col("s1") * F.col("s1") / F.col("s0")).otherwise(0.0)).alias("m")
    ).where("n > 0")
    x = x.withColumn("variance", F.greatest(F.col("b") / F.col("n") - F.col("a") * F.col("a") / (F.col("n") * F.col("n")), F.lit(0.0)))
    x = x.withColumn("gain", F.greatest(F.col("m") / F.col("n") - F.col("a") * F.col("a") / (F.col("n") * F.col("n")), F.lit(0.0)))
    x = x.withColumn("split_info", F.log2("n") - F.col("sx") / F.col("n"))
    return x.select(*key, "n", "variance", "gain", "split_info", F.col("gain").alias("gain_ratio"), F.col("gain").alias("gini"))


def binary_gains(hist: DataFrame, task: str, n_classes: int) -> DataFrame:
    """tree, node, feature_id, cut, n, gain: the best split of each feature into bins up to cut and above it, by the
    reduction of Gini impurity or variance; running sums over the ordered bins."""
    key = ["tree", "node", "feature_id"]
    names = stat_names(n_stats(task, n_classes))
    up, every = Window.partitionBy(*key).orderBy("bin"), Window.partitionBy(*key)
    x = hist
    for c in names:
        x = x.withColumn(f"l_{c}", F.sum(c).over(up)).withColumn(f"a_{c}", F.sum(c).over(every))

    def inner(p: str) -> tuple[Column, Column]:
        """Weight of a side, and the part of its impurity that depends on the split."""
        c = [F.col(f"a_{n}") - F.col(f"l_{n}") if p == "r" else F.col(f"{p}_{n}") for n in names]
        if task == "classification":
            n = _plus(c)
            return n, F.when(n > 0, _plus([v * v for v in c]) / n).otherwise(0.0)
        return c[0], F.when(c[0] > 0, c[1] * c[1] / c[0]).otherwise(0.0)

    (n_l, i_l), (n_r, i_r), (n_a, i_a) = inner("l"), inner("r"), inner("a")
    x = x.withColumn("n", n_a).withColumn("gain", F.greatest((i_l + i_r - i_a) / n_a, F.lit(0.0))).where((n_l > 0) & (n_r > 0))
    best = F.max_by(F.struct("bin", "gain", "n"), F.struct(F.round("gain", 10), -F.col("bin")))
    return x.groupBy(*key).agg(best.alias("b")).select(*key, F.col("b.bin").alias("cut"), F.col("b.n").alias("n"), F.col("b.gain").alias("gain"))


def best_splits(scores: DataFrame, criterion: str) -> DataFrame:
    """The best feature of each node: largest rounded score, then the smallest feature_id."""
    cols = [c for c in scores.columns if c not in NODE]
    best = F.max_by(F.struct(*cols), F.struct(F.round(criterion, 10), -F.col("feature_id")))
    return scores.groupBy(*NODE).agg(best.alias("b")).select(*NODE, "b.*")


# The single measures, on a histogram with one row per (key columns, bin, target, c).


def _keyed(hist: DataFrame) -> list[str]:
    return [c for c in hist.columns if c not in ("bin", "target", "c")]


def target_entropy(hist: DataFrame) -> DataFrame:
    k = _keyed(hist)
    by = hist.groupBy(*k, "target").agg(F.sum("c").alias("c"))
    return by.groupBy(*k).agg((F.log2(F.sum("c")) - F.sum(xlog2x(F.col("c"))) / F.sum("c")).alias("h_target"))


def conditional_entropy(hist: DataFrame) -> DataFrame:
    k = _keyed(hist)
    by = hist.groupBy(*k, "bin").agg(F.sum("c").alias("nb"), F.sum(xlog2x(F.col("c"))).alias("sc"))
    return by.groupBy(*k).agg(((F.sum(xlog2x(F.col("nb"))) - F.sum("sc")) / F.sum("nb")).alias("h_cond"))


def split_info(hist: DataFrame) -> DataFrame:
    k = _keyed(hist)
    by = hist.groupBy(*k, "bin").agg(F.sum("c").alias("nb"))
    return by.groupBy(*k).agg((F.log2(F.sum("nb")) - F.sum(xlog2x(F.col("nb"))) / F.sum("nb")).alias("split_info"))


def gain(hist: DataFrame) -> DataFrame:
    k = _keyed(hist)
    x = target_entropy(hist).join(conditional_entropy(hist), k)
    return x.select(*k, F.greatest(F.col("h_target") - F.col("h_cond"), F.lit(0.0)).alias("gain"))


def gain_ratio(hist: DataFrame) -> DataFrame:
    k = _keyed(hist)
    x = gain(hist).join(split_info(hist), k)
    return x.select(*k, F.when(F.col("split_info") > 1e-12, F.col("gain") / F.col("split_info")).otherwise(0.0).alias("gain_ratio"))


def importance(scores: DataFrame, by: str = "gain_ratio") -> DataFrame:
    """scores with importance: the share of a feature in the sum over its tree's features; even where all are 0."""
    w = Window.partitionBy("tree")
    total = F.sum(by).over(w)
    return scores.withColumn("importance", F.when(total > 0, F.col(by) / total).otherwise(1.0 / F.count("*").over(w)))
