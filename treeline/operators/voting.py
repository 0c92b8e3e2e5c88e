"""Prediction of single trees, their out-of-bag accuracy, and votes weighted by it."""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import poisson_numpy
from .growth import Node, bins_matrix, slots, walk_arrays

cloudpickle.register_pickle_by_value(sys.modules[__name__])


def tree_tables(nodes: list[Node], n_bins: int, task: str) -> tuple[dict[int, dict], dict[int, np.ndarray]]:
    trees = walk_arrays(nodes, n_bins)
    by: dict[int, list[Node]] = {}
    for x in sorted(nodes, key=lambda x: (x.depth, x.node)):
        by.setdefault(x.tree, []).append(x)
    values = {}
    for t in trees:
        s = np.array([x.stats for x in by[t]], float)
        values[t] = s.argmax(axis=1).astype(float) if task == "classification" else np.array([x.prediction(task) for x in by[t]])
    return trees, values


def tree_predict(rows: DataFrame, nodes: list[Node], n_bins: int, task: str, oob_seed: int | None = None) -> DataFrame:
    """row_id, tree, prediction (and target if there) of every tree; with oob_seed only for rows the tree has not drawn."""
    sent = rows.sparkSession.sparkContext.broadcast(tree_tables(nodes, n_bins, task))
    with_target = "target" in rows.columns

    def run(batches):
        trees, values = sent.value
        for batch in batches:
            bins, row = bins_matrix(batch), np.asarray(batch.column("row_id"))
            y = np.asarray(batch.column("target"), dtype=float) if with_target else None
            for t in sorted(values) if len(row) else []:
                p = values[t][slots(trees[t], bins)]
                ok = poisson_numpy(row, t, oob_seed) == 0 if oob_seed is not None else np.ones(len(row), bool)
                out = {"row_id": pa.array(row[ok]), "tree": pa.array(np.full(ok.sum(), t, np.int32)), "prediction": pa.array(p[ok])}
                if with_target:
                    out["target"] = pa.array(y[ok])
                yield pa.RecordBatch.from_pydict(out)

    return rows.mapInArrow(run, "row_id bigint, tree int, prediction double" + (", target double" if with_target else ""))


def oob_counts(rows: DataFrame, nodes: list[Node], n_bins: int, n_classes: int, seed: int) -> DataFrame:
    """first_t, target, right, rows: of the rows of a class that one of the first t trees has not drawn, how many the
    unweighted out-of-bag votes of these trees decide rightly, for every t. Votes are added up within the row."""
    sent = rows.sparkSession.sparkContext.broadcast(tree_tables(nodes, n_bins, "classification"))

    def run(batches):
        trees, values = sent.value
        order = sorted(values)
        right, count = (np.zeros((len(order), n_classes), np.int64) for _ in range(2))
        for batch in batches:
            bins, row = bins_matrix(batch), np.asarray(batch.column("row_id"))
            y = np.asarray(batch.column("target")).astype(np.int64)
            sums, voted, best = np.zeros((len(row), n_classes), np.int32), np.zeros(len(row), bool), np.zeros(len(row), np.int64)
            for i, t in enumerate(order if len(row) else []):
                at = np.flatnonzero(poisson_numpy(row, t, seed) == 0)
                sums[at, values[t][slots(trees[t], bins[at])].astype(np.int64)] += 1
                best[at], voted[at] = sums[at].argmax(axis=1), True
                right[i] += np.bincount(y[voted & (best == y)], minlength=n_classes)
                count[i] += np.bincount(y[voted], minlength=n_classes)
        i, c = np.nonzero(count)
        yield pa.RecordBatch.from_pydict({"first_t": pa.array(np.array(order, np.int32)[i] + np.int32(1)), "target": pa.array(c.astype(float)), "right": pa.array(right[i, c]), "rows": pa.array(count[i, c])})

    part = rows.mapInArrow(run, "first_t int, target double, right bigint, rows bigint")
    return part.groupBy("first_t", "target").agg(F.sum("right").alias("right"), F.sum("rows").alias("rows"))


def oob_by_tree(rows: DataFrame, tables: tuple[dict, dict], seed: int) -> DataFrame:
    """tree, oob_rows, oob_correct, ca of a classifier's trees on rows that they have not drawn, counted in the tasks."""
    sent = rows.sparkSession.sparkContext.broadcast(tables)

    def run(batches):
        trees, values = sent.value
        count = {t: [0, 0] for t in sorted(values)}
        for batch in batches:
            bins, row, y = bins_matrix(batch), np.asarray(batch.column("row_id")), np.asarray(batch.column("target"), dtype=float)
            for t in count if len(row) else []:
                at = np.flatnonzero(poisson_numpy(row, t, seed) == 0)
                count[t][0] += len(at)
                count[t][1] += int((values[t][slots(trees[t], bins[at])] == y[at]).sum())
        out = [(t, n, right) for t, (n, right) in count.items() if n]
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], kind) for i, kind in enumerate((pa.int32(), pa.int64(), pa.int64()))], ["tree", "oob_rows", "oob_correct"])

    part = rows.select("row_id", "target", "bins").mapInArrow(run, "tree int, oob_rows bigint, oob_correct bigint")
    out = part.groupBy("tree").agg(F.sum("oob_rows").alias("oob_rows"), F.sum("oob_correct").alias("oob_correct"))
    return out.withColumn("ca", F.col("oob_correct") / F.col("oob_rows"))


def tree_predict_joins(rows: DataFrame, nodes: DataFrame, max_depth: int) -> DataFrame:
    """The same by joins with the node table (tree, node, parent, in_bin, feature_id, is_leaf, prediction), one for
    each level; for node tables too large to send, and to check the other way."""
    trees = nodes.select("tree").distinct()
    at = rows.crossJoin(F.broadcast(trees)).withColumn("node", F.lit(0).cast("bigint"))  # a row per tree on the right
    inner = nodes.where(~F.col("is_leaf")).select("tree", "node", "feature_id")
    child = nodes.where("depth > 0").select("tree", F.col("parent").alias("node"), F.col("in_bin").alias("bin"), F.col("node").alias("child"))
    for _ in range(max_depth):
        at = at.join(inner, ["tree", "node"], "left").withColumn("bin", F.col("bins")[F.col("feature_id")])
        at = at.join(child, ["tree", "node", "bin"], "left").withColumn("node", F.coalesce("child", "node")).drop("child", "bin", "feature_id")
    return at.join(nodes.select("tree", "node", "prediction"), ["tree", "node"]).drop("bins", "node")


def tree_accuracy(votes: DataFrame, task: str = "classification", tau: float | None = None, kind: str = "tau") -> DataFrame:
    """tree, oob_rows, oob_correct, ca from out-of-bag votes with their targets. A classifier's ca is the share of
    right votes; a regressor's the share within tau of the target, or with kind 'r2' R squared, not below 0."""
    if task == "regression" and kind == "r2":
        y, p = F.col("target"), F.col("prediction")
        out = votes.groupBy("tree").agg(F.count("*").alias("oob_rows"), F.sum((y - p) * (y - p)).alias("e"), (F.var_pop(y) * F.count("*")).alias("v"))
        ca = F.when(F.col("v") > 0, F.greatest(F.lit(0.0), 1 - F.col("e") / F.col("v"))).otherwise(0.0)
        return out.select("tree", "oob_rows", F.lit(None).cast("bigint").alias("oob_correct"), ca.alias("ca"))
    right = F.col("prediction") == F.col("target") if task == "classification" else F.abs(F.col("prediction") - F.col("target")) <= tau
    out = votes.groupBy("tree").agg(F.count("*").alias("oob_rows"), F.sum(right.cast("bigint")).alias("oob_correct"))
    return out.withColumn("ca", F.col("oob_correct") / F.col("oob_rows"))


def attach_weights(votes: DataFrame, stats: DataFrame, kind: str = "weighted") -> DataFrame:
    """votes with weight: the tree's accuracy (0 for a tree without out-of-bag rows), or 1 for a direct vote."""
    if kind == "direct":
        return votes.withColumn("weight", F.lit(1.0))
    return votes.join(F.broadcast(stats.select("tree", F.col("ca").alias("weight"))), "tree", "left").fillna(0.0, ["weight"])  # a row per tree


def vote(votes: DataFrame) -> DataFrame:
    """row_id, prediction, score: the class with the largest sum of weights, ties to the smaller class."""
    s = votes.groupBy("row_id", "prediction").agg(F.round(F.sum("weight"), 9).alias("s"))
    best = F.max_by(F.struct("prediction", "s"), F.struct("s", -F.col("prediction")))
    return s.groupBy("row_id").agg(best.alias("b")).select("row_id", F.col("b.prediction").alias("prediction"), F.col("b.s").alias("score"))


def vote_regression(votes: DataFrame, normalise: bool = True) -> DataFrame:
    """row_id, prediction: weighted mean of the trees' values; without normalise the weighted sum over the number of
    trees, which shrinks towards 0 as weights are below 1."""
    top = F.sum(F.col("weight") * F.col("prediction"))
    under = F.sum("weight") if normalise else F.count("*").cast("double")
    return votes.groupBy("row_id").agg(F.when(under > 0, top / under).alias("prediction"))


def forest_predict(rows: DataFrame, nodes: list[Node], n_bins: int, task: str, weights: dict[int, float], n_classes: int, normalise: bool = True, with_target: bool = False, tables: tuple[dict, dict] | None = None) -> DataFrame:
    """row_id, prediction, score (and target if asked) in one pass: votes are added up within the row, nothing is
    shuffled. tables: those of tree_tables, if they are made already."""
    trees, values = tree_tables(nodes, n_bins, task) if tables is None else tables
    sent = rows.sparkSession.sparkContext.broadcast((trees, values, weights))

    def run(batches):
        trees, values, weights = sent.value
        for batch in batches:
            bins, row = bins_matrix(batch), np.asarray(batch.column("row_id"))
            if not len(row):
                continue
            if task == "classification":
                sums = np.zeros((len(row), n_classes))
                for t, v in values.items():
                    sums[np.arange(len(row)), v[slots(trees[t], bins)].astype(int)] += weights.get(t, 0.0)
                sums = np.round(sums, 9)
                p, score = sums.argmax(axis=1).astype(float), sums.max(axis=1)
            else:
                total, top = sum(weights.get(t, 0.0) for t in values), np.zeros(len(row))
                for t, v in values.items():
                    top += weights.get(t, 0.0) * v[slots(trees[t], bins)]
                under = total if normalise else len(values)
                p, score = top / under if under else top, np.full(len(row), total)
            out = {"row_id": pa.array(row), "prediction": pa.array(p), "score": pa.array(score)}
            if with_target:
                out["target"] = batch.column("target")
            yield pa.RecordBatch.from_pydict(out)

    kind = rows.schema["target"].dataType.simpleString() if with_target else ""
    return rows.mapInArrow(run, "row_id bigint, prediction double, score double" + f", target {kind}" * with_target)
