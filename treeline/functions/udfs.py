"""Functions for SQL users: grouped measures, a tree walk and slice cells as table functions, and views of a forest.

The measures gather a group into one Python call, so they are for groups that fit a task; the operators in
treeline.operators.impurity are two aggregates and have no such bound.
"""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf


def _entropy(counts) -> float:
    n = float(sum(counts))
    return -sum(c / n * math.log2(c / n) for c in counts if c) if n else 0.0


def make_udafs():
    @pandas_udf("double")
    def entropy_of(value: pd.Series) -> float:
        return _entropy(value.value_counts())

    @pandas_udf("double")
    def gain_ratio_of(value: pd.Series, target: pd.Series) -> float:
        n = len(value)
        info = _entropy(value.value_counts())
        cond = sum(len(g) / n * _entropy(g.value_counts()) for _, g in target.groupby(value))
        return max(0.0, _entropy(target.value_counts()) - cond) / info if info > 1e-12 else 0.0

    return entropy_of, gain_ratio_of


@udtf(returnType="feature_id int, bin int")
class SliceCells:
    """The cells of one row's bins."""

    def eval(self, bins):
        for i, b in enumerate(bins or []):
            yield i, b


def make_walk(forest):
    """A table function bins -> (tree, node, prediction) of a forest, for single rows; tables go through predict()."""
    task = forest.spec.task
    held: dict = {}
    for x in forest.node_list:
        held.setdefault(x.tree, {})[x.node] = (x.is_leaf, x.feature_id, x.cut, dict(x.children), x.prediction(task))

    @udtf(returnType="tree int, node bigint, prediction double")
    class WalkTree:
        def eval(self, bins):
            for tree, nodes in held.items():
                at = 0
                while True:
                    leaf, feature, cut, children, value = nodes[at]
                    key = None if leaf else bins[feature] if cut is None else (0 if bins[feature] <= cut else 1)
                    if leaf or key not in children:
                        yield tree, at, value
                        break
                    at = children[key]

    return WalkTree


def register(spark: SparkSession, forest=None, rows=None) -> None:
    """Registers entropy_of, gain_ratio_of and slice_cells, and for a forest walk_tree and the views nodes, selected,
    tree_stats, and with binned rows slices and votes."""
    from ..operators.layout import to_slices

    entropy_of, gain_ratio_of = make_udafs()
    spark.udf.register("entropy_of", entropy_of)
    spark.udf.register("gain_ratio_of", gain_ratio_of)
    spark.udtf.register("slice_cells", SliceCells)
    if forest is not None:
        spark.udtf.register("walk_tree", make_walk(forest))
        for name in ("nodes", "selected", "tree_stats"):
            getattr(forest, name).createOrReplaceTempView(name)
        if rows is not None:
            to_slices(rows).createOrReplaceTempView("slices")
            forest.votes(rows).createOrReplaceTempView("votes")
