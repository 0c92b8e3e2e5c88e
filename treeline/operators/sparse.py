"""Forests over many sparse features: only present cells are stored, joined and counted.

A cell (row_id, feature_id, bin) is there where the feature has a value; all others are in bin ABSENT, whose statistics
are what the present cells leave of the node's totals. Work and bytes follow the present cells, not rows x features;
the trees are those that dense rows give.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import poisson_weight
from ..session import stored
from . import growth as G
from . import impurity as I
from .model import Forest
from .spec import ForestSpec
from .voting import attach_weights, tree_accuracy, vote, vote_regression

ABSENT = 0
#: Up to so many wanted features are named in the scan's filter.
NAMED = 1_000


class Sparse(G.Vertical):
    """Histograms from present cells and assignments (tree, row_id, target, w, node)."""

    def __init__(self, cells: DataFrame, rows: DataFrame, weights: DataFrame, spec: ForestSpec, n_classes: int, n_features: int):
        super().__init__(cells, weights, spec, n_classes)
        self.n_features = n_features
        self.assigned = stored(self.assigned.join(rows.select("row_id", "target"), "row_id"), "assigned")

    def histogram(self, nodes: list[G.Node], live: list[G.Node], candidates: dict[int, list[int]]) -> DataFrame:
        spark, names = self.slices.sparkSession, I.stat_names(I.n_stats(self.spec.task, self.n_classes))
        open_ = spark.createDataFrame([(x.tree, x.node) for x in live], "tree int, node bigint")
        rows = self.assigned.join(F.broadcast(open_), ["tree", "node"], "left_semi")
        trees = sorted({x.tree for x in live})
        cells = self.slices
        if any(len(candidates[t]) < self.n_features for t in trees):
            wanted = sorted({f for t in trees for f in candidates[t]})
            if len(wanted) <= NAMED:
                cells = cells.where(F.col("feature_id").isin(wanted))
            pairs = spark.createDataFrame([(t, f) for t in trees for f in candidates[t]], "tree int, feature_id int")
            cells = cells.join(rows, "row_id").join(F.broadcast(pairs), ["tree", "feature_id"])  # the features of a tree group's trees
        else:
            cells = cells.join(rows, "row_id")
        present = I.histogram(cells, self.spec.task, self.n_classes)
        totals = rows.groupBy("tree", "node").agg(*[c.alias(f"all_{n}") for c, n in zip(I.stat_sums(self.spec.task, self.n_classes, F.col("w"), F.col("target")), names, strict=True)])
        there = present.groupBy("tree", "node", "feature_id").agg(*[F.sum(n).alias(n) for n in names])
        left = there.join(F.broadcast(totals), ["tree", "node"])  # a row per open node
        left = left.select("tree", "node", "feature_id", F.lit(ABSENT).alias("bin"), *[(F.col(f"all_{n}") - F.col(n)).alias(n) for n in names])
        weight = sum((F.col(n) for n in names), F.lit(0.0)) if self.spec.task == "classification" else F.col("s0")
        return present.unionByName(left.where(weight > 1e-9))

    def totals(self, hist: DataFrame, names: list[str]) -> DataFrame:
        sums = I.stat_sums(self.spec.task, self.n_classes, F.col("w"), F.col("target"))
        return self.assigned.groupBy("tree").agg(*[c.alias(n) for c, n in zip(sums, names, strict=True)])

    def every_score(self, scores: DataFrame, criterion: str) -> DataFrame:
        """Features that no row of a tree has score 0, and may be drawn at random as any other."""
        spark = scores.sparkSession
        features = spark.range(self.n_features).select(F.col("id").cast("int").alias("feature_id"))
        every = features.crossJoin(F.broadcast(self.assigned.select("tree").distinct()))  # a row per tree of the group
        return every.join(scores.select("tree", "feature_id", criterion), ["tree", "feature_id"], "left").fillna(0.0, [criterion])

    def advance(self, splits: list[G.Node]) -> None:
        spark = self.slices.sparkSession
        rows = [(x.tree, x.node, x.feature_id, b, c) for x in splits for key, c in x.children.items() for b in self._bins(x, key)]
        frame = spark.createDataFrame(rows, "tree int, node bigint, feature_id int, bin int, child bigint")
        own = self.assigned.join(F.broadcast(frame.select("tree", "node", "feature_id").distinct()), ["tree", "node"])
        own = with_bins(own, self.slices.where(F.col("feature_id").isin(sorted({x.feature_id for x in splits}))))
        moved = own.join(F.broadcast(frame), ["tree", "node", "feature_id", "bin"])
        self.assigned = stored(moved.select("tree", "row_id", "w", F.col("child").alias("node"), "target"), "assigned")


def with_bins(rows: DataFrame, cells: DataFrame) -> DataFrame:
    """rows (row_id, feature_id, ...) with the bin of that feature."""
    return rows.join(cells.select("row_id", "feature_id", "bin"), ["row_id", "feature_id"], "left").withColumn("bin", F.coalesce("bin", F.lit(ABSENT)))


def fit_sparse(cells: DataFrame, rows: DataFrame, n_features: int, classes: list, spec: ForestSpec) -> Forest:
    """A forest from present cells (row_id, feature_id from 0, bin other than ABSENT) and rows (row_id, target; classes
    as their places in classes). Samples are functional Poisson weights."""
    spec, n_classes = spec.sized(n_features), max(1, len(classes))
    nodes: list[G.Node] = []
    selected: list[tuple] = []
    for lo in range(0, spec.n_trees, spec.tree_group):
        trees = list(range(lo, min(lo + spec.tree_group, spec.n_trees)))
        source = Sparse(cells, rows, G.functional_weights(rows, trees, spec.seed), spec, n_classes, n_features)
        roots, candidates, chosen, first = G.reduced_roots(source, trees, n_features, spec, n_classes)
        selected += chosen
        nodes += G.grow(source, roots, candidates, spec, n_classes, first)
    out = Forest(rows.sparkSession, spec, [], classes, nodes, selected, [])
    votes = sparse_votes(out, cells, rows).where(poisson_weight(F.col("row_id"), F.col("tree"), spec.seed) == 0)
    tau = 0.5 * (rows.agg(F.stddev_pop("target")).first()[0] or 0.0) if spec.task == "regression" else None
    out.stats_rows = [tuple(r) for r in tree_accuracy(votes, spec.task, tau).orderBy("tree").collect()]  # a row per tree
    return out


def sparse_votes(forest: Forest, cells: DataFrame, rows: DataFrame) -> DataFrame:
    """row_id, tree, prediction (and target if there): rows walk down by a join with the cells of split features a level."""
    spark = rows.sparkSession
    used = sorted({x.feature_id for x in forest.node_list if not x.is_leaf})
    cells = cells.where(F.col("feature_id").isin(used)) if used else cells.limit(0)
    inner = [(x.tree, x.node, x.feature_id, b, c) for x in forest.node_list if not x.is_leaf for key, c in x.children.items() for b in _bins_of(x, key, forest.spec.n_bins)]
    step = F.broadcast(spark.createDataFrame(inner or [(-1, -1, -1, -1, -1)], "tree int, node bigint, feature_id int, bin int, child bigint"))
    split = F.broadcast(spark.createDataFrame([(t, n, f) for t, n, f, *_ in {(i[0], i[1], i[2]) for i in inner}] or [(-1, -1, -1)], "tree int, node bigint, feature_id int"))
    trees = sorted({x.tree for x in forest.node_list})
    kept = ["row_id", *(["target"] if "target" in rows.columns else [])]
    at = rows.select(*kept).withColumn("tree", F.explode(F.array(*[F.lit(t) for t in trees]))).withColumn("node", F.lit(0).cast("bigint"))
    for _ in range(max(x.depth for x in forest.node_list)):
        at = with_bins(at.join(split, ["tree", "node"], "left"), cells).join(step, ["tree", "node", "feature_id", "bin"], "left")
        at = at.select(*kept, "tree", F.coalesce("child", "node").alias("node"))
    said = forest.nodes.select("tree", "node", "prediction")
    return at.join(F.broadcast(said), ["tree", "node"]).select(*kept, "tree", "prediction")


def _bins_of(x: G.Node, key: int, n_bins: int) -> list[int]:
    return [key] if x.cut is None else [b for b in range(-1, n_bins) if (b <= x.cut) == (key == 0)]


def predict_sparse(forest: Forest, cells: DataFrame, rows: DataFrame) -> DataFrame:
    """row_id, prediction (and score) of rows by their present cells."""
    votes = attach_weights(sparse_votes(forest, cells, rows.select("row_id")), forest.tree_stats, forest.spec.vote)
    return vote(votes) if forest.spec.task == "classification" else vote_regression(votes, forest.spec.normalise)
