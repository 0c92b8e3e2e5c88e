"""Fitting a forest and the forest itself."""

from __future__ import annotations

import pickle
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import stored
from ..plans.cost import choose_layout
from . import growth as G
from .alike import oob_accuracy
from .binning import BinRule, binned, fit_bins, spec_frame
from .layout import to_slices
from .sampling import draw_weights, draws, partition_weights
from .spec import ForestSpec
from .voting import attach_weights, forest_predict, oob_by_tree, oob_counts, tree_accuracy, tree_predict, tree_tables, vote, vote_regression

NODE_DDL = "tree int, node bigint, parent bigint, depth int, in_bin int, feature_id int, cut int, is_leaf boolean, n double, stats array<double>, score double, prediction double, children map<int,bigint>"


def node_frame(spark: SparkSession, nodes: list[G.Node], task: str) -> DataFrame:
    rows = [
        (x.tree, x.node, x.parent, x.depth, x.in_bin, x.feature_id if not x.is_leaf else -1, x.cut, x.is_leaf, float(x.n(task)), [float(v) for v in x.stats], float(x.score), float(x.prediction(task)), dict(x.children))
        for x in nodes
    ]
    return spark.createDataFrame(rows, NODE_DDL)


@dataclass
class Forest:
    """Nodes of all trees, selected features, and the trees' out-of-bag accuracy; a thin handle on plain tables."""

    spark: SparkSession
    spec: ForestSpec
    rules: list[BinRule]
    classes: list
    node_list: list[G.Node]
    selected_rows: list[tuple]
    stats_rows: list[tuple]
    held: list = field(default_factory=list, repr=False, compare=False)  # the number of nodes and their tables

    @property
    def nodes(self) -> DataFrame:
        return node_frame(self.spark, self.node_list, self.spec.task)

    @property
    def selected(self) -> DataFrame:
        return self.spark.createDataFrame(self.selected_rows, "tree int, rank int, feature_id int, origin string")

    @property
    def tree_stats(self) -> DataFrame:
        return self.spark.createDataFrame(self.stats_rows, "tree int, oob_rows bigint, oob_correct bigint, ca double")

    @property
    def bin_spec(self) -> DataFrame:
        return spec_frame(self.spark, self.rules)

    def accuracy_of(self) -> dict[int, float]:
        if self.spec.vote == "direct":
            return {x.tree: 1.0 for x in self.node_list}
        return {r[0]: r[3] for r in self.stats_rows}

    def rows(self, df: DataFrame, row_id: str, target: str | None = None) -> DataFrame:
        out = binned(df, self.rules, row_id, target)
        if target and self.spec.task == "classification":
            out = out.withColumn("target", coded(F.col("target"), self.classes))
        return out

    def tables(self) -> tuple[dict, dict]:
        """The trees as arrays and their nodes' values, made once."""
        if not self.held or self.held[0] is not self.node_list or self.held[1] != len(self.node_list):
            self.held[:] = self.node_list, len(self.node_list), tree_tables(self.node_list, self.spec.n_bins, self.spec.task)
        return self.held[2]

    def predict(self, rows: DataFrame, first: int | None = None, with_target: bool = False) -> DataFrame:
        """row_id, prediction, score (and target) for binned rows, by the first trees only if asked."""
        tables = tuple({t: x for t, x in part.items() if first is None or t < first} for part in self.tables())
        return forest_predict(rows, self.node_list, self.spec.n_bins, self.spec.task, self.accuracy_of(), max(1, len(self.classes)), self.spec.normalise, with_target, tables)

    def votes(self, rows: DataFrame) -> DataFrame:
        return attach_weights(tree_predict(rows, self.node_list, self.spec.n_bins, self.spec.task), self.tree_stats, self.spec.vote)

    def oob_votes(self, rows: DataFrame) -> DataFrame:
        """Votes on rows that the tree has not drawn (functional weights), with targets."""
        return tree_predict(rows, self.node_list, self.spec.n_bins, self.spec.task, self.spec.seed)

    def oob_counts(self, rows: DataFrame) -> DataFrame:
        """first_t, target, right, rows: what the first t trees' out-of-bag votes decide, without a table of votes."""
        return oob_counts(rows, self.node_list, self.spec.n_bins, max(1, len(self.classes)), self.spec.seed)

    def importance(self) -> DataFrame:
        """feature, importance: the scores of a feature's splits, weighted by their rows."""
        inner = self.nodes.where(~F.col("is_leaf")).groupBy("feature_id").agg(F.sum(F.col("score") * F.col("n")).alias("v"))
        total = inner.agg(F.sum("v").alias("all"))
        return inner.crossJoin(F.broadcast(total)).join(self.bin_spec.select("feature_id", "feature"), "feature_id").select("feature", (F.col("v") / F.col("all")).alias("importance"))

    def save(self, path: str) -> None:
        """Node, selection, accuracy and bin tables, and the specification, under a path that Spark can write."""
        self.nodes.write.mode("overwrite").parquet(f"{path}/nodes")
        self.selected.write.mode("overwrite").parquet(f"{path}/selected")
        self.tree_stats.write.mode("overwrite").parquet(f"{path}/tree_stats")
        held = pickle.dumps((self.spec, self.rules, self.classes, [x.used for x in self.node_list]))
        self.spark.createDataFrame([(bytearray(held),)], "model binary").write.mode("overwrite").parquet(f"{path}/model")

    @staticmethod
    def load(spark: SparkSession, path: str) -> Forest:
        """Only from a path that you trust: the specification is pickled."""
        spec, rules, classes, _ = pickle.loads(bytes(spark.read.parquet(f"{path}/model").first()[0]))
        nodes = [
            G.Node(r.tree, r.node, r.parent, r.depth, r.in_bin, list(r.stats), frozenset(), r.feature_id, r.cut, r.is_leaf, r.score, dict(r.children))
            for r in spark.read.parquet(f"{path}/nodes").orderBy("tree", "depth", "node").collect()
        ]
        selected = [tuple(r) for r in spark.read.parquet(f"{path}/selected").collect()]
        stats = [tuple(r) for r in spark.read.parquet(f"{path}/tree_stats").collect()]
        return Forest(spark, spec, rules, classes, nodes, selected, stats)


def coded(target, classes: list):
    """The target as the place of its class in classes."""
    out = F.lit(None).cast("int")
    for i, c in reversed(list(enumerate(classes))):
        out = F.when(target == F.lit(c), F.lit(i)).otherwise(out)
    return out


def sample_weights(rows: DataFrame, trees: list[int], spec: ForestSpec) -> DataFrame | None:
    """Stored weights (tree, row_id, w), or None where weights are a function of row and tree."""
    if spec.sampling_scope == "partition":
        blocks = rows.select("row_id").withColumn("block", F.pmod(F.col("row_id"), F.lit(8)))
        return partition_weights(blocks, max(trees) + 1, "block", spec.seed).where("w > 0").select("tree", "row_id", "w")
    if spec.sampling == "poisson":
        return None
    n = rows.count()
    # draws name rows 0..N-1; ids need not be dense, so they are numbered in order
    from .layout import dense_row_id

    ids = dense_row_id(rows.select("row_id"), ["row_id"], "at")
    drawn = draw_weights(draws(rows.sparkSession, n, max(trees) + 1, spec.seed)).withColumnRenamed("row_id", "at")
    return drawn.join(ids, "at").select("tree", "row_id", "w")


def fit_binned(rows: DataFrame, rules: list[BinRule], classes: list, spec: ForestSpec, weights: DataFrame | None = None, first_tree: int = 0, alike: DataFrame | None = None) -> Forest:
    """A forest from binned rows (row_id, target, bins); weights: tree, row_id, w in place of drawn ones; alike: the same
    rows put together, with the weights drawn for these trees, which gives the same trees (classifiers, by rows)."""
    spark = rows.sparkSession
    n_features = len(rules)
    spec = spec.sized(n_features)
    n_classes = max(1, len(classes))
    if spec.layout == "auto":
        best, _ = choose_layout(rows.count(), n_features + 1, spec.n_trees, 2**spec.max_depth, spec.n_bins + 1, n_classes, spec.n_selected, spec.max_depth, int(spark.conf.get("spark.sql.shuffle.partitions")))
        spec = spec.but(layout=best if spec.n_bins < 255 or best != "blocks" else "horizontal")
    given = weights is not None
    if alike is not None and (given or spec.task != "classification" or spec.layout != "horizontal" or (spec.sampling, spec.sampling_scope) != ("poisson", "global")):
        raise ValueError("rows put together serve classifiers by rows with functional weights")
    nodes: list[G.Node] = []
    selected: list[tuple] = []
    blocks = stored(G.pack_rows(rows), "blocks") if spec.layout == "blocks" else None
    for lo in range(first_tree, first_tree + spec.n_trees, spec.tree_group):
        trees = list(range(lo, min(lo + spec.tree_group, first_tree + spec.n_trees)))
        own = weights if given else None if alike is not None else sample_weights(rows, trees, spec)
        if own is not None:
            own = stored(own.where(F.col("tree").isin(trees)), "weights")
        if spec.layout == "vertical" and own is None and spec.task == "classification" and spec.sampling == "poisson" and spec.n_bins < 255:
            source = G.VerticalBlocks(rows, trees, spec, n_classes, n_features)
        elif spec.layout == "vertical":
            w = own if own is not None else G.functional_weights(rows, trees, spec.seed)
            if spec.sampling == "copied":
                w = w.withColumn("w", F.explode(F.sequence(F.lit(1), F.col("w").cast("int")))).withColumn("w", F.lit(1))
            source = G.Vertical(stored(to_slices(rows), "slices"), w, spec, n_classes)
        else:
            packed = spec.layout == "blocks" and own is None  # stored weights stay beside their rows
            if alike is not None:
                own_rows = alike.select("row_id", "target", "bins", *[f"w{t}" for t in trees])
            else:
                own_rows = blocks if packed else G.weighted_rows(rows, trees, spec, own)
            source = G.Horizontal(own_rows, spec, n_classes)
        roots, candidates, chosen, first = G.reduced_roots(source, trees, n_features, spec, n_classes)
        selected += chosen
        nodes += G.grow(source, roots, candidates, spec, n_classes, first)
    out = Forest(spark, spec, rules, classes, nodes, selected, [])
    if alike is not None:
        out.stats_rows = [tuple(r) for r in oob_accuracy(alike, out.tables()).orderBy("tree").collect()]  # a row per tree
    else:
        out.stats_rows = oob_stats(out, rows, weights if given else None)
    return out


def oob_stats(forest: Forest, rows: DataFrame, weights: DataFrame | None) -> list[tuple]:
    spec = forest.spec
    if weights is None and spec.sampling == "poisson" and spec.sampling_scope == "global":
        if spec.task == "classification":
            return [tuple(r) for r in oob_by_tree(rows, forest.tables(), spec.seed).orderBy("tree").collect()]  # a row per tree
        votes = forest.oob_votes(rows)
    else:
        if weights is None:
            weights = sample_weights(rows, sorted({x.tree for x in forest.node_list}), spec)
        votes = tree_predict(rows, forest.node_list, spec.n_bins, spec.task).join(weights.where("w > 0").select("tree", "row_id"), ["tree", "row_id"], "left_anti")
    tau = None
    if spec.task == "regression":
        tau = 0.5 * (rows.agg(F.stddev_pop("target")).first()[0] or 0.0)
    return [tuple(r) for r in tree_accuracy(votes, spec.task, tau).orderBy("tree").collect()]  # a row per tree


def fit(df: DataFrame, target: str, spec: ForestSpec, features: list[str], row_id: str) -> Forest:
    """A forest from a table with one row per example: bins are learnt from it (quantiles by sketches, whose size does
    not grow with the table), then the trees."""
    rules = fit_bins(df, features, spec.n_bins, exact=False)
    classes = sorted(r[0] for r in df.select(target).where(F.col(target).isNotNull()).distinct().collect()) if spec.task == "classification" else []  # one per class
    rows = binned(df.where(F.col(target).isNotNull()), rules, row_id, target)
    if spec.task == "classification":
        rows = rows.withColumn("target", coded(F.col("target"), classes))
    else:
        rows = rows.withColumn("target", F.col("target").cast("double"))
    return fit_binned(stored(rows, "binned"), rules, classes, spec)


fit_hybrid = fit


def predict_classes(forest: Forest, predicted: DataFrame) -> DataFrame:
    """Class values in place of their codes."""
    lookup = F.array(*[F.lit(c) for c in forest.classes])
    return predicted.withColumn("prediction", lookup[F.col("prediction").cast("int")])


def vote_table(forest: Forest, rows: DataFrame) -> DataFrame:
    """The same answer as Forest.predict by a table of votes and aggregates."""
    votes = forest.votes(rows)
    return vote(votes) if forest.spec.task == "classification" else vote_regression(votes, forest.spec.normalise)
