"""The experiment workloads as registered queries, at sizes that one machine runs in a minute or a few.

The functions in plans.workloads take any trees, shares, methods, sets, seeds and slots; what the queries leave out is
in the README.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.math import rounded
from ..plans import cost as C
from ..plans import measures as M
from ..plans import workloads as W
from . import plans as P
from .training_sets import BAND, EIGHT, FLAG, QUALITY, STATUS, TOXIC

METHODS = ["hybrid", "classic", "dynamic", "library"]
TREES, SHARES = [1, 2, 5, 10, 20, 50], [0.2, 1.0]


def q_w1(spark, sf_dir):
    """Accuracy by trees, four methods, a learnable target."""
    return W.accuracy_by_trees(spark, sf_dir, TREES, METHODS, [TOXIC], [42])


def q_w1_sets(spark, sf_dir):
    """Accuracy on all eight sets, the three methods whose trees grow side by side."""
    return W.accuracy_by_trees(spark, sf_dir, [10], ["hybrid", "classic", "library"], list(EIGHT), [42])


def q_w1_seeds(spark, sf_dir):
    """Accuracy by trees over three splits of the rows, with a noise target as the control."""
    return W.accuracy_by_trees(spark, sf_dir, [5, 20], ["hybrid", "classic"], [QUALITY, STATUS], [42, 43, 44])


def q_w1_gap(spark, sf_dir):
    """How much more accurate the hybrid method is than the others, on average and at best."""
    grid = W.accuracy_by_trees(spark, sf_dir, [1, 5, 10], METHODS, [QUALITY], [42], dynamic_most=5)
    parts = [M.accuracy_gap(grid, "hybrid", m).withColumn("other", F.lit(m)) for m in METHODS[1:]]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def q_w2(spark, sf_dir):
    """Accuracy by rows, four methods."""
    return W.accuracy_by_rows(spark, sf_dir, SHARES, METHODS, QUALITY, 4)


def q_w2_band(spark, sf_dir):
    """Accuracy by rows on the larger learnable set."""
    return W.accuracy_by_rows(spark, sf_dir, [0.05, 0.2, 1.0], ["hybrid", "classic", "library"], BAND, 5)


def q_w3(spark, sf_dir):
    """Out-of-bag error over 25 and 50 trees, and that of a noise target."""
    own = [W.oob_by_trees(spark, sf_dir, [25, 50], s).withColumn("set", F.lit(s.name)) for s in (QUALITY, STATUS)]
    return own[0].unionByName(own[1])


def q_w4(spark, sf_dir):
    """Training seconds by size, four methods."""
    return W.time_by_size(spark, sf_dir, SHARES, METHODS, QUALITY, 3)


def q_w4_lines(spark, sf_dir):
    """Training seconds by size on the larger set, the methods whose trees grow side by side."""
    return W.time_by_size(spark, sf_dir, [0.05, 0.2, 1.0], ["hybrid", "classic", "library"], FLAG, 10)


def q_w5(spark, sf_dir):
    """Training seconds by slots, each number in a process of its own."""
    return spark.createDataFrame(W.time_by_slots(spark, sf_dir, [1, 2, 4], ["hybrid", "library"], QUALITY, n_trees=5), "slots int, method string, seconds double")


def q_w6(spark, sf_dir):
    """Speed-up over the stand-alone run."""
    return C.speedup(spark.createDataFrame(W.time_by_slots(spark, sf_dir, [1, 4], ["hybrid"], QUALITY, n_trees=5), "method_slots int, method string, seconds double").withColumnRenamed("method_slots", "slots"))


def q_w7(spark, sf_dir):
    return W.volume_by_trees(spark, P._catalog(spark, sf_dir), P.TREES)


def q_w8(spark, sf_dir):
    """Shuffle bytes of training by layout and partitions."""
    return W.communication(spark, sf_dir, FLAG, ["horizontal", "vertical", "library"], [4, 8, 16, 32], 3)


def q_comm_cost(spark, sf_dir):
    return W.communication(spark, sf_dir, QUALITY, ["horizontal", "vertical", "blocks"], [8], 2)


def q_w9(spark, sf_dir):
    """Reduction, vote and criterion against each other, over two splits."""
    return W.ablation(spark, sf_dir, TOXIC, [42, 43], 5)


def q_w10(spark, sf_dir):
    return C.operations(P._catalog(spark, sf_dir), 500, 16).withColumn("ops", rounded(F.col("ops"), 1))


def q_generalisation_gap(spark, sf_dir):
    return W.generalisation_by_method(spark, sf_dir, ["hybrid", "classic", "library"], QUALITY)


def q_grid(spark, sf_dir):
    """Accuracy by trees, features, bins and depth, one changed at a time."""
    base = {"n_trees": 5, "max_depth": 3}
    return W.grid(spark, sf_dir, TOXIC, [base, base | {"n_trees": 10}, base | {"n_selected": 4, "n_principal": 2}, base | {"n_selected": 8, "n_principal": 1}, base | {"n_bins": 16}, base | {"max_depth": 5}])


def q_training_time(spark, sf_dir):
    """Median seconds to train and to score."""
    from .forest import forest_of

    f, rows = forest_of(spark, sf_dir, QUALITY)
    took = [("train", C.timed(lambda: forest_of(spark, sf_dir, QUALITY)[0].nodes)), ("score", C.timed(lambda: f.predict(rows), 3))]
    return spark.createDataFrame(took, "what string, seconds double")


def q_peak_sampled(spark, sf_dir):
    """The most cells that any method holds as samples, by table and trees."""
    return C.volume(P._catalog(spark, sf_dir), P.TREES).groupBy("name", "trees").agg(F.max("cells").alias("peak_cells"), F.max_by("model", F.struct("cells", "model")).alias("model"))


_RUN = (
    q_w1, q_w1_sets, q_w1_seeds, q_w1_gap, q_w2, q_w2_band, q_w3, q_w4, q_w4_lines, q_w5, q_w6, q_w7, q_w8, q_comm_cost, q_w9, q_w10, q_generalisation_gap, q_grid, q_training_time, q_peak_sampled,
)
QUERIES = {f.__name__: f for f in _RUN}
SQL = {
    "q_w7": P._VOLUME + "SELECT *, cells * 8 AS bytes FROM v",
    "q_w10": f"WITH c AS ({P._CAT_SQL}) " + " UNION ALL ".join(f"SELECT name, '{k}' AS method, round({v.replace('4.0 / m', '16.0 / m').replace('4 * n', '16 * n')}, 1) + 0.0 AS ops FROM c" for k, v in P._OPS.items()),
    "q_peak_sampled": P._VOLUME + "SELECT name, trees, max(cells) AS peak_cells, arg_max(model, (cells, model)) AS model FROM v GROUP BY ALL",
}
