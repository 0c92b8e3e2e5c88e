"""Bootstrap samples: draw tables, their counts, and weights as a function of row and tree; out-of-bag rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import drawn_weight, mix, poisson_weight

#: Rows that a block of a partition-sampled table is drawn for: a fuller block is drawn from more often.
BLOCK_ROWS = 400


def draws(spark: SparkSession, n_rows: int, n_trees: int, seed: int = 42) -> DataFrame:
    """tree, draw, row_id: n_rows draws with replacement for each tree, by hash; needs no shuffle."""
    x = spark.range(n_rows * n_trees).select(F.expr(f"CAST(id DIV {n_rows} AS INT)").alias("tree"), (F.col("id") % n_rows).alias("draw"))
    return x.select("tree", "draw", (mix(F.col("draw"), F.col("tree"), seed) % n_rows).alias("row_id"))


def draw_arrays(drawn: DataFrame) -> DataFrame:
    """One row per sample, as an array in draw order; for small samples."""
    return drawn.groupBy("tree").agg(F.transform(F.sort_array(F.collect_list(F.struct("draw", "row_id"))), lambda x: x["row_id"]).alias("rows"))


def draw_weights(drawn: DataFrame) -> DataFrame:
    return drawn.groupBy("tree", "row_id").agg(F.count("*").alias("w"))


def trees(spark: SparkSession, n_trees: int) -> DataFrame:
    return spark.range(n_trees).select(F.col("id").cast("int").alias("tree"))


def poisson_weights(rows: DataFrame, n_trees: int, seed: int = 42) -> DataFrame:
    """row_id, tree, w for all trees, w = 0 where the row is out of the bag. Rows are copied in place, not shuffled."""
    every = rows.withColumn("tree", F.explode(F.array(*[F.lit(t) for t in range(n_trees)])))
    return every.withColumn("w", poisson_weight(F.col("row_id"), F.col("tree"), seed))


def partition_weights(rows: DataFrame, n_trees: int, block: str, seed: int = 42, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """The contrast: each block of rows draws by itself, and a row is drawn (rows of its block) / block_rows times on
    average. As the table grows in the same blocks, so does the share of it that a tree has drawn."""
    size = rows.groupBy(block).agg((F.count("*") / float(block_rows)).alias("__mean"))
    every = rows.join(size, block).withColumn("tree", F.explode(F.array(*[F.lit(t) for t in range(n_trees)])))
    return every.withColumn("w", drawn_weight(F.col("row_id"), F.col("tree"), F.col("__mean"), seed)).drop("__mean")


def multiplexed(slices: DataFrame, weights: DataFrame) -> DataFrame:
    """Samples over one copy of the slices: each cell meets its trees' weights (tree, row_id, w); no sample is stored."""
    return slices.join(weights.where("w > 0"), "row_id")


def oob(rows: DataFrame, weights: DataFrame, n_trees: int) -> DataFrame:
    """tree, row_id of rows that a tree has not drawn."""
    grid = rows.select("row_id").crossJoin(F.broadcast(trees(rows.sparkSession, n_trees)))  # n_trees rows on the right
    return grid.join(weights.where("w > 0").select("tree", "row_id"), ["tree", "row_id"], "left_anti").select("tree", "row_id")


def check_bags(rows: DataFrame, weights: DataFrame, n_trees: int) -> DataFrame:
    """tree, both, missing: rows that are in the bag and out of it, and rows in neither; all 0 if samples are sound."""
    grid = rows.select("row_id").crossJoin(F.broadcast(trees(rows.sparkSession, n_trees)))
    bag = weights.where("w > 0").select("tree", "row_id").distinct()
    out = oob(rows, weights, n_trees)
    both = bag.intersect(out).groupBy("tree").agg(F.count("*").alias("both"))
    union = bag.union(out).distinct()
    missing = grid.select("tree", "row_id").exceptAll(union).groupBy("tree").agg(F.count("*").alias("missing"))
    base = trees(rows.sparkSession, n_trees)
    return base.join(both, "tree", "left").join(missing, "tree", "left").select("tree", F.coalesce("both", F.lit(0)).alias("both"), F.coalesce("missing", F.lit(0)).alias("missing"))
