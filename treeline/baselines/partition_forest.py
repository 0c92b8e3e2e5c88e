"""A data-partitioned forest: each block of rows grows its own trees, and all trees vote directly."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import poisson_weight
from ..operators.binning import BinRule
from ..operators.model import Forest, fit_binned
from ..operators.spec import ForestSpec


def fit(rows: DataFrame, rules: list[BinRule], classes: list, spec: ForestSpec, blocks: int) -> Forest:
    """Tree t sees only rows of block t mod blocks: one job grows all of them, and no row meets another block's trees."""
    trees = F.explode(F.array(*[F.lit(t) for t in range(spec.n_trees)]))
    own = rows.select("row_id", F.pmod(F.col("row_id"), F.lit(blocks)).alias("block")).withColumn("tree", trees).where(F.col("tree") % blocks == F.col("block"))
    w = own.select("tree", "row_id", poisson_weight(F.col("row_id"), F.col("tree"), spec.seed).alias("w")).where("w > 0")
    return fit_binned(rows, rules, classes, spec.but(reduction=False, feature_draw="node", vote="direct"), w)
