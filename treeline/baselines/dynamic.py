"""A dynamic forest: trees in turn, each on rows weighted by how often the trees before were wrong on them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import poisson_weight
from ..operators.binning import BinRule
from ..operators.model import Forest, fit_binned
from ..operators.spec import ForestSpec
from ..session import stored

#: What a row weighs that every tree has right, before scaling.
FLOOR = 0.1


def next_weights(rows: DataFrame, oob_votes: DataFrame | None, tree: int, seed: int) -> DataFrame:
    """row_id, w of the next tree: the drawn weight times 1 - share of right out-of-bag votes + FLOOR (share 1/2 where
    there is none), scaled to mean 1."""
    drawn = poisson_weight(F.col("row_id"), F.lit(tree), seed)
    if oob_votes is None:
        x = rows.select("row_id", (drawn * (0.5 + FLOOR)).alias("v"))
    else:
        share = oob_votes.groupBy("row_id").agg(F.avg((F.col("prediction") == F.col("target")).cast("double")).alias("c"))
        x = rows.select("row_id").join(share, "row_id", "left").select("row_id", (drawn * (1 - F.coalesce("c", F.lit(0.5)) + FLOOR)).alias("v"))
    mean = x.agg(F.avg("v").alias("mean"))
    return x.crossJoin(F.broadcast(mean)).select("row_id", (F.col("v") / F.col("mean")).alias("w"))  # one row


def fit(rows: DataFrame, rules: list[BinRule], classes: list, spec: ForestSpec) -> Forest:
    """Trees one after another; a driver round for each."""
    out: Forest | None = None
    for t in range(spec.n_trees):
        votes = out.oob_votes(rows) if out else None
        w = stored(next_weights(rows, votes, t, spec.seed).where("w > 0").select(F.lit(t).alias("tree"), "row_id", "w"), "dynamic")
        one = fit_binned(rows, rules, classes, spec.but(n_trees=1, reduction=False, feature_draw="node", vote="direct"), w, first_tree=t)
        if out is None:
            out = one
        else:
            out.node_list += one.node_list
            out.stats_rows += one.stats_rows
    return out
