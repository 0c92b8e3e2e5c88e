"""Rows that no tree can tell apart, as one: the same bins and target, with the sum of their weights for each tree."""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import poisson_numpy
from ..session import stored
from .growth import decoded, gathered, slots

cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Rows are put together where at least so many are alike on average; else the columns of weights cost more than they save.
LEAST = 8
#: Rows put together that one task takes, at most: what a task costs besides is that of some 10,000.
TOGETHER = 65_536


def put_together(rows: DataFrame, n_bins: int, n_features: int, n_classes: int, n_trees: int, seed: int) -> DataFrame | None:
    """row_id (the least of those alike), target, bins, and for each tree the sum of the drawn weights (w<tree>) and the
    number of rows not drawn (o<tree>). None where few rows are alike, or their kinds do not fit 62 bits."""
    width = n_bins + 1
    if width**n_features * max(1, n_classes) >= 2**62:
        return None
    r = rows.agg(F.count("*").alias("n"), F.approx_count_distinct(F.struct("bins", "target")).alias("kinds")).first()
    if r["n"] < LEAST * r["kinds"]:
        return None
    sums = [f"{c}{t}" for t in range(n_trees) for c in "wo"]

    def run(batches):
        for row, y, bins, _ in gathered(part for batch in batches for part in decoded(batch)):
            code = y.astype(np.int64)
            for f in range(n_features):
                code = code * width + bins[:, f] + 1
            kinds, first, at = np.unique(code, return_index=True, return_inverse=True)
            least = row[first].astype(np.int64)
            np.minimum.at(least, at, row)
            out = [kinds, least]
            for t in range(n_trees):
                w = poisson_numpy(row, t, seed)
                out += [np.bincount(at, w, len(kinds)), np.bincount(at[w == 0], minlength=len(kinds)).astype(float)]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in out], ["code", "row_id", *sums])

    parts = rows.select("row_id", "target", "bins").mapInArrow(run, "code bigint, row_id bigint, " + ", ".join(f"{s} double" for s in sums))
    parts = parts.groupBy("code").agg(F.min("row_id").alias("row_id"), *[F.sum(s).alias(s) for s in sums])
    bins = F.array(*[F.expr(f"CAST((code DIV {width ** (n_features - 1 - f)}L) % {width} - 1 AS INT)") for f in range(n_features)])
    target = F.expr(f"code DIV {width ** n_features}L").cast(rows.schema["target"].dataType)
    return stored(parts.select("row_id", target.alias("target"), bins.alias("bins"), *sums), "alike").coalesce(1 + r["kinds"] // TOGETHER)


def oob_accuracy(alike: DataFrame, tables: tuple[dict, dict]) -> DataFrame:
    """tree, oob_rows, oob_correct, ca: those of the votes on rows not drawn, from rows put together."""
    sent = alike.sparkSession.sparkContext.broadcast(tables)

    def run(batches):
        trees, values = sent.value
        count = {t: np.zeros(2) for t in values}
        for batch in batches:
            for _, y, bins, _ in decoded(batch):
                for t, v in values.items():
                    n = np.asarray(batch.column(f"o{t}"))
                    count[t] += n.sum(), n[v[slots(trees[t], bins)] == y].sum()
        out = [(t, int(n), int(right)) for t, (n, right) in count.items() if n]
        tree, rows, right = zip(*out) if out else ((), (), ())
        yield pa.RecordBatch.from_arrays([pa.array(tree, pa.int32()), pa.array(rows, pa.int64()), pa.array(right, pa.int64())], ["tree", "oob_rows", "oob_correct"])

    part = alike.mapInArrow(run, "tree int, oob_rows bigint, oob_correct bigint")
    out = part.groupBy("tree").agg(F.sum("oob_rows").alias("oob_rows"), F.sum("oob_correct").alias("oob_correct"))
    return out.withColumn("ca", F.col("oob_correct") / F.col("oob_rows"))
