"""Layouts of a training set: one slice per feature, packed blocks, rows; dense row numbers."""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def dense_row_id(df: DataFrame, order: list[str], name: str = "row_id") -> DataFrame:
    """Numbers rows 0..N-1 in order: a range sort, one count per partition to the driver, and offsets.

    The sorted rows are written once, so that the counts and the numbers come from the same partitions.
    """
    from ..session import stored

    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    parts = df.repartitionByRange(n, *order).withColumn("__part", F.spark_partition_id())
    parts = stored(parts.sortWithinPartitions(*order).withColumn("__at", F.monotonically_increasing_id()), "sorted")
    counts = {r[0]: (r[1], r[2]) for r in parts.groupBy("__part").agg(F.count("*"), F.min("__at")).collect()}
    total, offsets = 0, []
    for p in sorted(counts):
        offsets.append((p, total - counts[p][1]))
        total += counts[p][0]
    frame = df.sparkSession.createDataFrame(offsets, "__part int, __offset bigint")
    return parts.join(F.broadcast(frame), "__part").withColumn(name, F.col("__at") + F.col("__offset")).drop("__part", "__at", "__offset")


def to_slices(rows: DataFrame, target: bool = True) -> DataFrame:
    """feature_id, row_id, bin and target from binned rows: the vertical layout."""
    cols = ["row_id", *(["target"] if target else [])]
    return rows.select(*cols, F.posexplode("bins").alias("feature_id", "bin")).select("feature_id", "row_id", "bin", *cols[1:])


def wide_to_slices(df: DataFrame, features: list[str], row_id: str, target: str) -> DataFrame:
    """feature, row_id, value, target from a wide table; values as strings so that kinds can be mixed."""
    wide = df.select(F.col(row_id).alias("row_id"), F.col(target).alias("target"), *[F.col(f).cast("string").alias(f) for f in features])
    return wide.unpivot(["row_id", "target"], features, "feature", "value")


def slice_of(slices: DataFrame, feature_id: int) -> DataFrame:
    return slices.where(F.col("feature_id") == feature_id)


def clustered(slices: DataFrame, partitions: int, blocks: int = 1) -> DataFrame:
    """Slices dealt out by feature; a large slice by (feature, block of rows), so that it spans several tasks."""
    if blocks == 1:
        return slices.repartition(partitions, "feature_id")
    return slices.withColumn("row_block", F.pmod(F.col("row_id"), F.lit(blocks)).cast("int")).repartition(partitions, "feature_id", "row_block")


def persist_slices(slices: DataFrame, name: str | None = None, buckets: int = 8) -> str:
    """Saves slices as a table bucketed by feature: later aggregates by feature need no exchange. Nothing is gathered."""
    name = name or f"slices_{uuid.uuid4().hex[:12]}"
    slices.write.bucketBy(buckets, "feature_id").sortBy("feature_id", "row_id").saveAsTable(name)
    return name


def append_slices(existing: DataFrame, new_rows: DataFrame) -> DataFrame:
    """Slices of more rows, by the same bins, after those there are."""
    return existing.unionByName(to_slices(new_rows))


def cache_slices(slices: DataFrame) -> DataFrame:
    """In memory, and on disk for what does not fit."""
    return slices.persist(StorageLevel.MEMORY_AND_DISK)


def slice_blocks(slices: DataFrame, rows_per_block: int = 65536) -> DataFrame:
    """feature_id, row_block, n, bins: one byte per cell, the row implied by its place (bins from -1 to 254)."""
    block = F.floor(F.col("row_id") / rows_per_block).cast("int")

    def pack(t: pa.Table) -> pa.Table:
        at, value = t["row_id"].to_numpy() % rows_per_block, t["bin"].to_numpy()
        cells = np.zeros(int(at.max()) + 1, np.uint8)
        cells[at] = value + 1
        return pa.table({"feature_id": t["feature_id"][:1], "row_block": t["row_block"][:1], "n": pa.array([len(at)], pa.int32()), "bins": pa.array([cells.tobytes()], pa.binary())})

    return slices.withColumn("row_block", block).groupBy("feature_id", "row_block").applyInArrow(pack, "feature_id int, row_block int, n int, bins binary")


def sparse_histogram(cells: DataFrame, rows: DataFrame, absent_bin: int = 0) -> DataFrame:
    """feature_id, bin, target, c from present cells (row_id, feature_id, bin) and rows (row_id, target): the counts of
    the absent bin are the totals by target less what is present, so the cost follows the present cells."""
    present = cells.join(rows, "row_id").groupBy("feature_id", "bin", "target").agg(F.count("*").alias("c"))
    totals = rows.groupBy("target").agg(F.count("*").alias("all"))
    by_target = present.groupBy("feature_id", "target").agg(F.sum("c").alias("there"))
    grid = present.select("feature_id").distinct().crossJoin(F.broadcast(totals))  # one row per class on the right
    absent = grid.join(by_target, ["feature_id", "target"], "left").select("feature_id", F.lit(absent_bin).alias("bin"), "target", (F.col("all") - F.coalesce("there", F.lit(0))).alias("c"))
    return present.union(absent.where("c > 0")).groupBy("feature_id", "bin", "target").agg(F.sum("c").alias("c"))
