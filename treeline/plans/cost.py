"""Cost formulas over catalogues, the choice of a layout, and shuffle bytes read from event logs."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Values a stored cell counts: the paper's count of two, with the row index as a third, and with a draw table beside.
VOLUMES = ("copied", "paper", "with_index", "with_draws")


def catalog(spark: SparkSession, entries: list[tuple[str, int, int]]) -> DataFrame:
    """name, n (rows), m (columns with the target)."""
    return spark.createDataFrame(entries, "name string, n bigint, m bigint")


def volume(cat: DataFrame, trees: list[int]) -> DataFrame:
    """name, trees, model, cells: copied samples grow with the trees, slices shared by all trees do not."""
    x = cat.withColumn("trees", F.explode(F.array(*[F.lit(t).cast("bigint") for t in trees])))
    n, m, t = F.col("n"), F.col("m"), F.col("trees")
    cells = F.array(
        F.struct(F.lit("copied").alias("model"), (n * m * t).alias("cells")),
        F.struct(F.lit("paper").alias("model"), (2 * n * (m - 1)).alias("cells")),
        F.struct(F.lit("with_index").alias("model"), (3 * n * (m - 1)).alias("cells")),
        F.struct(F.lit("with_draws").alias("model"), (3 * n * (m - 1) + n * t).alias("cells")),
    )
    return x.select("name", "trees", F.inline(cells))


def volume_break_even(volumes: DataFrame) -> DataFrame:
    """name, model, trees: the least number of trees from which the shared layout is no larger than copies."""
    copied = volumes.where("model = 'copied'").select("name", "trees", F.col("cells").alias("copied"))
    x = volumes.where("model <> 'copied'").join(copied, ["name", "trees"]).where("cells <= copied")
    return x.groupBy("name", "model").agg(F.min("trees").alias("trees"))


def allocation_traffic(cat: DataFrame, nodes: list[int]) -> DataFrame:
    x = cat.withColumn("nodes", F.explode(F.array(*[F.lit(v).cast("bigint") for v in nodes])))
    return x.select("name", "nodes", (2.0 * F.col("m") * F.col("n") / F.col("nodes")).alias("cells_per_node"))


def operations(cat: DataFrame, n_trees: int, n_selected: int) -> DataFrame:
    """name, method, ops: gain evaluations of the classic forest, of the reduced one, of the reduced one spread over
    trees and features exactly, and the bound N (log2 N + 1)."""
    n, m, t, s = F.col("n").cast("double"), F.col("m").cast("double"), float(n_trees), float(n_selected)
    log = F.log2(n)
    rows = F.array(
        F.struct(F.lit("classic").alias("method"), (t * m * n * log).alias("ops")),
        F.struct(F.lit("reduction").alias("method"), (t * m * n).alias("ops")),
        F.struct(F.lit("hybrid").alias("method"), (t * (m * n + s * n * log)).alias("ops")),
        F.struct(F.lit("parallel").alias("method"), (n + s / m * n * log).alias("ops")),
        F.struct(F.lit("bound").alias("method"), (n * (log + 1)).alias("ops")),
    )
    return cat.select("name", F.inline(rows))


def choose_layout(n: int, m: int, trees: int, nodes: int, bins: int, classes: int, selected: int, levels: int, map_tasks: int, feature_blocks: int = 8, cell: int = 16, row_id: int = 8, stat: int = 8) -> tuple[str, dict[str, float]]:
    """The layout that sends the fewest bytes, and the bytes of each: slices once and scores and row lists by level;
    rows in place and partial histograms by level; packed slices, row lists and histograms."""
    hist = trees * nodes * selected * bins * classes * stat
    cost = {
        "vertical": 2.0 * n * (m - 1) * cell + levels * (trees * nodes * selected * 48 + trees * n * row_id * feature_blocks),
        "horizontal": float(levels * min(map_tasks * hist, n * selected * trees * stat)),
        "blocks": n * (m - 1) * 1.0 + levels * (trees * n * row_id + map_tasks * hist / 8),
    }
    return min(cost, key=cost.get), cost


def timed(run: Callable[[], DataFrame], repeat: int = 1) -> float:
    """Median seconds to compute a frame fully."""
    took = []
    for _ in range(repeat):
        at = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        took.append(time.perf_counter() - at)
    return sorted(took)[len(took) // 2]


def normalised_time(times: DataFrame) -> DataFrame:
    """times (method, slots, seconds) with normalised: seconds over those of one slot."""
    first = F.first("seconds").over(Window.partitionBy("method").orderBy("slots"))
    return times.withColumn("normalised", F.col("seconds") / first)


def speedup(times: DataFrame) -> DataFrame:
    """method, slots, speedup (one slot's seconds over these) and ratio_printed (the inverse)."""
    x = normalised_time(times)
    return x.select("method", "slots", (1 / F.col("normalised")).alias("speedup"), F.col("normalised").alias("ratio_printed"))


def startup_cost(times: DataFrame) -> DataFrame:
    """method, fixed_s, s_per_unit: intercept and slope of seconds by size."""
    return times.groupBy("method").agg(F.regr_intercept("seconds", "size").alias("fixed_s"), F.regr_slope("seconds", "size").alias("s_per_unit"))


def shuffle_bytes(spark: SparkSession, log_path: str) -> DataFrame:
    """job_group, stage_id, shuffle_write, shuffle_read in bytes from an event log that Spark has written."""
    schema = (
        "Event STRING, `Stage ID` BIGINT, `Stage Info` STRUCT<`Stage ID`: BIGINT>, Properties MAP<STRING, STRING>, "
        "`Task Metrics` STRUCT<`Shuffle Write Metrics`: STRUCT<`Shuffle Bytes Written`: BIGINT>, `Shuffle Read Metrics`: STRUCT<`Local Bytes Read`: BIGINT, `Remote Bytes Read`: BIGINT>>"
    )
    log = spark.read.schema(schema).json(log_path)
    stages = log.where("Event = 'SparkListenerStageSubmitted'").select(F.col("Stage Info.Stage ID").alias("stage_id"), F.coalesce(F.col("Properties")["spark.jobGroup.id"], F.lit("")).alias("job_group"))
    w = F.col("Task Metrics")["Shuffle Write Metrics"]["Shuffle Bytes Written"]
    r = F.col("Task Metrics")["Shuffle Read Metrics"]
    tasks = log.where("Event = 'SparkListenerTaskEnd'").groupBy(F.col("Stage ID").alias("stage_id")).agg(
        F.coalesce(F.sum(w), F.lit(0)).alias("shuffle_write"), F.coalesce(F.sum(r["Local Bytes Read"] + r["Remote Bytes Read"]), F.lit(0)).alias("shuffle_read")
    )
    return stages.dropDuplicates(["stage_id"]).join(tasks, "stage_id")


def log2(x: float) -> float:
    return math.log2(x) if x > 0 else 0.0
