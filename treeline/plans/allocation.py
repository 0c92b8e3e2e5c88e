"""Placement of slices on workers: by running sums, or slice by slice to the first worker with room."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

PLACED = "feature_id int, worker int, unit_from bigint, unit_to bigint, units bigint"


def slice_volumes(slices: DataFrame) -> DataFrame:
    """feature_id, units: cells of each slice."""
    return slices.groupBy("feature_id").agg(F.count("*").alias("units"))


def workers(spark: SparkSession, capacities: list[int]) -> DataFrame:
    return spark.createDataFrame(list(enumerate(capacities)), "worker int, capacity bigint")


def _ends(df: DataFrame, order: str, size: str) -> DataFrame:
    w = Window.orderBy(order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return df.withColumn("stop", F.sum(size).over(w)).withColumn("start", F.col("stop") - F.col(size))


def allocate(volumes: DataFrame, capacity: DataFrame, policy: str = "prefix") -> DataFrame:
    """feature_id, worker, unit_from, unit_to, units: which part of a slice lies where. Catalogues only, no cells.

    prefix: slices laid end to end over workers laid end to end; pieces are the overlaps (a range join). first_fit:
    slices in order, each whole on the first worker with room; one that no worker can hold is cut over those that
    have room left.
    """
    if policy == "first_fit":
        return _first_fit(volumes, capacity)
    if policy != "prefix":
        raise ValueError(policy)
    s, w = _ends(volumes, "feature_id", "units"), _ends(capacity, "worker", "capacity")
    s = s.select("feature_id", F.col("start").alias("s0"), F.col("stop").alias("s1"))
    lo, hi = F.greatest("s0", "start"), F.least("s1", "stop")
    pieces = s.join(F.broadcast(w), (F.col("s0") < F.col("stop")) & (F.col("start") < F.col("s1")))  # a row per worker
    return pieces.select("feature_id", F.col("worker"), (lo - F.col("s0")).alias("unit_from"), (hi - F.col("s0")).alias("unit_to"), (hi - lo).alias("units")).where("units > 0")


def _first_fit(volumes: DataFrame, capacity: DataFrame) -> DataFrame:
    free = {r.worker: r.capacity for r in capacity.collect()}  # catalogues: a row per worker and per slice
    out = []
    for r in volumes.orderBy("feature_id").collect():
        order = sorted(free)
        home = next((w for w in order if r.units <= free[w]), None)
        if home is not None:
            out.append((r.feature_id, home, 0, r.units, r.units))
            free[home] -= r.units
            continue
        at = 0
        for w in order:
            part = min(free[w], r.units - at)
            if part > 0:
                out.append((r.feature_id, w, at, at + part, part))
                free[w] -= part
                at += part
    return volumes.sparkSession.createDataFrame(out, PLACED)


def scenario(placement: DataFrame, capacity: DataFrame) -> DataFrame:
    """placement with scenario: a cut over several workers, b alone on a worker that it fills, c hosted with others."""
    by_slice, by_worker = Window.partitionBy("feature_id"), Window.partitionBy("worker")
    x = placement.join(F.broadcast(capacity), "worker")
    x = x.withColumn("pieces", F.count("*").over(by_slice)).withColumn("guests", F.count("*").over(by_worker)).withColumn("load", F.sum("units").over(by_worker))
    kind = F.when(F.col("pieces") > 1, "a").when((F.col("guests") == 1) & (F.col("load") == F.col("capacity")), "b").otherwise("c")
    return x.select(*placement.columns, kind.alias("scenario"))


def storage_balance(placement: DataFrame, capacity: DataFrame) -> DataFrame:
    load = placement.groupBy("worker").agg(F.sum("units").alias("units"), F.countDistinct("feature_id").alias("slices"))
    x = capacity.join(load, "worker", "left").fillna(0, ["units", "slices"])
    return x.withColumn("filled", F.col("units") / F.col("capacity"))


def rebalance(placement: DataFrame, capacity: DataFrame) -> DataFrame:
    """feature_id, worker_from, worker_to: smallest slices of workers above their share of the load move to workers
    below it, in order, until neither is left. One row per slice on the driver."""
    pieces = [(r.feature_id, r.worker, r.units) for r in placement.orderBy("units", "feature_id").collect()]
    room = {r.worker: r.capacity for r in capacity.collect()}
    total, all_room = sum(p[2] for p in pieces), sum(room.values())
    load = dict.fromkeys(room, 0)
    for _, w, u in pieces:
        load[w] += u
    share = {w: total * c / all_room for w, c in room.items()}
    moves = []
    for f, w, u in pieces:
        if load[w] <= share[w] + 1e-9:
            continue
        to = next((v for v in sorted(room) if load[v] + u <= share[v] + 1e-9), None)
        if to is not None:
            moves.append((f, w, to))
            load[w] -= u
            load[to] += u
    return placement.sparkSession.createDataFrame(moves, "feature_id int, worker_from int, worker_to int")


def scale_delta(before: DataFrame, after: DataFrame) -> DataFrame:
    """Units that lie elsewhere, or are new, after trees, workers or rows have grown."""
    a = before.groupBy("feature_id", "worker").agg(F.sum("units").alias("u0"))
    b = after.groupBy("feature_id", "worker").agg(F.sum("units").alias("u1"))
    x = a.join(b, ["feature_id", "worker"], "full").fillna(0, ["u0", "u1"])
    return x.agg(F.sum(F.greatest(F.col("u1") - F.col("u0"), F.lit(0))).alias("arrived"), F.sum(F.greatest(F.col("u0") - F.col("u1"), F.lit(0))).alias("left"))
