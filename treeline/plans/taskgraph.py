"""The tasks of training as relations: score tasks (one for a node and a feature), split tasks (one for a node), their
order, where they run, and how a first-in-first-out queue would place the split tasks."""

from __future__ import annotations

import heapq

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def task_graph(nodes: DataFrame, selected: DataFrame, path: DataFrame | None = None) -> DataFrame:
    """task_id, kind, tree, stage, node, feature_id, parents, for every node that was split or scored.

    nodes: tree, node, parent, depth, is_leaf, feature_id, scored; a node is scored if it was open for a split. A
    score task waits for the split of the node's parent, a split task for all score tasks of its node; trees have no
    edges between them. path: tree, node, feature_id already used above the node.
    """
    open_nodes = nodes.where("scored").select("tree", "node", "parent", "depth")
    grid = open_nodes.join(F.broadcast(selected.select("tree", "feature_id")), "tree")
    if path is not None:
        grid = grid.join(path, ["tree", "node", "feature_id"], "left_anti")
    score_id = F.concat_ws("-", F.lit("score"), "tree", "node", "feature_id")
    split_id = lambda n: F.concat_ws("-", F.lit("split"), "tree", n)
    above = F.when(F.col("depth") == 0, F.array().cast("array<string>")).otherwise(F.array(split_id("parent")))
    score = grid.select(score_id.alias("task_id"), F.lit("score").alias("kind"), "tree", (F.col("depth") + 1).alias("stage"), "node", "feature_id", above.alias("parents"))
    split = score.groupBy("tree", "node", "stage").agg(F.sort_array(F.collect_list("task_id")).alias("parents"))
    split = split.select(split_id("node").alias("task_id"), F.lit("split").alias("kind"), "tree", "stage", "node", F.lit(-1).alias("feature_id"), "parents")
    return score.unionByName(split)


def locality_of(kind: Column) -> Column:
    """Score tasks run where their slice is; split tasks anywhere."""
    return F.when(kind == "score", "node-local").otherwise("any")


def schedule(tasks: DataFrame, placement: DataFrame) -> DataFrame:
    """tasks with locality, pool and workers: those that hold the slice for a score task, none for a split task."""
    homes = placement.groupBy("feature_id").agg(F.sort_array(F.collect_set("worker")).alias("workers"))
    x = tasks.join(F.broadcast(homes), "feature_id", "left")  # a row per slice
    kind = F.col("kind")
    return x.select(*tasks.columns, locality_of(kind).alias("locality"), F.when(kind == "score", "local").otherwise("cluster").alias("pool"), F.coalesce("workers", F.array().cast("array<int>")).alias("workers"))


def simulate_fifo(tasks: DataFrame, n_workers: int, period: int = 10) -> DataFrame:
    """task_id, tree, worker, ready, start, finish, starved of the split tasks of all trees in one queue.

    A tree's tasks of a stage form a set, which is appended when the stage before has ended; sets are taken first in,
    first out (ties by tree), each task by the worker that is free first. A task takes one unit for each score task it
    waits for. A timer ticks every `period` units; starved counts the ticks at which a ready task still had no worker.
    There are as many tasks as the model has nodes, and one queue is one group.
    """

    def run(part: pd.DataFrame) -> pd.DataFrame:
        sets = {k: own.sort_values("task_id") for k, own in part.groupby(["tree", "stage"])}
        free = [(0, w) for w in range(n_workers)]
        queue = [(0, tree, min(s for t, s in sets if t == tree)) for tree in sorted({t for t, _ in sets})]
        heapq.heapify(queue)
        out = []
        while queue:
            ready, tree, stage = heapq.heappop(queue)
            end = ready
            for r in sets[tree, stage].itertuples():
                at, w = heapq.heappop(free)
                start = max(at, ready)
                finish = start + int(r.cost)
                end = max(end, finish)
                heapq.heappush(free, (finish, w))
                out.append((r.task_id, tree, w, ready, start, finish, start // period - ready // period))
            if (tree, stage + 1) in sets:
                heapq.heappush(queue, (end, tree, stage + 1))
        return pd.DataFrame(out, columns=["task_id", "tree", "worker", "ready", "start", "finish", "starved"])

    work = tasks.where("kind = 'split'").select(F.lit(0).alias("queue"), "task_id", "tree", "stage", F.size("parents").alias("cost"))
    return work.groupBy("queue").applyInPandas(run, "task_id string, tree int, worker int, ready bigint, start bigint, finish bigint, starved bigint")


def dag_depth(tasks: DataFrame) -> DataFrame:
    return tasks.groupBy("tree").agg(F.max("stage").alias("stages"), F.count("*").alias("tasks"))


def workload_balance(scheduled: DataFrame, placement: DataFrame) -> DataFrame:
    """worker, tasks, units: score tasks of the slices on a worker and the cells they read."""
    by = scheduled.where("kind = 'score'").groupBy("feature_id").agg(F.count("*").alias("c"))
    x = placement.join(by, "feature_id", "left").fillna(0, ["c"])
    return x.groupBy("worker").agg(F.sum("c").alias("tasks"), F.sum(F.col("c") * F.col("units")).alias("units"))


def skew(balance: DataFrame, column: str = "units") -> DataFrame:
    return balance.agg((F.max(column) / F.avg(column)).alias("skew"), F.stddev_pop(column).alias("spread"))


def slice_reuse(tasks: DataFrame) -> DataFrame:
    """feature_id, stage, trees: in how many trees a slice is scored in a stage."""
    return tasks.where("kind = 'score'").groupBy("feature_id", "stage").agg(F.countDistinct("tree").alias("trees"))
