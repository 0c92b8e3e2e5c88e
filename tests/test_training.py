"""Sparse training, the task queue, placement moves, samples by blocks, layouts, and sessions without the package."""

import subprocess
import sys
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from treeline.functions.hashing import drawn_weight, poisson_weight
from treeline.operators import sampling as S
from treeline.operators.binning import fit_bins
from treeline.operators.growth import _block_histogram
from treeline.operators.model import fit_binned
from treeline.operators.sparse import ABSENT, fit_sparse, predict_sparse
from treeline.operators.spec import ForestSpec
from treeline.plans import allocation as A
from treeline.plans import taskgraph as T
from treeline.queries.forest import rows_of, word_cells
from treeline.queries.training_sets import TOXIC


def shape(f):
    return sorted((x.tree, x.node, x.depth, x.is_leaf, -1 if x.is_leaf else x.feature_id, tuple(x.stats)) for x in f.node_list)


@pytest.mark.parametrize("change", [{}, {"reduction": False}, {"tree": "cart", "n_principal": 4, "n_selected": 8}, {"tree_group": 2}])
def test_sparse_trees_are_the_dense_ones(spark, change):
    cells, rows = word_cells(spark, "/root/testdata/sf0.01", 24)
    cells = cells.where(F.col("bin") != ABSENT)
    wide = rows.join(cells.groupBy("row_id").agg(F.map_from_entries(F.collect_list(F.struct("feature_id", "bin"))).alias("m")), "row_id", "left")
    bins = F.array(*[F.coalesce(F.element_at("m", F.lit(i)), F.lit(ABSENT)) for i in range(24)])
    dense = wide.select("row_id", "target", bins.alias("bins"))
    spec = ForestSpec(n_trees=3, max_depth=3).but(**change)
    a, b = fit_binned(dense, [None] * 24, [0, 1], spec), fit_sparse(cells, rows, 24, [0, 1], spec)
    assert shape(a) == shape(b) and sorted(a.selected_rows) == sorted(b.selected_rows)
    assert [tuple(r) for r in a.stats_rows] == [tuple(r) for r in b.stats_rows]
    assert predict_sparse(b, cells, rows).exceptAll(a.predict(dense)).count() == 0


def test_many_sparse_features(spark):
    cells, rows = word_cells(spark, "/root/testdata/sf0.01")
    f = fit_sparse(cells, rows, 100_000, [0, 1], ForestSpec(n_trees=2, n_principal=50, n_selected=80, max_depth=3))
    got = predict_sparse(f, cells, rows).join(rows, "row_id")
    top = rows.groupBy("target").count().agg(F.max("count") / F.sum("count")).first()[0]
    assert got.agg(F.avg((F.col("prediction") == F.col("target")).cast("double"))).first()[0] > top
    assert {len([r for r in f.selected_rows if r[0] == t]) for t in (0, 1)} == {80}


@pytest.mark.parametrize("held", [1, 500, 10**9])
def test_histograms_are_put_out_in_parts(spark, held):
    rows, rules = rows_of(spark, "/root/testdata/sf0.001", TOXIC)
    sent = spark.sparkContext.broadcast(({}, {0: __import__("numpy").zeros(1, int), 1: __import__("numpy").zeros(1, int)}, {0: [0, 3], 1: [6]}))
    ddl = "tree int, live bigint, feature_id int, bin int, s0 double, s1 double"
    got = rows.mapInArrow(_block_histogram(sent, "classification", 2, 8, 42, held), ddl).groupBy("tree", "feature_id", "bin").agg(F.sum("s0").alias("s0"), F.sum("s1").alias("s1"))
    expect = []
    for t, f in ((0, 0), (0, 3), (1, 6)):
        w = poisson_weight(F.col("row_id"), F.lit(t), 42)
        cells = rows.select(F.lit(t).alias("tree"), F.lit(f).alias("feature_id"), F.col("bins")[f].alias("bin"), F.when(F.col("target") == 0, w).otherwise(0).alias("a"), F.when(F.col("target") == 1, w).otherwise(0).alias("b"))
        expect += [tuple(r) for r in cells.groupBy("tree", "feature_id", "bin").agg(F.sum("a"), F.sum("b")).where("sum(a) + sum(b) > 0").collect()]
    assert sorted(map(tuple, got.collect())) == sorted(expect)


def stepwise(tasks, workers):
    """One unit of time after the other: what is ready is queued in order, and idle workers take from its front."""
    left = {}
    for tree, stage, task, cost in sorted(tasks):
        left.setdefault(tree, {}).setdefault(stage, []).append((task, cost))
    queue, busy, open_, out, now = [], {}, {}, {}, 0
    ready = {}
    for tree in sorted(left):
        first = min(left[tree])
        queue += [(tree, first, task, cost) for task, cost in left[tree][first]]
        open_[tree], ready[tree] = [first, len(left[tree][first])], 0
    idle = [(0, w) for w in range(workers)]
    while queue or busy:
        for w in sorted(w for w, (_, end) in busy.items() if end == now):
            (tree, stage, task), _ = busy.pop(w)
            idle.append((now, w))
            open_[tree][1] -= 1
        for tree in sorted(open_):
            stage, n = open_[tree]
            if n == 0 and stage + 1 in left[tree]:
                queue += [(tree, stage + 1, task, cost) for task, cost in left[tree][stage + 1]]
                open_[tree], ready[tree] = [stage + 1, len(left[tree][stage + 1])], now
        idle.sort()
        while queue and idle:
            _, w = idle.pop(0)
            tree, stage, task, cost = queue.pop(0)
            busy[w] = ((tree, stage, task), now + cost)
            out[task] = (tree, w, ready[tree], now, now + cost)
        now += 1
    return out


@pytest.mark.parametrize("workers", [1, 3, 7])
def test_one_queue_for_all_trees(spark, workers):
    tasks = [(t, s, f"{t}-{s}-{i}", 1 + (t * 7 + s * 3 + i) % 4) for t in range(4) for s in range(1, 4) for i in range((t + s) % 3 + 1)]
    rows = [(task, "split", t, s, ["x"] * cost) for t, s, task, cost in tasks]
    frame = spark.createDataFrame(rows, "task_id string, kind string, tree int, stage int, parents array<string>")
    got = {r.task_id: r for r in T.simulate_fifo(frame, workers, 5).collect()}
    expect = stepwise(tasks, workers)
    assert {k: (r.tree, r.ready, r.start, r.finish) for k, r in got.items()} == {k: (v[0], v[2], v[3], v[4]) for k, v in expect.items()}
    assert all(r.starved == sum(r.ready < t <= r.start for t in range(0, 500, 5)) for r in got.values())
    for w in range(workers):
        own = sorted((r.start, r.finish) for r in got.values() if r.worker == w)
        assert all(a[1] <= b[0] for a, b in zip(own, own[1:], strict=False))


def test_moves_lessen_the_imbalance(spark):
    placed = spark.createDataFrame([(f, 0, 0, u, u) for f, u in enumerate([9, 7, 5, 4, 3, 2])], "feature_id int, worker int, unit_from long, unit_to long, units long")
    capacity = A.workers(spark, [30, 30, 30])
    moves = {r.feature_id: r for r in A.rebalance(placed, capacity).collect()}
    load = {0: 0, 1: 0, 2: 0}
    for r in placed.collect():
        load[moves[r.feature_id].worker_to if r.feature_id in moves else r.worker] += r.units
    assert sum(load.values()) == 30 and all(m.worker_from == 0 for m in moves.values()) and max(load[1], load[2]) <= 10 and load[0] < 30
    after = placed.withColumn("worker", F.when(F.col("feature_id").isin([f for f in moves]), F.lit(1)).otherwise(0))
    moved = sum(u for f, u in enumerate([9, 7, 5, 4, 3, 2]) if f in moves)
    assert tuple(A.scale_delta(placed, after).first()) == (moved, moved)


def test_block_draws_grow_with_the_table(spark):
    rows = spark.range(6000).select(F.col("id").alias("row_id"), (F.col("id") % 8).alias("block"))
    small, large = rows.where("row_id < 800"), rows
    share = lambda r: S.partition_weights(r, 2, "block").agg(F.avg((F.col("w") > 0).cast("double")), F.avg("w")).first()
    (a, m), (b, n) = share(small), share(large)
    assert a < b and m == pytest.approx(100 / 400, abs=0.06) and n == pytest.approx(750 / 400, abs=0.06)
    same = spark.range(3000).select(drawn_weight(F.col("id"), F.lit(3), F.lit(1.0)).alias("a"), poisson_weight(F.col("id"), F.lit(3)).alias("b"))
    assert same.where("least(a, 6) <> b").count() == 0


def test_specification_and_bins(spark):
    with pytest.raises(ValueError, match="criterion"):
        ForestSpec(criterion="info_gain").sized(9)
    df = spark.createDataFrame([(float(2**i), "ab"[i % 2], None if i else "z") for i in range(9)] + [(0.0, "a", None)], "x double, s string, t string")
    rules = fit_bins(df, ["x", "s", "t"], 4, cuts="log")
    assert rules[0].cuts == pytest.approx([4, 16, 64]) and rules[1].codes == {"a": 0, "b": 1} and rules[2].codes == {"z": 0}
    near, exact = fit_bins(df, ["x"], 4, exact=False), fit_bins(df, ["x"], 4)
    assert len(near[0].cuts) == len(exact[0].cuts) == 3


def test_incremental_forest_goes_on_after_a_restart(spark, tmp_path):
    from treeline.streaming.incremental import IncrementalForest

    rows, rules = rows_of(spark, "/root/testdata/sf0.001", TOXIC)
    parts = [rows.where(F.col("row_id") % 3 == i) for i in range(3)]
    spec, folder = ForestSpec(n_trees=3, max_depth=2), f"file://{tmp_path}/inc"
    one = IncrementalForest(rules, [0, 1], spec, fresh=1, folder=folder)
    one.update(parts[0], 0)
    one.update(parts[1], 1)
    two = IncrementalForest(rules, [0, 1], spec, fresh=1, folder=folder)
    two.update(parts[1], 1)
    assert two.next_tree == one.next_tree == 4 and shape(two.forest) == shape(one.forest) and two.history == one.history
    two.update(parts[2], 2)
    one.update(parts[2], 2)
    assert shape(two.forest) == shape(one.forest) and len(two.held) == 3


def test_executors_need_no_copy_of_the_package(tmp_path):
    root = Path(__file__).parents[1]
    code = f"""
import sys
from pyspark.sql import SparkSession
spark = SparkSession.builder.master("local[2]").config("spark.sql.shuffle.partitions", "2").config("spark.ui.enabled", "false").getOrCreate()
def there(batches):
    import importlib.util
    import pyarrow as pa
    for b in batches:
        yield pa.RecordBatch.from_pydict({{"found": [importlib.util.find_spec("treeline") is not None] * len(b)}})
assert not spark.range(1).mapInArrow(there, "found boolean").first().found
sys.path.insert(0, {str(root)!r})
from treeline.queries import forest, plans, streams
every = forest.QUERIES | plans.QUERIES | streams.QUERIES
for name in ("q_tree_depth2", "q_vote_weighted", "q_slice_blocks", "q_fifo", "q_stream_state"):
    every[name](spark, "/root/testdata/sf0.001").count()
"""
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True, timeout=600)
    assert done.returncode == 0, done.stderr[-2000:]
