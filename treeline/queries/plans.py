"""Registered queries of placement, task graphs, cost formulas and baselines, with their SQL twins where there are any."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..baselines import classic, dynamic, library, partition_forest
from ..functions.hashing import poisson_sql
from ..functions.math import rounded
from ..operators import layout as L
from ..operators import sampling as S
from ..operators.voting import tree_accuracy
from ..plans import allocation as A
from ..plans import cost as C
from ..plans import measures as M
from ..plans import taskgraph as T
from ..session import stored, table
from .forest import _REG, SPEC, _reg, forest_of, rows_of
from .forest_sql import Chain, forest_chain, out
from .training_sets import CHARGE, FLAG, QUALITY

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


# volumes and operations over catalogues

_CATALOG = [("lineitem", 11), ("orders", 6), ("documents", 5), ("embeddings", 65), ("events", 6)]
_CAT_SQL = " UNION ALL ".join(f"SELECT '{n}' AS name, count(*) AS n, {m}::BIGINT AS m FROM {n}" for n, m in _CATALOG)
TREES, NODES = [1, 2, 3, 10, 100, 500, 1000, 1500], [5, 10, 25, 50, 100]


def _catalog(spark, sf_dir):
    parts = [table(spark, sf_dir, n).agg(F.count("*").alias("n")).select(F.lit(n).alias("name"), "n", F.lit(m).cast("bigint").alias("m")) for n, m in _CATALOG]
    total = parts[0]
    for p in parts[1:]:
        total = total.union(p)
    return total


_VOLUME = f"""
WITH c AS ({_CAT_SQL}), t AS (SELECT unnest({TREES})::BIGINT AS trees), v AS (
  SELECT name, trees, 'copied' AS model, n * m * trees AS cells FROM c, t UNION ALL SELECT name, trees, 'paper', 2 * n * (m - 1) FROM c, t
  UNION ALL SELECT name, trees, 'with_index', 3 * n * (m - 1) FROM c, t UNION ALL SELECT name, trees, 'with_draws', 3 * n * (m - 1) + n * trees FROM c, t)
"""


@query(_VOLUME + "SELECT * FROM v")
def q_volume(spark, sf_dir):
    return C.volume(_catalog(spark, sf_dir), TREES)


@query(_VOLUME + "SELECT a.name, a.model, min(a.trees) AS trees FROM v a JOIN v b USING (name, trees) WHERE b.model = 'copied' AND a.model <> 'copied' AND a.cells <= b.cells GROUP BY ALL")
def q_volume_break_even(spark, sf_dir):
    return C.volume_break_even(C.volume(_catalog(spark, sf_dir), TREES))


@query(f"WITH c AS ({_CAT_SQL}) SELECT name, nodes, {out('2.0 * m * n / nodes')} AS cells_per_node FROM c, (SELECT unnest({NODES})::BIGINT AS nodes)")
def q_allocation_traffic(spark, sf_dir):
    return C.allocation_traffic(_catalog(spark, sf_dir), NODES).withColumn("cells_per_node", rounded(F.col("cells_per_node")))


_OPS = {"classic": "500.0 * m * n * log2(n)", "reduction": "500.0 * m * n", "hybrid": "500.0 * (m * n + 4 * n * log2(n))", "parallel": "n + 4.0 / m * n * log2(n)", "bound": "n * (log2(n) + 1)"}


@query(f"WITH c AS ({_CAT_SQL}) " + " UNION ALL ".join(f"SELECT name, '{k}' AS method, {out(v, 1)} AS ops FROM c" for k, v in _OPS.items()))
def q_ops(spark, sf_dir):
    return C.operations(_catalog(spark, sf_dir), 500, 4).withColumn("ops", rounded(F.col("ops"), 1))


#: The events as runs of methods: a run's size (or slots) is its user's group of eight, its seconds are its value.
_RUNS = "SELECT event_type AS method, 1 + user_id % 8 AS size, value AS seconds FROM events WHERE event_type IS NOT NULL AND user_id IS NOT NULL AND value IS NOT NULL"


def _runs(spark, sf_dir):
    e = table(spark, sf_dir, "events").where("event_type IS NOT NULL AND user_id IS NOT NULL AND value IS NOT NULL")
    return e.select(F.col("event_type").alias("method"), (1 + F.col("user_id") % 8).alias("size"), F.col("value").alias("seconds"))


@query(
    f"SELECT method, slots, {out('first_value(seconds) OVER w / seconds')} AS speedup, {out('seconds / first_value(seconds) OVER w')} AS ratio_printed "
    f"FROM (SELECT method, size AS slots, avg(seconds) AS seconds FROM ({_RUNS}) GROUP BY ALL) WINDOW w AS (PARTITION BY method ORDER BY slots)"
)
def q_speedup(spark, sf_dir):
    s = C.speedup(_runs(spark, sf_dir).groupBy("method", F.col("size").alias("slots")).agg(F.avg("seconds").alias("seconds")))
    return s.select("method", "slots", rounded(F.col("speedup")).alias("speedup"), rounded(F.col("ratio_printed")).alias("ratio_printed"))


@query(f"SELECT method, {out('regr_intercept(seconds, size)')} AS fixed_s, {out('regr_slope(seconds, size)')} AS s_per_unit FROM ({_RUNS}) GROUP BY method")
def q_startup_cost(spark, sf_dir):
    c = C.startup_cost(_runs(spark, sf_dir))
    return c.select("method", rounded(F.col("fixed_s")).alias("fixed_s"), rounded(F.col("s_per_unit")).alias("s_per_unit"))


# placement of the slices of lineitem and of embeddings

_SLICES = Chain(FLAG).text("SELECT feature_id, count(*) AS units FROM slices GROUP BY ALL")
_CAPS = [0.7, 1.0, 0.5, 1.6, 2.0]
_CAP_SQL = "SELECT w AS worker, floor(n * c)::BIGINT AS capacity FROM (SELECT count(*) AS n FROM lineitem), (SELECT unnest(range(5))::INTEGER AS w, unnest([0.7, 1.0, 0.5, 1.6, 2.0]) AS c)"
_ENDS = f"""
WITH RECURSIVE v AS ({_SLICES}), k AS ({_CAP_SQL}),
s AS (SELECT feature_id, sum(units) OVER (ORDER BY feature_id) - units AS s0, sum(units) OVER (ORDER BY feature_id) AS s1 FROM v),
w AS (SELECT worker, sum(capacity) OVER (ORDER BY worker) - capacity AS w0, sum(capacity) OVER (ORDER BY worker) AS w1 FROM k),
p AS (SELECT feature_id, worker, (greatest(s0, w0) - s0)::BIGINT AS unit_from, (least(s1, w1) - s0)::BIGINT AS unit_to, (least(s1, w1) - greatest(s0, w0))::BIGINT AS units FROM s JOIN w ON s0 < w1 AND w0 < s1),
l AS (SELECT p.*, count(*) OVER (PARTITION BY feature_id) AS pieces, count(*) OVER (PARTITION BY worker) AS guests, sum(units) OVER (PARTITION BY worker) AS load, capacity FROM p JOIN k USING (worker))
"""


def _volumes(spark, sf_dir):
    rows, _ = rows_of(spark, sf_dir, FLAG)
    return stored(A.slice_volumes(L.to_slices(rows)), "volumes")


def _capacity(spark, sf_dir):
    n = table(spark, sf_dir, "lineitem").count()
    return A.workers(spark, [int(n * c) for c in _CAPS])


@query(_ENDS + "SELECT * FROM p")
def q_allocate_prefix(spark, sf_dir):
    return A.allocate(_volumes(spark, sf_dir), _capacity(spark, sf_dir))


@query(_ENDS + "SELECT feature_id, worker, unit_from, unit_to, units, CASE WHEN pieces > 1 THEN 'a' WHEN guests = 1 AND load = capacity THEN 'b' ELSE 'c' END AS scenario FROM l")
def q_allocate_scenarios(spark, sf_dir):
    k = _capacity(spark, sf_dir)
    return A.scenario(A.allocate(_volumes(spark, sf_dir), k), k)


@query(_ENDS + f"SELECT k.worker, k.capacity, coalesce(sum(p.units), 0)::BIGINT AS units, count(DISTINCT feature_id) AS slices, {out('coalesce(sum(p.units), 0) / k.capacity')} AS filled FROM k LEFT JOIN p USING (worker) GROUP BY k.worker, k.capacity")
def q_storage_balance(spark, sf_dir):
    k = _capacity(spark, sf_dir)
    return A.storage_balance(A.allocate(_volumes(spark, sf_dir), k), k).withColumn("filled", rounded(F.col("filled")))


_FIRST = f"""
WITH RECURSIVE v AS ({_SLICES}), k AS ({_CAP_SQL}),
r AS (
  SELECT -1 AS feature_id, NULL::INTEGER AS home, (SELECT list(capacity ORDER BY worker) FROM k) AS free, []::BIGINT[] AS took
  UNION ALL
  SELECT v.feature_id, x.home,
    list_transform(r.free, lambda f, i: f - x.took[i]) AS free, x.took
  FROM r JOIN v ON v.feature_id = r.feature_id + 1, LATERAL (
    SELECT h AS home, CASE WHEN h IS NOT NULL THEN list_transform(r.free, lambda f, i: CASE WHEN i = h + 1 THEN v.units ELSE 0 END)
      ELSE list_transform(r.free, lambda f, i: greatest(0, least(f, v.units - coalesce(list_sum(r.free[1:i-1]), 0)))::BIGINT) END AS took
    FROM (SELECT list_position(list_transform(r.free, lambda f: f >= v.units), true) - 1 AS h)
  ) x
)
SELECT feature_id, (i - 1)::INTEGER AS worker, took[i]::BIGINT AS units FROM r, (SELECT unnest(range(1, 6)) AS i) WHERE feature_id >= 0 AND took[i] > 0
"""


@query(_FIRST)
def q_allocate_first_fit(spark, sf_dir):
    return A.allocate(_volumes(spark, sf_dir), _capacity(spark, sf_dir), "first_fit").select("feature_id", "worker", "units")


@query()
def q_rebalance(spark, sf_dir):
    before = A.allocate(_volumes(spark, sf_dir), _capacity(spark, sf_dir), "first_fit")
    n = table(spark, sf_dir, "lineitem").count()
    return A.rebalance(before, A.workers(spark, [int(n * c) for c in [*_CAPS, 2.0, 2.0]]))


@query()
def q_scale_delta(spark, sf_dir):
    v, n = _volumes(spark, sf_dir), table(spark, sf_dir, "lineitem").count()
    before, after = A.allocate(v, A.workers(spark, [2 * n] * 3)), A.allocate(v, A.workers(spark, [2 * n] * 2 + [n] * 3))
    return A.scale_delta(before, after)


# task graphs of the checked forest

_graph = forest_chain(QUALITY, 2)
_graph.add("open", "SELECT n.tree, n.node, 0 AS depth FROM n0 n WHERE n.n >= 2 UNION ALL SELECT n.tree, n.node, 1 FROM n1 n JOIN (SELECT tree, node FROM c1 GROUP BY ALL HAVING count(*) > 1) USING (tree, node) WHERE n.n >= 2")
_graph.add("score", "SELECT o.tree, o.node, o.depth, s.feature_id FROM open o JOIN selected s USING (tree) WHERE o.depth = 0 OR NOT EXISTS (SELECT 1 FROM path1 p WHERE p.tree = o.tree AND p.node = o.node AND p.feature_id = s.feature_id)")
_TASKS = (
    "SELECT 'score-' || tree || '-' || node || '-' || feature_id AS task_id, 'score' AS kind, tree, (depth + 1)::INTEGER AS stage, node, feature_id::INTEGER AS feature_id, "
    "CASE WHEN depth = 0 THEN '' ELSE 'split-' || tree || '-' || ((node - 1) // 9) END AS parents FROM score UNION ALL "
    "SELECT 'split-' || tree || '-' || node, 'split', tree, (depth + 1)::INTEGER, node, -1, string_agg('score-' || tree || '-' || node || '-' || feature_id, ',' ORDER BY 'score-' || tree || '-' || node || '-' || feature_id) FROM score GROUP BY tree, node, depth"
)
_graph.add("tasks", _TASKS)


def _tasks(spark, sf_dir):
    f, _ = forest_of(spark, sf_dir, QUALITY)
    open_nodes = {(x.tree, x.node) for x in f.node_list if x.depth < 2 and x.n("classification") >= 2 and not x.pure("classification")}
    nodes = [(x.tree, x.node, x.parent, x.depth, (x.tree, x.node) in open_nodes) for x in f.node_list]
    path = [(x.tree, x.node, u) for x in f.node_list for u in x.used] or [(-1, -1, -1)]
    frame = spark.createDataFrame(nodes, "tree int, node bigint, parent bigint, depth int, scored boolean")
    return stored(T.task_graph(frame, f.selected, spark.createDataFrame(path, "tree int, node bigint, feature_id int")), "tasks")


@query(_graph.text("SELECT * FROM tasks"))
def q_task_graph(spark, sf_dir):
    return _tasks(spark, sf_dir).withColumn("parents", F.array_join("parents", ","))


@query(_graph.text("SELECT kind, stage, CASE WHEN kind = 'score' THEN 'node-local' ELSE 'any' END AS locality, CASE WHEN kind = 'score' THEN 'local' ELSE 'cluster' END AS pool, count(*) AS tasks FROM tasks GROUP BY ALL"))
def q_task_schedule(spark, sf_dir):
    rows, _ = rows_of(spark, sf_dir, QUALITY)
    placed = A.allocate(A.slice_volumes(L.to_slices(rows)), A.workers(spark, [rows.count() * 4] * 3))
    return T.schedule(_tasks(spark, sf_dir), placed).groupBy("kind", "stage", "locality", "pool").agg(F.count("*").alias("tasks"))


@query()
def q_fifo(spark, sf_dir):
    return T.simulate_fifo(_tasks(spark, sf_dir), 3)


@query(_graph.text("SELECT tree, max(stage) AS stages, count(*) AS tasks FROM tasks GROUP BY tree"))
def q_dag_depth(spark, sf_dir):
    return T.dag_depth(_tasks(spark, sf_dir))


@query(_graph.text("SELECT feature_id, stage, count(DISTINCT tree) AS trees FROM tasks WHERE kind = 'score' GROUP BY ALL"))
def q_slice_reuse(spark, sf_dir):
    return T.slice_reuse(_tasks(spark, sf_dir))


@query(_graph.text("SELECT feature_id % 3 AS worker, count(*) AS tasks, count(*) * (SELECT count(*) FROM bins) AS units FROM tasks WHERE kind = 'score' GROUP BY 1"))
def q_workload_balance(spark, sf_dir):
    rows, _ = rows_of(spark, sf_dir, QUALITY)
    dealt = A.slice_volumes(L.to_slices(rows)).select("feature_id", (F.col("feature_id") % 3).alias("worker"), "units")
    return T.workload_balance(_tasks(spark, sf_dir), dealt)


# baselines

_classic = forest_chain(QUALITY, 2, reduction=False)
_classic.decide("direct")


@query(_classic.text(f"SELECT {out('avg((prediction = target)::INTEGER::DOUBLE)')} AS accuracy, count(*) AS rows FROM decided"))
def q_classic_forest(spark, sf_dir):
    """All features at each node of samples copied row by row, direct vote."""
    rows, rules = rows_of(spark, sf_dir, QUALITY)
    f = classic.fit(rows, rules, [0, 1], SPEC.but(n_selected=len(rules)), all_features=True, copies=True)
    d = f.predict(rows).join(rows.select("row_id", "target"), "row_id")
    return M.accuracy(d).withColumn("accuracy", rounded(F.col("accuracy")))


_drawn = forest_chain(QUALITY, 2, reduction=False, node_features=4)


@query(_drawn.text("SELECT tree, node, depth::INTEGER AS depth, n::DOUBLE AS n, feature_id::INTEGER AS feature_id, is_leaf, prediction FROM nodes"))
def q_classic_nodes(spark, sf_dir):
    """Trees of the classic forest: four random features at each node, copied samples."""
    rows, rules = rows_of(spark, sf_dir, QUALITY)
    f = classic.fit(rows, rules, [0, 1], SPEC.but(n_selected=4), copies=True)
    return f.nodes.select("tree", "node", "depth", "n", "feature_id", "is_leaf", "prediction")


def _dynamic_sql():
    c = forest_chain(QUALITY, 2)
    c.add("share", "SELECT row_id, avg((prediction = target)::INTEGER::DOUBLE) AS c FROM votes WHERE w = 0 AND tree < 3 GROUP BY row_id")
    c.add("raw", f"SELECT b.row_id, {poisson_sql('b.row_id', '3')} * (1 - coalesce(s.c, 0.5) + 0.1) AS v FROM bins b LEFT JOIN share s USING (row_id)")
    return c.text(f"SELECT row_id, {out('v / avg(v) OVER ()')} AS w FROM raw")


@query(_dynamic_sql())
def q_dynamic_weights(spark, sf_dir):
    f, rows = forest_of(spark, sf_dir, QUALITY)
    w = dynamic.next_weights(rows, f.oob_votes(rows).where("tree < 3"), 3, SPEC.seed)
    return w.select("row_id", rounded(F.col("w")).alias("w"))


@query()
def q_dynamic_forest(spark, sf_dir):
    rows, rules = rows_of(spark, sf_dir, QUALITY)
    f = dynamic.fit(rows, rules, [0, 1], SPEC)
    return M.accuracy(f.predict(rows).join(rows.select("row_id", "target"), "row_id"))


@query()
def q_partition_forest(spark, sf_dir):
    rows, rules = rows_of(spark, sf_dir, QUALITY)
    f = partition_forest.fit(rows, rules, [0, 1], SPEC, 2)
    return M.accuracy(f.predict(rows).join(rows.select("row_id", "target"), "row_id"))


@query()
def q_mllib_forest(spark, sf_dir):
    rows, rules = rows_of(spark, sf_dir, QUALITY)
    return M.accuracy(library.predict(library.fit(rows, 2, SPEC), rows))


def _drift_sql():
    c = Chain(QUALITY)
    c.weights("partition")
    return c.text(f"SELECT tree, {out('avg((w = 0)::INTEGER::DOUBLE)')} AS oob_share FROM weights GROUP BY tree")


@query(_drift_sql())
def q_partition_sampled(spark, sf_dir):
    rows, _ = rows_of(spark, sf_dir, QUALITY)
    w = S.partition_weights(rows.select("row_id", (F.col("row_id") % 8).alias("block")), SPEC.n_trees, "block")
    return w.groupBy("tree").agg(rounded(F.avg((F.col("w") == 0).cast("double"))).alias("oob_share"))


@query()
def q_layout_choice(spark, sf_dir):
    rows = []
    for name, n, m in [(r.name, r.n, r.m) for r in _catalog(spark, sf_dir).collect()]:
        best, cost = C.choose_layout(n, m, 100, 64, 32, 5, 16, 6, 200)
        rows += [(name, k, v, k == best) for k, v in cost.items()]
    return spark.createDataFrame(rows, "name string, layout string, bytes double, chosen boolean")


@query(_reg.text(f"SELECT tree, count(*) AS oob_rows, {out('greatest(0, 1 - sum((prediction - target) * (prediction - target)) / (var_pop(target) * count(*)))')} AS ca FROM votes WHERE w = 0 GROUP BY tree"))
def q_tree_accuracy_r2(spark, sf_dir):
    """R squared of the trees of a regression forest on their out-of-bag rows."""
    f, rows = forest_of(spark, sf_dir, CHARGE, _REG)
    return tree_accuracy(f.oob_votes(rows), "regression", kind="r2").select("tree", "oob_rows", rounded(F.col("ca")).alias("ca"))
