"""Registered queries of the forest methods, with their SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import materialised
from ..functions.features import filled, fold, hashed_words
from ..functions.hashing import drawn_sql, mix_sql, poisson_sql
from ..functions.math import rounded
from ..operators import impurity as I
from ..operators import layout as L
from ..operators import sampling as S
from ..operators.binning import binned, fit_bins
from ..operators.growth import functional_weights, root_histogram
from ..operators.model import Forest, fit_binned
from ..operators.reduction import reduce_features, selected_arrays
from ..operators.sparse import Sparse, fit_sparse, predict_sparse
from ..operators.spec import ForestSpec
from ..operators.voting import attach_weights, tree_predict, tree_predict_joins, vote, vote_regression
from ..plans import measures as M
from ..session import stored, table
from .forest_sql import Chain, forest_chain, out
from .training_sets import CHARGE, FLAG, LINE_ORDER, QUALITY, STATUS, TOXIC, TrainingSet

QUERIES: dict = {}
SQL: dict[str, str] = {}

#: The forest of the checked queries: small enough that SQL can grow it too.
SPEC = ForestSpec(n_trees=5, n_principal=3, n_selected=6, max_depth=2, layout="horizontal")


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


def rows_of(spark: SparkSession, sf_dir: str, data: TrainingSet):
    frame = data.frame(spark, sf_dir)
    frame = stored(frame, "features")
    rules = fit_bins(frame, list(data.features), SPEC.n_bins)
    return stored(binned(frame, rules, "row_id", "target"), "binned"), rules


def forest_of(spark: SparkSession, sf_dir: str, data: TrainingSet, spec: ForestSpec = SPEC) -> tuple[Forest, DataFrame]:
    rows, rules = rows_of(spark, sf_dir, data)
    return fit_binned(rows, rules, list(range(data.n_classes)), spec), rows


def whole_histogram(rows: DataFrame) -> DataFrame:
    return L.to_slices(rows).groupBy("feature_id", "bin", "target").agg(F.count("*").alias("c"))


def root_cells(spark: SparkSession, sf_dir: str, data: TrainingSet = QUALITY) -> DataFrame:
    rows, _ = rows_of(spark, sf_dir, data)
    w = S.poisson_weights(rows, SPEC.n_trees).where("w > 0").select("tree", "row_id", "w")
    cells = S.multiplexed(L.to_slices(rows), w).withColumn("node", F.lit(0).cast("bigint"))
    return I.histogram(cells, "classification", data.n_classes)


def root_gains(spark: SparkSession, sf_dir: str, data: TrainingSet = QUALITY) -> DataFrame:
    return I.gains(root_cells(spark, sf_dir, data), "classification", data.n_classes)


# rows, bins, slices

_chain = Chain(QUALITY)
_flag = Chain(FLAG)


@query(f"SELECT row_number() OVER (ORDER BY {', '.join(LINE_ORDER)}) - 1 AS row_id, {', '.join(LINE_ORDER[:4])} FROM lineitem")
def q_row_id(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").select(*LINE_ORDER)
    return L.dense_row_id(lines, list(LINE_ORDER)).select("row_id", *LINE_ORDER[:4])


def _bins(data):
    def run(spark, sf_dir):
        rows, rules = rows_of(spark, sf_dir, data)
        x = L.to_slices(rows).groupBy("feature_id", "bin").agg(F.count("*").alias("n"))
        return x

    return run


_BIN_SQL = "SELECT feature_id, bin, count(*) AS n FROM slices GROUP BY ALL"
QUERIES["q_bins_numeric"], SQL["q_bins_numeric"] = _bins(CHARGE), Chain(CHARGE).text(_BIN_SQL)
QUERIES["q_bins_categorical"], SQL["q_bins_categorical"] = _bins(STATUS), Chain(STATUS).text(_BIN_SQL)


@query("SELECT year(ts)::INTEGER AS year, month(ts)::INTEGER AS month, isodow(ts)::INTEGER AS weekday, hour(ts)::INTEGER AS hour, count(*) AS n FROM events GROUP BY ALL")
def q_bins_timestamp(spark, sf_dir):
    from ..functions.features import date_parts

    parts = date_parts(F.col("ts"))
    e = table(spark, sf_dir, "events").select(*[parts[p].alias(p) for p in ("year", "month", "weekday", "hour")])
    return e.groupBy("year", "month", "weekday", "hour").agg(F.count("*").alias("n"))


@query("SELECT (props->>'k')::BIGINT AS k, count(*) AS n FROM events GROUP BY ALL")
def q_bins_json(spark, sf_dir):
    from ..functions.features import json_number

    return table(spark, sf_dir, "events").groupBy(json_number(F.col("props"), "k").alias("k")).agg(F.count("*").alias("n"))


_CELL = "SELECT vec_id, unnest(range(len(embedding)))::INTEGER AS feature_id, unnest(embedding)::DOUBLE AS v, label FROM embeddings"


def _embedding_cells(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select("vec_id", "label", F.posexplode("embedding").alias("feature_id", "v"))


@query(f"SELECT feature_id, floor(v * 16)::INTEGER AS bin, count(*) AS n FROM ({_CELL}) GROUP BY ALL")
def q_bins_array(spark, sf_dir):
    cells = _embedding_cells(spark, sf_dir)
    return cells.groupBy("feature_id", F.floor(F.col("v").cast("double") * 16).cast("int").alias("bin")).agg(F.count("*").alias("n"))


@query(f"SELECT feature_id, label AS target, count(*) AS n, {out('avg(v)', 5)} AS mean FROM ({_CELL}) GROUP BY ALL")
def q_slices_embedding(spark, sf_dir):
    cells = _embedding_cells(spark, sf_dir)
    return cells.groupBy("feature_id", F.col("label").alias("target")).agg(F.count("*").alias("n"), rounded(F.avg(F.col("v").cast("double")), 5).alias("mean"))


@query(
    "SELECT ('0x' || substr(md5(w), 1, 8))::BIGINT % 256 AS feature, count(*) AS cells, sum(c)::BIGINT AS words FROM "
    "(SELECT doc_id, w, count(*) AS c FROM (SELECT doc_id, unnest(string_split(lower(text), ' ')) AS w FROM documents) WHERE w <> '' GROUP BY ALL) GROUP BY 1"
)
def q_slices_text(spark, sf_dir):
    words = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split(F.lower("text"), " ")).alias("w")).where("w <> ''")
    words = words.groupBy("doc_id", "w").agg(F.count("*").alias("c"))
    place = F.conv(F.substring(F.md5("w"), 1, 8), 16, 10).cast("bigint") % 256
    return words.groupBy(place.alias("feature")).agg(F.count("*").alias("cells"), F.sum("c").alias("words"))


_WIDE = ["l_quantity", "l_discount", "l_linestatus"]


@query("SELECT feature, value, target, count(*) AS n FROM (" + " UNION ALL ".join(f"SELECT '{f}' AS feature, {f}::VARCHAR AS value, l_returnflag AS target FROM lineitem" for f in _WIDE) + ") GROUP BY ALL")
def q_slices(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").withColumn("row_id", F.monotonically_increasing_id())
    return L.wide_to_slices(lines, _WIDE, "row_id", "l_returnflag").groupBy("feature", "value", "target").agg(F.count("*").alias("n"))


@query(_flag.text("SELECT feature_id, count(*) AS units, count(DISTINCT bin) AS bins, min(bin) AS low, max(bin) AS high FROM slices GROUP BY ALL"))
def q_slice_stats(spark, sf_dir):
    rows, _ = rows_of(spark, sf_dir, FLAG)
    return L.to_slices(rows).groupBy("feature_id").agg(F.count("*").alias("units"), F.countDistinct("bin").alias("bins"), F.min("bin").alias("low"), F.max("bin").alias("high"))


@query(_chain.text("SELECT row_id, bin, target FROM slices WHERE feature_id = 2"))
def q_slice_one(spark, sf_dir):
    rows, _ = rows_of(spark, sf_dir, QUALITY)
    return L.slice_of(L.to_slices(rows), 2).select("row_id", "bin", "target")


@query(_chain.text("SELECT feature_id, (row_id // 256)::INTEGER AS row_block, count(*)::INTEGER AS n FROM slices GROUP BY ALL"))
def q_slice_blocks(spark, sf_dir):
    rows, _ = rows_of(spark, sf_dir, QUALITY)
    return L.slice_blocks(L.to_slices(rows), 256).select("feature_id", "row_block", "n")


@query("SELECT 0 AS feature_id, o_orderpriority AS bin, count(*) AS n FROM orders GROUP BY ALL")
def q_append_slices(spark, sf_dir):
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("row_id"), F.lit(0).alias("target"), F.array("o_orderpriority").alias("bins"))
    old, new = orders.where("row_id % 3 <> 0"), orders.where("row_id % 3 = 0")  # the rows before, and those that come
    return L.append_slices(L.to_slices(old), new).groupBy("feature_id", "bin").agg(F.count("*").alias("n"))


@query(
    "WITH w AS (SELECT DISTINCT doc_id AS row_id, ('0x' || substr(md5(w), 1, 8))::BIGINT % 64 AS feature_id FROM (SELECT doc_id, unnest(string_split(lower(text), ' ')) AS w FROM documents) WHERE w <> ''), "
    "r AS (SELECT doc_id AS row_id, quality AS target FROM labels), c AS (SELECT * FROM w JOIN r USING (row_id)), t AS (SELECT target, count(*) AS n FROM r GROUP BY ALL), "
    "p AS (SELECT feature_id, target, count(*) AS c FROM c GROUP BY ALL), g AS (SELECT f.feature_id, t.target, t.n FROM (SELECT DISTINCT feature_id FROM c) f, t) "
    "SELECT feature_id, 1 AS bin, target, c FROM p UNION ALL SELECT feature_id, 0 AS bin, target, n - coalesce(c, 0) AS c FROM g LEFT JOIN p USING (feature_id, target) WHERE n - coalesce(c, 0) > 0"
)
def q_sparse_histogram(spark, sf_dir):
    words = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("row_id"), F.explode(F.split(F.lower("text"), " ")).alias("w")).where("w <> ''")
    place = F.conv(F.substring(F.md5("w"), 1, 8), 16, 10).cast("bigint") % 64
    cells = words.select("row_id", place.alias("feature_id"), F.lit(1).alias("bin")).distinct()
    return L.sparse_histogram(cells, table(spark, sf_dir, "labels").select(F.col("doc_id").alias("row_id"), F.col("quality").alias("target")))


# bootstrap samples

_N_ORDERS = "(SELECT count(*) FROM orders)"
_DRAWS = f"SELECT t.tree, d.draw, {mix_sql('d.draw', 't.tree')} % {_N_ORDERS} AS row_id FROM (SELECT range::INTEGER AS tree FROM range(3)) t, (SELECT range AS draw FROM range({_N_ORDERS})) d"
_PW = f"SELECT o_orderkey AS row_id, tree, {poisson_sql('o_orderkey', 'tree')} AS w FROM orders, (SELECT range::INTEGER AS tree FROM range(3))"


def _order_rows(spark, sf_dir):
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("row_id"))


def _order_draws(spark, sf_dir):
    return S.draws(spark, _order_rows(spark, sf_dir).count(), 3)


@query(_DRAWS)
def q_draws(spark, sf_dir):
    return _order_draws(spark, sf_dir)


@query(f"SELECT tree, count(*) AS draws, {out('sum(row_id * 1.0 * (draw % 97))')} AS mark FROM ({_DRAWS}) GROUP BY ALL")
def q_draw_arrays(spark, sf_dir):
    arrays = S.draw_arrays(_order_draws(spark, sf_dir))
    mark = F.aggregate(F.transform("rows", lambda r, i: r * 1.0 * (i % 97)), F.lit(0.0), lambda a, b: a + b)
    return arrays.select("tree", F.size("rows").cast("bigint").alias("draws"), rounded(mark).alias("mark"))


@query(f"SELECT tree, row_id, count(*) AS w FROM ({_DRAWS}) GROUP BY ALL")
def q_draw_weights(spark, sf_dir):
    return S.draw_weights(_order_draws(spark, sf_dir))


@query(_PW)
def q_poisson_weights(spark, sf_dir):
    return S.poisson_weights(_order_rows(spark, sf_dir), 3)


@query(f"SELECT tree, row_id FROM ({_PW}) WHERE w = 0")
def q_oob(spark, sf_dir):
    rows = _order_rows(spark, sf_dir)
    return S.oob(rows, S.poisson_weights(rows, 3), 3)


@query("SELECT range::INTEGER AS tree, 0::BIGINT AS \"both\", 0::BIGINT AS missing FROM range(3)")
def q_bag_invariants(spark, sf_dir):
    rows = _order_rows(spark, sf_dir)
    return S.check_bags(rows, S.poisson_weights(rows, 3), 3)


@query(f"SELECT tree, {out('avg((w = 0)::INTEGER::DOUBLE)')} AS oob_share, sum(w)::BIGINT AS drawn FROM ({_PW}) GROUP BY ALL")
def q_bag_share(spark, sf_dir):
    w = S.poisson_weights(_order_rows(spark, sf_dir), 3)
    return w.groupBy("tree").agg(rounded(F.avg((F.col("w") == 0).cast("double"))).alias("oob_share"), F.sum("w").alias("drawn"))


@query(
    f"SELECT tree, row_id % 8 AS block, {out('sum(w) / count(*)')} AS ratio FROM (SELECT row_id, tree, {drawn_sql('row_id', 'tree', 'mean')} AS w "
    f"FROM (SELECT o_orderkey AS row_id, count(*) OVER (PARTITION BY o_orderkey % 8) / {float(S.BLOCK_ROWS)} AS mean FROM orders), (SELECT range::INTEGER AS tree FROM range(3))) GROUP BY ALL"
)
def q_partition_sampling(spark, sf_dir):
    rows = _order_rows(spark, sf_dir).withColumn("block", F.col("row_id") % 8)
    return S.partition_weights(rows, 3, "block").groupBy("tree", "block").agg(rounded(F.sum("w") / F.count("*")).alias("ratio"))


# split scores on whole sets


def _whole_chain(data):
    c = Chain(data)
    c.whole()
    return c


_MEASURES = {
    "q_target_entropy": (I.target_entropy, "h_target"),
    "q_cond_entropy": (I.conditional_entropy, "h_cond"),
    "q_split_info": (I.split_info, "split_info"),
    "q_gain": (I.gain, "gain"),
    "q_gain_ratio": (I.gain_ratio, "gain_ratio"),
}


def _measure(f, name, data):
    def run(spark, sf_dir):
        rows, _ = rows_of(spark, sf_dir, data)
        return f(whole_histogram(rows)).select("feature_id", rounded(F.col(name)).alias(name))

    return run


for _suffix, _data in (("", FLAG), ("_docs", QUALITY)):
    for _name, (_f, _col) in _MEASURES.items():
        QUERIES[_name + _suffix] = _measure(_f, _col, _data)
        SQL[_name + _suffix] = _whole_chain(_data).text(f"SELECT feature_id, {out(_col)} AS {_col} FROM g")

_root = Chain(QUALITY)
_root.root()
_SCORES = ("h_target", "h_cond", "split_info", "gain", "gain_ratio", "gini")
_SCORE_SQL = ", ".join(f"{out(c)} AS {c}" for c in _SCORES)


@query(_root.text(f"SELECT tree, feature_id, n::DOUBLE AS n, {_SCORE_SQL} FROM g0"))
def q_gain_per_tree(spark, sf_dir):
    return root_gains(spark, sf_dir).select("tree", "feature_id", "n", *[rounded(F.col(c)).alias(c) for c in _SCORES])


@query(_root.text(f"SELECT tree, feature_id, {out('gain_ratio')} AS gain_ratio FROM g0"))
def q_multiplexed_gain(spark, sf_dir):
    """The draw table as copied rows must score as weights do."""
    rows, _ = rows_of(spark, sf_dir, QUALITY)
    w = S.poisson_weights(rows, SPEC.n_trees).where("w > 0").select("tree", "row_id", F.explode(F.sequence(F.lit(1), "w")).alias("draw"))
    cells = L.to_slices(rows).join(w, "row_id").withColumn("node", F.lit(0).cast("bigint")).withColumn("w", F.lit(1))
    g = I.gains(I.histogram(cells, "classification", 2), "classification", 2)
    return g.select("tree", "feature_id", rounded(F.col("gain_ratio")).alias("gain_ratio"))


_imp = Chain(QUALITY)
_imp.root()
_imp.importance("g0")


@query(_imp.text(f"SELECT tree, feature_id, {out('importance')} AS importance FROM imp"))
def q_importance(spark, sf_dir):
    return I.importance(root_gains(spark, sf_dir)).select("tree", "feature_id", rounded(F.col("importance")).alias("importance"))


_sel = Chain(QUALITY)
_sel.root()
_sel.select(3, 6)


def _selected(spark, sf_dir):
    return reduce_features(I.importance(root_gains(spark, sf_dir)), 3, 6)


@query(_sel.text("SELECT * FROM selected"))
def q_selected(spark, sf_dir):
    return _selected(spark, sf_dir)


@query(_sel.text("SELECT tree, rank, feature_id FROM selected WHERE origin = 'principal'"))
def q_reduce_topk(spark, sf_dir):
    return _selected(spark, sf_dir).where("origin = 'principal'").drop("origin")


@query(_sel.text("SELECT tree, rank, feature_id FROM selected WHERE origin = 'random'"))
def q_reduce_random(spark, sf_dir):
    return _selected(spark, sf_dir).where("origin = 'random'").drop("origin")


_NAMES = "[" + ", ".join(f"'{f}'" for f in QUALITY.features) + "]"


@query(_sel.text(f"SELECT tree, string_agg({_NAMES}[feature_id + 1], ',' ORDER BY rank) AS features FROM selected GROUP BY tree"))
def q_selected_arrays(spark, sf_dir):
    return selected_arrays(_selected(spark, sf_dir), list(QUALITY.features)).select("tree", F.array_join("features", ",").alias("features"))


@query(_root.text(f"SELECT tree, feature_id, {out('gini')} AS gini FROM g0 QUALIFY row_number() OVER (PARTITION BY tree ORDER BY round(gini, 10) DESC, feature_id) = 1"))
def q_gini_root(spark, sf_dir):
    return I.best_splits(root_gains(spark, sf_dir), "gini").select("tree", "feature_id", rounded(F.col("gini")).alias("gini"))


@query(_root.text("SELECT tree, feature_id, row_number() OVER (PARTITION BY tree ORDER BY round(gain, 10) DESC, feature_id)::INTEGER AS by_gain, row_number() OVER (PARTITION BY tree ORDER BY round(gain_ratio, 10) DESC, feature_id)::INTEGER AS by_ratio FROM g0"))
def q_info_gain_rank(spark, sf_dir):
    from pyspark.sql import Window

    rank = lambda c: F.row_number().over(Window.partitionBy("tree").orderBy(F.round(c, 10).desc(), "feature_id"))
    return root_gains(spark, sf_dir).select("tree", "feature_id", rank("gain").alias("by_gain"), rank("gain_ratio").alias("by_ratio"))


# trees

_two, _three = forest_chain(QUALITY, 2), forest_chain(QUALITY, 3)
_flag_two = forest_chain(FLAG, 2, n_principal=2, n_selected=4)
_classic = forest_chain(QUALITY, 2, reduction=False)
_gain = forest_chain(QUALITY, 2, criterion="gain")
_NODES = "SELECT tree, node, depth::INTEGER AS depth, n::DOUBLE AS n, feature_id::INTEGER AS feature_id, is_leaf, prediction FROM nodes"
_NODE_COLS = ["tree", "node", "depth", "n", "feature_id", "is_leaf", "prediction"]


@query(_two.text(f"SELECT tree, feature_id::INTEGER AS feature_id, {out('score')} AS score FROM best0"))
def q_root_split(spark, sf_dir):
    f, _ = forest_of(spark, sf_dir, QUALITY, SPEC.but(max_depth=1))
    return f.nodes.where("depth = 0 and not is_leaf").select("tree", "feature_id", rounded(F.col("score")).alias("score"))


@query(_two.text(f"SELECT tree, node, feature_id::INTEGER AS feature_id, {out('score')} AS score FROM best1"))
def q_level2_split(spark, sf_dir):
    f, _ = forest_of(spark, sf_dir, QUALITY)
    return f.nodes.where("depth = 1 and not is_leaf").select("tree", "node", "feature_id", rounded(F.col("score")).alias("score"))


@query(_two.text("SELECT n.tree, n.node, s.feature_id FROM n1 n JOIN selected s USING (tree) WHERE NOT EXISTS (SELECT 1 FROM path1 p WHERE p.tree = n.tree AND p.node = n.node AND p.feature_id = s.feature_id)"))
def q_candidates_l2(spark, sf_dir):
    f, _ = forest_of(spark, sf_dir, QUALITY, SPEC.but(max_depth=1))
    child, root = f.nodes.where("depth = 1"), f.nodes.where("depth = 0").select("tree", F.col("feature_id").alias("used"))
    return child.join(root, "tree").join(f.selected.select("tree", F.col("feature_id").alias("f")), "tree").where("f <> used").select("tree", "node", F.col("f").alias("feature_id"))


@query(_two.text(_NODES))
def q_tree_depth2(spark, sf_dir):
    f, _ = forest_of(spark, sf_dir, QUALITY)
    return f.nodes.select(*_NODE_COLS)


@query(_three.text(_NODES))
def q_tree_depth3(spark, sf_dir):
    f, _ = forest_of(spark, sf_dir, QUALITY, SPEC.but(max_depth=3))
    return f.nodes.select(*_NODE_COLS)


@query(_two.text(_NODES))
def q_tree_vertical(spark, sf_dir):
    """The same trees from slices and row-to-node tables."""
    f, _ = forest_of(spark, sf_dir, QUALITY, SPEC.but(layout="vertical"))
    return f.nodes.select(*_NODE_COLS)


@query(_two.text(_NODES))
def q_tree_blocks(spark, sf_dir):
    """The same trees from packed blocks."""
    f, _ = forest_of(spark, sf_dir, QUALITY, SPEC.but(layout="blocks"))
    return f.nodes.select(*_NODE_COLS)


@query(_flag_two.text(_NODES))
def q_tree_lines(spark, sf_dir):
    f, _ = forest_of(spark, sf_dir, FLAG, SPEC.but(n_principal=2, n_selected=4))
    return f.nodes.select(*_NODE_COLS)


def _grown(**change):
    """The same trees, or those of another specification, as a query."""

    def run(spark, sf_dir):
        f, _ = forest_of(spark, sf_dir, QUALITY, SPEC.but(**change))
        return f.nodes.select(*_NODE_COLS)

    return run


#: Ways to run that must not change the trees, and specifications whose trees SQL grows too.
_WAYS = {
    "q_tree_by_trees": {"parallel": "trees"}, "q_tree_by_features": {"parallel": "features"}, "q_tree_serial": {"parallel": "none"}, "q_tree_on_disk": {"state": "disk"},
    "q_tree_groups": {"tree_group": 2}, "q_tree_auto": {"layout": "auto"},
}
_OTHERS = {
    "q_tree_few_features": ({"n_principal": 2, "n_selected": 4}, {"n_principal": 2, "n_selected": 4}), "q_tree_shared_reduction": ({"reduction_scope": "shared"}, {"shared": True}),
    "q_tree_more_trees": ({"n_trees": 8}, {"n_trees": 8}), "q_tree_gini": ({"criterion": "gini"}, {"criterion": "gini"}), "q_tree_node_draw": ({"reduction": False, "feature_draw": "node", "n_selected": 4}, {"reduction": False, "node_features": 4}),
}
for _name, _change in _WAYS.items():
    QUERIES[_name], SQL[_name] = _grown(**_change), _two.text(_NODES)
for _name, (_change, _same) in _OTHERS.items():
    QUERIES[_name], SQL[_name] = _grown(**_change), forest_chain(QUALITY, 2, **_same).text(_NODES)


@query(_two.text(_NODES))
def q_tree_materialised(spark, sf_dir):
    """The baseline that writes and reads all state between steps."""
    rows, rules = rows_of(spark, sf_dir, QUALITY)
    return materialised.fit(rows, rules, [0, 1], SPEC).nodes.select(*_NODE_COLS)


@query(_chain.text("SELECT feature_id, bin, target, count(*) AS c FROM slices GROUP BY ALL"))
def q_slices_bucketed(spark, sf_dir):
    """Counts from slices saved as a table bucketed by feature."""
    name = L.persist_slices(L.to_slices(rows_of(spark, sf_dir, QUALITY)[0]))
    return spark.table(name).groupBy("feature_id", "bin", "target").agg(F.count("*").alias("c"))


@query(_chain.text("SELECT feature_id, bin, target, count(*) AS c FROM slices GROUP BY ALL"))
def q_slices_cached(spark, sf_dir):
    """Counts from slices held in memory, and on disk where that does not do."""
    held = L.cache_slices(L.to_slices(rows_of(spark, sf_dir, QUALITY)[0]))
    out_ = stored(held.groupBy("feature_id", "bin", "target").agg(F.count("*").alias("c")), "counts")
    held.unpersist()
    return out_


@query("SELECT doc_id, coalesce(source, (SELECT source FROM documents WHERE source IS NOT NULL GROUP BY source ORDER BY count(*) DESC, source LIMIT 1)) AS source FROM documents")
def q_imputed(spark, sf_dir):
    return filled(table(spark, sf_dir, "documents").select("doc_id", "source"), "source")


@query(f"SELECT fold, count(*) AS n FROM (SELECT {mix_sql('o_orderkey', '0', 7)} % 5 AS fold FROM orders) GROUP BY ALL")
def q_folds(spark, sf_dir):
    return table(spark, sf_dir, "orders").groupBy(fold(F.col("o_orderkey"), 5).alias("fold")).agg(F.count("*").alias("n"))


@query(_two.text("SELECT tree, depth::INTEGER AS depth, count(*) AS nodes, sum(is_leaf::BIGINT)::BIGINT AS leaves FROM nodes GROUP BY ALL"))
def q_forest_nodes(spark, sf_dir):
    f, _ = forest_of(spark, sf_dir, QUALITY)
    return f.nodes.groupBy("tree", "depth").agg(F.count("*").alias("nodes"), F.sum(F.col("is_leaf").cast("bigint")).alias("leaves"))


@query(_classic.text(_NODES))
def q_unreduced_forest(spark, sf_dir):
    f, _ = forest_of(spark, sf_dir, QUALITY, SPEC.but(reduction=False))
    return f.nodes.select(*_NODE_COLS)


@query(_gain.text(_NODES))
def q_info_gain_forest(spark, sf_dir):
    f, _ = forest_of(spark, sf_dir, QUALITY, SPEC.but(criterion="gain"))
    return f.nodes.select(*_NODE_COLS)


# prediction and votes


@query(_two.text("SELECT row_id, tree, prediction FROM votes"))
def q_tree_predict(spark, sf_dir):
    f, rows = forest_of(spark, sf_dir, QUALITY)
    return tree_predict(rows, f.node_list, SPEC.n_bins, "classification").select("row_id", "tree", "prediction")


@query(_two.text("SELECT row_id, tree, prediction FROM votes"))
def q_tree_predict_joins(spark, sf_dir):
    f, rows = forest_of(spark, sf_dir, QUALITY)
    return tree_predict_joins(rows.drop("target"), f.nodes, 2).select("row_id", "tree", "prediction")


@query(_two.text(f"SELECT tree, oob_rows, oob_correct, {out('ca')} AS ca FROM stats"))
def q_tree_accuracy(spark, sf_dir):
    f, _ = forest_of(spark, sf_dir, QUALITY)
    return f.tree_stats.withColumn("ca", rounded(F.col("ca")))


def _decided(kind: str, oob: bool = False, where: str = "", depth_chain=None):
    c = forest_chain(QUALITY, 2)
    c.decide(kind, oob, where)
    return c


@query(_decided("direct").text("SELECT row_id, prediction, score FROM decided"))
def q_vote_direct(spark, sf_dir):
    f, rows = forest_of(spark, sf_dir, QUALITY)
    return vote(attach_weights(tree_predict(rows, f.node_list, SPEC.n_bins, "classification"), f.tree_stats, "direct"))


@query(_decided("weighted").text(f"SELECT row_id, prediction, {out('score')} AS score FROM decided"))
def q_vote_weighted(spark, sf_dir):
    f, rows = forest_of(spark, sf_dir, QUALITY)
    return f.predict(rows).withColumn("score", rounded(F.col("score")))


@query(_decided("weighted").text(f"SELECT row_id, prediction, {out('score')} AS score FROM decided"))
def q_vote_table(spark, sf_dir):
    f, rows = forest_of(spark, sf_dir, QUALITY)
    return vote(f.votes(rows)).withColumn("score", rounded(F.col("score")))


def _both_votes():
    c = forest_chain(QUALITY, 2)
    c.decide("weighted", name="w")
    c.decide("direct", name="d")
    return c


@query(_both_votes().text("SELECT w.row_id, w.prediction AS weighted, d.prediction AS direct FROM w JOIN d USING (row_id) WHERE w.prediction <> d.prediction"))
def q_vote_diff(spark, sf_dir):
    f, rows = forest_of(spark, sf_dir, QUALITY)
    votes = stored(f.votes(rows), "votes")
    w, d = vote(votes), vote(votes.withColumn("weight", F.lit(1.0)))
    both = w.select("row_id", F.col("prediction").alias("weighted")).join(d.select("row_id", F.col("prediction").alias("direct")), "row_id")
    return both.where("weighted <> direct")


@query(_decided("weighted").text(f"SELECT {out('avg((prediction = target)::INTEGER::DOUBLE)')} AS accuracy, count(*) AS rows FROM decided"))
def q_accuracy(spark, sf_dir):
    """The flagship: text features, reduced weighted forest, accuracy on its own rows."""
    f, rows = forest_of(spark, sf_dir, QUALITY)
    d = f.predict(rows).join(rows.select("row_id", "target"), "row_id")
    return M.accuracy(d).withColumn("accuracy", rounded(F.col("accuracy")))


@query(_decided("weighted").text("SELECT target, sum((prediction = 0)::BIGINT)::BIGINT AS said_0, sum((prediction = 1)::BIGINT)::BIGINT AS said_1 FROM decided GROUP BY target"))
def q_confusion(spark, sf_dir):
    f, rows = forest_of(spark, sf_dir, QUALITY)
    d = f.predict(rows).join(rows.select("row_id", "target"), "row_id")
    return M.confusion(d, [0.0, 1.0]).toDF("target", "said_0", "said_1")


@query(
    _decided("weighted").text(
        "SELECT target::DOUBLE AS class, round(CASE WHEN named > 0 THEN hit / named ELSE 0 END, 6) + 0.0 AS precision, round(hit / n, 6) + 0.0 AS recall FROM "
        "(SELECT target, count(*) AS n, sum((prediction = target)::INTEGER) AS hit FROM decided GROUP BY target) LEFT JOIN (SELECT prediction AS target, count(*) AS named FROM decided GROUP BY prediction) USING (target)"
    )
)
def q_per_class(spark, sf_dir):
    f, rows = forest_of(spark, sf_dir, QUALITY)
    d = f.predict(rows).join(rows.select("row_id", "target"), "row_id")
    return M.per_class(d).select("class", rounded(F.col("precision")).alias("precision"), rounded(F.col("recall")).alias("recall"))


# out-of-bag error


def _oob_votes(spark, sf_dir):
    f, rows = forest_of(spark, sf_dir, QUALITY)
    return f.oob_votes(rows)


_oob = _decided("direct", oob=True)


@query(_oob.text(f"SELECT {out('1 - avg((prediction = target)::INTEGER::DOUBLE)')} AS oob_error, count(*) AS rows FROM decided"))
def q_oob_error(spark, sf_dir):
    return M.oob_curve(_oob_votes(spark, sf_dir), [SPEC.n_trees]).select(rounded(F.col("oob_error")).alias("oob_error"), "rows")


def _curve():
    c = forest_chain(QUALITY, 2)
    for t in range(1, SPEC.n_trees + 1):
        c.decide("direct", True, f"v.tree < {t}", f"d{t}")
    c.add("decided", " UNION ALL ".join(f"SELECT {t} AS first_t, * FROM d{t}" for t in range(1, SPEC.n_trees + 1)))
    return c


_curve_chain = _curve()
_ERR = out("1 - avg((prediction = target)::INTEGER::DOUBLE)")


@query(_curve_chain.text(f"SELECT first_t, {_ERR} AS oob_error, count(*) AS rows FROM decided GROUP BY ALL"))
def q_oob_curve(spark, sf_dir):
    return M.oob_curve(_oob_votes(spark, sf_dir), list(range(1, 6))).withColumn("oob_error", rounded(F.col("oob_error")))


@query(_curve_chain.text(f"SELECT first_t, target::DOUBLE AS target, {_ERR} AS oob_error, count(*) AS rows FROM decided GROUP BY first_t, decided.target"))
def q_oob_by_class(spark, sf_dir):
    return M.oob_error_by_class(_oob_votes(spark, sf_dir), list(range(1, 6))).withColumn("oob_error", rounded(F.col("oob_error")))


@query(_curve_chain.text(f"SELECT {out('max(e)')} AS max, {out('min(e)')} AS min, {out('avg(e)')} AS mean FROM (SELECT first_t, 1 - avg((prediction = target)::INTEGER::DOUBLE) AS e FROM decided GROUP BY first_t)"))
def q_curve_summary(spark, sf_dir):
    s = M.curve_summary(M.oob_curve(_oob_votes(spark, sf_dir), list(range(1, 6))))
    return s.select(*[rounded(F.col(c)).alias(c) for c in ("max", "min", "mean")])


@query(_curve_chain.text(f"SELECT first_t, {out('e - lag(e) OVER (ORDER BY first_t)')} AS step FROM (SELECT first_t, 1 - avg((prediction = target)::INTEGER::DOUBLE) AS e FROM decided GROUP BY first_t)"))
def q_convergence(spark, sf_dir):
    c = M.convergence(M.oob_curve(_oob_votes(spark, sf_dir), list(range(1, 6))))
    return c.select("first_t", rounded(F.col("step")).alias("step"))


# regression


def _regression_chain(depth: int = 1):
    """One level of variance-reducing splits of all rows' Poisson samples, by SQL."""
    c = Chain(CHARGE)
    c.weights()
    c.add("h", "SELECT tree, feature_id, bin, sum(w) AS s0, sum(w * s.target) AS s1 FROM slices s JOIN weights w USING (row_id) WHERE w > 0 GROUP BY ALL")
    c.add("g", "SELECT tree, feature_id, sum(s1 * s1 / s0) / sum(s0) - (sum(s1) / sum(s0)) * (sum(s1) / sum(s0)) AS gain FROM h GROUP BY ALL")
    c.add("best", "SELECT tree, feature_id, gain FROM g QUALIFY row_number() OVER (PARTITION BY tree ORDER BY gain DESC, feature_id) = 1")
    c.add("leaf", "SELECT h.tree, h.feature_id, h.bin, s1 / s0 AS prediction FROM h JOIN best USING (tree, feature_id)")
    c.add("votes", "SELECT w.row_id, w.target, w.tree, w.w, l.prediction FROM weights w JOIN best b USING (tree) JOIN slices s ON s.row_id = w.row_id AND s.feature_id = b.feature_id JOIN leaf l ON l.tree = w.tree AND l.bin = s.bin")
    c.add("tau", "SELECT 0.5 * stddev_pop(target) AS tau FROM bins")
    c.add("stats", "SELECT tree, avg((abs(prediction - target) <= tau)::INTEGER::DOUBLE) AS ca FROM votes, tau WHERE w = 0 GROUP BY tree")
    return c


_reg = _regression_chain()
_REG = SPEC.but(task="regression", max_depth=1, reduction=False)


def _regression(spark, sf_dir):
    return forest_of(spark, sf_dir, CHARGE, _REG)


@query(_reg.text("SELECT tree, feature_id, bin, round(prediction, 2) + 0.0 AS prediction FROM leaf"))
def q_regress_tree(spark, sf_dir):
    f, _ = _regression(spark, sf_dir)
    root = f.nodes.where("depth = 0").select("tree", F.col("feature_id").alias("f"))
    return f.nodes.where("depth = 1").join(root, "tree").select("tree", F.col("f").alias("feature_id"), F.col("in_bin").alias("bin"), rounded(F.col("prediction"), 2).alias("prediction"))


@query(_reg.text(f"SELECT tree, {out('ca')} AS ca FROM stats"))
def q_regress_accuracy(spark, sf_dir):
    f, _ = _regression(spark, sf_dir)
    return f.tree_stats.select("tree", rounded(F.col("ca")).alias("ca"))


@query(_reg.text("SELECT v.row_id, round(sum(ca * prediction) / 5, 2) + 0.0 AS prediction FROM votes v JOIN stats USING (tree) GROUP BY v.row_id"))
def q_regress_vote(spark, sf_dir):
    f, rows = _regression(spark, sf_dir)
    return vote_regression(f.votes(rows), normalise=False).withColumn("prediction", rounded(F.col("prediction"), 2))


@query(_reg.text("SELECT v.row_id, round(sum(ca * prediction) / sum(ca), 2) + 0.0 AS prediction FROM votes v JOIN stats USING (tree) GROUP BY v.row_id"))
def q_regress_vote_norm(spark, sf_dir):
    f, rows = _regression(spark, sf_dir)
    return f.predict(rows).select("row_id", rounded(F.col("prediction"), 2).alias("prediction"))


@query(_reg.text("SELECT round(sqrt(avg((p - target) * (p - target))), 2) + 0.0 AS rmse, round(avg(abs(p - target)), 2) + 0.0 AS mae FROM (SELECT v.row_id, any_value(v.target) AS target, sum(ca * prediction) / sum(ca) AS p FROM votes v JOIN stats USING (tree) GROUP BY v.row_id)"))
def q_rmse(spark, sf_dir):
    f, rows = _regression(spark, sf_dir)
    e = M.regression_error(f.predict(rows).join(rows.select("row_id", "target"), "row_id"))
    return e.select(rounded(F.col("rmse"), 2).alias("rmse"), rounded(F.col("mae"), 2).alias("mae"))


@query()
def q_cart_forest(spark, sf_dir):
    """Binary splits by Gini impurity, deeper than SQL follows."""
    f, rows = forest_of(spark, sf_dir, TOXIC, SPEC.but(tree="cart", max_depth=4))
    return f.nodes.select("tree", "node", "depth", "feature_id", "cut", "n", "prediction")


#: Hashed words of a document as features; a cell is binned by how often the word is there.
WORD_PLACES = 100_000


def word_cells(spark, sf_dir, places: int = WORD_PLACES):
    """Present cells (row_id, feature_id, bin) of the labelled documents' hashed words, and their rows (row_id, target)."""
    docs = table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id")
    words = hashed_words(docs, places).select("row_id", F.col("feature").alias("feature_id"), F.least(F.col("count"), F.lit(SPEC.n_bins - 1)).cast("int").alias("bin"))
    return stored(words, "cells"), stored(docs.select(F.col("doc_id").alias("row_id"), F.col("toxic").alias("target")), "rows")


@query()
def q_sparse_forest(spark, sf_dir):
    """Accuracy of a forest over 100,000 hashed words, of which a document has some hundred."""
    cells, rows = word_cells(spark, sf_dir)
    f = fit_sparse(cells, rows, WORD_PLACES, [0, 1], ForestSpec(n_trees=5, n_principal=100, n_selected=200, max_depth=3))
    return M.accuracy(predict_sparse(f, cells, rows).join(rows, "row_id"))


_sparse = Chain(QUALITY)
_sparse.weights()
_sparse.add("w8", "SELECT w.row_id, w.tree, w.w, l.toxic AS target FROM weights w JOIN labels l ON l.doc_id = w.row_id WHERE w.w > 0")
_sparse.add("cells", f"SELECT doc_id AS row_id, (('0x' || substr(md5(x), 1, 8))::BIGINT % 512)::INTEGER AS feature_id, least(count(*), {SPEC.n_bins - 1})::INTEGER AS bin FROM (SELECT doc_id, unnest(string_split(lower(text), ' ')) AS x FROM documents JOIN labels USING (doc_id)) WHERE x <> '' GROUP BY 1, 2")
_sparse.add("slices_", "SELECT w.row_id, w.tree, w.w, w.target, f.feature_id, coalesce(c.bin, 0) AS bin FROM w8 w CROSS JOIN (SELECT unnest(range(512))::INTEGER AS feature_id) f LEFT JOIN cells c ON c.row_id = w.row_id AND c.feature_id = f.feature_id")
_sparse.add("h0", "SELECT tree, 0::BIGINT AS node, feature_id, bin, target, sum(w) AS c FROM slices_ GROUP BY ALL")
_sparse.gains("h0", "g0")


@query(_sparse.text(f"SELECT tree, feature_id::INTEGER AS feature_id, {out('gain_ratio')} AS gain_ratio FROM g0 WHERE gain_ratio > 1e-7"))
def q_sparse_gain(spark, sf_dir):
    """Root scores from present cells only; SQL counts every cell."""
    cells, rows = word_cells(spark, sf_dir, 512)
    spec = SPEC.sized(512)
    source = Sparse(cells, rows, functional_weights(rows, list(range(spec.n_trees)), spec.seed), spec, 2, 512)
    g = I.gains(root_histogram(source, list(range(spec.n_trees)), 512, spec), "classification", 2)
    return g.where("gain_ratio > 1e-7").select("tree", "feature_id", rounded(F.col("gain_ratio")).alias("gain_ratio"))
