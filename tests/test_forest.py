"""Layouts and prediction ways agree; forests learn; models are saved; streams match batches."""

import pytest
from pyspark.sql import functions as F

from treeline.baselines import materialised
from treeline.operators.layout import append_slices, persist_slices, slice_blocks, to_slices
from treeline.operators.model import Forest, fit_binned, vote_table
from treeline.operators.spec import ForestSpec
from treeline.plans import measures as M
from treeline.queries.forest import rows_of
from treeline.queries.training_sets import TOXIC

SPEC = ForestSpec(n_trees=4, n_principal=3, n_selected=6, max_depth=3)


@pytest.fixture(scope="module")
def data(spark):
    return rows_of(spark, "/root/testdata/sf0.01", TOXIC)


@pytest.fixture(scope="module")
def forest(data):
    return fit_binned(data[0], data[1], [0, 1], SPEC)


def shape(f):
    return sorted((x.tree, x.node, x.depth, x.is_leaf, -1 if x.is_leaf else x.feature_id, tuple(x.stats)) for x in f.node_list)


@pytest.mark.parametrize("change", [{"layout": "vertical"}, {"layout": "blocks"}, {"state": "disk"}, {"parallel": "trees"}, {"parallel": "none"}, {"tree_group": 2}])
def test_ways_to_grow_agree(data, forest, change):
    assert shape(fit_binned(data[0], data[1], [0, 1], SPEC.but(**change))) == shape(forest)


def test_copied_rows_are_draws(data):
    few = SPEC.but(n_trees=2, sampling="multinomial")
    assert shape(fit_binned(data[0], data[1], [0, 1], few.but(layout="vertical", sampling="copied"))) == shape(fit_binned(data[0], data[1], [0, 1], few))


def test_materialised_baseline(data, forest):
    assert shape(materialised.fit(data[0], data[1], [0, 1], SPEC)) == shape(forest)


def test_children_partition_their_parent_and_paths_do_not_repeat(forest):
    by = {(x.tree, x.node): x for x in forest.node_list}
    for x in forest.node_list:
        if not x.is_leaf:
            kids = [by[x.tree, c] for c in x.children.values()]
            assert [sum(s) for s in zip(*(k.stats for k in kids), strict=True)] == pytest.approx(x.stats)
            assert all(k.is_leaf or k.feature_id != x.feature_id for k in kids)


def test_learns_and_votes_alike(data, forest):
    rows, _ = data
    own = {r.row_id: r.prediction for r in forest.predict(rows).collect()}
    assert own == {r.row_id: r.prediction for r in vote_table(forest, rows).collect()}
    acc = M.accuracy(forest.predict(rows).join(rows, "row_id")).first().accuracy
    top = max(r["count"] for r in rows.groupBy("target").count().collect()) / rows.count()
    assert acc > top and all(0 <= r[3] <= 1 for r in forest.stats_rows)


def test_multinomial_and_explicit_weights(data):
    f = fit_binned(data[0], data[1], [0, 1], SPEC.but(sampling="multinomial", n_trees=2))
    assert {sum(x.stats) for x in f.node_list if x.depth == 0} == {float(data[0].count())}


def test_save_and_load(spark, data, forest, tmp_path):
    forest.save(str(tmp_path / "f"))
    again = Forest.load(spark, str(tmp_path / "f"))
    assert again.predict(data[0]).exceptAll(forest.predict(data[0])).count() == 0
    assert again.importance().agg(F.sum("importance")).first()[0] == pytest.approx(1)


def test_slices_bucketed_need_no_exchange(spark, data):
    name = persist_slices(to_slices(data[0]))
    plan = spark.table(name).groupBy("feature_id", "bin", "target").count()._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan
    spark.sql(f"DROP TABLE {name}")


def test_blocks_and_appended_slices(data):
    s = to_slices(data[0])
    assert slice_blocks(s, 128).agg(F.sum("n")).first()[0] == s.count()
    a, b = data[0].where("row_id % 2 = 0"), data[0].where("row_id % 2 = 1")
    assert append_slices(to_slices(a), b).exceptAll(s).count() == 0


def test_noise_target_stays_near_the_majority(spark):
    from treeline.plans.workloads import accuracy_by_trees
    from treeline.queries.training_sets import STATUS

    r = accuracy_by_trees(spark, "/root/testdata/sf0.01", [5], ["hybrid"], [STATUS], [42]).first()
    assert abs(r.accuracy - r.majority) < 0.05


def test_reduction_finds_the_marker(data, forest):
    marker = TOXIC.features.index("marker")
    assert all(r[2] == marker for r in forest.selected_rows if r[1] == 1)


def test_incremental_forest_replaces_trees(spark, data, tmp_path):
    from treeline.streaming.incremental import IncrementalForest

    rows, rules = data
    rows.repartitionByRange(3, "row_id").write.parquet(str(tmp_path / "rows"))
    inc = IncrementalForest(rules, [0, 1], SPEC.but(n_trees=3), fresh=1)
    inc.run(spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "rows")))
    assert len({x.tree for x in inc.forest.node_list}) == 3 and inc.history

