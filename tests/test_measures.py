"""Formulas on hand-made frames."""

import pytest
from pyspark.sql import functions as F

from treeline.operators import impurity as I
from treeline.operators import sampling as S
from treeline.operators.reduction import reduce_features
from treeline.operators.spec import ForestSpec
from treeline.operators.voting import attach_weights, vote, vote_regression
from treeline.plans import allocation as A
from treeline.plans import cost as C
from treeline.plans import taskgraph as T


def scores(spark, rows):
    """feature values and binary targets -> gain table; rows: (feature_id, bin, target)."""
    h = spark.createDataFrame([(0, 0, f, b, t, 1) for f, b, t in rows], "tree int, node long, feature_id int, bin int, target int, w int")
    return {r.feature_id: r for r in I.gains(I.histogram(h, "classification", 2), "classification", 2).collect()}


def test_scores_of_perfect_constant_and_unique_features(spark):
    y = [0, 0, 0, 0, 1, 1, 1, 1]
    rows = [(0, t, t) for t in y] + [(1, 0, t) for t in y] + [(2, i, t) for i, t in enumerate(y)]
    g = scores(spark, rows)
    assert g[0].h_target == pytest.approx(1) and g[0].h_cond == pytest.approx(0) and g[0].gain_ratio == pytest.approx(1)
    assert g[1].split_info == pytest.approx(0) and g[1].gain_ratio == 0
    assert g[2].gain == pytest.approx(1) and g[2].split_info == pytest.approx(3) and g[2].gain_ratio == pytest.approx(1 / 3)


def test_importance_shares(spark):
    g = spark.createDataFrame([(0, 0, 1.0), (0, 1, 1 / 3), (0, 2, 0.0), (1, 0, 0.0), (1, 1, 0.0)], "tree int, feature_id int, gain_ratio double")
    v = {(r.tree, r.feature_id): r.importance for r in I.importance(g).collect()}
    assert v[0, 0] == pytest.approx(0.75) and v[0, 1] == pytest.approx(0.25) and v[0, 2] == 0 and v[1, 0] == pytest.approx(0.5)


def test_bags_are_disjoint_and_complete(spark):
    rows = spark.range(500).withColumnRenamed("id", "row_id")
    bad = S.check_bags(rows, S.poisson_weights(rows, 3), 3)
    assert bad.where("both > 0 or missing > 0").count() == 0
    d = S.draws(spark, 500, 3)
    assert {r[1] for r in d.groupBy("tree").count().collect()} == {500}
    assert S.draw_weights(d).agg(F.sum("w")).first()[0] == 1500


def test_out_of_bag_share(spark):
    rows = spark.range(20000).withColumnRenamed("id", "row_id")
    for r in S.poisson_weights(rows, 4).groupBy("tree").agg(F.avg((F.col("w") == 0).cast("double")), F.avg("w")).collect():
        assert abs(r[1] - 0.36788) < 5 * (0.36788 * 0.632 / 20000) ** 0.5 and abs(r[2] - 1) < 0.05


def test_selected_features_are_distinct_and_counted(spark):
    g = spark.createDataFrame([(t, f, 1.0 / (f + 1)) for t in range(4) for f in range(12)], "tree int, feature_id int, importance double")
    s = reduce_features(g, 3, 7).collect()
    for t in range(4):
        own = [r for r in s if r.tree == t]
        assert len({r.feature_id for r in own}) == 7 and [r.feature_id for r in own if r.origin == "principal"] == [0, 1, 2]


def test_votes(spark):
    v = spark.createDataFrame([(1, 0, 0.0), (1, 1, 1.0), (1, 2, 1.0)], "row_id long, tree int, prediction double")
    ca = spark.createDataFrame([(0, 0.9), (1, 0.4), (2, 0.4)], "tree int, ca double")
    assert vote(attach_weights(v, ca)).first().prediction == 0.0
    assert vote(attach_weights(v, ca, "direct")).first().prediction == 1.0
    r = spark.createDataFrame([(1, 0, 10.0), (1, 1, 20.0), (1, 2, 30.0)], "row_id long, tree int, prediction double")
    w = attach_weights(r, spark.createDataFrame([(0, 1.0), (1, 0.5), (2, 0.5)], "tree int, ca double"))
    assert vote_regression(w, normalise=False).first().prediction == pytest.approx(35 / 3)
    assert vote_regression(w).first().prediction == pytest.approx(17.5)


@pytest.mark.parametrize("policy", ["prefix", "first_fit"])
def test_placement(spark, policy):
    v = spark.createDataFrame([(0, 10), (1, 4), (2, 4), (3, 2)], "feature_id int, units long")
    k = A.workers(spark, [5, 5, 8, 2])
    kinds = {(r.feature_id, r.worker): r.scenario for r in A.scenario(A.allocate(v, k, policy), k).collect()}
    assert kinds == {(0, 0): "a", (0, 1): "a", (1, 2): "c", (2, 2): "c", (3, 3): "b"}


def test_task_graph_of_a_three_way_split(spark):
    nodes = spark.createDataFrame([(0, 0, -1, 0, True), (0, 1, 0, 1, True), (0, 2, 0, 1, True), (0, 3, 0, 1, True)], "tree int, node long, parent long, depth int, scored boolean")
    sel = spark.createDataFrame([(0, f) for f in range(4)], "tree int, feature_id int")
    path = spark.createDataFrame([(0, n, 0) for n in (1, 2, 3)], "tree int, node long, feature_id int")
    got = {(r.stage, r.kind): r["count"] for r in T.task_graph(nodes, sel, path).groupBy("stage", "kind").count().collect()}
    assert got == {(1, "score"): 4, (1, "split"): 1, (2, "score"): 9, (2, "split"): 3}


def test_costs(spark):
    cat = C.catalog(spark, [("x", 1000, 11)])
    v = {(r.model, r.trees): r.cells for r in C.volume(cat, [1, 2, 3, 10]).collect()}
    assert [v["copied", t] for t in (1, 2, 3, 10)] == [11000, 22000, 33000, 110000] and {v["paper", t] for t in (1, 2, 3, 10)} == {20000}
    assert C.volume_break_even(C.volume(cat, [1, 2, 3, 10])).where("model = 'paper'").first().trees == 2
    t = spark.createDataFrame([("a", 1, 100.0), ("a", 25, 4.0)], "method string, slots int, seconds double")
    assert C.speedup(t).where("slots = 25").first().speedup == pytest.approx(25)
    assert C.choose_layout(60000, 6, 4, 1, 8, 3, 5, 1, 8)[0] == "horizontal"


def test_spec_is_checked():
    assert ForestSpec().sized(9).n_selected == 6
    with pytest.raises(ValueError):
        ForestSpec(n_principal=5, n_selected=3).sized(9)
