"""The experiment workloads: what they read, count and repeat."""

import numpy as np
import pyarrow as pa
import pytest
from conftest import same

from treeline.baselines import classic
from treeline.functions.features import text_shape
from treeline.functions.hashing import PRIME, mix_numpy, poisson_numpy
from treeline.operators import alike as A
from treeline.operators import growth as G
from treeline.operators import layout
from treeline.operators.model import fit_binned
from treeline.operators.spec import ForestSpec
from treeline.operators.voting import tree_accuracy
from treeline.plans import measures as M
from treeline.plans import workloads as W
from treeline.queries import plans, training_sets
from treeline.queries.training_sets import BAND, FLAG, QUALITY, STATUS, TOXIC, TrainingSet

SMALL = "/root/testdata/sf0.001"


def test_roots_are_counted_once_and_used_features_left_out(spark, monkeypatch):
    train, _, rules = W.split_rows(spark, SMALL, STATUS)
    seen, plain = [], G.Horizontal.histogram

    def histogram(self, nodes, live, candidates):
        out = plain(self, nodes, live, candidates)
        used = {(x.tree, x.node): x.used for x in live}
        seen.append((live[0].depth, sum(r.feature_id in used[r.tree, r.node] for r in out.collect())))
        return out

    monkeypatch.setattr(G.Horizontal, "histogram", histogram)
    fit_binned(train, rules, [0, 1, 2], ForestSpec(n_trees=2, max_depth=3))
    assert seen == [(0, 0), (1, 0), (2, 0)]


def test_parts_are_gathered():
    parts = [(np.arange(n), np.ones(n), np.zeros((n, 2), np.int32), {0: np.full(n, n)}) for n in (3, 4, 5, 1)]
    got = list(G.gathered(iter(parts), 16))
    assert [len(p[0]) for p in got] == [7, 6] and got[0][3][0].tolist() == [3] * 3 + [4] * 4
    assert got[1][2].shape == (6, 2)


def test_small_sets_are_spread_over_the_slots(spark):
    train, test, _ = W.split_rows(spark, SMALL, STATUS)
    assert train.rdd.getNumPartitions() >= min(4, spark.sparkContext.defaultParallelism)
    assert train.count() + test.count() == STATUS.frame(spark, SMALL).count()


def test_features_are_made_once_for_all_splits(spark, monkeypatch):
    made, plain = [], TrainingSet.frame
    monkeypatch.setattr(TrainingSet, "frame", lambda self, *a: made.append(self.name) or plain(self, *a))
    got = W.accuracy_by_trees(spark, SMALL, [1, 2], ["hybrid"], [TOXIC, STATUS], [42, 43]).collect()
    assert sorted(made) == ["status", "toxic"]
    assert [(r.target, r.seed, r.trees) for r in got] == [(t, s, n) for t in ("toxic", "status") for s in (42, 43) for n in (1, 2)]


def test_out_of_bag_counts_are_those_of_the_votes(spark):
    train, _, rules = W.split_rows(spark, SMALL, STATUS)
    f = fit_binned(train, rules, [0, 1, 2], W.SPEC.but(n_trees=6, max_depth=3))
    votes, sizes = f.oob_votes(train), list(range(1, 7))
    expect = {(r.first_t, r.target): (r.oob_error, r["rows"]) for r in M.oob_error_by_class(votes, sizes).collect()}
    got = {(r.first_t, r.target): (1 - r.right / r["rows"], r["rows"]) for r in f.oob_counts(train).collect()}
    assert got.keys() == expect.keys() and all(got[k] == pytest.approx(expect[k]) for k in got)
    curve = {r.scale: r for r in W.oob_by_trees(spark, SMALL, [2, 3], STATUS).where("class = -1").collect()}
    own = W.fit_binned(train, rules, [0, 1, 2], W.SPEC.but(n_trees=3)).oob_votes(train)
    for s in (2, 3):
        r = M.curve_summary(M.oob_curve(own, list(range(1, s + 1)))).first()
        assert (curve[s]["max"], curve[s]["min"], curve[s]["mean"]) == pytest.approx((r["max"], r["min"], r["mean"]))


@pytest.mark.parametrize("name", ["q_speedup", "q_startup_cost"])
def test_times_come_from_a_given_table(spark, duck, name):
    frame = plans.QUERIES[name](spark, SMALL)
    assert any("events.parquet" in f for f in frame.inputFiles())
    left, right = same(frame, duck, plans.SQL[name])
    assert left == right and len(left) == (5 if name == "q_startup_cost" else 40)


def test_tables_are_read_by_the_session_whose_slots_are_timed_elsewhere(spark, monkeypatch):
    import base64
    import pickle
    import subprocess

    rows = []

    def run(*args, input, **more):
        n, _, path, rules, classes, methods, trees = pickle.loads(base64.b64decode(input))
        rows.append((n, spark.read.parquet(path).count(), len(rules), classes, trees))
        return subprocess.CompletedProcess(args, 0, f"ROW {methods[0]} {n}.5\n", "")

    monkeypatch.setattr(subprocess, "run", run)
    assert W.time_by_slots(spark, SMALL, [1, 2], ["hybrid"], TOXIC, 3) == [(1, "hybrid", 1.5), (2, "hybrid", 2.5)]
    n = W.split_rows(spark, SMALL, TOXIC)[0].count()
    assert n > 0 and rows == [(1, n, len(TOXIC.features), 2, 3), (2, n, len(TOXIC.features), 2, 3)]


def test_features_are_made_once_for_all_partitions(spark, monkeypatch):
    made, plain = [], TrainingSet.frame
    monkeypatch.setattr(TrainingSet, "frame", lambda self, *a: made.append(self.name) or plain(self, *a))
    before = spark.conf.get("spark.sql.shuffle.partitions")
    got = W.communication(spark, SMALL, STATUS, ["horizontal"], [2, 4], 1).collect()
    assert made == ["status"] and [r.partitions for r in got] == [2, 4] and all(r.shuffle_write > 0 for r in got)
    assert spark.conf.get("spark.sql.shuffle.partitions") == before


def test_training_rows_and_sizes_of_batches(spark, monkeypatch):
    made, sizes, plain, fit = [], [], W.split_rows, W.fit_binned
    monkeypatch.setattr(W, "split_rows", lambda *a, **k: made.append(1) or plain(*a, **k))
    monkeypatch.setattr(W, "fit_binned", lambda *a, **k: sizes.append(spark.conf.get(W.BATCH_BYTES)) or fit(*a, **k))
    before = spark.conf.get(W.BATCH_BYTES)
    got = W.communication(spark, SMALL, STATUS, ["horizontal", "vertical"], [2, 4], 1).collect()
    assert len(made) == 1 and set(sizes) == {str(2**31 - 1)} and len(sizes) == 4 and len(got) == 4
    assert spark.conf.get(W.BATCH_BYTES) == before


def _trees(forest):
    return sorted((x.tree, x.depth, x.node, x.parent, x.feature_id, tuple(x.stats), round(x.score, 10)) for x in forest.node_list)


def test_rows_put_together_give_the_same_trees(spark):
    train, test, rules = W.split_rows(spark, SMALL, STATUS)
    assert A.put_together(train, 8, len(rules), 3, 4, 42) is None  # few are alike
    rows = W.stored(train.selectExpr("explode(sequence(0, 11)) AS copy", "*").selectExpr("row_id + copy * 1000003 AS row_id", "target", "bins"), "copies")
    spec = W.SPEC.but(n_trees=4, max_depth=3)
    alike = A.put_together(rows, 8, len(rules), 3, 4, 42)
    assert alike.count() == train.select("bins", "target").distinct().count() and alike.schema["target"].dataType == rows.schema["target"].dataType
    for fit in (fit_binned, classic.fit):
        one, other = fit(rows, rules, [0, 1, 2], spec), fit(rows, rules, [0, 1, 2], spec, alike=alike)
        assert _trees(one) == _trees(other) and len(one.node_list) > 100
        assert one.stats_rows == other.stats_rows and len(one.stats_rows) == 4
        assert sorted(one.predict(test).collect()) == sorted(other.predict(test).collect())
    with pytest.raises(ValueError):
        fit_binned(rows, rules, [0, 1, 2], spec.but(layout="vertical"), alike=alike)


@pytest.mark.parametrize("cells, more", [(2_000_000, {"reduction": False}), (800, {"tree": "cart"})])
def test_packed_slices_give_the_same_trees(spark, monkeypatch, cells, more):
    train, _, rules = W.split_rows(spark, SMALL, STATUS)
    train = train.selectExpr("row_id * 1000003 - 77 AS row_id", "target", "IF(row_id % 7 = 0, transform(bins, (b, i) -> IF(i = 0, -1, b)), bins) AS bins")
    monkeypatch.setattr(G, "BLOCK_CELLS", cells)
    joined = []
    monkeypatch.setattr(G.Vertical, "histogram", lambda *a: joined.append(1))
    spec = W.SPEC.but(n_trees=3, max_depth=3, **more)
    one, other = fit_binned(train, rules, [0, 1, 2], spec), fit_binned(train, rules, [0, 1, 2], spec.but(layout="vertical"))
    assert _trees(one) == _trees(other) and len(one.node_list) > 20 and not joined
    assert one.stats_rows == other.stats_rows
    assert one.stats_rows == [tuple(r) for r in tree_accuracy(one.oob_votes(train)).orderBy("tree").collect()]


def test_rows_of_a_kind_are_counted_as_one():
    r = np.random.default_rng(3)
    bins, y = r.integers(-1, 3, (5000, 3)).astype(np.int32), r.integers(0, 2, 5000)
    own, target, kind = G.kinds_of(bins, y, 4, 2)
    assert (own[kind] == bins).all() and (target[kind] == y).all()
    assert len(target) == len(np.unique(np.column_stack([bins, y]), axis=0)) and G.kinds_of(bins[:100], y[:100], 4, 2) is None

    def counted(bins, y):
        rows = np.arange(len(y))
        sent = type("Sent", (), {"value": ({}, {0: np.zeros(1, np.int64), 1: np.zeros(1, np.int64)}, {0: [0, 2], 1: [1]})})
        batch = pa.RecordBatch.from_pydict({"row_id": rows, "target": y, "bins": pa.array(bins.tolist(), pa.list_(pa.int32()))})
        return [tuple(x.values()) for part in G._block_histogram(sent, "classification", 2, 3, 42)(iter([batch])) for x in part.to_pylist()]

    got = sorted(counted(bins, y))
    whole = {}
    for t, fs in ((0, [0, 2]), (1, [1])):
        w = poisson_numpy(np.arange(5000), t, 42)
        for f in fs:
            for b in range(-1, 3):
                whole[t, 0, f, b] = tuple(float(w[(bins[:, f] == b) & (y == c)].sum()) for c in (0, 1))
    assert got == sorted(k + v for k, v in whole.items())


def test_predictions_keep_targets_and_first_trees(spark):
    train, test, rules = W.split_rows(spark, SMALL, STATUS)
    f = fit_binned(train, rules, [0, 1, 2], W.SPEC.but(n_trees=3, max_depth=3))
    got = f.predict(test, 2, with_target=True)
    assert sorted((r.row_id, r.target) for r in got.collect()) == sorted((r.row_id, r.target) for r in test.collect())
    f.node_list = [x for x in f.node_list if x.tree < 2]
    assert sorted(f.predict(test).collect()) == sorted(got.drop("target").collect())


def test_what_sets_have_in_common_is_made_once(spark, monkeypatch):
    made, measured, numbered = [], training_sets._measured, layout.dense_row_id
    monkeypatch.setattr(training_sets, "_measured", lambda *a: made.append("texts") or measured(*a))
    monkeypatch.setattr(layout, "dense_row_id", lambda *a: made.append("lines") or numbered(*a))
    got = W.accuracy_by_trees(spark, SMALL, [1], ["hybrid"], [QUALITY, FLAG, TOXIC, BAND], [42]).collect()
    assert sorted(made) == ["lines", "texts"] and [r.target for r in got] == ["quality", "flag", "toxic", "band"]
    bases = training_sets.shared_bases(spark, SMALL, [QUALITY, FLAG, TOXIC, BAND])
    for s in (QUALITY, TOXIC, FLAG):
        assert sorted(s.frame(spark, SMALL, bases).collect()) == sorted(s.frame(spark, SMALL).collect())


def test_a_hash_by_shifts_is_that_of_remainders():
    rows = np.array([0, 1, 5, PRIME - 1, PRIME, PRIME + 1, 2**40 + 3, 2**62, -7, *np.random.default_rng(1).integers(0, 2**62, 2000)])

    def plain(row: int, tree: int, seed: int) -> int:
        r = row % PRIME
        a = (r * 1000003 + tree * 7919 + 17 + seed) % PRIME
        b = (a * a % PRIME + tree * 104729 + r * 31 + 5) % PRIME
        c = (b * b % PRIME + tree * 15485863 + r + 11) % PRIME
        return c * c % PRIME

    for tree, seed in ((0, 42), (9, 43), (1000, 0)):
        assert mix_numpy(rows, tree, seed).tolist() == [plain(int(r), tree, seed) for r in rows]


def test_text_measures_count_single_characters(spark):
    from pyspark.sql import functions as F

    texts = ["".join(map(chr, range(1, 0x3000))), "", "a\U0001f600!B\n«»¿ ", "An IDIOT,\n\nsaid HE.", "ıİ--"]
    shape = text_shape(F.col("text"))
    frame = spark.createDataFrame([(t,) for t in texts], "text string").select("text", *[shape[c].alias(c) for c in ("punct_share", "newlines", "upper_share", "marker")])
    for r in frame.collect():
        n = max(1, len(r.text))
        assert r.punct_share == sum(33 <= ord(c) < 127 and not c.isalnum() for c in r.text) / n
        assert (r.newlines, r.upper_share) == (r.text.count("\n"), sum("A" <= c <= "Z" for c in r.text) / n)
        assert r.marker == float("idiot" in r.text.lower())
