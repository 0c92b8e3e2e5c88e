"""Formats, SQL functions and views."""

import pytest
from pyspark.sql import functions as F

from treeline.functions import udfs
from treeline.operators.model import fit_binned
from treeline.operators.spec import ForestSpec
from treeline.queries.forest import rows_of
from treeline.queries.training_sets import TOXIC
from treeline.sources import files


def test_formats(spark, tmp_path):
    df = spark.createDataFrame([(1, "a", 0.5), (2, None, 1.5)], "id long, name string, x double")
    for form in ("parquet", "orc", "json", "csv"):
        files.write(df, str(tmp_path / form), form)
        assert files.read(spark, str(tmp_path / form), form, df.schema.simpleString()[7:-1].replace(":", " ")).exceptAll(df).count() == 0
    with pytest.raises(ValueError):
        files.read(spark, "x", "xml?")


def test_sparse_round_trip(spark, tmp_path):
    rows = spark.createDataFrame([(0, 1, [0, 3, 0, 2]), (1, 0, [1, 0, 0, 0])], "row_id long, target int, bins array<int>")
    files.write_libsvm(rows, str(tmp_path / "s"))
    got = files.sparse_cells(files.read(spark, str(tmp_path / "s"), "libsvm", numFeatures="4"))
    assert sorted((r.target, r.feature_id, r.value) for r in got.collect()) == [(0.0, 0, 1.0), (1.0, 1, 3.0), (1.0, 3, 2.0)]


def test_sql_surface(spark):
    rows, rules = rows_of(spark, "/root/testdata/sf0.001", TOXIC)
    f = fit_binned(rows, rules, [0, 1], ForestSpec(n_trees=2, max_depth=2))
    udfs.register(spark, f, rows)
    rows.createOrReplaceTempView("binned")
    walked = spark.sql("SELECT b.row_id, w.tree, w.prediction FROM binned b, LATERAL walk_tree(b.bins) w")
    votes = spark.sql("SELECT row_id, tree, prediction FROM votes")
    assert walked.exceptAll(votes).count() == 0 and votes.count() == 2 * rows.count()
    r = spark.sql("SELECT entropy_of(target) AS h, gain_ratio_of(bins[6], target) AS g FROM binned").first()
    assert 0 < r.h <= 1 and 0 <= r.g <= 1
    assert spark.sql("SELECT count(*) FROM binned b, LATERAL slice_cells(b.bins) c").first()[0] == rows.count() * len(rules)
    assert spark.table("slices").agg(F.countDistinct("feature_id")).first()[0] == len(rules)
