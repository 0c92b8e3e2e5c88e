"""Accuracy measures: of predictions, of out-of-bag votes by the number of trees, and between methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def right() -> F.Column:
    return (F.col("prediction") == F.col("target")).cast("double")


def accuracy(decided: DataFrame) -> DataFrame:
    """accuracy, rows from prediction and target."""
    return decided.agg(F.avg(right()).alias("accuracy"), F.count("*").alias("rows"))


def accuracy_gap(grid: DataFrame, ours: str, other: str) -> DataFrame:
    """target-wise mean and best difference (points) of two methods over a grid (target, method, trees, accuracy), and the
    number of trees at the best."""
    a = grid.where(F.col("method") == ours).select("target", "trees", F.col("accuracy").alias("a"))
    b = grid.where(F.col("method") == other).select("target", "trees", F.col("accuracy").alias("b"))
    x = a.join(b, ["target", "trees"]).withColumn("gap", 100 * (F.col("a") - F.col("b")))
    return x.groupBy("target").agg(F.avg("gap").alias("mean_gap"), F.max("gap").alias("best_gap"), F.max_by("trees", "gap").alias("at_trees"))


def confusion(decided: DataFrame, classes: list) -> DataFrame:
    return decided.groupBy("target").pivot("prediction", classes).count().fillna(0)


def per_class(decided: DataFrame) -> DataFrame:
    """class, precision, recall, f1."""
    hit = F.sum(right())
    t = decided.groupBy(F.col("target").cast("double").alias("class")).agg(F.count("*").alias("n"), hit.alias("hit"))
    p = decided.groupBy(F.col("prediction").alias("class")).agg(F.count("*").alias("named"))
    x = t.join(p, "class", "left").fillna(0, ["named"])
    x = x.withColumn("precision", F.when(F.col("named") > 0, F.col("hit") / F.col("named")).otherwise(0.0)).withColumn("recall", F.col("hit") / F.col("n"))
    both = F.col("precision") + F.col("recall")
    return x.select("class", "precision", "recall", F.when(both > 0, 2 * F.col("precision") * F.col("recall") / both).otherwise(0.0).alias("f1"))


def regression_error(decided: DataFrame) -> DataFrame:
    e = F.col("prediction") - F.col("target")
    return decided.agg(F.sqrt(F.avg(e * e)).alias("rmse"), F.avg(F.abs(e)).alias("mae"), (1 - F.sum(e * e) / (F.var_pop("target") * F.count("*"))).alias("r2"))


def oob_decisions(votes: DataFrame, sizes: list[int], weighted: bool = False) -> DataFrame:
    """first_t, row_id, target, prediction by the out-of-bag votes of the first t trees, for each t of sizes. Each vote
    is copied to the sizes above its tree, then counted: no self-join, no pairs."""
    x = votes.withColumn("first_t", F.explode(F.array(*[F.lit(t) for t in sizes]))).where("tree < first_t")
    weight = F.col("weight") if weighted else F.lit(1.0)
    s = x.groupBy("first_t", "row_id", "target", "prediction").agg(F.round(F.sum(weight), 9).alias("s"))
    best = F.max_by("prediction", F.struct("s", -F.col("prediction")))
    return s.groupBy("first_t", "row_id", "target").agg(best.alias("prediction"))


def oob_curve(votes: DataFrame, sizes: list[int], weighted: bool = False) -> DataFrame:
    d = oob_decisions(votes, sizes, weighted)
    return d.groupBy("first_t").agg((1 - F.avg(right())).alias("oob_error"), F.count("*").alias("rows"))


def oob_error_by_class(votes: DataFrame, sizes: list[int], weighted: bool = False) -> DataFrame:
    d = oob_decisions(votes, sizes, weighted)
    return d.groupBy("first_t", "target").agg((1 - F.avg(right())).alias("oob_error"), F.count("*").alias("rows"))


def curve_summary(curve: DataFrame, value: str = "oob_error", by: list[str] | None = None) -> DataFrame:
    return curve.groupBy(*(by or [])).agg(F.max(value).alias("max"), F.min(value).alias("min"), F.avg(value).alias("mean"))


def convergence(curve: DataFrame, value: str = "oob_error") -> DataFrame:
    """curve with step: the change from the point before."""
    return curve.withColumn("step", F.col(value) - F.lag(value).over(Window.orderBy("first_t")))


def generalisation_gap(train: DataFrame, test: DataFrame) -> DataFrame:
    a, b = accuracy(train).select(F.col("accuracy").alias("train")), accuracy(test).select(F.col("accuracy").alias("test"))
    return a.crossJoin(b).withColumn("gap", F.col("train") - F.col("test"))  # one row each


def log_loss(scored: DataFrame) -> DataFrame:
    p = F.least(F.greatest(F.col("p"), F.lit(1e-12)), F.lit(1 - 1e-12))
    return scored.agg(F.avg(F.when(F.col("target") == 1, -F.log(p)).otherwise(-F.log(1 - p))).alias("log_loss"))
