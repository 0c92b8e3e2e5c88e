"""Joins that Spark has no single operator for: range, as-of and interval joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_join(points: DataFrame, at: str, spans: DataFrame, lo: str, hi: str, width: int) -> DataFrame:
    """points with the spans [lo, hi) that hold them: an equi-join on buckets of the given width, then the bounds. A
    span is copied to the buckets it touches, so width should be near the usual span."""
    bucket = lambda c: F.floor(c / width).cast("bigint")
    spread = spans.withColumn("__bucket", F.explode(F.sequence(bucket(F.col(lo)), bucket(F.col(hi) - 1))))
    x = points.withColumn("__bucket", bucket(F.col(at))).join(spread, "__bucket")
    return x.where((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("__bucket")


def asof_join(left: DataFrame, right: DataFrame, keys: list[str], at: str, values: list[str]) -> DataFrame:
    """left rows with the values of the last right row of their keys not after them: both sides are united and sorted
    once, and the last value seen is carried on; equal times count as before."""
    a = left.select(*left.columns, *[F.lit(None).cast(right.schema[v].dataType).alias(f"__{v}") for v in values], F.lit(1).alias("__left"))
    others = [F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns if c not in keys and c != at]
    b = right.select(*keys, at, *others, *[F.col(v).alias(f"__{v}") for v in values], F.lit(0).alias("__left"))
    w = Window.partitionBy(*keys).orderBy(at, "__left").rowsBetween(Window.unboundedPreceding, 0)
    x = a.unionByName(b)
    for v in values:
        x = x.withColumn(v, F.last(f"__{v}", ignorenulls=True).over(w))
    return x.where("__left = 1").select(*left.columns, *[v for v in values if v not in left.columns])


def within(left: DataFrame, right: DataFrame, keys: list[str], at: str, most: int) -> DataFrame:
    """Pairs of rows with equal keys where right's time is after left's by `most` at most; right's columns end in _r.
    Times are cut into buckets of `most`, so that a right row meets two buckets only."""
    r = right.toDF(*[f"{c}_r" for c in right.columns])
    bucket = lambda c: F.floor(c / most).cast("bigint")
    a = left.withColumn("__b", bucket(F.col(at)))
    b = r.withColumn("__b", F.explode(F.array(bucket(F.col(f"{at}_r")), bucket(F.col(f"{at}_r")) - 1)))
    on = [a[k] == b[f"{k}_r"] for k in keys] + [a["__b"] == b["__b"]]
    return a.join(b, on).where((F.col(f"{at}_r") > F.col(at)) & (F.col(f"{at}_r") <= F.col(at) + most)).drop("__b")


def plain_time(ts: Column) -> Column:
    """A time as text without trailing zeros of its fraction."""
    return ts.cast("string")
