"""Bins: quantile or width cuts for numbers, dictionary codes for strings; null is bin -1."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


@dataclass
class BinRule:
    feature_id: int
    feature: str
    kind: str  # "numeric" or "string"
    cuts: list[float] = field(default_factory=list)
    codes: dict[str, int] = field(default_factory=dict)
    other: int = 0

    def column(self) -> Column:
        """The bin of the feature: the number of cuts below a number, the code of a string."""
        v = F.col(f"`{self.feature}`")
        if self.kind == "numeric":
            over = [(v.cast("double") > F.lit(float(c))).cast("int") for c in self.cuts]
            return F.when(v.isNull(), -1).otherwise(reduce(lambda a, b: a + b, over, F.lit(0)))
        out = F.when(v.isNull(), F.lit(-1))
        for value, code in self.codes.items():
            out = out.when(v == value, F.lit(code))
        return out.otherwise(F.lit(self.other))


def quantile_cuts(df: DataFrame, names: list[str], n_bins: int, exact: bool = True) -> dict[str, list[float]]:
    """n_bins - 1 cuts of each column in one pass; exact=False takes sketches, which is what large tables need."""
    shares = [i / n_bins for i in range(1, n_bins)]
    of = F.percentile if exact else (lambda c, p: F.percentile_approx(c, p, 10_000))
    row = df.agg(*[of(F.col(f"`{n}`").cast("double"), shares).alias(n) for n in names]).first()
    return {n: [float(x) for x in (row[n] or [])] for n in names}


def width_cuts(df: DataFrame, names: list[str], n_bins: int) -> dict[str, list[float]]:
    row = df.agg(*[F.struct(F.min(n).cast("double"), F.max(n).cast("double")).alias(n) for n in names]).first()
    return {n: [] if row[n][0] is None else [row[n][0] + (row[n][1] - row[n][0]) * i / n_bins for i in range(1, n_bins)] for n in names}


def dictionary_codes(df: DataFrame, names: list[str], n_bins: int) -> dict[str, dict[str, int]]:
    """For each column the n_bins - 1 most frequent values by (count desc, value asc), in one job; the rest share the
    last code."""
    cells = df.select(F.explode(F.array(*[F.struct(F.lit(n).alias("name"), F.col(f"`{n}`").alias("value")) for n in names])).alias("c")).select("c.*")
    top = cells.where("value is not null").groupBy("name", "value").agg(F.count("*").alias("c"))
    top = top.withColumn("code", F.row_number().over(Window.partitionBy("name").orderBy(F.desc("c"), "value")) - 1).where(F.col("code") < n_bins - 1)
    out: dict[str, dict[str, int]] = {n: {} for n in names}
    for r in top.orderBy("name", "code").collect():  # n_bins - 1 rows a column
        out[r["name"]][r["value"]] = r["code"]
    return out


def log_cuts(df: DataFrame, names: list[str], n_bins: int) -> dict[str, list[float]]:
    """Cuts of equal ratio between the least value above 0 and the largest; what is not above 0 is in the first bin."""
    row = df.agg(*[F.struct(F.min(F.when(F.col(n) > 0, F.col(n))).cast("double"), F.max(n).cast("double")).alias(n) for n in names]).first()
    ratio = {n: (row[n][1] / row[n][0]) ** (1 / n_bins) for n in names if row[n][0]}
    return {n: [row[n][0] * ratio[n] ** i for i in range(1, n_bins)] if n in ratio else [] for n in names}


def fit_bins(df: DataFrame, features: list[str], n_bins: int = 8, exact: bool = True, cuts: str = "quantile") -> list[BinRule]:
    kinds = dict(df.dtypes)
    numeric = [f for f in features if kinds[f] != "string"]
    by = {"quantile": lambda: quantile_cuts(df, numeric, n_bins, exact), "width": lambda: width_cuts(df, numeric, n_bins), "log": lambda: log_cuts(df, numeric, n_bins)}
    found = by[cuts]() if numeric else {}
    strings = [f for f in features if f not in found]
    codes = dictionary_codes(df, strings, n_bins) if strings else {}
    rules = []
    for i, f in enumerate(features):
        if f in found:
            rules.append(BinRule(i, f, "numeric", cuts=found[f]))
        else:
            rules.append(BinRule(i, f, "string", codes=codes[f], other=n_bins - 1))
    return rules


def binned(df: DataFrame, rules: list[BinRule], row_id: str, target: str | None) -> DataFrame:
    """row_id, target, bins: one array of bins per row."""
    cols = [F.col(row_id).cast("bigint").alias("row_id")]
    if target:
        cols.append(F.col(target).alias("target"))
    return df.select(*cols, F.array(*[r.column() for r in rules]).alias("bins"))


def spec_frame(spark, rules: list[BinRule]) -> DataFrame:
    rows = [(r.feature_id, r.feature, r.kind, r.cuts, r.codes) for r in rules]
    return spark.createDataFrame(rows, "feature_id int, feature string, kind string, cuts array<double>, codes map<string,int>")


def winsorised(df: DataFrame, name: str, lo: float = 0.01, hi: float = 0.99) -> DataFrame:
    a, b = df.agg(F.percentile(name, [lo, hi])).first()[0]
    return df.withColumn(name, F.least(F.greatest(F.col(name), F.lit(a)), F.lit(b)))
