"""A training corpus in five stages: toxicity, near duplicates, benchmark passages, personal data, source mix.

Each stage takes all rows that the stage before kept, written and read again as Parquet, and returns the columns of
documents; the last returns the mix: the rows it takes with source_size, target, epochs and taken words.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treeline.llm.common import drop_stored, noting, rows_in, shared_dir, table
from treeline.llm.decontaminate import decontaminated
from treeline.llm.mixing import mixed
from treeline.llm.near_dedup import near_duplicates
from treeline.llm.pii import with_surrogates
from treeline.llm.toxicity import TOXIC_FROM, fit_toxicity

#: Near duplicates: words of a shingle and percent of the union that two texts share.
SHINGLE, SIMILAR = 5, 80


#: What the stage before has stored and sent, and nothing reads once its output is written.
_left: dict[str, list] = {}


def _stage(f):
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        app = spark.sparkContext.applicationId
        drop_stored(spark, _left.pop(app, []))
        with noting([]) as kept:
            out = f(spark, docs, sf_dir)
        if f is not _last:
            _left[app] = kept
        return out

    run_stage.__doc__ = f.__doc__
    return run_stage


def _numbered(docs: DataFrame) -> tuple[DataFrame, str]:
    """Rows numbered by their place in the Parquet files that docs reads, alike in each scan of them (docs must be a plain
    scan, as every stage's is), and the name of the new column, which no column of docs has."""
    name = "__pipeline_row"
    while name in docs.columns:
        name += "_"
    return docs.withColumn(name, F.monotonically_increasing_id()), name


@_stage
def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents scored TOXIC_FROM or more by models learnt from the labelled documents; null texts stay."""
    names = [f"__{i}" if c != "text" else c for i, c in enumerate(docs.columns)]
    model = fit_toxicity(docs.select("doc_id", "text"), table(spark, sf_dir, "labels"))
    scored = model.score(docs.toDF(*names), keep_text=True)
    return scored.where(F.col("score") < TOXIC_FROM).select(*names).toDF(*docs.columns)


@_stage
def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps of each component the row with the least doc_id (null last); texts without words all stay."""
    rows, row = _numbered(docs)
    found = near_duplicates(rows.select(F.col(row).alias("doc_id"), "text"), SHINGLE, SIMILAR)
    ids = rows.select(row, F.col("doc_id").alias("id"))
    own = found.select(F.col("doc_id").alias(row), "component_id").join(ids, row)
    first = own.groupBy("component_id").agg(F.min(F.struct(F.col("id").isNull(), "id", row)).alias("first")).select(f"first.{row}")
    return rows_in(rows, first, row).select(*docs.columns)


@_stage
def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents in which a window of a benchmark item occurs."""
    names = [f"__{i}" if c != "text" else c for i, c in enumerate(docs.columns)]
    judged = decontaminated(docs.toDF(*names), table(spark, sf_dir, "benchmark"))
    return judged.where(~F.col("contaminated")).select(*names).toDF(*docs.columns)


@_stage
def private_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Puts surrogates in place of personal data in all texts."""
    names = [f"__{i}" if c != "text" else c for i, c in enumerate(docs.columns)]
    return with_surrogates(docs.toDF(*names)).select(*names).toDF(*docs.columns)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The rows that the mix takes: all columns, and size, source_size, target, epochs (whole passes), taken (words),
    which replace columns of docs by these names."""
    rows, row = _numbered(docs)
    taken = mixed(rows.select("doc_id", "text", "source", row), carry=[row]).where("taken > 0")
    new = ["size", "source_size", "target", "epochs", "taken"]
    return rows.select(*[c for c in rows.columns if c not in new]).join(taken.select(row, *new), row).drop(row)


#: Its result is the caller's, who may read it at any time: what it needs stays.
_last = mix
mix = _stage(mix)

STAGES = [
    ("toxicity", toxicity),
    ("near_dedup", near_dedup),
    ("decontaminate", decontaminate),
    ("private_data", private_data),
    ("mix", mix),
]

#: Model scores, components and keyed surrogates have no SQL twin; tests compare run() with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        path = f"{shared_dir(spark)}/treeline-stage-{name}-{uuid.uuid4().hex}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)


def queries() -> dict:
    return {"pipeline": run}


def oracle_sql() -> dict[str, str]:
    return {"pipeline": ORACLE_SQL} if ORACLE_SQL else {}
