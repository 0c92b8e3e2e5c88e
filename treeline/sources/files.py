"""Sources and sinks: training sets and results in the formats that Spark reads and writes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

FORMATS = ("parquet", "orc", "json", "csv", "text", "libsvm", "binaryFile")


def read(spark: SparkSession, path: str, form: str = "parquet", schema: str | None = None, **options: str) -> DataFrame:
    """A table in one of FORMATS. Give csv and json a schema: inferring one reads all data once more."""
    if form not in FORMATS:
        raise ValueError(f"{form!r} is none of {FORMATS}")
    reader = spark.read.options(**({"header": "true"} if form == "csv" else {}) | options)
    return (reader.schema(schema) if schema else reader).format(form).load(path)


def write(df: DataFrame, path: str, form: str = "parquet", by: list[str] | None = None, mode: str = "error", **options: str) -> None:
    writer = df.write.mode(mode).options(**({"header": "true"} if form == "csv" else {}) | options)
    (writer.partitionBy(*by) if by else writer).format(form).save(path)


def sparse_cells(libsvm: DataFrame) -> DataFrame:
    """row_id, target, feature_id, value from a sparse training set (label, features): only cells that are there."""
    from pyspark.ml.functions import vector_to_array

    rows = libsvm.select(F.monotonically_increasing_id().alias("row_id"), F.col("label").alias("target"), F.posexplode(vector_to_array("features")).alias("feature_id", "value"))
    return rows.where("value <> 0")


def write_libsvm(rows: DataFrame, path: str) -> None:
    """Binned rows (row_id, target, bins) as text 'label index:value ...' with indexes from 1; bin 0 is not written."""
    cell = F.transform("bins", lambda b, i: F.when(b != 0, F.concat((i + 1).cast("string"), F.lit(":"), b.cast("string"))))
    line = F.concat_ws(" ", F.col("target").cast("double").cast("string"), F.array_compact(cell))
    rows.select(line.alias("value")).write.text(path)
