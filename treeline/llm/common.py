"""What the text operators share: the shared folder, table loading and row keys."""

from __future__ import annotations

import contextlib
import gc
import tempfile
import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Word patterns of the operators: words between ASCII white space, and runs of digits, letters and non-ASCII.
SPACED_WORD = r"[^\x20\x09-\x0D]+"
PLAIN_WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: PLAIN_WORD over text whose A-Z have not been lowered yet.
PLAIN_WORD_ANY_CASE = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or one of our own where it is unset."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        base = spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.split("[")[0] == "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = "file://" + tempfile.mkdtemp(prefix="treeline-")
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


def stored(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """Writes df to the shared folder and reads it back: cuts lineage, survives lost executors, keeps columns packed."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/treeline-{name}-{uuid.uuid4().hex}"
    writer = df.write
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    if _noted is not None:
        _noted.append(path)
    writer.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


_noted: list | None = None


def send(spark: SparkSession, value):
    """A broadcast of plain arrays (executors need no copy of the package to read it)."""
    out = spark.sparkContext.broadcast(value)
    if _noted is not None:
        _noted.append(out)
    return out


@contextlib.contextmanager
def noting(kept: list):
    """Notes in kept what stored() writes and send() sends meanwhile, for drop_stored() once nothing reads it."""
    global _noted
    before, _noted = _noted, kept
    try:
        yield kept
    finally:
        _noted = before


def drop_stored(spark: SparkSession, kept: list) -> None:
    """Deletes stored tables and broadcasts, and has the driver collect what hung on them: Spark's cleaner frees the
    shuffles and broadcasts of executors only once the driver's own garbage goes."""
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    for x in kept:
        if isinstance(x, str):
            at = jvm.org.apache.hadoop.fs.Path(x)
            at.getFileSystem(conf).delete(at, True)
        else:
            x.destroy()
    if kept:
        gc.collect()
        jvm.System.gc()


#: Bits of a bitmap of fixed size (8 MB).
BITMAP_BITS = 1 << 26


def bitmap(places: DataFrame) -> np.ndarray:
    """The bits at the places (column at, 0 to BITMAP_BITS - 1), packed: at most 2048 rows of 4 KB come to the driver."""
    at = places.select((F.col("at") + 1).alias("at"))  # places from 1 on fall into buckets from 1 on
    rows = at.groupBy(F.expr("bitmap_bucket_number(at)").alias("bucket")).agg(F.expr("bitmap_construct_agg(bitmap_bit_position(at))").alias("bits"))
    out = np.zeros(BITMAP_BITS // 8, np.uint8)
    for bucket, part in rows.collect():
        lo = (bucket - 1) * 4096
        out[lo : lo + len(part)] |= np.frombuffer(bytes(part), np.uint8)
    return out


#: Bitmaps of row numbers are sent to every task up to so many bytes (8 for each 16 rows or so at least).
BITMAPS_SENT = 64_000_000


def rows_in(rows: DataFrame, ids: DataFrame, key: str) -> DataFrame:
    """rows whose key, a monotonically_increasing_id of a scan, is among ids. One bit a row, by partition, goes to the
    rows, which stay where they are; beyond BITMAPS_SENT both sides are joined instead."""
    part, at = F.shiftrightunsigned(key, 33), F.col(key).bitwiseAND((1 << 33) - 1) + 1

    def cut(df: DataFrame) -> DataFrame:
        df = df.withColumn("__part", part).withColumn("__at", at)
        return df.withColumn("__bucket", F.expr("bitmap_bucket_number(__at)")).withColumn("__bit", F.expr("bitmap_bit_position(__at)"))

    maps = stored(cut(ids.select(key)).groupBy("__part", "__bucket").agg(F.expr("bitmap_construct_agg(__bit)").alias("__bits")), "bitmaps")
    if maps.count() * 4096 > BITMAPS_SENT:
        return rows.join(ids.select(key).distinct(), key, "left_semi").select(*rows.columns)
    byte = F.conv(F.hex(F.substring(F.col("__bits"), (F.col("__bit") / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    is_in = byte.bitwiseAND(F.pow(F.lit(2), F.col("__bit") % 8).cast("int")) != 0
    return cut(rows).join(F.broadcast(maps), ["__part", "__bucket"]).where(is_in).select(*rows.columns)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ascii_lower(col):
    """Lower-cases A-Z only, as far as ASCII words can tell. The Kelvin sign is the one other character whose lower
    case is ASCII; texts that hold it take the slower exact way."""
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    return F.when(F.contains(col, F.lit("K")), F.translate(col, upper, lower)).otherwise(F.lower(col))


#: Rows of an Arrow batch: texts and sets of hashes are large rows, and a worker holds a batch or two.
BATCH_ROWS = 2000


def small_batches(spark: SparkSession) -> None:
    """Lowers the session's Arrow batch size, where it is larger; it changes no result."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(name, "10000"))
    if now <= 0 or now > BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))


def n_parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
