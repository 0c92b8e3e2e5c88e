"""Mixing sources to target weights: hash-random order in each source, prefix sums of sizes, exact cuts, epochs.

Each row gets a hash-random key. A source's keys are cut into as many equal ranges as it has RANGE_ROWS rows, so a hot
source spreads over many tasks; rows are ordered within a range, ranges within their source, and the two prefix sums
give each row the words that stand before it. A source gives whole epochs and then, of one more pass, exactly the
words its target still lacks; the document at the cut gives its first words.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import SPACED_WORD, stored, table

#: The weights that sources get in turn, and the largest multiple of a source's size it may give.
WEIGHTS, MOST = (5, 2, 1), 3
RANGE_ROWS = 4096


def words_in(text):
    return F.coalesce(F.regexp_count(text, F.lit(SPACED_WORD)), F.lit(0)).cast("bigint")


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST, share: float = 1.0) -> DataFrame:
    """source, source_size, rows, target from one row per source (source, source_size, rows).

    Sources in code-point order (null last) weigh weights in turn and share `share` of all sizes; a target stops at
    most * source_size and the excess goes to the others by weight until none is above. That level is found at once:
    with sources in order of most * size / weight, those below the level stop, the others get level * weight.
    One row per source is sorted in one task; sources are a catalogue, not data.
    """
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    turn = (F.row_number().over(by_name) - 1) % len(weights) + 1
    x = sizes.withColumn("w", F.element_at(F.array(*[F.lit(int(v)) for v in weights]), turn.cast("int")))
    x = x.withColumn("limit", F.col("source_size") * most).withColumn("full_at", F.col("limit") / F.col("w"))
    order = Window.orderBy("full_at", F.col("source").asc_nulls_last())
    ahead = order.rowsBetween(Window.unboundedPreceding, -1)
    rest = order.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    every = Window.partitionBy()
    x = x.withColumn("total", F.sum("source_size").over(every) * F.lit(float(share)))
    x = x.withColumn("level", (F.col("total") - F.coalesce(F.sum("limit").over(ahead), F.lit(0))) / F.sum("w").over(rest))
    x = x.withColumn("first", F.struct(F.row_number().over(order).alias("at"), "level"))  # the first below its own stop
    x = x.withColumn("level", F.min(F.when(F.col("level") < F.col("full_at"), F.col("first"))).over(every)["level"])
    target = F.when(F.col("level").isNull(), F.col("limit").cast("double")).otherwise(F.least(F.col("limit").cast("double"), F.col("level") * F.col("w")))
    return x.select("source", "source_size", "rows", target.alias("target"))


def mixed(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST, share: float = 1.0, carry: tuple | list = ()) -> DataFrame:
    """One row per row of docs (doc_id, text, source): doc_id, source, size, source_size, target, epochs, taken, and
    the columns of docs named in carry.

    size counts words between ASCII white space (null text: 0). Each row is taken `epochs` times whole and once more
    for taken - epochs * size words (0 for most). A source's taken words are its target without the fraction. The
    order is by a hash of doc_id and source, then doc_id, then size: reruns agree, and rows equal in these are
    interchangeable. A null source is a source of its own; sources without words get nothing; an empty table gives
    no rows; other columns play no part.
    """
    base = docs.select(*carry, "doc_id", "source", words_in(F.col("text")).alias("size"))
    base = stored(base.withColumn("key", F.md5(F.concat_ws("|", F.col("doc_id").cast("string"), "source").cast("binary"))), "sizes")
    sizes = base.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("rows"))
    goal = targets(sizes, weights, most, share).withColumn("ranges", F.ceil(F.col("rows") / RANGE_ROWS)).withColumn("s", F.coalesce(F.concat(F.lit("="), "source"), F.lit("")))
    goal = stored(goal.drop("source", "rows"), "goals")
    # keys are even, so their first 32 bits times the number of ranges is a range in key order
    upper = F.conv(F.substring("key", 1, 8), 16, 10).cast("bigint")
    placed = base.withColumn("s", F.coalesce(F.concat(F.lit("="), "source"), F.lit(""))).join(goal, "s")
    placed = placed.withColumn("range", F.floor(upper * F.col("ranges") / F.lit(2.0**32)).cast("bigint"))
    part = placed.groupBy("s", "range").agg(F.sum("size").alias("held"))
    before = F.sum("held").over(Window.partitionBy("s").orderBy("range").rowsBetween(Window.unboundedPreceding, -1))
    part = part.select("s", "range", F.coalesce(before, F.lit(0)).alias("before"))
    own = Window.partitionBy("s", "range").orderBy("key", F.col("doc_id").asc_nulls_last(), "size").rowsBetween(Window.unboundedPreceding, -1)
    out = placed.withColumn("within", F.coalesce(F.sum("size").over(own), F.lit(0))).join(part, ["s", "range"])
    epochs = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("bigint")
    left = F.floor(F.col("target") - F.col("epochs") * F.col("source_size")).cast("bigint")
    cut = F.greatest(F.lit(0), F.least(F.col("size"), F.col("left") - F.col("before") - F.col("within")))
    out = out.withColumn("epochs", epochs).withColumn("left", left)
    taken = (F.col("epochs") * F.col("size") + cut).cast("bigint")
    return out.select(*carry, "doc_id", "source", "size", "source_size", "target", "epochs", taken.alias("taken"))


def op1_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = mixed(table(spark, sf_dir, "documents").select("doc_id", "text", "source"))
    return out.select("doc_id", "size", "source_size", "target", "taken")


OP1_SQL = """
WITH d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS size FROM documents
), s AS (
  SELECT source, sum(size)::BIGINT AS source_size, [5, 2, 1][(row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 + 1] AS w FROM d GROUP BY source
), f AS (
  SELECT *, 3 * source_size AS most, 3 * source_size / w AS full_at, row_number() OVER o AS place,
    coalesce(sum(3 * source_size) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ahead,
    sum(w) OVER (o ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rest, sum(source_size) OVER () AS total
  FROM s WINDOW o AS (ORDER BY 3 * source_size / w, source ASC NULLS LAST)
), l AS (
  SELECT arg_min((total - ahead) / rest, place) AS level FROM f WHERE (total - ahead) / rest < full_at
), t AS (
  SELECT source, source_size, coalesce(least(most, level * w), most)::DOUBLE AS target FROM f CROSS JOIN l
), p AS (
  SELECT d.doc_id, d.size, t.source_size, t.target, CASE WHEN t.source_size > 0 THEN floor(t.target / t.source_size) ELSE 0 END AS epochs,
    coalesce(sum(d.size) OVER (PARTITION BY d.source ORDER BY md5(concat_ws('|', d.doc_id::VARCHAR, d.source)), d.doc_id, d.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source
)
SELECT doc_id, size, source_size, target, (epochs * size + greatest(0, least(size, floor(target - epochs * source_size) - before)))::BIGINT AS taken FROM p
"""
