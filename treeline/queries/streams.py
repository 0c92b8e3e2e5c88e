"""Registered queries on streams: files of events played as a stream, compared with the same over a batch."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..functions.math import rounded
from ..session import shared_dir, table
from ..streaming import incremental as N
from ..streaming import state as P
from ..streaming import windows as W
from .forest import SPEC, forest_of, rows_of
from .forest_sql import forest_chain, out
from .training_sets import QUALITY

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


def _stream(spark, sf_dir):
    """All events as a stream of files in order of time, and one late mark after them to close windows."""
    events = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")
    path = f"{shared_dir(spark)}/treeline-events-{uuid.uuid4().hex}"
    events.repartitionByRange(4, "ts").write.parquet(path)
    last = events.agg((F.max("ts") + F.expr("INTERVAL 10 DAYS")).alias("ts"))
    mark = last.select(F.lit(-1).cast("bigint").alias("event_id"), "ts", F.lit(-1).cast("bigint").alias("user_id"), F.lit("mark").alias("event_type"), F.lit(0.0).alias("value"))
    mark.coalesce(1).write.mode("append").parquet(path)
    return W.event_stream(spark, path, events.schema, 100), events


@query(f"SELECT user_id, strftime(time_bucket(INTERVAL 1 HOUR, ts), '%Y-%m-%d %H') AS hour, count(*) AS n, {out('avg(value)')} AS mean FROM events GROUP BY ALL")
def q_stream_hourly(spark, sf_dir):
    x = W.run_to_table(W.hourly(_stream(spark, sf_dir)[0]), name="hourly").where("user_id >= 0")
    return x.select("user_id", F.date_format("window.start", "yyyy-MM-dd HH").alias("hour"), "n", rounded(F.col("mean")).alias("mean"))


@query(
    "SELECT event_type, strftime(to_timestamp(s * 900) AT TIME ZONE 'UTC', '%Y-%m-%d %H:%M') AS start, count(*) AS n FROM "
    "(SELECT event_type, unnest(range(floor(epoch(ts) / 900)::BIGINT - 3, floor(epoch(ts) / 900)::BIGINT + 1)) AS s FROM events) GROUP BY ALL"
)
def q_stream_sliding(spark, sf_dir):
    x = W.run_to_table(W.sliding(_stream(spark, sf_dir)[0]), name="sliding").where("event_type <> 'mark'")
    return x.select("event_type", F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("start"), "n")


_SESSIONS = (
    "WITH m AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 30 MINUTE OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), "
    "g AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM m) "
    "SELECT user_id, n, count(*) AS sessions FROM (SELECT user_id, s, count(*) AS n FROM g GROUP BY ALL) GROUP BY ALL"
)


@query(_SESSIONS)
def q_stream_sessions(spark, sf_dir):
    x = W.run_to_table(W.sessions(_stream(spark, sf_dir)[0]), name="sessions").where("user_id >= 0")
    return x.groupBy("user_id", "n").agg(F.count("*").alias("sessions"))


@query("SELECT count(*) AS events, count(DISTINCT event_id) AS ids FROM events")
def q_stream_dedup(spark, sf_dir):
    s, _ = _stream(spark, sf_dir)
    x = W.run_to_table(W.distinct_events(s.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))), name="dedup").where("event_id >= 0")
    return x.agg(F.count("*").alias("events"), F.countDistinct("event_id").alias("ids"))


@query("SELECT b.event_id, count(*) AS clicks FROM events b JOIN events c ON c.user_id = b.user_id AND b.event_type = 'purchase' AND c.event_type = 'click' AND b.ts >= c.ts AND b.ts <= c.ts + INTERVAL 1 HOUR GROUP BY ALL")
def q_stream_join(spark, sf_dir):
    x = W.run_to_table(W.clicks_then_purchases(_stream(spark, sf_dir)[0]), name="join")
    return x.groupBy("event_id").agg(F.count("*").alias("clicks"))


@query(f"SELECT user_id, count(*) AS n, {out('avg(value)')} AS mean FROM events GROUP BY ALL")
def q_stream_state(spark, sf_dir):
    x = W.run_to_table(P.running_means(_stream(spark, sf_dir)[0]), "update", "state").where("user_id >= 0")
    last = x.groupBy("user_id").agg(F.max(F.struct("n", "mean")).alias("l"))
    return last.select("user_id", "l.n", rounded(F.col("l.mean")).alias("mean"))


def _row_stream(spark, rows):
    path = f"{shared_dir(spark)}/treeline-rows-{uuid.uuid4().hex}"
    rows.repartitionByRange(4, "row_id").write.parquet(path)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)


_scored = forest_chain(QUALITY, 2)
_scored.decide("weighted")


@query(_scored.text("SELECT row_id, prediction FROM decided"))
def q_stream_score(spark, sf_dir):
    f, rows = forest_of(spark, sf_dir, QUALITY)
    stream = _row_stream(spark, rows)
    from ..operators.voting import forest_predict

    scored = forest_predict(stream, f.node_list, SPEC.n_bins, "classification", f.accuracy_of(), 2)
    return W.run_to_table(scored, name="score").select("row_id", "prediction")


@query()
def q_stream_forest(spark, sf_dir):
    """Accuracy of each tree on rows it had not seen, batch by batch."""
    rows, rules = rows_of(spark, sf_dir, QUALITY)
    forest = N.IncrementalForest(rules, [0, 1], SPEC)
    forest.run(_row_stream(spark, rows))
    return spark.createDataFrame(forest.history, "batch int, tree int, accuracy double")
