"""Training sets from the given tables, as Spark frames and as SQL text."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.features import TEXT_SHAPE_SQL, text_shape
from ..session import stored, table


@dataclass(frozen=True)
class TrainingSet:
    name: str
    features: tuple[str, ...]
    strings: tuple[str, ...]
    target: str
    n_classes: int
    sql: str  # row_id, target and the features

    def frame(self, spark: SparkSession, sf_dir: str, bases: dict | None = None) -> DataFrame:
        """row_id, target and the features as columns; bases: what sets have in common, made once (shared_bases)."""
        return _FRAMES[self.name](spark, sf_dir, bases)


_SHAPE = tuple(TEXT_SHAPE_SQL)
_SHAPE_SQL = ", ".join(f"{sql} AS {name}" for name, sql in TEXT_SHAPE_SQL.items())


def _measured(docs: DataFrame) -> DataFrame:
    """docs with the measures of their texts."""
    return docs.select(*[c for c in docs.columns if c != "text"], *[c.alias(n) for n, c in text_shape(F.col("text")).items()])


def _texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stored(_measured(table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")), "texts")


def _documents(target: str):
    def frame(spark: SparkSession, sf_dir: str, bases: dict | None = None) -> DataFrame:
        labels = table(spark, sf_dir, "labels")
        docs = bases["texts"].join(labels, "doc_id") if bases and "texts" in bases else _measured(table(spark, sf_dir, "documents").join(labels, "doc_id"))
        return docs.select(F.col("doc_id").alias("row_id"), F.col(target).alias("target"), *_SHAPE, "lang", "source")

    return frame


def _documents_sql(target: str) -> str:
    return f"SELECT doc_id AS row_id, {target} AS target, {_SHAPE_SQL}, lang, source FROM documents JOIN labels USING (doc_id)"


LINE_ORDER = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_shipdate")
_LINE_ID = f"row_number() OVER (ORDER BY {', '.join(LINE_ORDER)}) - 1"


def _lines(spark: SparkSession, sf_dir: str, bases: dict | None = None) -> DataFrame:
    from ..operators.layout import dense_row_id

    if bases and "lines" in bases:
        return bases["lines"]
    cols = ["l_quantity", "l_discount", "l_tax", "l_extendedprice", "l_linenumber", "l_returnflag", "l_linestatus"]
    return dense_row_id(table(spark, sf_dir, "lineitem").select(*LINE_ORDER, "l_discount", "l_tax", "l_returnflag", "l_linestatus"), list(LINE_ORDER)).select("row_id", *cols)


def _flag(spark: SparkSession, sf_dir: str, bases: dict | None = None) -> DataFrame:
    flag = F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2)
    return _lines(spark, sf_dir, bases).select("row_id", flag.alias("target"), "l_quantity", "l_discount", "l_tax", "l_linenumber", "l_linestatus")


def _charge(spark: SparkSession, sf_dir: str, bases: dict | None = None) -> DataFrame:
    y = F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax"))
    return _lines(spark, sf_dir, bases).select("row_id", F.round(y, 2).alias("target"), "l_quantity", "l_discount", "l_tax", "l_extendedprice")


def _status(spark: SparkSession, sf_dir: str, bases: dict | None = None) -> DataFrame:
    status = F.when(F.col("o_orderstatus") == "F", 0).when(F.col("o_orderstatus") == "O", 1).otherwise(2)
    orders = table(spark, sf_dir, "orders").join(table(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    return orders.select(F.col("o_orderkey").alias("row_id"), status.alias("target"), "o_totalprice", F.month("o_orderdate").cast("double").alias("month"), "c_acctbal", "o_orderpriority", "c_mktsegment")


QUALITY = TrainingSet("quality", (*_SHAPE, "lang", "source"), ("lang", "source"), "quality", 2, _documents_sql("quality"))
TOXIC = TrainingSet("toxic", (*_SHAPE, "lang", "source"), ("lang", "source"), "toxic", 2, _documents_sql("toxic"))
FLAG = TrainingSet(
    "flag", ("l_quantity", "l_discount", "l_tax", "l_linenumber", "l_linestatus"), ("l_linestatus",), "l_returnflag", 3,
    f"SELECT {_LINE_ID} AS row_id, CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END AS target, l_quantity, l_discount, l_tax, l_linenumber::DOUBLE AS l_linenumber, l_linestatus FROM lineitem",
)
CHARGE = TrainingSet(
    "charge", ("l_quantity", "l_discount", "l_tax", "l_extendedprice"), (), "charge", 0,
    f"SELECT {_LINE_ID} AS row_id, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 2) AS target, l_quantity, l_discount, l_tax, l_extendedprice FROM lineitem",
)
STATUS = TrainingSet(
    "status", ("o_totalprice", "month", "c_acctbal", "o_orderpriority", "c_mktsegment"), ("o_orderpriority", "c_mktsegment"), "o_orderstatus", 3,
    "SELECT o_orderkey AS row_id, CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 ELSE 2 END AS target, o_totalprice, month(o_orderdate)::DOUBLE AS month, c_acctbal, o_orderpriority, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey",
)
#: Further stand-ins for the accuracy experiments, without SQL twins: the language by text shape, the quarter of a
#: line's price after discount (learnable by construction), the label of an embedding and the type of an event (noise).
LANGUAGES, EVENTS = ("en", "de", "fr", "es"), ("click", "view", "purchase", "error", "signup")
DIMENSIONS = 16


def _code(c, values):
    out = F.lit(len(values))
    for i, v in reversed(list(enumerate(values))):
        out = F.when(c == v, i).otherwise(out)
    return out


def _language(spark: SparkSession, sf_dir: str, bases: dict | None = None) -> DataFrame:
    kept = F.col("lang").isin(*LANGUAGES)
    docs = bases["texts"].where(kept) if bases and "texts" in bases else _measured(table(spark, sf_dir, "documents").where(kept))
    return docs.select(F.col("doc_id").alias("row_id"), _code(F.col("lang"), LANGUAGES).alias("target"), *_SHAPE, "source")


def _band(spark: SparkSession, sf_dir: str, bases: dict | None = None) -> DataFrame:
    price = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    lines = _lines(spark, sf_dir, bases)
    quarters = lines.agg(F.percentile_approx(price, [0.25, 0.5, 0.75], 10_000).alias("q"))
    band = F.size(F.filter("q", lambda q: q < price))
    return lines.crossJoin(F.broadcast(quarters)).select("row_id", band.alias("target"), "l_quantity", "l_discount", "l_tax", "l_extendedprice", "l_linenumber", "l_linestatus")  # one row


def _embedding(spark: SparkSession, sf_dir: str, bases: dict | None = None) -> DataFrame:
    dims = [F.col("embedding")[i].cast("double").alias(f"x{i}") for i in range(DIMENSIONS)]
    return table(spark, sf_dir, "embeddings").where("vec_id is not null and label is not null").select(F.col("vec_id").alias("row_id"), F.col("label").alias("target"), *dims)


def _event(spark: SparkSession, sf_dir: str, bases: dict | None = None) -> DataFrame:
    ts = F.col("ts")
    return table(spark, sf_dir, "events").select(
        F.col("event_id").alias("row_id"), _code(F.col("event_type"), EVENTS).alias("target"), "value", F.hour(ts).cast("double").alias("hour"),
        F.dayofweek(ts).cast("double").alias("weekday"), F.get_json_object("props", "$.k").cast("double").alias("k"), (F.col("user_id") % 64).cast("double").alias("user"),
    )


LANG = TrainingSet("lang", (*_SHAPE, "source"), ("source",), "lang", 5, "")
BAND = TrainingSet("band", ("l_quantity", "l_discount", "l_tax", "l_extendedprice", "l_linenumber", "l_linestatus"), ("l_linestatus",), "band", 4, "")
EMBEDDING = TrainingSet("embedding", tuple(f"x{i}" for i in range(DIMENSIONS)), (), "label", 10, "")
EVENT = TrainingSet("event", ("value", "hour", "weekday", "k", "user"), (), "event_type", 6, "")
EIGHT = (QUALITY, TOXIC, FLAG, STATUS, LANG, BAND, EMBEDDING, EVENT)

_FRAMES = {"lang": _language, "band": _band, "embedding": _embedding, "event": _event, "quality": _documents("quality"), "toxic": _documents("toxic"), "flag": _flag, "charge": _charge, "status": _status}

#: What several sets are made from: the sets, and how it is made.
_BASES = {
    "texts": (("quality", "toxic", "lang"), _texts),
    "lines": (("flag", "band", "charge"), _lines),
}


def shared_bases(spark: SparkSession, sf_dir: str, sets: list) -> dict[str, DataFrame]:
    """What two or more of the sets have in common: text measures, numbered lines."""
    names = [s.name for s in sets]
    shared = [(base, make) for base, (users, make) in _BASES.items() if sum(n in users for n in names) > 1]
    with ThreadPoolExecutor(max(1, len(shared))) as pool:
        return dict(pool.map(lambda x: (x[0], x[1](spark, sf_dir)), shared))
