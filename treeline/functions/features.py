"""Builders of training columns from text, dates, JSON, arrays, maps and pages."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Words that mark toxic texts in the given tables.
MARKERS = ("clown", "disgusting", "idiot", "loser", "moron", "pathetic", "scum", "stupid", "trash", "worthless")


def text_shape(text: Column) -> dict[str, Column]:
    """Cheap measures of a text; null texts give nulls. Runs of other characters go at once, and a named class
    is one lookup a character, a union of ranges many calls."""
    words = F.split(F.lower(text), " ")
    n, n_words = F.greatest(F.length(text), F.lit(1)), F.size(words)
    return {
        "len": F.length(text).cast("double"),
        "words": n_words.cast("double"),
        "distinct_ratio": F.size(F.array_distinct(words)) / n_words,
        "punct_share": F.length(F.regexp_replace(text, r"\P{Punct}+", "")) / n,
        "newlines": F.length(F.regexp_replace(text, r"[^\n]+", "")).cast("double"),
        "upper_share": F.length(F.regexp_replace(text, "[^A-Z]+", "")) / n,
        "marker": reduce(lambda a, b: a | b, [F.lower(text).contains(m) for m in MARKERS]).cast("double"),
    }


#: The same measures in DuckDB's SQL.
TEXT_SHAPE_SQL = {
    "len": "length(text)::DOUBLE",
    "words": "len(string_split(lower(text), ' '))::DOUBLE",
    "distinct_ratio": "len(list_distinct(string_split(lower(text), ' '))) / len(string_split(lower(text), ' '))",
    "punct_share": "length(regexp_replace(text, '[^!-/:-@\\[-`{-~]', '', 'g')) / greatest(length(text), 1)",
    "newlines": "length(regexp_replace(text, '[^\\n]', '', 'g'))::DOUBLE",
    "upper_share": "length(regexp_replace(text, '[^A-Z]', '', 'g')) / greatest(length(text), 1)",
    "marker": f"CASE WHEN regexp_matches(lower(text), '{'|'.join(MARKERS)}') THEN 1.0 ELSE 0.0 END::DOUBLE",
}


def hashed_words(docs: DataFrame, places: int, text: str = "text", row_id: str = "doc_id") -> DataFrame:
    """row_id, feature, count: words hashed (MD5) into places. Long and sparse: only places that occur."""
    words = docs.select(F.col(row_id).alias("row_id"), F.explode(F.split(F.lower(text), " ")).alias("word")).where("word <> ''")
    place = (F.conv(F.substring(F.md5("word"), 1, 8), 16, 10).cast("bigint") % places).cast("int")
    return words.groupBy("row_id", place.alias("feature")).agg(F.count("*").alias("count"))


def date_parts(ts: Column) -> dict[str, Column]:
    """Year to hour, ISO day of week (Monday 1) and days since 1970."""
    return {
        "year": F.year(ts),
        "quarter": F.quarter(ts),
        "month": F.month(ts),
        "weekday": F.weekday(ts) + 1,
        "hour": F.hour(ts),
        "epoch_day": F.datediff(ts, F.lit("1970-01-01").cast("date")),
    }


def json_number(props: Column, field: str) -> Column:
    return F.from_json(props, f"{field} BIGINT")[field]


def array_features(values: Column) -> dict[str, Column]:
    x = F.transform(values, lambda v: v.cast("double"))
    return {
        "norm": F.sqrt(F.aggregate(x, F.lit(0.0), lambda s, v: s + v * v)),
        "top": F.array_max(x),
        "argmax": F.array_position(x, F.array_max(x)).cast("int") - 1,
    }


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, v: s + v)


def page_features(url: Column, html: Column) -> dict[str, Column]:
    plain = F.regexp_replace(html, "<[^>]*>", " ")
    return {
        "lang": F.regexp_extract(html, r'<html lang="([a-z]+)"', 1),
        "links": F.regexp_count(html, F.lit("<a ")),
        "host": F.parse_url(url, F.lit("HOST")),
        "tld": F.regexp_extract(F.parse_url(url, F.lit("HOST")), r"\.([a-z]+)$", 1),
        "plain_len": F.length(plain),
    }


def filled(df: DataFrame, column: str, how: str = "mode") -> DataFrame:
    """Nulls of a column replaced by its mode, median or mean."""
    agg = {"mode": F.mode, "median": F.median, "mean": F.avg}[how](column)
    return df.crossJoin(F.broadcast(df.agg(agg.alias("__fill")))).withColumn(column, F.coalesce(column, "__fill")).drop("__fill")


def fold(row_id: Column, n: int, seed: int = 7) -> Column:
    """A row's fold from 0 to n - 1, by hash."""
    from .hashing import mix

    return (mix(row_id, F.lit(0), seed) % n).cast("int")
