"""License scans by diagonal voting, in DataFrame expressions only.

Every text's rolling word 3-grams are joined to the places where templates hold them; a template that stands in a text
puts its hits on one diagonal (text place minus template place). Votes are counted by diagonal, neighbouring diagonals
(words put in or left out) are merged, and a span counts if its verified grams cover enough of the template. Phrases
are templates that must be covered whole on one diagonal.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import PLAIN_WORD, ascii_lower, table

K = 3
#: Diagonals at most so far apart are one placement; a span may be so many times its template's length.
NEAR, STRETCH = 4, 1.5
#: Share of a template's grams that a span must hold for its label.
ENOUGH = 0.7
#: Up to so many template grams the table of grams is broadcast (about 100 bytes each) and a bit table sifts places first.
GRAMS_SENT = 100_000

#: Phrases whose every place counts, and their labels.
PHRASES = (
    ("mit", "under the mit license"),
    ("apache-2", "apache license version 2"),
    ("cc-by-nc", "cc by nc"),
)
#: Wording of common license notices, and their labels.
NOTICES = (
    ("mit", "released under the mit license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction"),
    ("apache-2", "licensed under the apache license version 2 0"),
    ("apache-2", "you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0"),
    ("cc-by-nc", "licensed under cc by nc 4 0"),
    ("cc-by-nc", "licensed under a creative commons attribution noncommercial 4 0 international license"),
    ("cc-by", "licensed under cc by 4 0"),
    ("cc-by-sa", "licensed under cc by sa 4 0"),
    ("cc-by", "licensed under a creative commons attribution 4 0 international license"),
    ("gpl-3", "this work is licensed under the gnu general public license version 3"),
    ("gpl", "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation"),
    ("lgpl", "under the terms of the gnu lesser general public license"),
    ("agpl-3", "licensed under the gnu affero general public license version 3"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("mpl-2", "this source code form is subject to the terms of the mozilla public license v 2 0"),
    ("unlicense", "this is free and unencumbered software released into the public domain"),
)


def _template_rows(phrases, notices) -> list[tuple]:
    rows = []
    for number, (base, label, text) in enumerate([(True, *p) for p in phrases] + [(False, *p) for p in notices]):
        words = re.findall(r"[0-9a-z\x80-\U0010ffff]+", text.lower())
        grams = [words[i : i + K] for i in range(len(words) - K + 1)]
        if not grams:
            raise ValueError(f"a template needs {K} words at least: {text!r}")
        rows += [(number, label, base, len(words), len(grams), i, *g) for i, g in enumerate(grams)]
    return rows


def _sieve(hashes: list[int]) -> tuple[list[int], int]:
    """A bit table, as longs, that holds the low bits of the hashes; so large that one place in 64 at most is set."""
    longs = 1024
    while longs < len(hashes) and longs < 1 << 16:
        longs *= 2
    table = [0] * longs
    for h in hashes:
        at = h & (64 * longs - 1)
        table[at >> 6] |= 1 << (at & 63)
    return [x - (1 << 64) if x >= 1 << 63 else x for x in table], longs


def scanned(docs: DataFrame, phrases=PHRASES, notices=NOTICES) -> DataFrame:
    """Per row of docs (doc_id, text): doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score.

    A-Z are lowered; words are runs of digits, letters and non-ASCII. n_base counts the places of all phrases,
    first_word and last_word are the least and greatest start (null if none), base_labels and labels are sorted and
    comma-joined (empty if none). score is the largest share of a notice that a span covers, 1 where a phrase stands.
    Null and empty texts have no words and score 0. Each row is judged by itself: repeated rows and null ids too.
    """
    spark = docs.sparkSession
    rows = spark.createDataFrame(_template_rows(phrases, notices), "template int, label string, base boolean, t_words int, t_grams int, t_at int, w0 string, w1 string, w2 string")
    rows = rows.select("template", "label", "base", "t_words", "t_grams", "t_at", F.xxhash64("w0", "w1", "w2").alias("h"), F.concat_ws(" ", "w0", "w1", "w2").alias("gram"))
    hashes = [r.h for r in rows.select("h").distinct().collect()]  # as many as templates have grams
    small = len(hashes) <= GRAMS_SENT
    texts = docs.select("doc_id", F.monotonically_increasing_id().alias("rid"), F.regexp_extract_all(ascii_lower(F.coalesce("text", F.lit(""))), F.lit(PLAIN_WORD), F.lit(0)).alias("words"))

    def gram_hash(i):
        return F.struct(i.alias("at"), F.xxhash64(F.col("words")[i], F.col("words")[i + 1], F.col("words")[i + 2]).alias("h"))

    places = F.transform(F.sequence(F.lit(0), F.size("words") - K), gram_hash)
    if small:
        bits, longs = _sieve(hashes)
        sieve = F.lit(bits)

        def known(x):
            at = x["h"].bitwiseAND(64 * longs - 1)
            return F.getbit(sieve[F.shiftright(at, 6).cast("int")], at.bitwiseAND(63).cast("int")) == 1

        places = F.filter(places, known)
    texts = texts.withColumn("places", F.when(F.size("words") >= K, places))
    found = F.transform("places", lambda x: F.struct(x["at"].alias("at"), x["h"].alias("h"), F.concat_ws(" ", F.slice(F.col("words"), x["at"] + 1, K)).alias("gram")))
    texts = texts.select("doc_id", "rid", F.size("words").cast("bigint").alias("n_words"), F.explode_outer(found).alias("p"))
    texts = texts.select("doc_id", "rid", "n_words", F.col("p.at").alias("at"), F.col("p.h").alias("h"), F.col("p.gram").alias("gram"))
    hits = texts.join(F.broadcast(rows) if small else rows, ["h", "gram"], "left")
    key = ["rid", "doc_id", "n_words"]
    votes = hits.groupBy(*key, "template", (F.col("at") - F.col("t_at")).alias("diagonal")).agg(
        F.any_value("label").alias("label"),
        F.any_value("base").alias("base"),
        F.any_value("t_words").alias("t_words"),
        F.any_value("t_grams").alias("t_grams"),
        F.collect_set("t_at").alias("at_template"),
        F.min("at").alias("first"),
        F.max("at").alias("last"),
    )
    by = Window.partitionBy("rid", "template").orderBy("diagonal")
    new = F.coalesce((F.col("diagonal") - F.lag("diagonal").over(by) > NEAR), F.lit(True)) | F.col("base")
    merged = votes.withColumn("group", F.sum(new.cast("int")).over(by)).groupBy(*key, "template", "group").agg(
        F.any_value("label").alias("label"),
        F.any_value("base").alias("base"),
        F.any_value("t_words").alias("t_words"),
        F.any_value("t_grams").alias("t_grams"),
        F.size(F.array_distinct(F.flatten(F.collect_list("at_template")))).alias("covered"),
        F.min("diagonal").alias("start"),
        (F.max("last") + K - F.min("first")).alias("span"),
    )
    place = F.col("base") & (F.col("covered") == F.col("t_grams"))
    cover = F.when(place, F.lit(1.0)).when(~F.col("base") & (F.col("span") <= F.col("t_words") * STRETCH), F.col("covered") / F.col("t_grams")).otherwise(F.lit(0.0))
    out = merged.withColumn("cover", cover).groupBy(*key).agg(
        F.count(F.when(place, 1)).alias("n_base"),
        F.min(F.when(place, F.col("start"))).cast("bigint").alias("first_word"),
        F.max(F.when(place, F.col("start"))).cast("bigint").alias("last_word"),
        F.array_join(F.array_sort(F.collect_set(F.when(place, F.col("label")))), ",").alias("base_labels"),
        F.array_join(F.array_sort(F.collect_set(F.when(F.col("cover") >= ENOUGH, F.col("label")))), ",").alias("labels"),
        F.coalesce(F.max("cover"), F.lit(0.0)).alias("score"),
    )
    return out.select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score")


def op7_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scanned(table(spark, sf_dir, "documents"))
