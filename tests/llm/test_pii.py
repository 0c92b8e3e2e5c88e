"""Surrogates: coreference, check digits, long secrets, spaces that do not run out."""

import re

from pyspark.sql import functions as F

from treeline.llm import pii


def replaced(spark, texts, key="k"):
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return [r.text for r in pii.with_surrogates(docs, key).orderBy("doc_id").collect()]


def test_short_and_full_names_are_one_person(spark):
    a, b, c, d = replaced(spark, ["Mr. John Smith met us. Mr. Smith left.", "Dr. Anna Smith and Mrs. ANNA SMITH came", "John Smith and Mr John Smith", "Herr Smith, Frau Müller, Господин Иван Петров, Госпожа Петров"])
    full, short = re.match(r"Mr\. (\w+ \w+) met us\. Mr\. (\w+) left\.", a).groups()
    assert full.split()[1] == short != "Smith" and full.split()[0] in pii._GIVEN["latin", "m"]
    woman = re.match(r"Dr\. (\w+ \w+) and Mrs\. (\w+ \w+) came", b).groups()
    assert woman[0].upper() == woman[1] and woman[0].split()[1] == short and woman[0].split()[0] in pii._GIVEN["latin", "f"]
    assert c == f"{full} and Mr {full}"
    assert d.startswith(f"Herr {short}, Frau ") and "Müller" not in d
    given, family, alone = re.search(r"Господин (\w+) (\w+), Госпожа (\w+)", d).groups()
    assert family == alone != "Петров" and given in pii._GIVEN["cyrillic", "m"]


def luhn(digits):
    return sum(sum(divmod(int(x) * (1 + i % 2), 10)) for i, x in enumerate(reversed(digits))) % 10 == 0


def test_check_digits_stay_right(spark):
    cards, accounts = ["4111 1111 1111 1111", "5500-0000-0000-0004", "340000000000009"], ["DE89 3704 0044 0532 0130 00", "GB82WEST12345698765432"]
    wrong = "4111 1111 1111 1112"
    got = replaced(spark, [f"x {v} y" for v in [*cards, *accounts, wrong]])
    for old, new in zip(cards, got, strict=False):
        new = new[2:-2]
        assert re.sub(r"\d", "0", new) == re.sub(r"\d", "0", old) and new != old and luhn(re.sub(r"\D", "", new))
    for old, new in zip(accounts, got[3:], strict=False):
        new = new[2:-2]
        plain = new.replace(" ", "")
        assert re.sub("[0-9]", "0", re.sub("[A-Z]", "A", new)) == re.sub("[0-9]", "0", re.sub("[A-Z]", "A", old)) and new[:2] == old[:2]
        assert int("".join(str(int(c, 36)) for c in plain[4:] + plain[:4])) % 97 == 1
    assert "1112" not in got[5] or not got[5].startswith("x 4111")


def test_very_long_texts_and_secrets(spark):
    secret, filler = "aZ9-" * 2500, "word " * 60_000
    (got,) = replaced(spark, [f'{filler}token = "{secret}" {filler}Mrs. Jane Doe'])
    assert secret[:40] not in got and "Jane Doe" not in got and got.startswith(filler) and len(got) > 600_000
    assert len(re.search(r'token = "([^"]*)"', got)[1]) == len(secret)


def test_a_kind_that_runs_out_grows(spark):
    """More numbers than their layout has surrogates: all get different ones none the less."""
    texts = [f"call +1 {i // 100:02d} {i % 100:02d} now" for i in range(9_000)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    out = [r.text for r in pii.with_surrogates(docs, "k").collect()]
    assert len(set(out)) == 9_000
    named = pii.entities(docs, "k")
    assert named.agg(F.max("attempt")).first()[0] >= pii.WIDER and named.count() == 9_000 == named.select("surrogate").distinct().count()
    twice = docs.union(docs).withColumn("n_entities", F.lit("clash"))
    both = pii.with_surrogates(twice, "k")
    assert both.columns == ["doc_id", "text", "n_entities"] and both.groupBy("doc_id").agg(F.count_distinct("text").alias("c")).where("c <> 1").isEmpty()
    assert pii.with_surrogates(docs.limit(0)).count() == 0
