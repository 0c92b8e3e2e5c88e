"""Extra columns with clashing names, repeated rows and empty tables, for every operator and pipeline stage; license
places and repeated passages against brute force."""

import re

import corpus_pipeline
import pytest
from pyspark.sql import functions as F

from treeline.llm import decontaminate, knn, licenses, mixing, near_dedup, passages, pii, quality, toxicity, warc

CLASH = ("n_words", "score", "n_entities", "size", "target", "taken", "component_id", "kept", "cls", "rid", "__row", "__found", "n_hit", "spans", "__pipeline_row")
PLAIN = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def lowered(t):
    return PLAIN.findall((t or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")))


def clashing(df, names=CLASH):
    return df.select("*", *[F.lit("clash").alias(n) for n in names if n not in df.columns])


@pytest.fixture(scope="module")
def docs(spark, small):
    return spark.read.parquet(f"{small}/documents.parquet").limit(60)


@pytest.fixture(scope="module")
def operators(spark, small):
    labels = spark.read.parquet(f"{small}/labels.parquet")
    grades = labels.select("doc_id", F.col("quality").alias("grade"))
    bench = spark.read.parquet(f"{small}/benchmark.parquet")
    every = spark.read.parquet(f"{small}/documents.parquet")
    tox, good = toxicity.fit_toxicity(every, labels), quality.fit_quality(every, grades, 2)
    return {
        "mix": lambda d: mixing.mixed(d).select("doc_id", "taken"),
        "toxicity": lambda d: tox.score(d).select("doc_id", F.round("score", 6)),
        "near": lambda d: near_dedup.near_duplicates(d),
        "surrogates": lambda d: pii.with_surrogates(d).select("doc_id", "text", "n_entities"),
        "decontaminate": lambda d: decontaminate.decontaminated(d, bench, keep=["doc_id"]),
        "licenses": lambda d: licenses.scanned(d),
        "quality": lambda d: good.score(d).select("doc_id", "tails"),
        "passages": lambda d: passages.marked(d),
    }


@pytest.mark.parametrize("name", ["mix", "toxicity", "near", "surrogates", "decontaminate", "licenses", "quality", "passages"])
def test_clashing_repeated_and_empty(docs, operators, name):
    run = operators[name]
    plain = sorted(map(str, run(docs).collect()))
    assert sorted(map(str, run(clashing(docs)).collect())) == plain
    twice = run(docs.union(docs))
    assert twice.count() == 2 * len(plain)
    if name != "mix":
        by: dict = {}
        for r in twice.collect():
            by.setdefault(r.doc_id, set()).add(str(r))
        assert all(len(v) == 1 for v in by.values())
    assert run(docs.limit(0)).count() == 0


def test_clashing_pages_and_vectors(spark, small):
    pages = spark.read.parquet(f"{small}/pages.parquet").limit(30)
    vectors = spark.read.parquet(f"{small}/embeddings.parquet").limit(120)
    names = ("payload", "digest", "record_type", "chunk", "cell", "x", "dim", "rank", "query_id")
    for run, df in ((lambda d: warc.round_trip(d) if hasattr(warc, "round_trip") else None, pages), (lambda d: knn.top_products(d, "vec_id % 50 = 0"), vectors)):
        if run(df) is not None:
            assert sorted(map(str, run(clashing(df, names)).collect())) == sorted(map(str, run(df).collect()))


@pytest.mark.parametrize("stage", [name for name, _ in corpus_pipeline.STAGES])
def test_stages_with_clashing_columns_and_empty_tables(spark, small, tmp_path, stage):
    run = dict(corpus_pipeline.STAGES)[stage]
    base = spark.read.parquet(f"{small}/documents.parquet").limit(80)
    clashing(base).write.parquet(f"{tmp_path}/rows")
    base.write.parquet(f"{tmp_path}/plain")
    rows, plain = spark.read.parquet(f"{tmp_path}/rows"), spark.read.parquet(f"{tmp_path}/plain")
    out = run(spark, rows, small)
    assert set(rows.columns) <= set(out.columns)
    got = out.collect()  # what a stage has stored goes once the next begins
    if stage != "mix":
        assert out.columns == rows.columns and all(r[c] == "clash" for r in got for c in CLASH)
    assert sorted(r.doc_id for r in got) == sorted(r.doc_id for r in run(spark, plain, small).select("doc_id").collect())
    base.limit(0).write.parquet(f"{tmp_path}/none")
    assert run(spark, spark.read.parquet(f"{tmp_path}/none"), small).count() == 0


def test_license_places_equal_brute_force(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    got = {r.doc_id: r for r in licenses.scanned(docs).collect()}
    phrases = [(label, text.split()) for label, text in licenses.PHRASES]
    for r in docs.select("doc_id", "text").collect():
        w = lowered(r.text)
        places = [(i, label) for label, p in phrases for i in range(len(w) - len(p) + 1) if w[i : i + len(p)] == p]
        g = got[r.doc_id]
        assert (g.n_words, g.n_base) == (len(w), len(places))
        assert (g.first_word, g.last_word) == ((min(places)[0], max(places)[0]) if places else (None, None))
        assert g.base_labels == ",".join(sorted({label for _, label in places}))
        assert set(g.base_labels.split(",")) - {""} <= set(g.labels.split(","))


def test_repeated_passages_are_found(spark):
    """Of all windows of 50 words that an earlier document has too, 95 % at least lie in marked spans."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text").dropDuplicates(["doc_id"])
    rows = sorted((r.doc_id, r.text or "") for r in docs.collect())
    spans = {r.doc_id: r.spans for r in passages.marked(docs).collect()}
    seen: set = set()
    repeated = held = 0
    for i, text in rows:
        raw = text.translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
        found = [(m.start(), m.end(), m.group()) for m in PLAIN.finditer(raw)]
        at = [0]
        for c in raw:
            at.append(at[-1] + len(c.encode()))
        own = []
        for j in range(len(found) - 49):
            key = hash(tuple(w for *_, w in found[j : j + 50]))
            own.append(key)
            if key in seen:
                repeated += 1
                a, b = at[found[j][0]], at[found[j + 49][1]]
                held += any(s.start <= a and b <= s.stop for s in spans[i])
        seen.update(own)
    assert repeated > 100 and held >= 0.95 * repeated
