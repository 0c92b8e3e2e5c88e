"""The text operators against brute force, with nulls, empty and repeated rows, and empty tables."""

import hashlib
import re

import pytest
from pyspark.sql import functions as F

from treeline.llm import decontaminate, knn, licenses, mixing, near_dedup, passages, pii, quality, toxicity, warc
from treeline.llm.components import components

LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
SPACED, PLAIN = re.compile(r"[^\x20\x09-\x0D]+"), re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
DOCS = "doc_id long, text string, source string"


def words(t, pattern=PLAIN):
    return pattern.findall((t or "").translate(LOW))


def long_text(seed, n):
    out, x = [], seed
    for _ in range(n):
        x = (x * 1103515245 + 12345) % 2**31
        out.append(f"w{x % 997}")
    return out


@pytest.fixture(scope="module")
def docs(spark):
    base = long_text(7, 120)
    near = [*base]
    near[60] = "changed"
    rows = [
        (1, " ".join(base), "a"), (2, " ".join(base), "a"), (3, " ".join(near), "b"), (4, " ".join(long_text(9, 80)), "b"),
        (5, None, None), (6, "", "a"), (7, "one Two", "c"), (8, "ONE two", "c"), (9, " \n ", None), (10, "ÄÖ " * 30, "b"),
        (11, " ".join(long_text(11, 60) + base[:70] + long_text(13, 60)), "c"), (4, " ".join(long_text(9, 80)), "b"), (None, "x y z", "a"),
    ]
    return spark.createDataFrame(rows, DOCS)


def test_near_duplicates(docs):
    rows = [(r.doc_id, r.text) for r in docs.collect()]

    def shingles(t):
        w = words(t, SPACED)
        return {tuple(w[i : i + 4]) for i in range(max(1, len(w) - 3))} if w else set()

    sets = [shingles(t) for _, t in rows]
    root = list(range(len(rows)))
    for _ in rows:
        for i, a in enumerate(sets):
            for j, b in enumerate(sets):
                if a and b and 100 * len(a & b) >= 80 * len(a | b):
                    root[i] = root[j] = min(root[i], root[j])
    expect = []
    for i, (d, _) in enumerate(rows):
        ids = [rows[j][0] for j in range(len(rows)) if root[j] == root[i] and rows[j][0] is not None] if sets[i] else []
        c = min(ids) if ids else d
        expect.append((str(d), len(sets[i]), str(c), d == c))
    got = [(str(r.doc_id), r.n_shingles, str(r.component_id), r.kept) for r in near_dedup.near_duplicates(docs).collect()]
    assert sorted(got) == sorted(expect)
    assert near_dedup.near_duplicates(docs.limit(0)).count() == 0


def test_large_bucket_of_unlinked_copies(spark):
    """More near copies than SMALL, some too far from the leader: found block by block, as brute force finds them."""
    base = long_text(3, 150)
    rows = []
    for i in range(60):
        w = [*base]
        for k in range(i % 12):
            w[(i * 17 + k * 13) % 150] = f"z{i}x{k}"
        rows.append((i, " ".join(w)))
    sets = [{tuple(t.split()[i : i + 4]) for i in range(147)} for _, t in rows]
    root = list(range(60))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(60):
        for j in range(i):
            if 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    got = {r.doc_id: r.component_id for r in near_dedup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {i: find(i) for i in range(60)}


def test_components(spark):
    edges = [(i, i + 1) for i in range(30)] + [(100, 101), (102, 101), (5, 3)]
    got = {r.node: r.root for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**dict.fromkeys(range(31), 0), 100: 100, 101: 100, 102: 100}


@pytest.mark.parametrize("sent", [10**9, 0])
def test_decontamination(spark, docs, sent):
    items = [(1, " ".join(long_text(9, 80)[20:45])), (2, "two"), (3, None), (4, ""), (None, " ".join(long_text(7, 120)[5:20])), (1, "never seen words at all")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    windows = {}
    for i, t in items:
        w = words(t)
        for j in range(len(w) - min(10, len(w)) + 1 if w else 0):
            windows.setdefault(tuple(w[j : j + min(10, len(w))]), set()).add("null" if i is None else str(i))
    expect = []
    for r in docs.collect():
        w, hit, found = words(r.text), set(), set()
        for key, ids in windows.items():
            for j in range(len(w) - len(key) + 1):
                if tuple(w[j : j + len(key)]) == key:
                    hit |= set(range(j, j + len(key)))
                    found |= ids
        expect.append((str(r.doc_id), len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit)))
    got = decontaminate.decontaminated(docs, bench, broadcast_bytes=sent, keep=["doc_id"]).collect()
    assert sorted((str(r.doc_id), r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated) for r in got) == sorted(expect)
    assert decontaminate.decontaminated(docs, bench.limit(0)).where("contaminated").count() == 0


def test_licenses(spark):
    texts = ["Under the MIT License! under the mit license", None, "", "Apache License, Version 2.0", "CC-BY NC", "Licensed under the Apache License version 2", "mit", "Permission is hereby granted, free of charge, to any person who is obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction"]
    got = {r.doc_id: r for r in licenses.scanned(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert len(got) == len(texts)
    assert (got[0].n_base, got[0].first_word, got[0].last_word, got[0].base_labels) == (2, 0, 4, "mit")
    assert (got[1].n_words, got[1].n_base, got[1].first_word, got[1].labels) == (0, 0, None, "")
    assert got[3].base_labels == "apache-2" and got[4].base_labels == "cc-by-nc" and got[6].n_base == 0
    assert got[7].base_labels == "" and got[7].labels == "mit" and 0.7 <= got[7].score < 1


def test_mixing(spark, docs):
    got = mixing.mixed(docs).collect()
    sizes = {}
    for r in docs.collect():
        sizes[r.source] = sizes.get(r.source, 0) + len(words(r.text, SPACED))
    weights = {s: (5, 2, 1)[i % 3] for i, s in enumerate(sorted(sizes, key=lambda s: (s is None, s or "")))}
    total, full = sum(sizes.values()), {}
    while True:
        rest = [s for s in sizes if s not in full]
        level = (total - sum(full.values())) / sum(weights[s] for s in rest) if rest else 0
        above = [s for s in rest if level * weights[s] > 3 * sizes[s]]
        if not above:
            break
        full |= {s: 3 * sizes[s] for s in above}
    target = {s: full.get(s, level * weights[s]) for s in sizes}
    assert len(got) == docs.count()
    for s in sizes:
        own = [r for r in got if r.source == s]
        assert all(r.target == pytest.approx(target[s]) and r.source_size == sizes[s] and 0 <= r.taken <= 3 * r.size for r in own)
        assert abs(sum(r.taken for r in own) - target[s]) < 1
    again = mixing.mixed(docs.repartition(3)).collect()
    assert sorted(map(str, again)) == sorted(map(str, got))
    assert mixing.mixed(docs.limit(0)).count() == 0


def test_warc_round_trip(spark, tmp_path):
    big, one = "é" * 700_000, "x" * 1500
    rows = [(1, "http://a", big), (2, "http://b", one), (3, "http://c", one), (4, None, None), (5, "http://d\r\nX: y", "short"), (6, "u", "short"), (None, "n", one), (3, "http://c", one)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    warc.write_archive(pages, str(tmp_path / "a"), chunk_bytes=100_000)
    got = warc.read_archive(spark, str(tmp_path / "a")).collect()
    assert len(got) == len(rows) and all(r.intact for r in got)
    by = {}
    for r in got:
        by.setdefault(r.page_id, r)
    for i, _, html in rows:
        assert by[i].payload_digest == hashlib.sha1((html or "").encode()).hexdigest() and by[i].payload_bytes == len((html or "").encode())
    assert (by[2].record_type, by[2].refers_to, by[3].record_type, by[5].record_type, by[6].record_type) == ("revisit", 3, "response", "response", "response")
    assert spark.read.parquet(str(tmp_path / "a")).where("several = 'true'").groupBy("record_id").count().first()[1] == 14
    chunks = spark.read.parquet(str(tmp_path / "a")).withColumn("data", F.when((F.col("chunk_no") == 3) & (F.col("several") == "true"), F.lit(b"broken")).otherwise(F.col("data")))
    chunks.write.partitionBy("several").parquet(str(tmp_path / "b"))
    assert warc.read_archive(spark, str(tmp_path / "b")).where("not intact").count() == 1
    warc.write_archive(pages.limit(0), str(tmp_path / "c"))


def test_surrogates(spark):
    a = "Mail jo.doe@corp.example.com or +1 (212) 555-0134, card 4111 1111 1111 1111, ip 10.1.2.3. Mrs. Anna Smith, token = \"0123456789abcdef0123456789abcdef01234567\""
    texts = [a, "Again jo.doe@corp.example.com and 4111-1111-1111-1111; other jo.dot@corp.example.com", None, "", "nothing here 12", "ssn 123-45-6789 iban DE89370400440532013000", "two 7536784127813050 4845168114407329 cards"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r for r in pii.with_surrogates(docs, "k").collect()}
    assert got[2].text is None and got[3].text == "" and got[4].text == texts[4] and got[4].n_entities == 0
    for i, secret in ((0, "jo.doe"), (0, "555-0134"), (0, "4111"), (0, "10.1.2.3"), (0, "Anna"), (0, "0123456789abcdef"), (1, "jo.doe"), (5, "123-45"), (5, "DE8937"), (6, "7536784127813050"), (6, "4845168114407329")):
        assert secret not in got[i].text
    mail = lambda t: re.findall(r"\S+@\S+\.org", t)
    assert mail(got[0].text)[0] == mail(got[1].text)[0] != mail(got[1].text)[1]
    digits = lambda t: re.sub(r"\D", "", t)
    card = re.search(r"card ([\d ]{19})", got[0].text)[1]
    assert digits(card) == digits(re.search(r"(\d{4}-\d{4}-\d{4}-\d{4})", got[1].text)[1])
    assert "Mrs. " in got[0].text and re.search(r"\+1 \(\d{3}\) \d{3}-\d{4}", got[0].text)
    pii_map = pii.entities(docs, "k")
    assert pii_map.count() == pii_map.select("surrogate").distinct().count()
    inline = {r.doc_id: r.text for r in pii.with_surrogates(docs, "k").collect()}
    assert inline == {i: r.text for i, r in got.items()}
    assert pii.with_surrogates(docs, "other").where("doc_id = 0").first().text != got[0].text


def test_secrets_of_any_length_and_keys_of_letters(spark):
    token, key = "aB3x" * 100, "AKIA" + "QWERTYUIOPASDFGH"
    docs = spark.createDataFrame([(0, f'token = "{token}"'), (1, f"the key {key} is here"), (2, f"password: '{token[:200]}c'")], "doc_id long, text string")
    got = {r.doc_id: r for r in pii.with_surrogates(docs, "k").collect()}
    assert token[:20] not in got[0].text and key not in got[1].text and token[:20] not in got[2].text
    assert [got[i].n_entities for i in range(3)] == [1, 1, 1] and len(got[0].text) == len(docs.first().text)


def test_colliding_surrogates_are_keyed_anew(spark):
    texts = [f"Mr. Person{chr(97 + i % 26)}{chr(97 + i // 26)}" for i in range(120)] + ["Mr. Personaa and Mr. Personba"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    m = pii.entities(docs, "k")
    assert m.count() == 120 == m.select("surrogate").distinct().count()
    out = {r.doc_id: r.text for r in pii.with_surrogates(docs, "k").collect()}
    assert len({out[i] for i in range(120)}) == 120 and out[120] == f"{out[0]} and {out[1]}"


def test_top_products(spark):
    vec = lambda i: [((i * 37 + j * 11) % 29 - 14) / 10 for j in range(6)]
    rows = [(i, vec(i % 40)) for i in range(130)] + [(200, None), (201, [1.0, None, 1.0, 1.0, 1.0, 1.0]), (202, [float("nan")] * 6), (None, vec(1)), (50, vec(10)), (100, [1.0, 2.0])]
    got = knn.top_products(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), "vec_id % 50 = 0").collect()
    import numpy as np

    q = lambda v: np.floor(np.array(v, np.float32).astype(float) * 256)
    ok = {i: q(v) for i, v in rows[:130]}
    for query in (0, 50):
        best = sorted(((-int(ok[query] @ x), i) for i, x in ok.items() if i != query))[:5]
        assert [(r.vec_id, r.score) for r in sorted((r for r in got if r.query_id == query), key=lambda r: r.rank)] == [(i, -s) for s, i in best]
    assert knn.top_products(spark.createDataFrame([], "vec_id long, embedding array<float>"), "vec_id % 50 = 0").count() == 0


def test_passages(spark, docs):
    got = {r.doc_id: r for r in passages.marked(docs).collect()}
    assert got[1].n_spans == 0 or got[2].n_spans == 0
    assert sum(got[i].n_spans > 0 for i in (1, 2, 3, 11)) == 3 and got[4].n_spans == got[7].n_spans == got[5].n_spans == 0
    texts = {r.doc_id: (r.text or "").encode() for r in docs.collect()}
    for i, r in got.items():
        for s in r.spans:
            own = words(texts[i][s.start : s.stop].decode())
            assert len(own) == s.words >= 50
            there = words(texts[s.lead_id][s.lead_start :].decode())[: len(own)]
            assert sum(a == b for a, b in zip(own, there, strict=False)) >= 0.8 * len(own)
    assert passages.marked(docs.limit(0)).count() == 0


@pytest.mark.parametrize("every", [10, 15, 20])
def test_passages_with_changed_words(spark, every):
    rows, kept = [], {}
    for k in range(12):
        base = long_text(1000 + 17 * k, 300)
        base = [f"{w}k{k}" if i % 3 else f"{w}i{i}" for i, w in enumerate(base)]
        copy = [f"new{k}x{i}" if i % every == every // 2 else w for i, w in enumerate(base)]
        rows += [(k, " ".join(base)), (100 + k, " ".join(copy))]
        kept[100 + k] = len(" ".join(copy))
    got = {r.doc_id: r for r in passages.marked(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    share = {i: got[i].repeated_bytes / n for i, n in kept.items()}
    assert min(share.values()) >= 0.9
    assert all(len(got[i].spans) == 1 and got[i].spans[0].lead_id == i - 100 for i in kept)
    assert all(got[k].n_spans == 0 for k in range(12))


def test_parts_of_a_failing_chain_are_judged_alone(spark):
    rows, expect = [], {}
    for k, gap in enumerate((60, 100, 150)):
        one, two = [f"a{k}x{i}" for i in range(100)], [f"b{k}x{i}" for i in range(100)]
        rows += [(k, " ".join(one + two)), (100 + k, " ".join(one + [f"g{k}x{i}" for i in range(gap)] + two))]
        expect[100 + k] = len(" ".join(one)) + len(" ".join(two))
    got = {r.doc_id: r for r in passages.marked(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {i: got[i].repeated_bytes for i in expect} == expect and all(got[i].n_spans == 2 for i in expect)


@pytest.mark.parametrize("size", [30, 90, 400])
def test_passages_of_long_words_are_whole(spark, size):
    rows, expect = [], {}
    for k in range(8):
        word = lambda name: hashlib.sha512(name.encode()).hexdigest() * 4
        shared = " ".join(word(f"{k} {i}")[:size] for i in range(50 + k))
        around = [" ".join(word(f"{side} {k} {i}")[:size] for i in range(30)) for side in "abcd"]
        rows += [(k, f"{around[0]} {shared} {around[1]}"), (100 + k, f"{around[2]} {shared} {around[3]}")]
        expect[100 + k] = (len(around[2]) + 1, len(around[2]) + 1 + len(shared))
    got = {r.doc_id: r for r in passages.marked(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {i: [(s.start, s.stop) for s in got[i].spans] for i in expect} == {i: [v] for i, v in expect.items()}


def test_chains_and_common_subsequence():
    import numpy as np

    seg = np.array([[0, 0, 50], [60, 60, 50], [120, 300, 20], [130, 125, 60]])
    assert passages.chains(seg)[0] == [0, 1, 3]
    assert passages.common_in_order(list("abcbdab"), list("bdcaba")) == 4


def test_toxicity_learns_only_from_its_rows(spark):
    d, lab = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    model = toxicity.fit_toxicity(d, lab)
    got = model.score(d.select("doc_id", "text")).join(lab, "doc_id").where(toxicity.held_out(F.col("doc_id")))
    t, o = (got.where(f"toxic = {i}").agg(F.avg("score")).first()[0] for i in (1, 0))
    assert t > o + 0.3
    flipped = lab.withColumn("toxic", F.when(toxicity.held_out(F.col("doc_id")), 1 - F.col("toxic")).otherwise(F.col("toxic")))
    assert toxicity.fit_toxicity(d, flipped).weights == pytest.approx(model.weights)
    odd = spark.createDataFrame([(1, None), (2, ""), (None, "x"), (3, "w " * 5000)], "doc_id long, text string")
    assert all(0 <= r.score <= 1 for r in model.score(odd).collect())
    assert toxicity.fit_toxicity(odd, lab.limit(0)).score(odd).where("score < 0.01").count() == 4


def test_quality(spark):
    d, lab = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    train = lab.where(~toxicity.held_out(F.col("doc_id"))).select("doc_id", F.col("quality").alias("grade"))
    model = quality.fit_quality(d, train, 2)
    r = model.score(d.select("doc_id", "text")).join(lab, "doc_id").where(toxicity.held_out(F.col("doc_id")))
    assert r.agg(F.avg(((F.col("tails")[0] >= 0.5) == (F.col("quality") == 1)).cast("double"))).first()[0] > 0.9
    three = quality.fit_quality(d, lab.select("doc_id", (F.col("quality") + F.col("quality") * (1 - F.col("toxic"))).cast("int").alias("grade")), 3)
    assert list(three.thresholds) == sorted(three.thresholds)
    odd = spark.createDataFrame([(1, None), (2, "")], "doc_id long, text string")
    assert model.score(odd).count() == 2
    assert quality.fit_quality(d, train.limit(0), 2).score(odd).first().tails == [0.5]
