"""The toxicity model against a plain-Python one, and its ways for large models."""

import collections
import math
import re
import subprocess
import sys
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from treeline.llm import toxicity

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def spelt(word):
    """(context, step) of every letter: a context is what the step sees before it."""
    letters = [*word, "END"]
    for i, c in enumerate(letters):
        seen = letters[:i] if i < toxicity.REACH else ["SLID", *letters[i - toxicity.REACH + 1 : i]]
        yield tuple(seen), (*seen, c)


def plain_model(counts):
    """Word -> log-likelihood ratio, from {word: (toxic texts, ordinary texts)}."""
    step = collections.defaultdict(lambda: [0, 0, 0])
    home = {}
    for w, (t, o) in counts.items():
        for context, s in spelt(w):
            home[s] = context
            for i, v in enumerate((t, o, (t > 0) + (o > 0))):
                step[s][i] += v
    total, kinds = collections.defaultdict(lambda: [0, 0, 0]), collections.defaultdict(lambda: [0, 0, 0])
    for s, n in step.items():
        for i in range(3):
            total[home[s]][i] += n[i]
            kinds[home[s]][i] += n[i] > 0
    d = []
    for i in range(3):
        one, two = (sum(n[i] == k for n in step.values()) for k in (1, 2))
        d.append(min(0.9, max(0.1, one / (one + 2 * two) if one else 0.5)))

    def backoff(c, i):
        return d[i] * kinds[c][i] / total[c][i] if total[c][i] else 1.0

    def chance(s, i):
        c = home[s]
        shared = (max(step[s][2] - d[2], 0) + d[2] * kinds[c][2] / 256) / total[c][2]
        return (max(step[s][i] - d[i], 0) / total[c][i] if total[c][i] else 0.0) + backoff(c, i) * shared

    def ratio(word):
        out = 0.0
        for context, s in spelt(word):
            if s in home:
                out += math.log(chance(s, 0) / chance(s, 1))
            elif context in total:
                out += math.log(backoff(context, 0) / backoff(context, 1))
        return out

    return ratio


TEXTS = [
    ("you fool and utter foolishness", 1), ("a fine day, a fine morning", 0), ("fools rush in; foolproof", 1), ("the food is fine", 0),
    ("Überraschungseier ÜBERRASCHUNG überragend", 0), ("extraordinarily unpronounceable-compoundwordsoflength", 1), ("漢字仮名交じり文の長い文章です", 0), ("漢字の悪口", 1),
    ("", 0), (None, 1), ("fool fool fool", 1),
]


def test_ratios_equal_a_plain_model(spark):
    counts = collections.defaultdict(lambda: [0, 0])
    for text, toxic in TEXTS:
        for w in set(WORD.findall((text or "").lower())):
            counts[w][1 - toxic] += 1
    ratio = plain_model(counts)
    words = spark.createDataFrame([(bytearray(w.encode()), *n) for w, n in counts.items()], "word binary, toxic bigint, ordinary bigint")
    table = toxicity.stored(toxicity._model_table(words), "model")
    sent = toxicity._sent(table, table.count(), ["step", "unseen"])
    asked = [*counts, "foolhardy", "foo", "unknown", "漢字", "z" * 300, "extraordinarily", "compoundwordsoflengthening"]
    docs = spark.createDataFrame([(i, w) for i, w in enumerate(asked)] + [(900, " ".join(asked)), (901, None), (902, "")], "i long, text string")
    for model in (sent, table):
        got = {r.i: r for r in toxicity._text_features(docs, model).collect()}
        for i, w in enumerate(asked):
            assert got[i]["__s"] == pytest.approx(ratio(w), abs=1e-4), w
            assert got[i]["__top"] == pytest.approx(max(0, ratio(w)), abs=1e-4)
        assert got[900]["__n"] == len(asked) and got[900]["__s"] == pytest.approx(sum(map(ratio, asked)), abs=1e-3)
        assert got[901]["__n"] == got[902]["__n"] == 0 == got[902]["__s"]


@pytest.mark.parametrize("frequent", [0, 500, 10**9])
def test_joined_model_scores_alike(spark, monkeypatch, frequent):
    d, lab = (spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet") for t in ("documents", "labels"))
    one = {r.doc_id: r.score for r in toxicity.fit_toxicity(d, lab).score(d.select("doc_id", "text")).collect()}
    monkeypatch.setattr(toxicity, "WORDS_SENT", frequent)
    model = toxicity.fit_toxicity(d, lab, steps_sent=0)
    out = model.score(d.select("doc_id", "text"), keep_text=True)
    assert out.columns == ["doc_id", "text", "score"]
    assert {r.doc_id: r.score for r in out.collect()} == pytest.approx(one, abs=1e-5)


def test_held_out_rows_are_told_apart(spark):
    """Of the held-out third of sf0.1, with the threshold of the registered query."""
    d, lab = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    got = toxicity.fit_toxicity(d, lab).score(d.select("doc_id", "text")).join(lab, "doc_id").where(toxicity.held_out(F.col("doc_id")))
    found = {r.toxic: r.p for r in got.groupBy("toxic").agg(F.avg((F.col("score") >= toxicity.TOXIC_FROM).cast("int")).alias("p")).collect()}
    assert found[1] >= 0.84 and found[0] <= 0.01


def test_executors_need_no_copy_of_the_package(tmp_path):
    """A session whose workers cannot import the package runs what broadcasts models."""
    root = Path(__file__).parents[2]
    code = f"""
import sys
from pyspark.sql import SparkSession
spark = SparkSession.builder.master("local[2]").config("spark.sql.shuffle.partitions", "2").config("spark.ui.enabled", "false").getOrCreate()
def there(batches):
    import importlib.util
    import pyarrow as pa
    for b in batches:
        yield pa.RecordBatch.from_pydict({{"found": [importlib.util.find_spec("treeline") is not None] * len(b)}})
assert not spark.range(1).mapInArrow(there, "found boolean").first().found
sys.path.insert(0, {str(root)!r})
from treeline.llm.queries import queries
d = "/root/testdata/sf0.001"
for name in ("op2_toxicity", "op4_near_dedup", "op6_decontaminate", "op9_passages", "op10_top_products"):
    print(name, queries()[name](spark, d).count())
"""
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True, timeout=600)
    assert done.returncode == 0, done.stderr[-2000:]
