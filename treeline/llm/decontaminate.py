"""Benchmark decontamination by winnowing: fingerprints shared by training and test texts, extended to whole spans.

A fingerprint is the least hash among `w` neighbouring `k`-grams, so any span of w + k - 1 words that two texts share
holds a fingerprint of both. With n = w + k - 1 every shared window of n words is found; hits are extended word by
word to the longest equal span and checked on the words themselves. Items of fewer than n words are one window, whose
one k-gram is the item.
"""

from __future__ import annotations

import hashlib
import sys

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .common import n_parts, small_batches, table

cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Test texts up to so many bytes are sent to every task; larger sets are joined by fingerprint.
BROADCAST_BYTES = 16_000_000


def winnow(grams: np.ndarray, w: int) -> np.ndarray:
    """Which places hold the last least hash of some window of w neighbouring grams (all of a window inside `grams`)."""
    n = len(grams) - w + 1
    if n <= 0:
        return np.zeros(len(grams), bool)
    least = grams[:n].copy()
    for j in range(1, w):
        np.minimum(least, grams[j : n + j], out=least)
    out, open_ = np.zeros(len(grams), bool), np.ones(n, bool)
    for j in range(w - 1, -1, -1):
        here = open_ & (grams[j : n + j] == least)
        out[j : n + j] |= here
        open_ &= ~here
    return out


class Items:
    """Test items: words, and places of their fingerprints by gram length."""

    def __init__(self, ids: list, texts: pa.Array, n: int):
        self.n, self.k = n, (n + 1) // 2
        self.w = n - self.k + 1
        self.ids, self.hashes, self.words = [], [], []
        found: dict[int, list] = {}
        for lo, data, offsets in K.chunks(texts):
            words = K.Words(data, offsets, K.PLAIN)
            for i in range(len(offsets) - 1):
                at = words.of(i)
                m = at.stop - at.start
                if not m:
                    continue
                item = len(self.ids)
                self.ids.append("null" if ids[lo + i] is None else str(ids[lo + i]))
                self.hashes.append(words.hash[at])
                self.words.append([words.text(j) for j in range(at.start, at.stop)])
                own = words.hash[at]
                k = self.k if m >= n else m
                grams = _grams(own, k)
                picked = np.flatnonzero(winnow(grams, self.w)) if m >= n else np.array([0])
                found.setdefault(k if m >= n else -m, []).extend((grams[q], item, q) for q in picked)
        self.tables = {}
        for k, rows in found.items():
            rows.sort(key=lambda r: r[0])
            self.tables[k] = (np.array([r[0] for r in rows], np.uint64), [r[1:] for r in rows])


def _grams(h: np.ndarray, k: int) -> np.ndarray:
    words = K.Words.__new__(K.Words)
    words.hash = h
    return words.grams(k)[: len(h) - k + 1]


def _equal_run(x: np.ndarray, y: np.ndarray) -> int:
    m = min(len(x), len(y))
    differ = np.flatnonzero(x[:m] != y[:m])
    return int(differ[0]) if len(differ) else m


def spans(words: K.Words, items: Items):
    """Yields (first word, word after the last, item) of every longest shared span of n words or a whole short item."""
    bounds = words.bounds
    for kind, (keys, places) in items.tables.items():
        k = abs(kind)
        if len(words.hash) < k:
            continue
        grams = words.grams(k)
        doc_of = np.searchsorted(bounds, np.arange(len(grams)), side="right") - 1
        inside = np.arange(len(grams)) + k <= bounds[doc_of + 1]
        if kind > 0:
            inside &= winnow(grams, items.w)
        at = np.flatnonzero(inside)
        left = np.searchsorted(keys, grams[at], side="left")
        hit = left < len(keys)
        hit[hit] = keys[left[hit]] == grams[at][hit]
        seen: dict = {}
        for p, lo in zip(at[hit].tolist(), left[hit].tolist(), strict=True):
            doc = int(doc_of[p])
            for j in range(lo, len(keys)):
                if keys[j] != keys[lo]:
                    break
                item, q = places[j]
                diagonal = (doc, item, p - q)
                if kind > 0 and seen.get(diagonal, -1) >= p + k:
                    continue
                own, a, b = items.hashes[item], int(bounds[doc]), int(bounds[doc + 1])
                if kind > 0:
                    back = _equal_run(words.hash[a:p][::-1], own[:q][::-1])
                    on = _equal_run(words.hash[p:b], own[q:])
                else:
                    back, on = 0, k
                lo_p, hi_p, lo_q = p - back, p + on, q - back
                seen[diagonal] = hi_p
                if kind > 0 and hi_p - lo_p < items.n:
                    continue
                if all(words.text(lo_p + i) == items.words[item][lo_q + i] for i in range(hi_p - lo_p)):
                    yield doc, lo_p, hi_p, item


def _digest(ids: set) -> str:
    return hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest()


def _score(items_of, keep: list[str]):
    def run(batches):
        items = items_of()
        for batch in batches:
            n_words, n_hit, found = [], [], []
            for _, data, offsets in K.chunks(batch.column("text")):
                words = K.Words(data, offsets, K.PLAIN)
                mask, own = np.zeros(len(words.hash) + 1, np.int64), {}
                for doc, a, b, item in spans(words, items):
                    mask[a:b] = 1
                    own.setdefault(doc, set()).add(items.ids[item])
                total = np.concatenate([[0], np.cumsum(mask)])
                n_words.append(np.diff(words.bounds))
                n_hit.append(total[words.bounds[1:]] - total[words.bounds[:-1]])
                found += [own.get(i, set()) for i in range(len(offsets) - 1)]
            hit = np.concatenate(n_hit) if n_hit else np.zeros(0, np.int64)
            cols = {n: batch.column(n) for n in keep}
            cols |= {
                "n_words": pa.array(np.concatenate(n_words) if n_words else hit, pa.int64()),
                "n_hit": pa.array(hit, pa.int64()),
                "n_items": pa.array([len(x) for x in found], pa.int64()),
                "items_sha256": pa.array([_digest(x) for x in found], pa.string()),
                "contaminated": pa.array(hit > 0, pa.bool_()),
            }
            yield pa.RecordBatch.from_pydict(cols)

    return run


_ADDED = ("n_words", "n_hit", "n_items", "items_sha256", "contaminated")
_ADDED_DDL = "n_words bigint, n_hit bigint, n_items bigint, items_sha256 string, contaminated boolean"


def decontaminated(docs: DataFrame, benchmark: DataFrame, n: int = 10, broadcast_bytes: int = BROADCAST_BYTES, keep: list[str] | None = None) -> DataFrame:
    """The columns of docs named in keep (all by default) and n_words, n_hit, n_items, items_sha256, contaminated.
    docs has text, benchmark has item_id and text.

    A word is hit if it lies in an occurrence of n consecutive words of an item, or of all words of a shorter item.
    n_items counts distinct item_ids with an occurrence (a null id counts as one id, written null), items_sha256 is
    the SHA-256 of them, sorted as strings and joined by commas. Null and empty texts have no words and no hits; null
    and empty items never occur. Repeated rows get the same answer each; columns of docs named as an added one are
    replaced. An empty benchmark hits nothing.
    """
    spark = docs.sparkSession
    small_batches(spark)
    docs = docs.drop(*_ADDED)
    keep = docs.columns if keep is None else keep
    items = benchmark.select(F.col("item_id").cast("string").alias("item_id"), "text").where("text is not null")
    size = items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    if size > broadcast_bytes:
        return _joined(docs, items, n).select(*keep, *_ADDED)
    rows = items.toArrow()
    sent = spark.sparkContext.broadcast((rows["item_id"].to_pylist(), rows["text"].to_pylist()))

    def items_of():
        ids, texts = sent.value
        return Items(ids, pa.array(texts, pa.string()), n)

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*keep).schema.fields)
    return docs.mapInArrow(_score(items_of, keep), f"{schema}, {_ADDED_DDL}")


def _fingerprints(n: int, id_name: str, lengths: list[int]):
    """key, id: what may show that two texts share a window; short items by their own length."""
    k = (n + 1) // 2
    w = n - k + 1

    def run(batches):
        for batch in batches:
            ids = batch.column(id_name).to_pylist()
            keys, own = [], []
            for lo, data, offsets in K.chunks(batch.column("text")):
                words = K.Words(data, offsets, K.PLAIN)
                for i in range(len(offsets) - 1):
                    h = words.hash[words.of(i)]
                    if len(h) >= n:
                        grams = _grams(h, k)
                        part = grams[winnow(grams, w)]
                    else:
                        part = h[:0]
                    short = [m for m in lengths if m <= len(h)] if lengths else ([len(h)] if 0 < len(h) < n else [])
                    part = np.unique(np.concatenate([part, *[_grams(h, m) ^ np.uint64(m) for m in short]]))
                    keys.append(part.view(np.int64))
                    own += [ids[lo + i]] * len(part)
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys) if keys else [], pa.int64()), pa.array(own, pa.int64())], ["key", id_name])

    return run


def _pair_spans(n: int):
    def run(batches):
        for batch in batches:
            rid, item, word = [], [], []
            for i in range(batch.num_rows):
                items = Items([batch.column("item_id")[i].as_py()], batch.column("item_text").slice(i, 1), n)
                for _, data, offsets in K.chunks(batch.column("text").slice(i, 1)):
                    hit = set()
                    for _, a, b, _ in spans(K.Words(data, offsets, K.PLAIN), items):
                        hit.update(range(a, b))
                    rid += [batch.column("rid")[i].as_py()] * len(hit)
                    item += items.ids * len(hit)
                    word += sorted(hit)
            yield pa.RecordBatch.from_arrays([pa.array(rid, pa.int64()), pa.array(item, pa.string()), pa.array(word, pa.int64())], ["rid", "item_id", "word"])

    return run


def _joined(docs: DataFrame, items: DataFrame, n: int) -> DataFrame:
    """For test sets too large to send to every task: fingerprints of both sides meet in a join, then pairs are checked."""
    from .common import PLAIN_WORD_ANY_CASE, stored

    docs = stored(docs.withColumn("rid", F.monotonically_increasing_id()), "docs")
    items = stored(items.withColumn("iid", F.monotonically_increasing_id()), "items")
    count = F.regexp_count("text", F.lit(PLAIN_WORD_ANY_CASE))
    lengths = [r[0] for r in items.select(count.alias("m")).where(f"m between 1 and {n - 1}").distinct().collect()]  # below n values
    left = docs.select("rid", "text").mapInArrow(_fingerprints(n, "rid", lengths or [n]), "key bigint, rid bigint")
    right = items.select("iid", "text").mapInArrow(_fingerprints(n, "iid", []), "key bigint, iid bigint")
    pairs = left.join(right, "key").select("rid", "iid").distinct().repartition(n_parts(docs.sparkSession), "rid")
    full = pairs.join(docs.select("rid", "text"), "rid").join(items.select("iid", "item_id", F.col("text").alias("item_text")), "iid")
    hits = stored(full.select("rid", "text", "item_id", "item_text").mapInArrow(_pair_spans(n), "rid bigint, item_id string, word bigint"), "hits")
    words = hits.select("rid", "word").distinct().groupBy("rid").agg(F.count("*").alias("n_hit"))
    names = hits.select("rid", "item_id").distinct().groupBy("rid").agg(F.array_sort(F.collect_list("item_id")).alias("names"))
    out = docs.join(words, "rid", "left").join(names, "rid", "left")
    names = F.coalesce("names", F.array().cast("array<string>"))
    return out.select(
        *[c for c in docs.columns if c != "rid"],
        F.coalesce(count.cast("bigint"), F.lit(0)).alias("n_words"),
        F.coalesce("n_hit", F.lit(0)).alias("n_hit"),
        F.size(names).cast("bigint").alias("n_items"),
        F.sha2(F.array_join(names, ",").cast("binary"), 256).alias("items_sha256"),
        (F.coalesce("n_hit", F.lit(0)) > 0).alias("contaminated"),
    )


def op6_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return decontaminated(docs, table(spark, sf_dir, "benchmark"), keep=["doc_id"])


OP6_SQL = """
WITH d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM documents
), i AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM benchmark
), iw AS (
  SELECT item_id, least(10, len(w)) AS n, array_to_string(w[p:p + least(10, len(w)) - 1], ' ') AS k FROM (SELECT *, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS p FROM i WHERE len(w) > 0)
), dw AS (
  SELECT doc_id, p, n, array_to_string(w[p:p + n - 1], ' ') AS k FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM d, (SELECT DISTINCT n FROM iw) WHERE len(w) >= n)
), h AS (
  SELECT doc_id, p, n, item_id FROM dw JOIN iw USING (n, k)
), words AS (
  SELECT doc_id, count(DISTINCT x) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + n)) AS x FROM h) GROUP BY doc_id
), items AS (
  SELECT doc_id, count(*) AS n_items, string_agg(name, ',' ORDER BY name) AS names FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS name FROM h) GROUP BY doc_id
)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN words USING (doc_id) LEFT JOIN items USING (doc_id)
"""
