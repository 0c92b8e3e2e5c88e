"""Quality by ordinal cumulative-link regression: one set of hashed-text weights and ordered thresholds.

P(grade >= j) = 1 / (1 + exp(b_j - w.x)) with b_1 <= b_2 <= ...; x holds hashed words, hashed word shapes and bins of
how varied, long and repetitive a text is. The expected grade is the sum of the tail probabilities.
"""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .common import small_batches, stored, table
from .toxicity import held_out

cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Hashed places: words, word shapes, bins of text statistics.
WORD_PLACES, SHAPE_PLACES, BINS = 1 << 15, 1 << 12, 12
N_STATS = 5
PLACES = WORD_PLACES + SHAPE_PLACES + N_STATS * BINS
#: Most rated rows the weights are fitted on (chosen by a hash of doc_id).
RATED_ROWS = 12_000
KEEP_FROM = 0.5

_class = np.zeros(256, np.uint8)  # punctuation counts by itself
_class[97:123], _class[65:91], _class[48:58], _class[128:] = 1, 2, 3, 1
_class[:] = np.where(_class > 0, _class, np.arange(256))


def _shapes(data: np.ndarray, words: K.Words) -> np.ndarray:
    """A hash of each word's runs of character classes, such as capital-small-percent."""
    kind = _class[data]
    inside = np.flatnonzero(K.SPACED[K.LOWER[data]])
    lengths = words.end - words.start
    first = np.cumsum(lengths) - lengths
    seq = kind[inside]
    new = np.ones(len(seq), bool)
    new[1:] = seq[1:] != seq[:-1]
    new[first] = True
    run = np.cumsum(new)
    place = run - np.repeat(run[first], lengths)
    part = np.where(new, (seq.astype(np.uint64) + np.uint64(1)) * K._powers(int(place.max()) + 2)[place + 1], np.uint64(0))
    return K.mix(np.add.reduceat(part, first))


def _bin(x: float, lo: float, hi: float) -> int:
    return int(min(BINS - 1, max(0, (x - lo) / (hi - lo) * BINS)))


def features(texts: pa.Array):
    """For each text the places and values of its features."""
    for _, data, offsets in K.chunks(texts):
        words = K.Words(data, offsets, K.SPACED)
        shapes = _shapes(data, words) if len(words.hash) else np.zeros(0, np.uint64)
        for i in range(len(offsets) - 1):
            at = words.of(i)
            h, n = words.hash[at], at.stop - at.start
            raw = data[offsets[i] : offsets[i + 1]]
            if not n:
                yield np.array([PLACES - 1], np.int32), np.array([1.0], np.float32)
                continue
            w, wc = np.unique((h % np.uint64(WORD_PLACES)).astype(np.int32), return_counts=True)
            s, sc = np.unique((shapes[at] % np.uint64(SHAPE_PLACES)).astype(np.int32), return_counts=True)
            lines = np.flatnonzero(np.diff(np.searchsorted(np.flatnonzero(raw == 10), words.start[at] - offsets[i])) > 0) if n > 1 else []
            stats = (
                _bin(len(np.unique(h)) / n, 0, 1),
                _bin(np.log1p(n), 0, 10),
                _bin(len(raw) / n, 2, 14),
                _bin(float(wc.max()) / n, 0, 0.5),
                _bin((len(lines) + 1) / n, 0, 0.3),
            )
            idx = np.concatenate([w, s + WORD_PLACES, [WORD_PLACES + SHAPE_PLACES + j * BINS + b for j, b in enumerate(stats)]])
            yield idx.astype(np.int32), np.concatenate([np.sqrt(wc / n) * 0.5, sc / n * 2, np.ones(N_STATS)]).astype(np.float32)


def _packed(batches):
    for batch in batches:
        idx, val = [], []
        for i, v in features(batch.column("text")):
            idx.append(i.tobytes())
            val.append(v.tobytes())
        yield pa.RecordBatch.from_arrays([batch.column("grade"), pa.array(idx, pa.binary()), pa.array(val, pa.binary())], ["grade", "idx", "val"])


def fit_cumulative_link(rows: list[tuple[np.ndarray, np.ndarray]], grades: np.ndarray, n_grades: int, places: int = PLACES, turns: int = 200, ridge: float = 3e-5):
    """weights and ordered thresholds by full-batch adaptive gradient steps on the mean log-likelihood."""
    idx = np.concatenate([i for i, _ in rows])
    val = np.concatenate([v for _, v in rows]).astype(np.float64)
    sizes = np.array([len(i) for i, _ in rows])
    first = np.cumsum(sizes) - sizes
    own = np.repeat(np.arange(len(rows)), sizes)
    w = np.zeros(places)
    share = np.clip(np.array([(grades >= j).mean() for j in range(1, n_grades)]), 1e-3, 1 - 1e-3)
    b = np.log((1 - share) / share)
    gaps = np.concatenate([[b[0]], np.log(np.maximum(np.diff(b), 1e-2))])  # b rises: first value, then logs of steps
    m1, m2 = [np.zeros(places), np.zeros(len(gaps))], [np.zeros(places), np.zeros(len(gaps))]
    sigmoid = lambda z: 1 / (1 + np.exp(-np.clip(z, -35, 35)))
    for t in range(1, turns + 1):
        b = np.cumsum(np.concatenate([gaps[:1], np.exp(gaps[1:])]))
        s = np.add.reduceat(val * w[idx], first)
        edge = np.concatenate([[-np.inf], b, [np.inf]])
        hi, lo = edge[grades + 1], edge[grades]
        p_hi, p_lo = sigmoid(np.clip(hi, -1e3, 1e3) - s), sigmoid(np.clip(lo, -1e3, 1e3) - s)
        p = np.maximum(p_hi - p_lo, 1e-9)
        d_hi, d_lo = p_hi * (1 - p_hi) / p, p_lo * (1 - p_lo) / p
        n = len(rows)
        g_w = np.bincount(idx, weights=val * (d_hi - d_lo)[own], minlength=places) / n + ridge * w
        g_b = np.array([(-(d_hi * (grades == j)).sum() + (d_lo * (grades == j + 1)).sum()) / n for j in range(n_grades - 1)])
        later = np.cumsum(g_b[::-1])[::-1]
        g_gap = later * np.concatenate([[1.0], np.exp(gaps[1:])])
        for k, (x, g, rate) in enumerate(((w, g_w, 0.1), (gaps, g_gap, 0.05))):
            m1[k] = 0.9 * m1[k] + 0.1 * g
            m2[k] = 0.999 * m2[k] + 0.001 * g * g
            x -= rate * (m1[k] / (1 - 0.9**t)) / (np.sqrt(m2[k] / (1 - 0.999**t)) + 1e-8)
    return w, np.cumsum(np.concatenate([gaps[:1], np.exp(gaps[1:])]))


class QualityModel:
    def __init__(self, spark: SparkSession, weights: np.ndarray, thresholds: np.ndarray):
        self.thresholds = thresholds
        self.sent = spark.sparkContext.broadcast(weights.astype(np.float32))

    def score(self, docs: DataFrame) -> DataFrame:
        """docs without text, with expected_grade and tails (P(grade >= 1), P(grade >= 2), ...). Null and empty texts
        have one feature of their own; repeated rows get equal scores; columns so named are replaced."""
        docs = docs.drop("expected_grade", "tails")
        sent, b = self.sent, self.thresholds

        def run(batches):
            w = sent.value
            for batch in batches:
                z = np.array([float((v * w[i]).sum()) for i, v in features(batch.column("text"))])
                tails = 1 / (1 + np.exp(np.clip(b[None, :] - z[:, None], -35, 35))) if len(z) else np.zeros((0, len(b)))
                cols = {n: batch.column(n) for n in batch.schema.names if n != "text"}
                cols["expected_grade"] = pa.array(tails.sum(axis=1), pa.float64())
                cols["tails"] = pa.array(list(tails), pa.list_(pa.float64()))
                yield pa.RecordBatch.from_pydict(cols)

        schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.drop("text").schema.fields)
        return docs.mapInArrow(run, f"{schema + ', ' if schema else ''}expected_grade double, tails array<double>")


def fit_quality(docs: DataFrame, ratings: DataFrame, n_grades: int, rated_rows: int = RATED_ROWS) -> QualityModel:
    """Learns from docs (doc_id, text) and ratings (doc_id, grade from 0 to n_grades - 1).

    The rated_rows rated ids that come first by hash are used, the only bound on what is learnt from. Null ids and
    grades and grades out of range are left out; an id rated twice has the lower grade. Without ratings all weights
    are 0 and every tail is one half.
    """
    spark = docs.sparkSession
    small_batches(spark)
    rated = ratings.where(F.col("doc_id").isNotNull() & F.col("grade").between(0, n_grades - 1)).groupBy(F.col("doc_id").cast("bigint").alias("doc_id")).agg(F.min(F.col("grade").cast("int")).alias("grade"))
    rated = stored(rated.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rated_rows), "rated")
    own = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").join(F.broadcast(rated), "doc_id")  # rated_rows rows
    rows = own.dropDuplicates(["doc_id"]).select("grade", "text").mapInArrow(_packed, "grade int, idx binary, val binary").toArrow()
    if not len(rows):
        return QualityModel(spark, np.zeros(PLACES), np.zeros(n_grades - 1))
    pairs = [(np.frombuffer(i, np.int32), np.frombuffer(v, np.float32)) for i, v in zip(rows["idx"].to_pylist(), rows["val"].to_pylist(), strict=True)]
    return QualityModel(spark, *fit_cumulative_link(pairs, rows["grade"].to_numpy(), n_grades))


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Grades 0 (poor), 1 (good but toxic), 2 (good): kept are texts whose grade is 1 at least with KEEP_FROM chance.
    The third of ids that the toxicity query holds out is not learnt from here either."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    labels = table(spark, sf_dir, "labels").where(~held_out(F.col("doc_id")))
    grade = F.when(F.col("quality") == 0, 0).when(F.col("toxic") == 1, 1).otherwise(2)
    scored = fit_quality(docs, labels.where("quality is not null").select("doc_id", grade.alias("grade")), 3).score(docs)
    good = F.col("tails")[0]
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "expected_grade", good.alias("p_good"), F.col("tails")[1].alias("p_best"), (good >= KEEP_FROM).alias("kept"))
