"""Toxicity by two class-conditional Kneser-Ney models of how words are spelt.

A word is a path of letters and an end mark, each step conditioned on the letters of the word before it, REACH - 1 at
most (of a longer word the last ones, so every letter counts). Each class has its own counts of every step; both discount
them by D and hand the freed mass to one shared backoff, which counts in how many word types of either class a step
occurs. A word's log-likelihood ratio is the sum over its steps; steps that neither class has seen cost only the
classes' backoff weights, so rare words are judged by what is known of their parts. A text is judged by the mean ratio
over its words (length-normalised), the share of words that lean to toxic, how many different ones are marked as such
and the largest ratio, turned into a probability on labelled rows that the counts have not seen.
"""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .common import BITMAP_BITS, bitmap, send, small_batches, stored, table

cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Letters of a word that a step sees, itself included.
REACH = 10
#: From which log-likelihood ratios on a word leans to toxic, and is marked.
STRONG, MARKED = 2.0, 6.0
#: Labelled rows that the final probability is fitted on, at most; the counts take all the others.
CALIBRATION_ROWS = 20_000
#: Most words, and bytes of words, a task holds before it puts out their counts.
HELD_WORDS, HELD_BYTES = 150_000, 8_000_000
#: Most steps of the model sent to every task (16 bytes each, 128 MB); a larger model is joined to the distinct words
#: of the texts, of which only about so many, the most frequent ones, are then sent (12 bytes each).
STEPS_SENT, WORDS_SENT = 8_000_000, 1_000_000
#: Rows of a broadcast that come to the driver at once.
FETCHED = 1_000_000
TOXIC_FROM = 0.7
_TURN, _SLID = np.uint64(0x9E3779B97F4A7C15), np.uint64(0x2545F4914F6CDD1D)
#: The context of a word's first letter.
ROOT = 0


def held_out(doc_id):
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def _letters(data: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The characters of words that lie one after the other in data, as numbers, each word closed by a 0 (which no word
    has), and where each begins."""
    n = len(data) + len(lengths)
    spelt = np.zeros(n + 3, np.uint32)
    first = np.cumsum(lengths + 1) - lengths - 1
    spelt[np.arange(len(data)) + np.repeat(np.arange(len(lengths)), lengths)] = data
    more = (spelt & 0xC0) == 0x80  # bytes that go on with a character
    more[first] = more[n:] = False
    at = np.flatnonzero(~more[:n])
    out = spelt[at].copy()
    on = np.ones(len(at), bool)
    for d in range(1, 4):
        on &= more[at + d]
        out |= np.where(on, spelt[at + d], 0) << np.uint32(8 * d)
    return out.astype(np.uint64), np.searchsorted(at, first)


def _spelt(words: K.Words, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    lengths = words.end[at] - words.start[at]
    place = np.arange(int(lengths.sum())) - np.repeat(np.cumsum(lengths) - lengths, lengths)
    return _letters(words.bytes[np.repeat(words.start[at], lengths) + place], lengths)


def _step(context: np.ndarray, letter: np.ndarray) -> np.ndarray:
    return K.mix(context * _TURN + letter + np.uint64(1))


def _steps(letters: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The context of every letter of the words and the step from it, as hashes.

    The first REACH letters of a word have all letters before them as context, so a step is the next one's context;
    later ones have the REACH - 1 letters before them, wherever they stand.
    """
    n = len(letters)
    lengths = np.diff(np.append(first, n))
    context, step = np.zeros(n, np.uint64), np.zeros(n, np.uint64)
    at, h, left = first, np.full(len(first), ROOT, np.uint64), lengths
    for j in range(REACH):
        on = left > j
        at, h, left = at[on], h[on], left[on]
        context[at + j] = h
        h = _step(h, letters[at + j])
        step[at + j] = h
    at, left = first[lengths > REACH] + REACH, lengths[lengths > REACH] - REACH
    if len(at):
        late = np.repeat(at, left) + np.arange(int(left.sum())) - np.repeat(np.cumsum(left) - left, left)
        h = np.full(len(late), _SLID, np.uint64)
        for d in range(REACH - 1, 0, -1):
            h = h * _TURN + letters[late - d] + np.uint64(1)
        context[late] = K.mix(h)
        step[late] = _step(context[late], letters[late])
    return context, step


def _plain_words(batch: pa.RecordBatch):
    """Row range, words, the distinct ones and which of these each word is, for chunks of the batch."""
    for lo, data, offsets in K.chunks(batch.column("text")):
        words = K.Words(data, offsets, K.PLAIN)
        _, first, inverse = np.unique(words.hash, return_index=True, return_inverse=True)
        yield slice(lo, lo + len(offsets) - 1), words, first, inverse


class _Held:
    """Counts by word that a task holds, put out when they are many."""

    def __init__(self, names: list[str]):
        self.names, self.counts, self.size = names, {}, 0

    def add(self, key: bytes, n: list[int]) -> None:
        old = self.counts.get(key)
        self.counts[key] = n if old is None else [a + b for a, b in zip(old, n, strict=True)]
        self.size += len(key) if old is None else 0

    def full(self) -> bool:
        return len(self.counts) > HELD_WORDS or self.size > HELD_BYTES

    def rows(self) -> pa.RecordBatch:
        n = np.array(list(self.counts.values()), np.int64).reshape(-1, len(self.names))
        cols = [pa.array(list(self.counts), pa.binary()), *(pa.array(n[:, i]) for i in range(n.shape[1]))]
        self.counts, self.size = {}, 0
        return pa.RecordBatch.from_arrays(cols, ["word", *self.names])


def _texts_with(words: K.Words, first: np.ndarray, inverse: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Each pair of a text and a distinct word in it once, and how often the word is there."""
    doc = np.repeat(np.arange(len(words.bounds) - 1), np.diff(words.bounds))
    pair, n = np.unique(doc * max(1, len(first)) + inverse, return_counts=True)
    return *np.divmod(pair, max(1, len(first))), n


def _count_words(batches):
    """word, toxic, ordinary: texts of each class with the word, summed over what a task can hold."""
    held = _Held(["toxic", "ordinary"])
    for batch in batches:
        label = np.asarray(batch.column("toxic"))
        for own, words, first, inverse in _plain_words(batch):
            doc, which, _ = _texts_with(words, first, inverse)
            toxic = np.bincount(which, weights=label[own][doc], minlength=len(first)).astype(np.int64)
            ordinary = np.bincount(which, minlength=len(first)) - toxic
            for j, t, n in zip(first.tolist(), toxic.tolist(), ordinary.tolist(), strict=True):
                held.add(words.text(j), [t, n])
            if held.full():
                yield held.rows()
    yield held.rows()


def _count_steps(batches):
    """step, context, toxic, ordinary, types of distinct words (word, toxic, ordinary), summed by batch."""
    for batch in batches:
        counts = [np.asarray(batch.column(c)) for c in ("toxic", "ordinary")]
        for lo, data, offsets in K.chunks(batch.column("word")):
            letters, first = _letters(data, np.diff(offsets))
            n = np.diff(np.append(first, len(letters)))
            context, step = _steps(letters, first)
            step, at, inverse = np.unique(step, return_index=True, return_inverse=True)
            own = [np.repeat(c[lo : lo + len(n)], n) for c in counts]
            own.append((own[0] > 0).astype(np.int64) + (own[1] > 0))
            sums = [np.bincount(inverse, weights=c, minlength=len(step)).astype(np.int64) for c in own]
            cols = [step.view(np.int64), context[at].view(np.int64), *sums]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], ["step", "context", "toxic", "ordinary", "types"])


class _Model:
    """Keys in order with the ratio of each as a step, and of steps unseen in it as a context; read by upper bits."""

    def __init__(self, keys: np.ndarray, step: np.ndarray, unseen: np.ndarray):
        self.keys, self.step, self.unseen = keys, step, unseen
        bits = max(1, len(keys).bit_length() - 3)
        self.shift = np.uint64(64 - bits)
        self.index = np.append(np.searchsorted(keys, np.arange(1 << bits, dtype=np.uint64) << self.shift), len(keys))

    def find(self, h: np.ndarray) -> np.ndarray:
        """The place of each hash among the keys, or -1."""
        if not len(self.keys):
            return np.full(len(h), -1)
        top = (h >> self.shift).astype(np.int64)
        at, end = self.index[top], self.index[top + 1]
        out, left = np.full(len(h), -1), np.flatnonzero(at < end)
        at = at.copy()
        while len(left):
            key = self.keys[at[left]]
            hit = left[key == h[left]]
            out[hit] = at[hit]
            left = left[key < h[left]]
            at[left] += 1
            left = left[at[left] < end[left]]
        return out

    def ratios(self, letters: np.ndarray, first: np.ndarray) -> np.ndarray:
        """Log-likelihood ratio of each word: its known steps, and the unseen ones from known contexts."""
        if not len(first):
            return np.zeros(0)
        context, step = _steps(letters, first)
        at = self.find(step)
        out = np.where(at >= 0, self.step[at] if len(self.step) else 0.0, 0.0).astype(np.float64)
        new = np.flatnonzero(at < 0)
        at = self.find(context[new])
        out[new] = np.where(at >= 0, self.unseen[at] if len(self.unseen) else 0.0, 0.0)
        return np.add.reduceat(out, first)


def _per_text(words: K.Words, ratio: np.ndarray, inverse: np.ndarray) -> list[np.ndarray]:
    """Words, sum of their ratios, strong words, the largest ratio above 0 and different marked words, for each text.
    inverse tells equal words apart from others."""
    b = words.bounds
    total, strong = np.append(0, np.cumsum(ratio)), np.append(0, np.cumsum(ratio >= STRONG))
    top = np.zeros(len(b) - 1)
    some = np.flatnonzero(b[1:] > b[:-1])
    if len(some):
        top[some] = np.maximum(np.maximum.reduceat(ratio, b[some]), 0)
    marked = np.flatnonzero(ratio >= MARKED)
    own = np.unique(np.stack([np.searchsorted(b, marked, side="right") - 1, inverse[marked]]), axis=1)[0]
    return [np.diff(b), total[b[1:]] - total[b[:-1]], strong[b[1:]] - strong[b[:-1]], top, np.bincount(own, minlength=len(b) - 1)]


_ADDED = (("__n", pa.int64()), ("__s", pa.float64()), ("__strong", pa.int64()), ("__top", pa.float64()), ("__marks", pa.int64()))


def _features(sent, keep_text: bool):
    """The columns _ADDED of each text, in place of text or beside it."""

    def run(batches):
        model = _Model(*sent.value)
        for batch in batches:
            cols: list = [[] for _ in _ADDED]
            for _, words, first, inverse in _plain_words(batch):
                ratio = model.ratios(*_spelt(words, first))[inverse]
                for c, v in zip(cols, _per_text(words, ratio, inverse), strict=True):
                    c.append(v)
            out = {n: batch.column(n) for n in batch.schema.names if keep_text or n != "text"}
            out |= {name: pa.array(np.concatenate(c) if c else [], kind) for (name, kind), c in zip(_ADDED, cols, strict=True)}
            yield pa.RecordBatch.from_pydict(out)

    return run


def _model_table(words: DataFrame) -> DataFrame:
    """key, step, unseen from word, toxic, ordinary: the smoothed log-likelihood ratios of every step."""
    counts = ("toxic", "ordinary", "types")
    steps = words.mapInArrow(_count_steps, "step bigint, context bigint, toxic bigint, ordinary bigint, types bigint")
    steps = stored(steps.groupBy("step").agg(F.min("context").alias("context"), *[F.sum(c).alias(c) for c in counts]), "steps")
    few = steps.agg(*[F.sum((F.col(c) == i).cast("long")).alias(f"{c}{i}") for c in counts for i in (1, 2)]).first()

    def discount(c: str) -> float:
        one, two = few[f"{c}1"] or 0, few[f"{c}2"] or 0
        return min(0.9, max(0.1, one / (one + 2 * two) if one else 0.5))

    d = {c: F.lit(discount(c)) for c in counts}
    total = steps.groupBy("context").agg(
        *[F.sum(c).alias(f"{c}_all") for c in d], *[F.sum((F.col(c) > 0).cast("long")).alias(f"{c}_kinds") for c in d]
    )
    x = steps.join(total, "context")
    shared = (F.greatest(F.col("types") - d["types"], F.lit(0.0)) + d["types"] * F.col("types_kinds") / 256) / F.col("types_all")

    def backoff(c: str):
        return F.when(F.col(f"{c}_all") > 0, d[c] * F.col(f"{c}_kinds") / F.col(f"{c}_all")).otherwise(1.0)

    def chance(c: str):
        own = F.when(F.col(f"{c}_all") > 0, F.greatest(F.col(c) - d[c], F.lit(0.0)) / F.col(f"{c}_all")).otherwise(0.0)
        return own + backoff(c) * shared

    step = x.select(F.col("step").alias("key"), F.log(chance("toxic") / chance("ordinary")).cast("float").alias("step"))
    unseen = total.select(F.col("context").alias("key"), F.log(backoff("toxic") / backoff("ordinary")).cast("float").alias("unseen"))
    none = F.lit(0.0).cast("float")
    return step.join(unseen, "key", "full").select("key", F.coalesce("step", none).alias("step"), F.coalesce("unseen", none).alias("unseen"))


def _sent(table_: DataFrame, rows: int, values: list[str]):
    """A stored table of key and values, of a bounded number of rows, as a broadcast of arrays in order of the keys."""
    parts = min(256, max(1, -(-rows // FETCHED)))
    keys, out = np.zeros(rows, np.uint64), [np.zeros(rows, np.float32) for _ in values]
    lo = 0
    # by ranges of the keys, which are hashes, so that each part is sorted where it comes to lie
    part = F.floor(F.shiftrightunsigned(F.col("key"), 56) * parts / 256)
    for i in range(parts):
        got = table_.where(part == i).toArrow()
        own = got["key"].to_numpy().view(np.uint64)
        order = np.argsort(own)
        keys[lo : lo + len(own)] = own[order]
        for column, name in zip(out, values, strict=True):
            column[lo : lo + len(own)] = got[name].to_numpy()[order]
        lo += len(own)
        del got, own, order
    return send(table_.sparkSession, (keys, *out))


def _vocabulary(batches):
    """word, n: the words of texts and in how many of them they are, summed over what a task can hold."""
    held = _Held(["n"])
    for batch in batches:
        for _, words, first, inverse in _plain_words(batch):
            _, which, _ = _texts_with(words, first, inverse)
            for j, n in zip(first.tolist(), np.bincount(which, minlength=len(first)).tolist(), strict=True):
                held.add(words.text(j), [n])
            if held.full():
                yield held.rows()
    yield held.rows()


def _word_steps(batches):
    """key (the word's hash), n, at, context of every step of distinct words."""
    for batch in batches:
        n = np.asarray(batch.column("n"))
        for lo, data, offsets in K.chunks(batch.column("word")):
            lengths = np.diff(offsets)
            letters, first = _letters(data, lengths)
            steps = np.diff(np.append(first, len(letters)))
            context, step = _steps(letters, first)
            # as texts of their own, the words get the hashes that they have within texts
            h = K.Words(data, offsets, K.PLAIN).hash
            cols = [np.repeat(h.view(np.int64), steps), np.repeat(n[lo : lo + len(lengths)], steps), step.view(np.int64), context.view(np.int64)]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], ["key", "n", "at", "context"])


def _known_features(sent):
    """For each text, a row of the columns _ADDED of its frequent words (__n of all), and a row for each other word."""

    def run(batches):
        keys, ratios = sent.value
        model = _Model(keys, ratios, ratios)
        for batch in batches:
            row = np.asarray(batch.column("__row"))
            for own, words, first, inverse in _plain_words(batch):
                at = model.find(words.hash[first])
                ratio = np.where(at >= 0, ratios[at] if len(ratios) else 0.0, 0.0).astype(np.float64)[inverse]
                n, s, strong, top, marks = _per_text(words, ratio, inverse)
                doc, which, times = _texts_with(words, first, inverse)
                rare = at[which] < 0
                doc, which, times = doc[rare], which[rare], times[rare]
                none = np.zeros(len(doc), np.int64)
                ids = np.concatenate([words.hash[first][which].view(np.int64), np.zeros(len(n), np.int64)])
                cols = [pa.array(np.concatenate([row[own][doc], row[own]])), pa.array(ids, mask=np.arange(len(ids)) >= len(doc))]
                for (_, kind), v, w in zip(_ADDED, (times, none, none, none, none), (n, s, strong, top, marks), strict=True):
                    cols.append(pa.array(np.concatenate([v, w]), kind))
                yield pa.RecordBatch.from_arrays(cols, ["__row", "key", *[name for name, _ in _ADDED]])

    return run


def _joined_features(docs: DataFrame, model: DataFrame, keep_text: bool) -> DataFrame:
    """As _features, for a model of any size: the steps of the texts' distinct words are joined to it, the ratios of the
    most frequent words are sent to the texts, and the other words of each text are joined to theirs."""
    rows = stored(docs.withColumn("__row", F.monotonically_increasing_id()), "rows")
    words = rows.select("text").mapInArrow(_vocabulary, "word binary, n bigint").groupBy("word").agg(F.sum("n").alias("n"))
    steps = words.mapInArrow(_word_steps, "key bigint, n bigint, at bigint, context bigint")
    steps = steps.join(model.select(F.col("key").alias("at"), "step", F.lit(True).alias("known")), "at", "left")
    steps = steps.join(model.select(F.col("key").alias("context"), "unseen"), "context", "left")
    part = F.when(F.col("known"), F.col("step")).otherwise(F.coalesce("unseen", F.lit(0.0))).cast("double")
    ratios = stored(steps.groupBy("key").agg(F.sum(part).cast("float").alias("ratio"), F.max("n").alias("n")), "ratios")
    size = F.floor(F.log2("n")).cast("int")
    least, frequent = 64, 0
    for r in ratios.groupBy(size.alias("size")).count().orderBy(F.desc("size")).collect():  # 64 rows at most
        if frequent + r["count"] > WORDS_SENT:
            break
        least, frequent = r["size"], frequent + r["count"]
    sent = _sent(ratios.where(size >= least), frequent, ["ratio"])
    kinds = ", ".join(f"{name} {'bigint' if kind == pa.int64() else 'double'}" for name, kind in _ADDED)
    known = stored(rows.select("__row", "text").mapInArrow(_known_features(sent), f"__row bigint, key bigint, {kinds}"), "known")
    ratio = F.col("ratio").cast("double")
    rare = known.where("key is not null").select("__row", "key", F.col("__n").alias("times")).join(ratios.where(size < least).select("key", "ratio"), "key").select(
        "__row", F.lit(0).cast("bigint").alias("__n"), (F.col("times") * ratio).alias("__s"), F.when(ratio >= STRONG, F.col("times")).otherwise(0).alias("__strong"),
        F.greatest(ratio, F.lit(0.0)).alias("__top"), (ratio >= MARKED).cast("bigint").alias("__marks"),
    )
    every = known.where("key is null").drop("key").union(rare).groupBy("__row")
    out = every.agg(*[(F.max if name == "__top" else F.sum)(name).alias(name) for name, _ in _ADDED])
    return rows.select(*[c for c in rows.columns if keep_text or c != "text"]).join(out, "__row").drop("__row")


def _text_features(docs: DataFrame, model, keep_text: bool = False) -> DataFrame:
    """docs with the columns _ADDED, and without text unless it is kept. model: a broadcast or a table."""
    if isinstance(model, DataFrame):
        return _joined_features(docs, model, keep_text)
    own = docs if keep_text else docs.drop("text")
    added = [f"{name} {'bigint' if kind == pa.int64() else 'double'}" for name, kind in _ADDED]
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in own.schema.fields), *added])
    return docs.mapInArrow(_features(model, keep_text), schema)


def _inputs():
    n = F.greatest(F.col("__n"), F.lit(1))
    return [F.lit(1.0), F.col("__s") / n, F.sqrt(F.col("__strong") / n), F.least(F.col("__top"), F.lit(12.0)), F.log1p(F.col("__marks")), F.log1p(F.col("__n"))]


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, turns: int = 30) -> np.ndarray:
    """Weights by Newton's method with a ridge on all but the first column."""
    w = np.zeros(x.shape[1])
    r = np.full(x.shape[1], ridge)
    r[0] = 1e-6
    for _ in range(turns):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - y) + r * w
        h = (x * (p * (1 - p))[:, None]).T @ x + np.diag(r)
        step = np.linalg.solve(h, g)
        w -= np.clip(step, -5, 5)
        if np.abs(step).max() < 1e-8:
            break
    return w


class ToxicityModel:
    """Class-conditional models (a broadcast, or a table where they are large) and the final probability."""

    def __init__(self, steps, weights: list[float]):
        self.steps, self.weights = steps, weights

    def score(self, docs: DataFrame, keep_text: bool = False) -> DataFrame:
        """All columns of docs (text only if kept), with score (double, 0 to 1). Null and empty texts have no words:
        they get the score of such texts among the labelled rows (near the share of toxic rows). A column named score
        is replaced. Repeated rows get the same score each."""
        out = _text_features(docs.drop("score"), self.steps, keep_text)
        z = F.lit(0.0)
        for w, x in zip(self.weights, _inputs(), strict=True):
            z = z + F.lit(float(w)) * x
        return out.withColumn("score", 1 / (1 + F.exp(-z))).drop(*[name for name, _ in _ADDED])


def _labelled(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, text, toxic of labelled rows outside the held-out third. Ids that have no label are left before the
    shuffle by a bitmap of fixed size (8 MB) of the labelled ids; the join is exact."""
    labels = labels.where("doc_id is not null and toxic is not null").groupBy(F.col("doc_id").cast("bigint").alias("doc_id")).agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    labels = labels.where(~held_out(F.col("doc_id")))
    sent = send(docs.sparkSession, bitmap(labels.select(F.pmod("doc_id", F.lit(BITMAP_BITS)).alias("at"))))

    def known(batches):
        for batch in batches:
            ids = np.asarray(batch.column("doc_id").fill_null(0)) % BITMAP_BITS
            yield batch.filter(pa.array(((sent.value[ids >> 3] >> (ids & 7).astype(np.uint8)) & 1).astype(bool)))

    docs = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").where(~held_out(F.col("doc_id")))
    return docs.mapInArrow(known, "doc_id bigint, text string").join(labels, "doc_id")


def fit_toxicity(docs: DataFrame, labels: DataFrame, calibration_rows: int = CALIBRATION_ROWS, steps_sent: int = STEPS_SENT) -> ToxicityModel:
    """Learns from docs (doc_id, text) and labels (doc_id, toxic 0/1), never from rows of the held-out third.

    Every fifth labelled row by hash, calibration_rows at most (more only where rows share an id), fits the
    probability; all others fill the counts. A model of more than steps_sent steps is joined, not sent.
    Null labels and ids are left out; a doc_id labelled both ways is toxic. Without labelled rows, or with one class
    only, every score is the share of toxic rows (0.0 without any).
    """
    small_batches(docs.sparkSession)
    train = stored(_labelled(docs, labels), "labelled")
    fifth = F.pmod(F.xxhash64("doc_id"), F.lit(5)) == 0
    counted = train.where(~fifth).select("text", "toxic").mapInArrow(_count_words, "word binary, toxic bigint, ordinary bigint")
    words = stored(counted.groupBy("word").agg(F.sum("toxic").alias("toxic"), F.sum("ordinary").alias("ordinary")), "words")
    table_ = stored(_model_table(words), "model")
    n = table_.count()
    steps = table_ if n > steps_sent else _sent(table_, n, ["step", "unseen"])
    rank = F.xxhash64(F.lit(1), "doc_id")
    last = train.where(fifth).select(rank.alias("r")).orderBy("r").limit(calibration_rows).agg(F.max("r")).first()[0]
    sample = train.where(fifth & (rank <= F.lit(last))) if last is not None else train.limit(0)
    rows = _text_features(sample.select("doc_id", "toxic", "text"), steps).select("toxic", F.array(*_inputs()).alias("x")).toArrow()
    y = rows["toxic"].to_numpy().astype(float)
    if not len(y) or y.min() == y.max():
        share = np.clip(y.mean() if len(y) else 0.0, 1e-9, 1 - 1e-9)
        return ToxicityModel(steps, [float(np.log(share / (1 - share))), *[0] * (len(_inputs()) - 1)])
    return ToxicityModel(steps, fit_logistic(np.array(rows["x"].to_pylist()), y).tolist())


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = fit_toxicity(docs, table(spark, sf_dir, "labels")).score(docs)
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= TOXIC_FROM).cast("int").alias("predicted"))
