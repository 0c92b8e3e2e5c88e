"""Repeated passages, exact or nearly so: shared word k-mers as seeds, collinear chains, alignment.

Seeds are the k-mers that winnowing keeps, so every shared span of W + K - 1 words has one. Each occurrence of a seed
is paired with the first occurrence (least document, least place) only, never with all others. The pairs of two
documents are chained in order with a cost for gaps, by a Fenwick tree over the second document's places; the chains'
stretches of text are then aligned word by word, from seed to seed and outwards, over differing words too.
"""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import kernels as K
from .common import BITMAP_BITS, bitmap, n_parts, send, small_batches, stored, table
from .decontaminate import winnow

cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Words of a seed and seeds of a winnowing window; words a passage has at least; share of its words that must match.
WORDS, WINDOW, LEAST, IDENTITY = 8, 10, 50, 0.8
#: Cost of a word of gap against a matched word, of a word of shift between the two texts; bytes of context around a
#: chain, and bytes that its last seed may take.
GAP, SHIFT, PAD, TAIL = 0.25, 0.25, 240, 160
#: Score of a differing word against 1 for an equal one: a stretch of IDENTITY has 0. How far a growing end may fall
#: below its best score.
DIFFER, DROP = -IDENTITY / (1 - IDENTITY), 30.0
#: Bytes of text that are cut into words at once for alignment.
ALIGN_BYTES = 500_000
#: Chains of two documents that are aligned in their own context first; where there are more, whole texts are cheaper.
FEW = 2


def _shared_seeds(sent):
    """Seeds whose hash may be a shared one, by a bitmap of fixed size that misses none."""

    def run(batches):
        bits = sent.value
        for batch in _seeds(batches):
            at = np.asarray(batch.column("h")) % (8 * len(bits))
            yield batch.filter(pa.array((bits[at >> 3] >> (at & 7).astype(np.uint8) & 1).astype(bool)))

    return run


def _seeds(batches):
    """h, rid, at: kept seeds and their places, the byte in the upper 32 bits and the word in the lower."""
    for batch in batches:
        ids = batch.column("rid").to_pylist()
        out: list = [[], [], []]
        for lo, data, offsets in K.chunks(batch.column("text")):
            words = K.Words(data, offsets, K.PLAIN)
            if len(words.hash) < WORDS:
                continue
            grams = words.grams(WORDS)
            doc = np.searchsorted(words.bounds, np.arange(len(grams)), side="right") - 1
            keep = np.flatnonzero(winnow(grams, WINDOW) & (np.arange(len(grams)) + WORDS <= words.bounds[doc + 1]))
            out[0].append(grams[keep].view(np.int64))
            out[1].append(np.array(ids[lo : lo + len(offsets) - 1], np.int64)[doc[keep]])
            out[2].append((words.start[keep] - offsets[doc[keep]] << 32) + keep - words.bounds[doc[keep]])
        cols = [np.concatenate(c).astype(np.int64) if c else np.zeros(0, np.int64) for c in out]
        yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], ["h", "rid", "at"])


class Fenwick:
    """Prefix maxima: put(i, value, item), best(i) over places below i."""

    def __init__(self, n: int):
        self.tree = [(-np.inf, -1)] * (n + 1)

    def put(self, i: int, value: float, item: int) -> None:
        i += 1
        while i < len(self.tree):
            if value > self.tree[i][0]:
                self.tree[i] = (value, item)
            i += i & -i

    def best(self, i: int) -> tuple[float, int]:
        out = (-np.inf, -1)
        while i > 0:
            if self.tree[i][0] > out[0]:
                out = self.tree[i]
            i -= i & -i
        return out


def segments(p: np.ndarray, q: np.ndarray, p_byte: np.ndarray, q_byte: np.ndarray) -> np.ndarray:
    """Runs of seeds on one diagonal that touch or nearly so, as rows (p, q, length in words, bytes of the first seed in
    both texts, bytes of the last)."""
    order = np.lexsort((p, p - q))
    p, q, p_byte, q_byte = p[order], q[order], p_byte[order], q_byte[order]
    new = np.ones(len(p), bool)
    new[1:] = ((p - q)[1:] != (p - q)[:-1]) | (p[1:] > p[:-1] + 2 * WORDS)
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(p)) - 1
    out = np.stack([p[first], q[first], p[last] + WORDS - p[first], p_byte[first], q_byte[first], p_byte[last], q_byte[last]], axis=1)
    return out[np.lexsort((out[:, 1], out[:, 0]))]


def chains(seg: np.ndarray) -> list[list[int]]:
    """Best collinear chains of segments (p, q, length, ...) in order of p, each segment in one chain at most.

    A chain's score is its matched words less GAP for each word it skips in either text and SHIFT for each word that
    the diagonal moves; a segment follows one that ends before it in both texts.
    """
    n = len(seg)
    if n == 1:
        return [[0]]
    p, q, size = seg[:, 0], seg[:, 1], seg[:, 2]
    p_end, q_end = p + size, q + size
    ranks = np.unique(q_end)
    # two trees: chains that move the diagonal up and down pay SHIFT by the same linear terms with either sign
    above, below = Fenwick(len(ranks)), Fenwick(len(ranks))
    score, back = size.astype(float), [-1] * n
    by_end = np.argsort(p_end, kind="stable")
    done = 0
    for i in range(n):
        while done < n and p_end[by_end[done]] <= p[i]:
            j = int(by_end[done])
            at = int(np.searchsorted(ranks, q_end[j]))
            gap = GAP * (p_end[j] + q_end[j])
            above.put(at, score[j] + gap - SHIFT * (p_end[j] - q_end[j]), j)
            below.put(at, score[j] + gap + SHIFT * (p_end[j] - q_end[j]), j)
            done += 1
        upto = int(np.searchsorted(ranks, q[i], side="right"))
        for tree in (above, below):
            _, j = tree.best(upto)
            if j >= 0:
                shift = abs((p[i] - q[i]) - (p_end[j] - q_end[j]))
                s = score[j] + size[i] - GAP * (p[i] - p_end[j] + q[i] - q_end[j]) - SHIFT * shift
                if s > score[i]:
                    score[i], back[i] = s, j
    out, used = [], [False] * n
    for i in np.argsort(-score, kind="stable").tolist():
        chain = []
        while i >= 0 and not used[i]:
            used[i] = True
            chain.append(i)
            i = back[i]
        if chain:
            out.append(chain[::-1])
    return out


_ITEM = pa.struct([("p0", pa.int32()), ("p1", pa.int32()), ("q0", pa.int32()), ("q1", pa.int32()), ("own", pa.binary())])


def _chain_rows(batches):
    """Streams pairs in order of (rid, lead); one row for two documents, with their chains."""
    held: list = []

    def flush():
        whole = pa.Table.from_batches(held).combine_chunks()
        key = np.stack([whole["rid"].to_numpy(), whole["lead"].to_numpy()], axis=1)
        cut = np.flatnonzero((np.diff(key, axis=0) != 0).any(axis=1)) + 1
        at, lead_at = whole["at"].to_numpy(), whole["lead_at"].to_numpy()
        p, q, p_byte, q_byte = at & 0xFFFFFFFF, lead_at & 0xFFFFFFFF, at >> 32, lead_at >> 32
        ids: list = [[], []]
        n, out = [0], [[] for _ in range(5)]
        for a, b in zip(np.append(0, cut), np.append(cut, len(whole)), strict=True) if len(whole) else ():
            seg = segments(p[a:b], q[a:b], p_byte[a:b], q_byte[a:b])
            for chain in chains(seg):
                own = seg[chain]
                places = (own[:, :3] - [own[0, 0], own[0, 1], 0]).astype("<i4").tobytes()
                for c, v in zip(out, (own[0, 3], own[-1, 5], own[0, 4], own[-1, 6], places), strict=True):
                    c.append(v)
            ids[0].append(key[a, 0])
            ids[1].append(key[a, 1])
            n.append(len(out[0]))
        items = pa.StructArray.from_arrays([pa.array(c, f.type) for c, f in zip(out, _ITEM, strict=True)], fields=list(_ITEM))
        items = pa.ListArray.from_arrays(pa.array(n, pa.int32()), items)
        return pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in ids), items], ["rid", "lead", "items"])

    for batch in batches:
        if not batch.num_rows:
            continue
        # all rows of the last document wait for the next batch
        rid = batch.column("rid").to_numpy()
        change = np.flatnonzero(rid[1:] != rid[:-1])
        if held and held[-1].column("rid")[-1].as_py() != rid[0]:
            yield flush()
            held.clear()
        if len(change):
            at = int(change[-1]) + 1
            held.append(batch.slice(0, at))
            yield flush()
            held.clear()
            held.append(batch.slice(at))
        else:
            held.append(batch)
    if held:
        yield flush()


class Stretches:
    """Words of many short stretches of text at once; words that a stretch's ends may have cut are left out."""

    def __init__(self, column: pa.Array, begins: np.ndarray, least_size: np.ndarray):
        """begins tells which stretches begin with their text; those shorter than least_size end with it."""
        ((_, data, offsets),) = K.chunks(column, 1 << 40)
        words = K.Words(data, offsets, K.PLAIN)
        self.hash, self.start, self.end, self.offsets = words.hash, words.start, words.end, offsets
        self.ends = np.diff(offsets) < least_size
        self.begins = begins
        lo, hi = words.bounds[:-1].copy(), words.bounds[1:].copy()
        some = lo < hi
        lo[some] += ~begins[some] & (self.start[lo[some]] == offsets[:-1][some])
        some = lo < hi
        hi[some] -= ~self.ends[some] & (self.end[hi[some] - 1] == offsets[1:][some])
        self.lo, self.hi = lo, hi

    def place(self, t: np.ndarray, byte: np.ndarray) -> np.ndarray:
        """The words that start at a byte of the stretches t."""
        return np.maximum(np.searchsorted(self.start, self.offsets[t] + byte), self.lo[t])


def grown(a: np.ndarray, b: np.ndarray, i: np.ndarray, j: np.ndarray, i_room: np.ndarray, j_room: np.ndarray, step: int):
    """Words of a and of b, and equal ones among them, by which many stretches grow in one direction at once.

    i, j: the first words outside; i_room, j_room: how many there are. Equal words count 1 and differing ones DIFFER;
    each end stops at its best score, and is given up DROP below it. A differing word is taken as put in, left out or
    changed, by the two words that follow. Also tells how far was looked in both.
    """
    n = len(i)
    now = np.zeros((4, n))  # words of a, of b, equal words, score
    best = np.zeros((4, n))
    act = np.flatnonzero((i_room > 0) & (j_room > 0))
    while len(act):
        # equal words are passed many at a time, the more the fewer stretches still grow
        width = min(512, max(4, 8192 // len(act)))
        x, y = (now[c, act].astype(np.int64)[:, None] + np.arange(width) for c in (0, 1))
        same = (x < i_room[act][:, None]) & (y < j_room[act][:, None])
        same &= a[np.clip(i[act][:, None] + step * x, 0, len(a) - 1)] == b[np.clip(j[act][:, None] + step * y, 0, len(b) - 1)]
        run = np.where(same.all(axis=1), width, same.argmin(axis=1))
        now[:, act] += run
        up = act[now[3, act] > best[3, act]]
        best[:, up] = now[:, up]
        off = act[(run < width) & (now[0, act] < i_room[act]) & (now[1, act] < j_room[act])]
        if len(off):
            u, v = now[0, off].astype(np.int64), now[1, off].astype(np.int64)

            def equal(du: int, dv: int) -> np.ndarray:
                x, y = u + du, v + dv  # noqa: B023
                ok = (x < i_room[off]) & (y < j_room[off])  # noqa: B023
                return ok & (a[np.clip(i[off] + step * x, 0, len(a) - 1)] == b[np.clip(j[off] + step * y, 0, len(b) - 1)])  # noqa: B023

            changed = equal(1, 1)
            more = ~changed & equal(1, 0) & equal(2, 1)
            less = ~changed & ~more & equal(0, 1) & equal(1, 2)
            now[0, off] += ~less
            now[1, off] += ~more
            now[3, off] += DIFFER
        act = act[(now[3, act] >= best[3, act] - DROP) & (now[0, act] < i_room[act]) & (now[1, act] < j_room[act])]
    return best[:3].astype(np.int64), now[:2].astype(np.int64)


def common_in_order(x: list, y: list) -> int:
    """Length of the longest common subsequence, one bit for each item of x."""
    places: dict = {}
    for i, v in enumerate(x):
        places[v] = places.get(v, 0) | 1 << i
    every = (1 << len(x)) - 1
    row = every
    for v in y:
        m = row & places.get(v, 0)
        row = ((row + m) | (row - m)) & every
    return len(x) - row.bit_count()


def columns(a: np.ndarray, b: np.ndarray, anchors: np.ndarray) -> np.ndarray:
    """Rows (words of a, words of b, equal ones) of the stretch that anchors (place in a, place in b, words) span: one
    for each word of an anchor and one for each gap."""
    out, at_a, at_b = [], None, None
    for i, j, n in anchors.tolist():
        if at_a is not None:
            cut = max(max(i, at_a) - i, max(j, at_b) - j)
            if cut >= n:
                continue
            i, j, n = i + cut, j + cut, n - cut
            x, y = a[at_a:i], b[at_b:j]
            if len(x) or len(y):
                out.append(np.array([[len(x), len(y), common_in_order(x.tolist(), y.tolist()) if len(x) and len(y) else 0]]))
        out.append(np.ones((n, 3), np.int64))
        out[-1][:, 2] = a[i : i + n] == b[j : j + n]
        at_a, at_b = i + n, j + n
    return np.concatenate(out)


def stretches_above(score: np.ndarray) -> list[tuple[int, int]]:
    """Where the maximal stretches of positive score begin and end, found in one pass."""
    kept: list = []
    total = 0.0
    for k, s in enumerate(score.tolist()):
        total += s
        if s <= 0:
            continue
        own = (k, k + 1, total - s, total)
        while True:
            at = len(kept) - 1
            while at >= 0 and kept[at][2] >= own[2]:
                at -= 1
            if at < 0 or kept[at][3] >= own[3]:
                break
            own = (kept[at][0], k + 1, kept[at][2], total)
            del kept[at:]
        kept.append(own)
    return [(lo, hi) for lo, hi, _, _ in kept]


def _aligned(pad: int | None):
    def run(batches):
        for batch in batches:
            size = np.cumsum(np.asarray(pc.binary_length(batch.column("a"))).astype(np.int64) + np.asarray(pc.binary_length(batch.column("b"))))
            cuts = np.flatnonzero(np.diff(size // ALIGN_BYTES)) + 1 if len(size) else []
            for lo, hi in zip([0, *cuts], [*cuts, batch.num_rows], strict=True):
                if hi > lo:
                    yield _align_rows(batch.slice(lo, hi - lo), pad)

    return run


def _align_rows(batch: pa.RecordBatch, pad: int | None) -> pa.RecordBatch:
    """Spans found, without own, and with own the chains that equal words still follow where their text is cut.

    With pad, each row is a chain in its stretches; without, all chains (items) of two documents in their whole texts.
    """
    if pad is None:
        items = batch.column("items")
        t = np.repeat(np.arange(len(batch)), np.diff(np.asarray(items.offsets)))
        flat = pa.RecordBatch.from_struct_array(items.flatten())
    else:
        t, flat = np.arange(len(batch)), batch
    rid, lead = (batch.column(c).to_numpy()[t] for c in ("rid", "lead"))
    p0, p1, q0, q1 = (flat.column(c).to_numpy().astype(np.int64) for c in ("p0", "p1", "q0", "q1"))
    a_from, b_from = (np.maximum(0, v - pad) if pad else 0 * v for v in (p0, q0))
    whole = np.ones(len(batch), bool)
    a = Stretches(batch.column("a"), a_from == 0 if pad else whole, p1 + TAIL + pad - a_from if pad else np.inf)
    b = Stretches(batch.column("b"), b_from == 0 if pad else whole, q1 + TAIL + pad - b_from if pad else np.inf)
    packed = flat.column("own").cast(pa.large_binary())
    cut = np.frombuffer(packed.buffers()[1], np.int64)[packed.offset : packed.offset + len(packed) + 1] // 12
    own = np.frombuffer(packed.buffers()[2], "<i4", int(cut[-1]) * 3).reshape(-1, 3).astype(np.int64)
    x0, y0 = a.place(t, p0 - a_from), b.place(t, q0 - b_from)
    last = own[cut[1:] - 1]
    x1, y1 = x0 + last[:, 0] + last[:, 2], y0 + last[:, 1] + last[:, 2]
    is_open = (x1 > a.hi[t]) | (y1 > b.hi[t])

    def grow(row, x0, x1, y0, y1):
        """The stretches grown both ways, and the equal words added."""
        at = t[row]
        rooms = [(x0 - a.lo[at], y0 - b.lo[at]), (a.hi[at] - x1, b.hi[at] - y1)]
        back, seen = grown(a.hash, b.hash, x0 - 1, y0 - 1, *rooms[0], -1)
        is_open[row[((seen[0] + 2 >= rooms[0][0]) & ~a.begins[at]) | ((seen[1] + 2 >= rooms[0][1]) & ~b.begins[at])]] = True
        on, seen = grown(a.hash, b.hash, x1, y1, *rooms[1], 1)
        is_open[row[((seen[0] + 2 >= rooms[1][0]) & ~a.ends[at]) | ((seen[1] + 2 >= rooms[1][1]) & ~b.ends[at])]] = True
        return np.stack([x0 - back[0], x1 + on[0], y0 - back[1], y1 + on[1], back[2] + on[2]], axis=1)

    out: list = []

    def judge(i: int, w: np.ndarray, equal: int) -> bool:
        passed = w[1] - w[0] >= LEAST and equal + w[4] >= IDENTITY * max(w[1] - w[0], w[3] - w[2])
        if passed:
            out.append((i, *w[:4]))
        return bool(passed)

    def align(row: np.ndarray) -> None:
        g = grow(row, x0[row], x1[row], y0[row], y1[row])
        parts: list = []
        for k in np.flatnonzero(~is_open[row] & (g[:, 1] - g[:, 0] >= LEAST)).tolist():
            i = int(row[k])
            col = columns(a.hash, b.hash, own[cut[i] : cut[i + 1]] + [x0[i], y0[i], 0])
            if not judge(i, g[k], int(col[:, 2].sum())):
                at = np.concatenate([[[0, 0, 0]], np.cumsum(col, axis=0)])
                for lo, hi in stretches_above(col[:, 2] + DIFFER * (col[:, :2].max(axis=1) - col[:, 2])):
                    parts.append((i, x0[i] + at[lo, 0], x0[i] + at[hi, 0], y0[i] + at[lo, 1], y0[i] + at[hi, 1], at[hi, 2] - at[lo, 2]))
        if parts:
            own_parts = np.array(parts, np.int64)
            for part, w in zip(own_parts.tolist(), grow(*own_parts[:, :5].T), strict=True):
                judge(part[0], w, part[5])

    left = np.flatnonzero(~is_open)
    if pad:
        align(left)
    left = left[np.lexsort((x0[left], t[left]))] if not pad else left[:0]
    take = 1
    while len(left):
        # the first chains left of each two documents, twice as many each time; what their spans hold, with all equal
        # words around, is done too
        begins = np.flatnonzero(np.append(True, t[left][1:] != t[left][:-1]))
        first = np.arange(len(left)) - np.repeat(begins, np.diff(np.append(begins, len(left)))) < take
        take *= 2
        align(left[first])
        left = left[~first]
        if len(out) and len(left):
            left = left[~_held(np.array(out, np.int64), t, left, x0[left], x1[left], a)]
    done = np.array(out, np.int64).reshape(-1, 5)
    i, u0, u1, v0, _ = done[~is_open[done[:, 0]]].T
    begin, stop, lead_begin = a.start[u0] - a.offsets[t[i]], a.end[u1 - 1] - a.offsets[t[i]], b.start[v0] - b.offsets[t[i]]
    spans = (rid[i], lead[i], a_from[i] + begin, a_from[i] + stop, b_from[i] + lead_begin, u1 - u0, 0 * i)
    o = np.flatnonzero(is_open)
    cols = [pa.array(np.concatenate(c), pa.int64()) for c in zip(spans, (rid[o], lead[o], p0[o], p1[o], q0[o], 0 * o, q1[o]), strict=True)]
    cols.append(pa.concat_arrays([pa.nulls(len(i), pa.binary()), flat.column("own").take(pa.array(o, pa.int64()))]))
    return pa.RecordBatch.from_arrays(cols, ["rid", "lead", "start", "stop", "lead_start", "words", "q1", "own"])


def _held(found: np.ndarray, t: np.ndarray, left: np.ndarray, x0: np.ndarray, x1: np.ndarray, a: Stretches) -> np.ndarray:
    """Which chains left lie in a found span of their two documents with WINDOW words to spare, or up to a text's end."""
    own, lo, hi = t[found[:, 0]], found[:, 1], found[:, 2]
    lo, hi = np.where(lo == a.lo[own], lo - WINDOW, lo), np.where(hi == a.hi[own], hi + WINDOW, hi)
    wide = np.int64(len(a.hash) + 4 * WINDOW)  # places of one row stay below those of the next
    order = np.argsort(own * wide + lo, kind="stable")
    key = (own * wide + lo)[order]
    reach = np.maximum.accumulate((own * wide + hi)[order])
    at = np.searchsorted(key, t[left] * wide + x0 - WINDOW, side="right") - 1
    return (at >= 0) & (reach[np.maximum(at, 0)] >= t[left] * wide + x1 + WINDOW)


def numbered(docs: DataFrame) -> DataFrame:
    """docs (doc_id, text) with rid: doc_id, or where ids are null or stand for different texts, a hash below 0."""
    base = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    mark = F.xxhash64("doc_id", "text")
    ids = base.select("doc_id", mark.alias("t")).groupBy("doc_id").agg(F.min("t").alias("lo"), F.max("t").alias("hi"))
    clash = stored(ids.where("lo <> hi or doc_id is null").select(F.col("doc_id").alias("clash")), "clashes")
    if clash.isEmpty():
        return base.withColumn("rid", F.col("doc_id"))
    hashed = -F.abs(F.shiftright(mark, 1)) - 1
    return base.join(clash, base.doc_id.eqNullSafe(clash.clash), "left").select(
        "doc_id", "text", F.when(F.col("doc_id").isNull() | F.col("clash").isNotNull(), hashed).otherwise(F.col("doc_id")).alias("rid")
    )


def repeated_passages(docs: DataFrame) -> DataFrame:
    """rid, lead, start, stop, lead_start, words: passages of LEAST words that repeat an earlier document's or place's.

    docs: doc_id, rid, text as from numbered(). Bytes of the UTF-8 text from start to before stop repeat those of the
    document lead from lead_start on, with IDENTITY of the words equal in order. lead is the least rid that shares a
    seed, so of all copies of a passage one stays unmarked.
    """
    small_batches(docs.sparkSession)
    seeds = docs.select("rid", "text").mapInArrow(_seeds, "h bigint, rid bigint, at bigint")
    first = seeds.groupBy("h").agg(F.min(F.struct("rid", "at")).alias("l"), F.count("*").alias("c")).where("c > 1")
    # stored, so that the join below has a stage of its own, in which Spark splits the places of a very common seed
    first = stored(first.select("h", F.col("l.rid").alias("lead"), F.col("l.at").alias("lead_at")), "first")
    shared = send(docs.sparkSession, bitmap(first.select(F.pmod("h", F.lit(BITMAP_BITS)).alias("at"))))
    again = docs.select("rid", "text").mapInArrow(_shared_seeds(shared), "h bigint, rid bigint, at bigint")
    pairs = again.join(first, "h").where("rid <> lead or at <> lead_at").select("rid", "lead", "at", "lead_at")
    pairs = pairs.repartition(n_parts(docs.sparkSession), "rid").sortWithinPartitions("rid", "lead", "at")
    item = "struct<p0:int,p1:int,q0:int,q1:int,own:binary>"
    found = stored(pairs.mapInArrow(_chain_rows, f"rid bigint, lead bigint, items array<{item}>"), "chains")
    texts = docs.select("rid", F.col("text").cast("binary").alias("raw"))
    return _align_chains(found, texts)


_SPANS = "rid bigint, lead bigint, start bigint, stop bigint, lead_start bigint, words bigint, q1 bigint, own binary"


def _align_chains(found: DataFrame, texts: DataFrame) -> DataFrame:
    """FEW chains of two documents are aligned in PAD bytes of context; those that go on past it, and the chains of
    documents that have more, all together in whole texts."""

    def stretch(lo: str, hi: str):
        at = F.greatest(F.col(lo) - PAD, F.lit(0))
        return F.substring(F.col("raw"), at + 1, F.col(hi) + TAIL + PAD - at)

    def beside(chains: DataFrame, a, b) -> DataFrame:
        own = chains.join(texts, "rid").withColumn("a", a).drop("raw")
        return own.join(texts.withColumnRenamed("rid", "lead"), "lead").withColumn("b", b).drop("raw")

    few = found.where(F.size("items") <= FEW).select("rid", "lead", F.explode("items").alias("i")).select("rid", "lead", "i.*")
    cols = ["rid", "lead", "p0", "p1", "q0", "q1", "own", "a", "b"]
    near = stored(beside(few, stretch("p0", "p1"), stretch("q0", "q1")).select(*cols).mapInArrow(_aligned(PAD), _SPANS), "aligned")
    item = F.struct(F.col("start").cast("int").alias("p0"), F.col("stop").cast("int").alias("p1"), F.col("lead_start").cast("int").alias("q0"), F.col("q1").cast("int").alias("q1"), "own")
    going = near.where("own is not null").groupBy("rid", "lead").agg(F.collect_list(item).alias("items"))  # FEW at most
    going = going.union(found.where(F.size("items") > FEW))
    far = beside(going, F.col("raw"), F.col("raw")).select("rid", "lead", "items", "a", "b").mapInArrow(_aligned(None), _SPANS)
    return _widest(near.where("own is null").union(far).select("rid", "lead", "start", "stop", "lead_start", "words"))


def _widest(spans: DataFrame) -> DataFrame:
    """Spans that no other span of the same two documents holds: several chains may grow into one passage."""
    before = Window.partitionBy("rid", "lead").orderBy("start", F.desc("stop"), "lead_start").rowsBetween(Window.unboundedPreceding, -1)
    return spans.withColumn("held", F.coalesce(F.max("stop").over(before) >= F.col("stop"), F.lit(False))).where("not held").drop("held")


def marked(docs: DataFrame) -> DataFrame:
    """doc_id, n_spans, repeated_bytes, longest_words, spans (start, stop, words, lead_id, lead_start) for every row of
    docs (doc_id, text).

    Null, empty and short texts have no spans. Rows equal in doc_id and text are one document and get equal answers,
    so they do not repeat each other. lead_id is the rid of the document repeated: its doc_id, or a number below 0 for
    rows whose doc_id is null or stands for several texts. Other columns are ignored.
    """
    rows = numbered(docs)
    alone = rows.groupBy("rid").agg(F.count("*").alias("c")).where("c > 1").isEmpty()
    found = repeated_passages(rows if alone else rows.dropDuplicates(["rid"]))
    span = F.struct("start", "stop", "words", F.col("lead").alias("lead_id"), "lead_start")
    own = found.groupBy("rid").agg(F.array_sort(F.collect_list(span)).alias("spans"), F.max("words").alias("longest_words"))
    zero = F.struct(F.lit(0).cast("bigint").alias("stop"), F.lit(0).cast("bigint").alias("sum"))
    step = lambda acc, s: F.struct(F.greatest(acc["stop"], s["stop"]).alias("stop"), (acc["sum"] + F.greatest(F.lit(0), s["stop"] - F.greatest(acc["stop"], s["start"]))).alias("sum"))
    own = own.withColumn("repeated_bytes", F.aggregate("spans", zero, step, lambda acc: acc["sum"]))
    none = F.array().cast("array<struct<start:bigint,stop:bigint,words:bigint,lead_id:bigint,lead_start:bigint>>")
    return rows.select("doc_id", "rid").join(own, "rid", "left").select(
        "doc_id",
        F.coalesce(F.size("spans"), F.lit(0)).cast("bigint").alias("n_spans"),
        F.coalesce("repeated_bytes", F.lit(0)).cast("bigint").alias("repeated_bytes"),
        F.coalesce("longest_words", F.lit(0)).cast("bigint").alias("longest_words"),
        F.coalesce("spans", none).alias("spans"),
    )


def op9_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return marked(table(spark, sf_dir, "documents").select("doc_id", "text"))
