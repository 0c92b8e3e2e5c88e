"""NumPy kernels over Arrow text columns. Pickled by value, so executors need no copy of the package."""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Texts are worked on in chunks of so many bytes, or one at a time if longer.
CHUNK_BYTES = 1_000_000
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_space = np.zeros(256, bool)
_space[[32, 9, 10, 11, 12, 13]] = True
#: Which bytes, after A-Z are lowered, belong to a word.
SPACED = ~_space
PLAIN = np.zeros(256, bool)
PLAIN[48:58] = PLAIN[97:123] = PLAIN[128:] = True


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit integers (xor-shift and multiply)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_BYTE = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_BASE = np.uint64(0xD6E8FEB86659FD93)


def _powers(n: int) -> np.ndarray:
    out = np.full(max(n, 1), _BASE, np.uint64)
    out[0] = 1
    return np.cumprod(out, dtype=np.uint64)


def chunks(texts: pa.Array, most: int = CHUNK_BYTES):
    """Cuts an Arrow column of texts, or of UTF-8 bytes, into (first row, bytes, offsets); nulls have no bytes."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = texts.cast(pa.large_binary() if pa.types.is_binary(texts.type) else pa.large_string())
    n = len(texts)
    if not n:
        return
    offsets = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + n + 1]
    raw = texts.buffers()[2]
    data = np.frombuffer(raw, np.uint8) if raw is not None else np.zeros(0, np.uint8)
    if texts.null_count:
        valid = texts.is_valid().to_numpy(zero_copy_only=False)
        lengths = np.where(valid, np.diff(offsets), 0)
        if (np.diff(offsets)[~valid] > 0).any():
            data = np.concatenate([data[offsets[i] : offsets[i + 1]] for i in np.flatnonzero(valid)] or [data[:0]])
            offsets = np.concatenate([[0], np.cumsum(lengths)])
    lo = 0
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + most, side="right")) - 1)
        hi = min(hi, n)
        yield lo, data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
        lo = hi
    pa.default_memory_pool().release_unused()


class Words:
    """Words of a chunk of texts: byte range and hash of each, and which words belong to which text."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, kind: np.ndarray = SPACED):
        low = LOWER[data]
        isw = kind[low]
        n = len(low)
        edge = np.zeros(n + 1, bool)
        edge[offsets] = True
        before = np.empty(n, bool)
        if n:
            before[0] = False
            before[1:] = isw[:-1]
        after = np.empty(n, bool)
        if n:
            after[-1] = False
            after[:-1] = isw[1:]
        self.bytes = low
        self.start = np.flatnonzero(isw & (~before | edge[:-1]))
        self.end = np.flatnonzero(isw & (~after | edge[1:])) + 1
        self.bounds = np.searchsorted(self.start, offsets)  # words of text i: bounds[i]:bounds[i+1]
        lengths = self.end - self.start
        if len(self.start):
            inside = np.flatnonzero(isw)
            first = np.cumsum(lengths) - lengths
            place = np.arange(len(inside)) - np.repeat(first, lengths)
            part = _BYTE[low[inside]] * _powers(int(lengths.max()))[place]
            self.hash = mix(np.add.reduceat(part, first) + lengths.astype(np.uint64))
        else:
            self.hash = np.zeros(0, np.uint64)

    def grams(self, k: int) -> np.ndarray:
        """Hash of the k words from each place on; only places with k words in their text mean anything."""
        h = self.hash
        out = np.zeros(len(h), np.uint64)
        for j in range(k):
            step = np.zeros(len(h), np.uint64)
            step[: max(0, len(h) - j)] = h[j:]
            out = (out + step) * _BASE + np.uint64(j + 1)
        return mix(out)

    def of(self, i: int) -> slice:
        return slice(int(self.bounds[i]), int(self.bounds[i + 1]))

    def text(self, j: int) -> bytes:
        return self.bytes[self.start[j] : self.end[j]].tobytes()


def shingle_sets(words: Words, k: int):
    """For each text its distinct k-word shingle hashes, sorted; all words as one where there are fewer than k."""
    grams = words.grams(k)
    for i in range(len(words.bounds) - 1):
        a, b = int(words.bounds[i]), int(words.bounds[i + 1])
        if b - a >= k:
            yield np.unique(grams[a : b - k + 1])
        elif b > a:
            yield words_as_one(words.hash[a:b])
        else:
            yield np.zeros(0, np.uint64)


def words_as_one(h: np.ndarray) -> np.ndarray:
    x = np.array([len(h)], np.uint64)
    for v in h:
        x = (x + v) * _BASE + np.uint64(7)
    return mix(x ^ np.uint64(0x5851F42D4C957F2D))


def set_key(s: np.ndarray) -> bytes:
    """128 bits that stand for a set of hashes."""
    if not len(s):
        return b""
    with np.errstate(over="ignore"):
        a = np.add.reduce(mix(s ^ np.uint64(0x2545F4914F6CDD1D)))
        b = np.add.reduce(mix(s + np.uint64(0x632BE59BD9B4E019)))
        return mix(np.array([a, b ^ np.uint64(len(s))], np.uint64)).astype(">u8").tobytes()


def hash_family(n: int, seed: int = 20) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    return rng.integers(1, 2**32, n, dtype=np.uint32) | np.uint32(1), rng.integers(0, 2**32, n, dtype=np.uint32)


def min_hashes(s: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least value of each hash of the family over the set."""
    x = (s >> np.uint64(32)).astype(np.uint32)
    out = np.full(len(a), 0xFFFFFFFF, np.uint32)
    for i in range(0, len(x), 1024):
        part = x[i : i + 1024]
        out = np.minimum(out, (a[:, None] * part[None, :] + b[:, None]).min(axis=1))
    return out


def binary(rows: list, kind=None) -> pa.Array:
    return pa.array(rows, kind or pa.binary())
