"""A hash of (row, tree, seed) that Spark and SQL engines compute alike, and bootstrap weights from it."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: The modulus, and the distribution function of the Poisson law of mean 1 at 0..5.
PRIME = 2147483647
POISSON = (0.36787944117144233, 0.7357588823428847, 0.9196986029286058, 0.9810118431238462, 0.9963401531726563, 0.9994058151824183)


def mix(row: Column, tree: Column, seed: int = 42) -> Column:
    """Three squaring rounds modulo 2^31 - 1; 0 <= mix < PRIME."""
    p = F.lit(PRIME).cast("bigint")
    r = row.cast("bigint") % p
    t = tree.cast("bigint")
    a = (r * 1000003 + t * 7919 + (17 + seed)) % p
    b = ((a * a) % p + t * 104729 + r * 31 + 5) % p
    c = ((b * b) % p + t * 15485863 + r + 11) % p
    return (c * c) % p


def _folded(x: np.ndarray) -> np.ndarray:
    """x modulo 2^31 - 1 for 0 <= x < 2^62: the high bits count once each, so they are added to the low ones."""
    x = (x >> 31) + (x & PRIME)
    x = (x >> 31) + (x & PRIME)
    x[x == PRIME] = 0
    return x


def mix_numpy(row: np.ndarray, tree: int, seed: int = 42) -> np.ndarray:
    tree, seed = int(tree) % PRIME, int(seed)
    r = np.atleast_1d(row).astype(np.int64) % np.int64(PRIME)
    a = _folded(r * 1000003 + (tree * 7919 + 17 + seed) % PRIME)
    b = _folded(_folded(a * a) + r * 31 + (tree * 104729 + 5) % PRIME)
    c = _folded(_folded(b * b) + r + (tree * 15485863 + 11) % PRIME)
    return _folded(c * c)


def mix_sql(row: str, tree: str, seed: int = 42) -> str:
    """The same as text for a SQL engine with 64-bit integers."""
    p, row, tree = PRIME, f"CAST({row} AS BIGINT)", f"CAST({tree} AS BIGINT)"
    a = f"((({row}) % {p} * 1000003 + ({tree}) * 7919 + {17 + seed}) % {p})"
    b = f"(({a} * {a} % {p} + ({tree}) * 104729 + ({row}) % {p} * 31 + 5) % {p})"
    c = f"(({b} * {b} % {p} + ({tree}) * 15485863 + ({row}) % {p} + 11) % {p})"
    return f"({c} * {c} % {p})"


def uniform(row: Column, tree: Column, seed: int = 42) -> Column:
    return mix(row, tree, seed) / F.lit(float(PRIME))


def poisson_weight(row: Column, tree: Column, seed: int = 42) -> Column:
    """How often a row is drawn for a tree, as a function of both: nothing is stored."""
    u = uniform(row, tree, seed)
    w = F.lit(len(POISSON))
    for k in range(len(POISSON) - 1, -1, -1):
        w = F.when(u < POISSON[k], F.lit(k)).otherwise(w)
    return w


def poisson_numpy(row: np.ndarray, tree: int, seed: int = 42) -> np.ndarray:
    return np.searchsorted(np.array(POISSON), mix_numpy(row, tree, seed) / float(PRIME), side="right")


def poisson_sql(row: str, tree: str, seed: int = 42) -> str:
    u = f"({mix_sql(row, tree, seed)} / {float(PRIME)}::DOUBLE)"
    cases = " ".join(f"WHEN {u} < {p}::DOUBLE THEN {k}" for k, p in enumerate(POISSON))
    return f"(CASE {cases} ELSE {len(POISSON)} END)"


#: Draws of a row are counted up to so many.
MOST_DRAWS = 24


def drawn_weight(row: Column, tree: Column, mean: Column, seed: int = 42) -> Column:
    """poisson_weight with any mean: how many steps of the distribution function the row's number has passed."""
    def passed(x: Column) -> Column:
        none = F.exp(-x["mean"])
        start = F.struct(none.alias("step"), none.alias("total"), (x["u"] >= none).cast("int").alias("w"))

        def on(acc: Column, k: Column) -> Column:
            step = acc["step"] * x["mean"] / k
            return F.struct(step.alias("step"), (acc["total"] + step).alias("total"), (acc["w"] + (x["u"] >= acc["total"] + step).cast("int")).alias("w"))

        return F.aggregate(F.transform(F.sequence(F.lit(1), F.lit(MOST_DRAWS - 1)), lambda k: k.cast("double")), start, on, lambda acc: acc["w"])

    return F.transform(F.array(F.struct(uniform(row, tree, seed).alias("u"), mean.alias("mean"))), passed)[0]


def drawn_sql(row: str, tree: str, mean: str, seed: int = 42) -> str:
    u = f"({mix_sql(row, tree, seed)} / {float(PRIME)}::DOUBLE)"
    below = f"exp(-({mean})) * list_sum(list_transform(range(k + 1), lambda j: pow({mean}, j) / gamma(j + 1.0)))"
    return f"len(list_filter(range({MOST_DRAWS}), lambda k: {u} >= {below}))"
