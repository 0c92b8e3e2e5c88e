"""Level-by-level growth of all trees at once.

Each level is one job: a histogram of (tree, node, feature, bin) for all live nodes, scores, the best split of each
node, and its children. Only the chosen splits, which are the model, come to the driver. Histograms come from one of
two layouts: `Horizontal` walks rows down the trees so far and counts in NumPy blocks, so no row-to-node table
exists; `Vertical` joins per-feature slices with a table of (tree, row, node), and `VerticalBlocks` does so where both
are packed by blocks of rows.
"""

from __future__ import annotations

import sys
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import mix, poisson_numpy, poisson_weight
from ..session import stored
from . import impurity as I
from .reduction import reduce_features
from .spec import ForestSpec

cloudpickle.register_pickle_by_value(sys.modules[__name__])


@dataclass(slots=True)
class Node:
    tree: int
    node: int
    parent: int
    depth: int
    in_bin: int
    stats: list[float]
    used: frozenset = frozenset()
    feature_id: int = -1
    cut: int | None = None
    is_leaf: bool = True
    score: float = 0.0
    children: dict[int, int] = field(default_factory=dict)

    def n(self, task: str) -> float:
        return sum(self.stats) if task == "classification" else self.stats[0]

    def prediction(self, task: str) -> float:
        if task == "classification":
            return float(max(range(len(self.stats)), key=lambda i: (self.stats[i], -i)))
        return self.stats[1] / self.stats[0] if self.stats[0] else 0.0

    def pure(self, task: str) -> bool:
        if task == "classification":
            return sum(s > 0 for s in self.stats) <= 1
        n, a, b = self.stats
        return b / n - (a / n) ** 2 <= 1e-12 if n else True


def child_id(parent: int, in_bin: int, arity: int, depth: int) -> int:
    """A-ary heap number of a child (bins from -1); a hash of the path where that would leave 64 bits."""
    out = arity * parent + in_bin + 2
    if out < 2**62 and parent >= 0:
        return out
    h = (parent * 0x9E3779B97F4A7C15 + in_bin + 2) & (2**64 - 1)
    return -(((h ^ (h >> 29)) * 0xBF58476D1CE4E5B9 & (2**62 - 1)) + 1)


def walk_arrays(nodes: list[Node], n_bins: int) -> dict[int, dict]:
    """Trees as arrays: feature and children by bin of every node, depth and node numbers. Plain data, so that tasks
    read it without a copy of the package."""
    trees: dict[int, dict] = {}
    by: dict[int, list[Node]] = {}
    for x in nodes:
        by.setdefault(x.tree, []).append(x)
    for t, own in by.items():
        own.sort(key=lambda x: (x.depth, x.node))
        at = {x.node: i for i, x in enumerate(own)}
        feature = np.array([-1 if x.is_leaf else x.feature_id for x in own], np.int32)
        child = np.full((len(own), n_bins + 1), -1, np.int32)
        for i, x in enumerate(own):
            if x.is_leaf:
                continue
            if x.cut is None:
                for b, c in x.children.items():
                    child[i, b + 1] = at[c]
                continue
            for b in range(-1, n_bins):
                key = 0 if b <= x.cut else 1
                if key in x.children:
                    child[i, b + 1] = at[x.children[key]]
        trees[t] = {"feature": feature, "child": child, "depth": own[-1].depth, "node": np.array([x.node for x in own], np.int64)}
    return trees


def slots(tree: dict, bins: np.ndarray) -> np.ndarray:
    """The place in the tree's arrays where each row stops: a leaf, or a node that has no child for its bin."""
    at = np.zeros(len(bins), np.int32)
    going = np.arange(len(bins))
    for _ in range(tree["depth"]):
        f = tree["feature"][at[going]]
        going, f = going[f >= 0], f[f >= 0]
        if not len(going):
            break
        nxt = tree["child"][at[going], bins[going, f] + 1]
        going, nxt = going[nxt >= 0], nxt[nxt >= 0]
        at[going] = nxt
    return at


def bins_matrix(batch) -> np.ndarray:
    col = batch.column("bins")
    flat = np.asarray(col.flatten())
    return flat.reshape(len(col), -1) if len(col) else np.zeros((0, 0), np.int32)


def pack_rows(rows: DataFrame, block_rows: int = 65536) -> DataFrame:
    """Binned rows as blocks: ids, targets and one byte per cell, feature after feature (bins from -1 to 254)."""

    def pack(t: pa.Table) -> pa.Table:
        n = len(t)
        bins = np.asarray(t["bins"].combine_chunks().flatten()).reshape(n, -1)
        cells = np.ascontiguousarray((bins + 1).astype(np.uint8).T).tobytes()
        ids, y = t["row_id"].to_numpy().astype("<i8").tobytes(), t["target"].to_numpy().astype("<f8").tobytes()
        return pa.table({"n": pa.array([n], pa.int32()), "ids": pa.array([ids], pa.binary()), "targets": pa.array([y], pa.binary()), "cells": pa.array([cells], pa.binary())})

    block = F.floor(F.col("row_id") / block_rows)
    return rows.withColumn("row_block", block).groupBy("row_block").applyInArrow(pack, "n int, ids binary, targets binary, cells binary")


def decoded(batch):
    """row ids, targets, bins and stored weights by tree, of a batch of rows or of each packed block in it."""
    if "cells" in batch.schema.names:
        for n, ids, y, cells in zip(*(batch.column(c).to_pylist() for c in ("n", "ids", "targets", "cells")), strict=True):
            bins = np.frombuffer(cells, np.uint8).reshape(-1, n).T.astype(np.int32) - 1
            yield np.frombuffer(ids, "<i8"), np.frombuffer(y, "<f8"), bins, {}
    elif batch.num_rows:
        own = {int(c[1:]): np.asarray(batch.column(c)) for c in batch.schema.names if c[0] == "w" and c[1:].isdigit()}
        yield np.asarray(batch.column("row_id")), np.asarray(batch.column("target")), bins_matrix(batch), own


#: Cells of dense counts a task holds (8 bytes each); what is more is put out and summed by the shuffle.
HELD_CELLS = 4_000_000
#: Bins of rows that are counted at once (4 bytes each): the more, the fewer partial counts where not all can be held.
GATHERED = 8_000_000


def gathered(parts, most: int = GATHERED):
    """Decoded parts with those of one kind put together up to so many bins."""

    def joined(held: list):
        one = held[0]
        if len(held) == 1:
            return one
        return *(np.concatenate([h[i] for h in held]) for i in range(3)), {t: np.concatenate([h[3][t] for h in held]) for t in one[3]}

    held: list = []
    size = 0
    for part in parts:
        if held and size + part[2].size > most:
            yield joined(held)
            held, size = [], 0
        held.append(part)
        size += part[2].size
    if held:
        yield joined(held)


def kinds_of(bins: np.ndarray, y: np.ndarray, width: int, n_classes: int) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """Rows with the same bins and class as one: bins and targets of each kind, and every row's kind. None where there
    may be more than a quarter as many kinds as rows."""
    n_features = bins.shape[1]
    if not n_features or 4 * width**n_features * n_classes > len(y):
        return None
    code = y.astype(np.int64)
    for f in range(n_features):
        code = code * width + (bins[:, f] + 1)
    seen = np.bincount(code, minlength=width**n_features * n_classes) > 0
    kinds = np.flatnonzero(seen)
    own = np.stack([kinds // width ** (n_features - 1 - f) % width - 1 for f in range(n_features)], axis=1)
    return own, kinds // width**n_features, (np.cumsum(seen) - 1)[code]


def _block_histogram(sent, task: str, n_classes: int, n_bins: int, seed: int, held: int = HELD_CELLS):
    """Partial histograms of a task's rows, summed before they leave it as far as memory allows.

    Counts of a tree and feature are dense over its live nodes; where these are many more than the rows of a batch,
    only the cells that occur are counted.
    """
    k = I.n_stats(task, n_classes)
    width = n_bins + 1
    names = ["tree", "live", "feature_id", "bin", *I.stat_names(k)]

    def rows(cells: list):
        """One batch of cells (tree, feature, node and bin as one code, statistics)."""
        n = [len(c) for *_, c, _ in cells]
        code, s = np.concatenate([c for *_, c, _ in cells]), np.concatenate([x for *_, x in cells])
        cols = [np.repeat(np.array([c[0] for c in cells], np.int32), n), code // width, np.repeat(np.array([c[1] for c in cells], np.int32), n), (code % width - 1).astype(np.int32)]
        return pa.RecordBatch.from_arrays([pa.array(c) for c in [*cols, *(s[:, i] for i in range(k))]], names)

    def run(batches):
        trees, live, candidates = sent.value  # live: tree -> number of each slot; candidates: tree -> features
        dense: dict = {}
        loose: list = []
        size = 0

        def out():
            cells = list(loose)
            for (t, f), part in dense.items():
                part = part.reshape(-1, k)
                at = np.flatnonzero(part.any(axis=1))
                cells.append((t, f, at, part[at]))
            if cells:
                yield rows(cells)

        for row, y, bins, stored_weights in gathered(part for batch in batches for part in decoded(batch)):
            alike = kinds_of(bins, y, width, k) if task == "classification" and not stored_weights else None
            if alike:
                bins, y, kind = alike
            for t, features in candidates.items():
                w = stored_weights.get(t)
                w = poisson_numpy(row, t, seed) if w is None else w
                if alike:
                    w = np.bincount(kind, w, len(y))
                number = live[t]
                node = number[slots(trees[t], bins)] if t in trees else np.zeros(len(y), np.int64)
                ok = (w > 0) & (node >= 0)
                if not ok.any():
                    continue
                node, wt, own, yt = node[ok], w[ok].astype(float), bins[ok], y[ok]
                n_cells = (int(number.max()) + 1) * width
                for f in features:
                    code = node * width + own[:, f] + 1
                    sparse = n_cells > 8 * len(code)
                    if sparse:
                        seen, code = np.unique(code, return_inverse=True)
                    m = (len(seen) if sparse else n_cells) * k
                    if task == "classification":
                        part = np.bincount(code * k + yt.astype(np.int64), weights=wt, minlength=m)
                    else:
                        part = sum(np.bincount(code * k + i, weights=wt * yt.astype(float) ** i, minlength=m) for i in range(3))
                    if sparse:
                        loose.append((t, f, seen, part.reshape(-1, k)))
                        size += m
                    elif (t, f) in dense:
                        dense[t, f] += part
                    else:
                        dense[t, f] = part
                        size += m
                    if size > held:
                        yield from out()
                        dense.clear()
                        loose.clear()
                        size = 0
        yield from out()

    return run


def _named(count, names):
    """The cells of count with nodes in place of their numbers, without features that a node's path has used."""

    def run(batches):
        ids, features, used = names.value  # tree -> node of each number, sorted features, used (number, place of feature)
        for cells in count(batches):
            tree, live, feature = (np.asarray(cells.column(c)) for c in ("tree", "live", "feature_id"))
            node, keep = np.zeros(len(tree), np.int64), np.ones(len(tree), bool)
            for t in np.unique(tree).tolist():
                at = np.flatnonzero(tree == t)
                node[at] = ids[t][live[at]]
                if t in used:
                    keep[at] = ~used[t][live[at], np.searchsorted(features[t], feature[at])]
            out = pa.RecordBatch.from_arrays([pa.array(node) if c == "live" else cells.column(c) for c in cells.schema.names], ["node" if c == "live" else c for c in cells.schema.names])
            yield out if keep.all() else out.filter(pa.array(keep))

    return run


class Dense:
    """What a source says whose histograms hold every feature of every node."""

    #: Whether histograms leave out the features that a node's path has used.
    leaves_used = False

    def totals(self, hist: DataFrame, names: list[str]) -> DataFrame:
        """tree and the statistics of its root."""
        return hist.where("feature_id = 0").groupBy("tree").agg(*[F.sum(s).alias(s) for s in names])

    def every_score(self, scores: DataFrame, criterion: str) -> DataFrame:
        """Root scores of all features of all trees."""
        return scores


class Horizontal(Dense):
    """Histograms from binned rows in place, or from packed blocks of them; rows find their nodes by walking the trees
    so far."""

    leaves_used = True

    def __init__(self, rows: DataFrame, spec: ForestSpec, n_classes: int):
        self.rows, self.spec, self.n_classes = rows, spec, n_classes

    def histogram(self, nodes: list[Node], live: list[Node], candidates: dict[int, list[int]]) -> DataFrame:
        spec, spark = self.spec, self.rows.sparkSession
        trees = walk_arrays(nodes, spec.n_bins)
        by: dict[int, list[Node]] = {}
        for x in live:
            by.setdefault(x.tree, []).append(x)
        numbers, ids, features, used = {}, {}, {}, {}
        for t, own in by.items():
            ids[t] = np.array([x.node for x in own], np.int64)
            known = trees[t]["node"]
            order = np.argsort(known)
            numbers[t] = np.full(len(known), -1, np.int64)
            numbers[t][order[np.searchsorted(known, ids[t], sorter=order)]] = np.arange(len(own))
            place = {f: i for i, f in enumerate(sorted(candidates[t]))}
            features[t] = np.array(list(place), np.int64)
            past = [(i, place[f]) for i, x in enumerate(own) for f in x.used if f in place]
            if past:
                used[t] = np.zeros((len(own), len(place)), bool)
                used[t][tuple(np.array(past).T)] = True
        sent = spark.sparkContext.broadcast(({t: trees[t] for t in by}, numbers, {t: candidates[t] for t in by}))
        names = spark.sparkContext.broadcast((ids, features, used))
        k = I.n_stats(spec.task, self.n_classes)
        ddl = "tree int, node bigint, feature_id int, bin int, " + ", ".join(f"{s} double" for s in I.stat_names(k))
        part = self.rows.mapInArrow(_named(_block_histogram(sent, spec.task, self.n_classes, spec.n_bins, spec.seed), names), ddl)
        return part.groupBy(*I.CELL).agg(*[F.sum(s).alias(s) for s in I.stat_names(k)])

    def advance(self, splits: list[Node]) -> None:
        pass


class Vertical(Dense):
    """Histograms from slices (feature_id, row_id, bin, target) and assignments (tree, row_id, node, w)."""

    def __init__(self, slices: DataFrame, weights: DataFrame, spec: ForestSpec, n_classes: int):
        self.slices, self.spec, self.n_classes = slices, spec, n_classes
        self.assigned = weights.where("w > 0").select("tree", "row_id", "w", F.lit(0).cast("bigint").alias("node"))

    def histogram(self, nodes: list[Node], live: list[Node], candidates: dict[int, list[int]]) -> DataFrame:
        """Only slices of wanted features are read, and only open nodes' rows meet them: what is sent are the features of
        a tree group's trees and their open nodes, not each pair of these."""
        spark = self.slices.sparkSession
        wanted = spark.createDataFrame([(t, f) for t in sorted({x.tree for x in live}) for f in candidates[t]], "tree int, feature_id int")
        nodes_open = spark.createDataFrame([(x.tree, x.node) for x in live], "tree int, node bigint")
        slices = self.slices.where(F.col("feature_id").isin(sorted({f for x in live for f in candidates[x.tree]})))
        rows = self.assigned.join(F.broadcast(nodes_open), ["tree", "node"], "left_semi")
        cells = slices.join(rows, "row_id").join(F.broadcast(wanted), ["tree", "feature_id"])
        return I.histogram(cells, self.spec.task, self.n_classes)

    def advance(self, splits: list[Node]) -> None:
        """Rows of split nodes move to the child of their bin; rows of leaves drop out."""
        spark = self.slices.sparkSession
        rows = [(x.tree, x.node, x.feature_id, b, c) for x in splits for key, c in x.children.items() for b in self._bins(x, key)]
        frame = spark.createDataFrame(rows, "tree int, node bigint, feature_id int, bin int, child bigint")
        moved = self.assigned.join(F.broadcast(frame.select("tree", "node", "feature_id").distinct()), ["tree", "node"]).join(self.slices.select("feature_id", "row_id", "bin"), ["feature_id", "row_id"])
        moved = moved.join(F.broadcast(frame), ["tree", "node", "feature_id", "bin"]).select("tree", "row_id", "w", F.col("child").alias("node"))
        self.assigned = stored(moved, "assigned")

    def _bins(self, x: Node, key: int) -> list[int]:
        if x.cut is None:
            return [key]
        return [b for b in range(-1, self.spec.n_bins) if (b <= x.cut) == (key == 0)]


#: Cells of a block of slices with its assignments: rows times features and trees.
BLOCK_CELLS = 2_000_000


def pack_slices(rows: DataFrame, block_rows: int, n_classes: int) -> DataFrame:
    """Slices of binned rows, packed where the rows are: row_block, feature_id, bins (one byte a cell, from 0 for bin -1)
    and targets; and as feature -1 the block's row ids. Targets that are no class become n_classes."""
    kind = "<u1" if n_classes < 256 else "<u4"

    def run(batches):
        from pyspark import TaskContext

        parts = (part[:3] + ({},) for batch in batches for part in decoded(batch))
        first, number = TaskContext.get().partitionId() << 32, 0
        for ids, y, bins, _ in gathered(parts):
            y = y.astype(float)
            y = np.where((y >= 0) & (y < n_classes), y, n_classes).astype(kind)
            for at in range(0, len(ids), block_rows):
                own, targets = slice(at, at + block_rows), y[at : at + block_rows].tobytes()
                cells = (bins[own] + 1).astype(np.uint8).T
                n = len(cells)
                names = ["row_block", "feature_id", "bins", "targets"]
                cols = [pa.array([first + number] * (n + 1), pa.int64()), pa.array(range(-1, n), pa.int32()), pa.array([ids[own].astype("<i8").tobytes(), *(c.tobytes() for c in cells)], pa.binary()), pa.array([b"", *[targets] * n], pa.binary())]
                yield pa.RecordBatch.from_arrays(cols, names)
                number += 1

    return rows.select("row_id", "target", "bins").mapInArrow(run, "row_block bigint, feature_id int, bins binary, targets binary")


class VerticalBlocks(Dense):
    """Vertical for classifiers whose weights are a function of row and tree: slices and assignments are packed by
    blocks of rows and meet by block, where a row is its place. Nodes of a tree go by number, 0 for rows that are out."""

    ASSIGNED = "tree int, row_block bigint, w binary, nodes binary"

    def __init__(self, rows: DataFrame, trees: list[int], spec: ForestSpec, n_classes: int, n_features: int):
        self.spec, self.n_classes = spec, n_classes
        packed = stored(pack_slices(rows, max(1, BLOCK_CELLS // (n_features + len(trees))), n_classes), "slices")
        self.slices = packed.where("feature_id >= 0")
        self.numbers = {t: {0: 1} for t in trees}
        seed = spec.seed

        def draw(batches):
            for batch in batches:
                for block, ids in zip(batch.column("row_block").to_pylist(), batch.column("bins").to_pylist(), strict=True):
                    for t in trees:
                        w = poisson_numpy(np.frombuffer(ids, "<i8"), t, seed).astype(np.uint8)
                        cols = [pa.array([t], pa.int32()), pa.array([block], pa.int64()), pa.array([w.tobytes()], pa.binary()), pa.array([(w > 0).astype("<u2").tobytes()], pa.binary())]
                        yield pa.RecordBatch.from_arrays(cols, ["tree", "row_block", "w", "nodes"])

        ids = packed.where("feature_id = -1").select("row_block", "bins")
        self.assigned, self.kind = stored(ids.mapInArrow(draw, self.ASSIGNED), "assigned"), "<u2"

    def _met(self, features: dict[int, list[int]], run, ddl: str) -> DataFrame:
        """What run makes of each block's slices of the trees' features and its assignments of these trees."""
        slices = self.slices.where(F.col("feature_id").isin(sorted({f for fs in features.values() for f in fs})))
        rows = self.assigned.where(F.col("tree").isin(sorted(features)))
        return slices.groupBy("row_block").cogroup(rows.groupBy("row_block")).applyInArrow(run, ddl)

    def histogram(self, nodes: list[Node], live: list[Node], candidates: dict[int, list[int]]) -> DataFrame:
        """Only slices of wanted features are read, and only open nodes' rows are counted."""
        k, width, spec, kind = self.n_classes, self.spec.n_bins + 1, self.spec, self.kind
        names = I.stat_names(k)
        by: dict[int, list[int]] = {}
        for x in live:
            by.setdefault(x.tree, []).append(x.node)
        place = {t: np.full(max(self.numbers[t].values()) + 1, -1, np.int64) for t in by}
        for t, own in by.items():
            place[t][[self.numbers[t][n] for n in own]] = np.arange(len(own))
        wanted = {t: sorted(candidates[t]) for t in by}
        sent = self.slices.sparkSession.sparkContext.broadcast(({t: np.array(own, np.int64) for t, own in by.items()}, place, wanted))
        targets_kind = "<u1" if k < 256 else "<u4"

        def count(slices: pa.Table, assigned: pa.Table) -> pa.Table:
            ids, place, wanted = sent.value
            found = {f: (b, y) for f, b, y in zip(*(slices[c].to_pylist() for c in ("feature_id", "bins", "targets")), strict=True)}
            out = []
            for t, w, at in zip(*(assigned[c].to_pylist() for c in ("tree", "w", "nodes")), strict=True):
                node = place[t][np.frombuffer(at, kind)]
                rows = np.flatnonzero(node >= 0)
                if not len(rows):
                    continue
                node, w = node[rows] * (width * k), np.frombuffer(w, np.uint8)[rows].astype(float)
                n_cells = len(ids[t]) * width
                for f in wanted[t]:
                    y = np.frombuffer(found[f][1], targets_kind)[rows]
                    code, own = node + np.frombuffer(found[f][0], np.uint8)[rows] * np.int64(k) + y, w
                    if not (known := y < k).all():
                        code, own = code[known], w[known]
                    if n_cells > 8 * len(code):
                        seen, code = np.unique(code // k, return_inverse=True), code % k
                        cells, part = seen[0], np.bincount(seen[1] * k + code, weights=own, minlength=len(seen[0]) * k).reshape(-1, k)
                    else:
                        part = np.bincount(code, weights=own, minlength=n_cells * k).reshape(-1, k)
                        cells = np.flatnonzero(part.any(axis=1))
                        part = part[cells]
                    out.append((np.full(len(cells), t, np.int32), ids[t][cells // width], np.full(len(cells), f, np.int32), (cells % width - 1).astype(np.int32), *part.T))
            cols = [np.concatenate(c) for c in zip(*out, strict=True)] if out else [np.zeros(0, d) for d in (np.int32, np.int64, np.int32, np.int32, *[float] * k)]
            return pa.table([pa.array(c) for c in cols], [*I.CELL, *names])

        part = self._met(wanted, count, "tree int, node bigint, feature_id int, bin int, " + ", ".join(f"{s} double" for s in names))
        return part.groupBy(*I.CELL).agg(*[F.sum(s).alias(s) for s in names])

    def advance(self, splits: list[Node]) -> None:
        """Rows of split nodes move to the child of their bin; rows of leaves drop out."""
        by: dict[int, list[Node]] = {}
        for x in splits:
            by.setdefault(x.tree, []).append(x)
        numbers = {t: {c: i + 1 for i, c in enumerate(c for x in own for c in x.children.values())} for t, own in by.items()}
        old, kind = self.kind, "<u2" if max(len(n) for n in numbers.values()) < 2**16 else "<u4"
        step: dict[int, dict[int, np.ndarray]] = {}  # tree -> feature -> child by node and bin
        for t, own in by.items():
            size = max(self.numbers[t].values()) + 1, self.spec.n_bins + 1
            for x in own:
                table = step.setdefault(t, {}).setdefault(x.feature_id, np.zeros(size, kind))
                for key, c in x.children.items():
                    for b in bins_of(x, key, self.spec.n_bins):
                        table[self.numbers[t][x.node], b + 1] = numbers[t][c]
        sent = self.slices.sparkSession.sparkContext.broadcast(step)

        def move(slices: pa.Table, assigned: pa.Table) -> pa.Table:
            step = sent.value
            bins = {f: np.frombuffer(b, np.uint8) for f, b in zip(slices["feature_id"].to_pylist(), slices["bins"].to_pylist(), strict=True)}
            moved = []
            for t, at in zip(assigned["tree"].to_pylist(), assigned["nodes"].to_pylist(), strict=True):
                node = np.frombuffer(at, old)
                child = np.zeros(len(node), kind)
                for f, table in step[t].items():
                    child += table[node, bins[f]]  # a node is split by one feature
                moved.append(child.tobytes())
            return assigned.set_column(assigned.schema.get_field_index("nodes"), "nodes", pa.array(moved, pa.binary()))

        moved = self._met({t: list(tables) for t, tables in step.items()}, move, self.ASSIGNED)
        self.assigned, self.numbers, self.kind = stored(moved, "assigned"), numbers, kind


def bins_of(x: Node, key: int, n_bins: int) -> list[int]:
    """The bins that lead to a node's child."""
    return [key] if x.cut is None else [b for b in range(-1, n_bins) if (b <= x.cut) == (key == 0)]


def node_features(scores: DataFrame, m: int, seed: int) -> DataFrame:
    """Only m features of each node, by a hash of (feature, tree, node)."""
    from pyspark.sql import Window

    key = mix(F.col("feature_id") + F.col("node") * 131, F.col("tree"), seed + 2)
    order = Window.partitionBy("tree", "node").orderBy(key, "feature_id")
    return scores.withColumn("__r", F.row_number().over(order)).where(F.col("__r") <= m).drop("__r")


def _split_level(hist: DataFrame, live: list[Node], spec: ForestSpec, n_classes: int, leaves_used: bool = False) -> list[Node]:
    """Chooses the split of every live node; returns the children. Winning cells come to the driver: they are the model.
    leaves_used: hist has no features that a node's path has used."""
    spark = hist.sparkSession
    hist = stored(hist, "histogram") if spec.state == "disk" else hist.persist()
    binary = spec.tree == "cart"
    scores = I.binary_gains(hist, spec.task, n_classes) if binary else I.gains(hist, spec.task, n_classes)
    criterion = "gain" if binary else spec.criterion
    if not binary and not leaves_used:
        used = [(x.tree, x.node, f) for x in live for f in x.used]
        if used:
            scores = scores.join(F.broadcast(spark.createDataFrame(used, "tree int, node bigint, feature_id int")), ["tree", "node", "feature_id"], "left_anti")
    if spec.feature_draw == "node":
        scores = node_features(scores, spec.n_selected, spec.seed)
    best = I.best_splits(scores, criterion).where(F.round(criterion, 10) > spec.min_gain)
    cut = F.col("cut") if binary else F.lit(None).cast("int")
    best = best.select("tree", "node", "feature_id", cut.alias("cut"), F.col(criterion).alias("score"))
    names = I.stat_names(I.n_stats(spec.task, n_classes))
    cells = hist.join(F.broadcast(best), ["tree", "node", "feature_id"]).toArrow()  # one best per live node of a tree group
    if spec.state != "disk":
        hist.unpersist()
    weight = np.add.reduce([cells[c].to_numpy() for c in (names if spec.task == "classification" else names[:1])])
    cells = cells.filter(pa.array(weight > 0)).sort_by([(c, "ascending") for c in ("tree", "node", "bin")])
    tree, node, bins, feature, score, cuts = (cells[c].to_pylist() for c in ("tree", "node", "bin", "feature_id", "score", "cut"))
    stats = np.column_stack([cells[c].to_numpy() for c in names]).tolist() if len(tree) else []
    first: dict = {}
    starts = [i for i in range(len(tree)) if not i or node[i] != node[i - 1] or tree[i] != tree[i - 1]]
    for i, end in zip(starts, [*starts[1:], len(tree)], strict=True):
        first[tree[i], node[i]] = i, end
    children = []
    for x in live:
        at, end = first.get((x.tree, x.node), (0, 0))
        if at == end:
            continue
        cut = cuts[at]
        merged: dict[int, list[float]] = {}
        for i in range(at, end):
            key = bins[i] if cut is None else (0 if bins[i] <= cut else 1)
            merged[key] = [a + b for a, b in zip(merged[key], stats[i], strict=True)] if key in merged else stats[i]
        x.score = score[at]
        if len(merged) < 2:
            continue
        x.feature_id, x.cut, x.is_leaf = feature[at], cut, False
        used = x.used if binary else x.used | {x.feature_id}
        for b in sorted(merged):
            number = child_id(x.node, b, spec.n_bins + 1, x.depth + 1)
            x.children[b] = number
            children.append(Node(x.tree, number, x.node, x.depth + 1, b, merged[b], used))
    return children


def _open(x: Node, candidates: dict[int, list[int]], spec: ForestSpec) -> bool:
    def left() -> bool:
        return spec.tree == "cart" or any(f not in x.used for f in candidates[x.tree])

    return x.depth < spec.max_depth and x.n(spec.task) >= spec.min_rows and not x.pure(spec.task) and left()


def grow(source, roots: list[Node], candidates: dict[int, list[int]], spec: ForestSpec, n_classes: int, first: DataFrame | None = None) -> list[Node]:
    """Grows the trees of roots from histograms of source; candidates: features of each tree; first: the histogram of
    the roots, if it is there already."""
    nodes = list(roots)
    live = [x for x in roots if _open(x, candidates, spec)]
    while live:
        known = first is not None and live[0].depth == 0 and spec.parallel == "both"
        hist = (of_candidates(first, live, candidates) if spec.reduction else first) if known else _histogram(source, nodes, live, candidates, spec)
        children = _split_level(hist, live, spec, n_classes, source.leaves_used)
        nodes += children
        split = [x for x in live if not x.is_leaf]
        if not split:
            break
        live = [x for x in children if _open(x, candidates, spec)]
        if live:
            source.advance(split)
    return nodes


def _histogram(source, nodes: list[Node], live: list[Node], candidates: dict[int, list[int]], spec: ForestSpec) -> DataFrame:
    """One job for all trees and features of a level; without one or both kinds of parallelism, one job for each
    feature, tree, or pair of them (for the ablation)."""
    if spec.parallel == "both":
        return source.histogram(nodes, live, candidates)
    trees = sorted({x.tree for x in live})
    features = sorted({f for t in trees for f in candidates[t]})
    by_tree = [[t] for t in trees] if spec.parallel in ("features", "none") else [trees]
    by_feature = [[f] for f in features] if spec.parallel in ("trees", "none") else [features]
    parts = []
    for own in by_tree:
        for some in by_feature:
            group = [x for x in live if x.tree in own]
            wanted = {t: [f for f in candidates[t] if f in some] for t in own}
            if any(wanted.values()):
                parts.append(stored(source.histogram(nodes, group, wanted), "histogram"))
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


def of_candidates(hist: DataFrame, live: list[Node], candidates: dict[int, list[int]]) -> DataFrame:
    """The cells of live trees' own features."""
    wanted = hist.sparkSession.createDataFrame([(x.tree, f) for x in live for f in candidates[x.tree]], "tree int, feature_id int")
    return hist.join(F.broadcast(wanted), ["tree", "feature_id"], "left_semi")  # n_selected rows per tree


def root_histogram(source, trees: list[int], n_features: int, spec: ForestSpec) -> DataFrame:
    roots = [Node(t, 0, -1, 0, -1, []) for t in trees]
    every = list(range(n_features))
    return source.histogram(roots, roots, dict.fromkeys(trees, every))


def reduced_roots(source, trees: list[int], n_features: int, spec: ForestSpec, n_classes: int) -> tuple[list[Node], dict[int, list[int]], list, DataFrame]:
    """Roots with their statistics, features of each tree, the selection rows (tree, rank, feature_id, origin), and the
    roots' histogram."""
    hist = stored(root_histogram(source, trees, n_features, spec), "root")
    names = I.stat_names(I.n_stats(spec.task, n_classes))
    totals = source.totals(hist, names).collect()  # a row per tree
    roots = [Node(r.tree, 0, -1, 0, -1, [r[s] for s in names]) for r in sorted(totals, key=lambda r: r.tree)]
    everything = dict.fromkeys([r.tree for r in roots], list(range(n_features)))
    if not spec.reduction:
        return roots, everything, [(t, i + 1, f, "all") for t, fs in everything.items() for i, f in enumerate(fs)], hist
    scores = source.every_score(I.gains(hist, spec.task, n_classes), spec.criterion)
    if spec.reduction_scope == "shared":
        mean = scores.groupBy("feature_id").agg(F.avg(spec.criterion).alias(spec.criterion))
        scores = scores.select("tree").distinct().crossJoin(F.broadcast(mean))  # one row per feature on the right
    chosen = reduce_features(I.importance(scores, spec.criterion), spec.n_principal, spec.n_selected, spec.seed)
    rows = [(r.tree, r.rank, r.feature_id, r.origin) for r in chosen.collect()]  # n_selected rows per tree
    selected: dict[int, list[int]] = {}
    for t, _, f, _ in sorted(rows):
        selected.setdefault(t, []).append(f)
    return roots, selected, sorted(rows), hist


def weighted_rows(rows: DataFrame, trees: list[int], spec: ForestSpec, weights: DataFrame | None) -> DataFrame:
    """binned rows with stored weights as columns w<tree>, where weights are not a function of row and tree."""
    if weights is None:
        return rows
    wide = weights.groupBy("row_id").agg(*[F.sum(F.when(F.col("tree") == t, F.col("w")).otherwise(0)).cast("double").alias(f"w{t}") for t in trees])
    cols = [F.coalesce(F.col(f"w{t}"), F.lit(0.0)).alias(f"w{t}") for t in trees]
    return rows.join(wide, "row_id", "left").select(*rows.columns, *cols)


def functional_weights(rows: DataFrame, trees: list[int], seed: int) -> DataFrame:
    every = rows.select("row_id").withColumn("tree", F.explode(F.array(*[F.lit(t) for t in trees])))
    return every.withColumn("w", poisson_weight(F.col("row_id"), F.col("tree"), seed)).where("w > 0")
