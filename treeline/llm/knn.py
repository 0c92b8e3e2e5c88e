"""Exact top-k inner products by a Voronoi join: pivots, cell summaries, group bounds, and local solution.

Every vector goes to the cell of its nearest pivot. From each cell's size, radius, largest norm and least distances to
the pivot, a query knows a score that its k-th best reaches at least, and for each cell one that nothing in it exceeds.
Queries of neighbouring cells form blocks; a cell's chunks are copied to the blocks in which some query's bounds admit
the cell, and a query to the chunks that its own bounds admit, and nowhere else. Each chunk meets each block in one
bounded task, and the best of all chunks are ranked at the end.
"""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import stored, table

cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Vectors of a cell's chunk and queries of a block that meet in one task.
CHUNK, BLOCK = 4096, 4096
#: Pivots grow with the root of the rows, up to so many (they are sent to every task: 8 bytes a component).
MOST_PIVOTS = 4096
#: Up to so many pairs of a cell and a block, the visited ones are broadcast; more are joined.
PAIRS_SENT = 200_000


def _packed(x: np.ndarray) -> bytes:
    return (x.astype("<i4") if not len(x) or np.abs(x).max() < 2**31 else x.astype("<f8")).tobytes()


def _unpacked(raw: bytes, dim: int) -> np.ndarray:
    return np.frombuffer(raw, "<i4" if len(raw) == 4 * dim else "<f8").astype(np.float64)


def _scaled(batch) -> list[np.ndarray]:
    col = batch.column("embedding")
    values = np.asarray(col.flatten().cast(pa.float64()))
    x = np.floor(values * 256.0)
    ends = np.cumsum(np.asarray(col.value_lengths()))
    return np.split(x, ends[:-1]) if len(ends) else []


def _by_dim(dims: list[int]) -> dict[int, np.ndarray]:
    dims = np.array(dims, np.int64)
    return {int(d): np.flatnonzero(dims == d) for d in np.unique(dims)}


class Pivots:
    """Pivots by dimension; vectors of a dimension without pivots belong to the cell of the zero vector."""

    def __init__(self, rows: list[np.ndarray]):
        self.of: dict[int, np.ndarray] = {}
        for x in rows:
            self.of.setdefault(len(x), []).append(x)
        self.of = {d: np.array(v) for d, v in self.of.items()}

    def get(self, dim: int) -> np.ndarray:
        return self.of.get(dim, np.zeros((1, dim)))

    def nearest(self, x: np.ndarray) -> np.ndarray:
        """The cell of each row of x: any pivot will do for right results, the nearest for tight bounds."""
        p = self.get(x.shape[1])
        return ((p * p).sum(axis=1) - 2 * (x @ p.T)).argmin(axis=1)


def _assign(pivots: Pivots):
    def run(batches):
        for batch in batches:
            xs = _scaled(batch)
            n = len(xs)
            cell, dist, norm = np.zeros(n, np.int32), np.zeros(n), np.zeros(n)
            for dim, at in _by_dim([len(x) for x in xs]).items():
                x = np.array([xs[i] for i in at]).reshape(len(at), dim)
                cell[at] = pivots.nearest(x)
                dist[at] = np.sqrt(((pivots.get(dim)[cell[at]] - x) ** 2).sum(axis=1))
                norm[at] = np.sqrt((x * x).sum(axis=1))
            cols = {"vec_id": batch.column("vec_id"), "dim": pa.array([len(x) for x in xs], pa.int32()), "cell": pa.array(cell), "dist": pa.array(dist), "norm": pa.array(norm)}
            yield pa.RecordBatch.from_pydict(cols | {"x": pa.array([_packed(x) for x in xs], pa.binary())})

    return run


def _grouped(pivots: Pivots, asked: list) -> tuple[dict, int]:
    """(dim, cell) -> (first block, blocks) for cells with queries (dim, cell, n), and the number of blocks: cells
    that are neighbours on the pivots' longest axis share blocks of about BLOCK queries; a larger cell has its own."""
    out, block, held = {}, 0, 0
    for dim in sorted({d for d, *_ in asked}):
        p = pivots.get(dim)
        p = p - p.mean(axis=0)
        axis = p @ np.linalg.svd(p, full_matrices=False)[2][0] if p.size else np.zeros(len(p))
        own = sorted(((float(axis[c]), c, n) for d, c, n in asked if d == dim))
        block, held = block + (held > 0), 0
        for _, c, n in own:
            if held and held + n > BLOCK:
                block, held = block + 1, 0
            parts = -(-n // BLOCK)
            out[dim, c] = (block, parts)
            block, held = (block + parts, 0) if parts > 1 else (block, held + n)
    return out, block + (held > 0)


def _visits(pivots: Pivots, cells: dict, k: int, blocks: dict):
    """Copies each query to the chunks of the cells that may hold one of its k best."""

    def run(batches):
        for batch in batches:
            out: list = []
            dims, homes, ids, raw = (batch.column(c).to_pylist() for c in ("dim", "cell", "vec_id", "x"))
            for dim, some in _by_dim(dims).items():
                own = cells[dim]
                for lo in range(0, len(some), 256):
                    at = some[lo : lo + 256]
                    v = np.array([_unpacked(raw[i], dim) for i in at]).reshape(len(at), dim)
                    size = np.sqrt((v * v).sum(axis=1))[:, None]
                    dot = v @ pivots.get(dim).T
                    slack = 1e-9 * (1 + size * own["norm"].max())
                    high = np.minimum(dot[:, own["cell"]] + size * own["radius"], size * own["norm"]) + slack
                    # own copies may be among the nearest, so one more than k is asked to reach the bound
                    low = dot[:, own["near_cell"]] - size * own["near"]
                    n = low.shape[1]
                    least = np.partition(low, n - k - 1, axis=1)[:, n - k - 1, None] - slack if n > k else np.full((len(at), 1), -np.inf)
                    for i, q in enumerate(at.tolist()):
                        first, parts = blocks[dim, homes[q]]
                        block = first + ids[q] % parts
                        for c in np.flatnonzero(high[i] >= least[i]).tolist():
                            out += [(dim, int(own["cell"][c]), j, block, ids[q], raw[q]) for j in range(int(own["chunks"][c]))]
                        if len(out) > 5000:
                            yield _visit_batch(out)
                            out = []
            yield _visit_batch(out)

    return run


def _visit_batch(rows: list) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) or [[]] * 6
    kinds = (pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], ["dim", "cell", "chunk", "block", "query_id", "x"])


def scores(q: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Integer inner products; exact also where doubles are not, then held within 64 bits."""
    if not q.size or not v.size or q.shape[1] * np.abs(q).max() * np.abs(v).max() < 2**53:
        return (q @ v.T).astype(np.int64)
    whole = [[int(a) for a in row] for row in v]
    top = 2**63 - 1
    return np.array([[max(-top, min(top, sum(int(a) * b for a, b in zip(x, y, strict=True)))) for y in whole] for x in q], np.int64)


def _solve(k: int):
    """The k best of a chunk's vectors for each query of a block."""

    empty = pa.table({n: pa.array([], pa.int64()) for n in ("query_id", "vec_id", "score")})

    def run(queries: pa.Table, data: pa.Table) -> pa.Table:
        if not len(queries) or not len(data):
            return empty
        dim = data["dim"][0].as_py()
        ids = data["vec_id"].to_numpy()
        order = np.argsort(ids, kind="stable")
        ids = ids[order]
        raw = data["x"].to_pylist()
        v = np.array([_unpacked(raw[i], dim) for i in order]).reshape(len(ids), dim)
        repeated = bool((np.diff(ids) == 0).any())
        qid, qraw = queries["query_id"].to_numpy(), queries["x"].to_pylist()
        out: list = [[], [], []]
        for lo in range(0, len(qid), 256):
            q = np.array([_unpacked(r, dim) for r in qraw[lo : lo + 256]]).reshape(-1, dim)
            s = scores(q, v)
            for i, row in enumerate(s):
                own = int(qid[lo + i])
                m = k + 1
                if repeated or len(row) <= m:
                    at = np.arange(len(row))
                else:
                    at = np.flatnonzero(row >= np.partition(row, len(row) - m)[len(row) - m])
                at = at[np.argsort(-row[at].astype(object) if row.min() == -(2**63) else -row[at], kind="stable")]
                seen: set = set()
                for j in at:
                    if len(seen) == k:
                        break
                    x = int(ids[j])
                    if x != own and x not in seen:
                        seen.add(x)
                        out[0].append(own)
                        out[1].append(x)
                        out[2].append(int(row[j]))
        return pa.table({n: pa.array(c, pa.int64()) for n, c in zip(("query_id", "vec_id", "score"), out, strict=True)})

    return run


def top_products(vectors: DataFrame, query: str, k: int = 5) -> DataFrame:
    """query_id, rank, vec_id, score: for each row that the SQL condition `query` on vec_id admits, the k other rows
    with the largest inner product of floor(256 * component), ties to the smaller vec_id.

    Rows with a null vec_id, a null vector or a null or non-finite component take no part. Vectors are compared with
    those of their own length; empty ones score 0. Rows that repeat a vec_id count once per query, with their best
    score; a query repeated with other components is asked with the greatest of them. A query with fewer than k
    others gets all; an empty table gives no rows.
    """
    bad = F.exists("embedding", lambda e: e.isNull() | F.isnan(e) | (F.abs(e) == float("inf")))
    own = vectors.select(F.col("vec_id").cast("bigint").alias("vec_id"), "embedding").where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull()).where(~bad)
    count = own.count()
    n_pivots = int(min(MOST_PIVOTS, max(1, np.sqrt(count) / 8)))
    picked = own.orderBy(F.xxhash64("vec_id"), "vec_id").limit(n_pivots).toArrow()
    pivots = Pivots(_scaled(picked.combine_chunks().to_batches()[0]) if len(picked) else [])
    data = own.mapInArrow(_assign(pivots), "vec_id bigint, dim int, cell int, dist double, norm double, x binary")
    data = stored(data, "cells")
    summary = data.groupBy("dim", "cell").agg(F.count("*").alias("n"), F.max("dist").alias("radius"), F.max("norm").alias("norm")).collect()
    # by vec_id, for copies of one id are one answer
    near = data.groupBy("dim", "cell", "vec_id").agg(F.max("dist").alias("dist"))
    near = near.withColumn("r", F.row_number().over(Window.partitionBy("dim", "cell").orderBy("dist"))).where(F.col("r") <= k + 1).select("dim", "cell", "dist").collect()
    cells: dict = {}
    for dim in {r.dim for r in summary}:
        rows, close = [r for r in summary if r.dim == dim], [r for r in near if r.dim == dim]
        cells[dim] = {
            "cell": np.array([r.cell for r in rows]),
            "radius": np.array([r.radius for r in rows]),
            "norm": np.array([r.norm for r in rows]),
            "chunks": np.array([-(-r.n // CHUNK) for r in rows]),
            "near_cell": np.array([r.cell for r in close]),
            "near": np.array([r.dist for r in close]),
        }
    asked = data.where(query).groupBy("vec_id", "dim").agg(F.max(F.struct("x", "cell")).alias("m"))
    one = Window.partitionBy("vec_id").orderBy(F.col("dim").desc())
    asked = asked.withColumn("r", F.row_number().over(one)).where("r = 1").select("vec_id", "dim", "m.cell", "m.x")
    asked = stored(asked, "queries")
    # a row per cell
    blocks, n_blocks = _grouped(pivots, [tuple(r) for r in asked.groupBy("dim", "cell").count().collect()])
    visits = asked.mapInArrow(_visits(pivots, cells, k, blocks), "dim int, cell int, chunk bigint, block bigint, query_id bigint, x binary")
    visits = stored(visits, "visits")
    chunks = data.sparkSession.createDataFrame([(d, int(c), int(n)) for d, o in cells.items() for c, n in zip(o["cell"], o["chunks"], strict=True)], "dim int, cell int, chunks int")
    spread = data.join(F.broadcast(chunks), ["dim", "cell"])  # MOST_PIVOTS rows for each dimension
    spread = spread.withColumn("chunk", F.pmod(F.xxhash64("vec_id"), F.col("chunks").cast("bigint")))
    if sum(len(o["cell"]) for o in cells.values()) * n_blocks <= PAIRS_SENT:
        pairs = visits.groupBy("dim", "cell").agg(F.collect_set("block").alias("blocks"))
        spread = spread.join(F.broadcast(pairs), ["dim", "cell"]).withColumn("block", F.explode("blocks"))
    else:  # by chunk, so that no key has more than CHUNK vectors or so
        pairs = visits.select("dim", "cell", "chunk", F.col("block").alias("visitor")).distinct()
        spread = spread.join(pairs, ["dim", "cell", "chunk"]).withColumnRenamed("visitor", "block")
    key = ["dim", "cell", "chunk", "block"]
    spread = spread.select(*key, "vec_id", "x")
    visits = visits.toDF(*visits.columns)
    local = visits.groupBy(*key).cogroup(spread.groupBy(*key)).applyInArrow(_solve(k), "query_id bigint, vec_id bigint, score bigint")
    best = local.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id"))
    return best.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op10_top_products(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_products(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"), "vec_id % 50 = 0")


OP10_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda e: floor(256 * CAST(e AS DOUBLE))) AS x FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda e: e IS NULL OR NOT isfinite(e))) = 0
), p AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(q.x, c.x) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.x) = len(c.x) WHERE q.vec_id % 50 = 0
), r AS (
  SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM p
)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""
