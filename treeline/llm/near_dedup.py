"""Near-duplicate documents: many hash minima, banding, signature and exact checks, connected components.

Documents with one shingle set are one class; only classes are hashed, banded and compared. A bucket's classes are
paired with the bucket's leader, not with each other. After the links found so become components, only members of
different components in a bucket are still open (further rounds of leaders reduce these). What is left is compared
in full: pair by pair in buckets of a few members, and block by block, in tasks that put out links only, in large
ones. So no bucket is capped and no link between components is lost.
"""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .common import BITMAP_BITS, bitmap, send, small_batches, stored, table
from .components import components

cloudpickle.register_pickle_by_value(sys.modules[__name__])

N_HASHES, BANDS = 128, 32
#: Pairs whose signatures agree in a smaller share than threshold - SLACK are not looked at again; with 128 minima
#: an estimate falls so far short of the truth once in about 1e8 pairs.
SLACK = 0.2
#: Rounds of leaders before the rest is compared; buckets up to SMALL classes by pairs, others in blocks of BLOCK.
ROUNDS, SMALL, BLOCK = 1, 24, 512
#: Row numbers keep a partition in their upper bits, which SPREAD brings down into a bitmap of them.
SPREAD = 4294967


def _class_rows(k: int, sign: bool):
    a, b = K.hash_family(N_HASHES)

    def run(batches):
        for batch in batches:
            keys, sizes, sigs = [], [], []
            for _, data, offsets in K.chunks(batch.column("text")):
                for s in K.shingle_sets(K.Words(data, offsets), k):
                    keys.append(K.set_key(s))
                    sizes.append(len(s))
                    if sign:
                        sigs.append(K.min_hashes(s, a, b).tobytes() if len(s) else None)
            cols = [batch.column(n) for n in batch.schema.names if n != "text"]
            names = [n for n in batch.schema.names if n != "text"]
            out = [*cols, pa.array(keys, pa.binary()), pa.array(sizes, pa.int64())]
            names += ["cls", "n_shingles"]
            if sign:
                out.append(pa.array(sigs, pa.binary()))
                names.append("sig")
            yield pa.RecordBatch.from_arrays(out, names)

    return run


def _set_rows(k: int, sent):
    """cls, shingles (packed hashes) of texts whose rows may be asked for."""

    def run(batches):
        for batch in batches:
            ids = np.asarray(batch.column("doc_id").fill_null(0))
            ids = (ids + (ids >> 33) * SPREAD) % BITMAP_BITS
            batch = batch.filter(pa.array((sent.value[ids >> 3] >> (ids & 7).astype(np.uint8) & 1).astype(bool)))
            held, keys, out = 0, [], []
            for _, data, offsets in K.chunks(batch.column("text")):
                for s in K.shingle_sets(K.Words(data, offsets), k):
                    keys.append(K.set_key(s))
                    out.append(s.tobytes())
                    held += 8 * len(s)
                    if held > 8_000_000:
                        yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), pa.array(out, pa.binary())], ["cls", "shingles"])
                        held, keys, out = 0, [], []
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), pa.array(out, pa.binary())], ["cls", "shingles"])

    return run


def _agreeing(least: float):
    """Keeps pairs whose signatures agree in at least this share of places."""

    def run(batches):
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            sig = [np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint32).reshape(n, -1) for c in ("sig_a", "sig_b")]
            ok = pa.array((sig[0] == sig[1]).mean(axis=1) >= least)
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], ["a", "b"]).filter(ok)

    return run


def _linked(percent: int):
    """Keeps pairs with 100 * intersection >= percent * union of their full sets."""

    def run(batches):
        for batch in batches:
            a, b = batch.column("set_a"), batch.column("set_b")
            keep = []
            for i in range(batch.num_rows):
                x, y = np.frombuffer(a[i].as_buffer(), np.uint64), np.frombuffer(b[i].as_buffer(), np.uint64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(100 * both >= percent * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return run


def _band_keys(sig: Column) -> Column:
    width = 4 * N_HASHES // BANDS
    return F.array(*[F.xxhash64(F.lit(i), F.substring(sig, i * width + 1, width)) for i in range(BANDS)])


def near_duplicates(docs: DataFrame, k: int = 4, percent: int = 80) -> DataFrame:
    """Every row of docs (doc_id, text; other columns are ignored) as doc_id, n_shingles, component_id, kept.

    Links join texts whose sets of k-word shingles have 100 * intersection >= percent * union; texts of fewer than k
    words count as one shingle. component_id is the least doc_id reachable, kept tells whether it is the row's own.
    Null and empty texts, and texts of white space, have no shingles and stand alone. Rows may repeat: equal rows are
    in one component and all carry the same answer. A null doc_id is never a component_id unless all its component
    has none. Empty tables give no rows.
    """
    spark = docs.sparkSession
    small_batches(spark)
    base = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    rows = stored(base.mapInArrow(_class_rows(k, True), "doc_id bigint, cls binary, n_shingles bigint, sig binary"), "signed")
    classes = rows.where("n_shingles > 0").groupBy("cls").agg(F.min("doc_id").alias("rep"), F.max("n_shingles").alias("n"), F.any_value("sig").alias("sig"))
    classes = stored(classes, "classes")
    links = _links(spark, base, classes, k, percent)
    size = rows.select("doc_id", "cls", "n_shingles")
    if links is None or links.isEmpty():
        whole = classes.select("cls", F.col("rep").alias("component_id"))
    else:
        roots = stored(components(links), "roots")
        least = roots.join(classes.select(F.col("cls").alias("node"), "rep"), "node").groupBy("root").agg(F.min("rep").alias("low"))
        low = roots.join(least, "root").select(F.col("node").alias("cls"), "low")
        whole = classes.select("cls", "rep").join(low, "cls", "left").select("cls", F.coalesce("low", "rep").alias("component_id"))
    return size.join(whole, "cls", "left").select(
        "doc_id",
        "n_shingles",
        F.coalesce("component_id", "doc_id").alias("component_id"),
        F.coalesce(F.col("doc_id").eqNullSafe(F.coalesce("component_id", "doc_id")), F.lit(False)).alias("kept"),
    )


def _links(spark: SparkSession, docs: DataFrame, classes: DataFrame, k: int, percent: int) -> DataFrame | None:
    """a, b: links that connect what the full set of links connects; None where no two classes share a bucket."""
    banded = classes.select("cls", "n", F.posexplode(_band_keys(F.col("sig"))).alias("band", "bucket"))
    shared = banded.groupBy("bucket").agg(F.count("*").alias("c")).where("c > 1").select("bucket")
    banded = stored(banded.join(shared, "bucket"), "banded")
    links, members = None, banded.withColumn("root", F.col("cls"))
    for turn in range(ROUNDS):
        pairs = stored(_leader_pairs(members, turn, percent).distinct(), "pairs")
        if pairs.isEmpty():
            return links
        likely = stored(_likely(classes, pairs, percent), "likely")
        found = stored(_confirmed(likely, _sets(docs, classes, likely, k), percent), "found")
        links = found if links is None else stored(links.union(found), "links")
        if not links.isEmpty():
            roots = stored(components(links).select(F.col("node").alias("cls"), "root"), "roots")
            members = banded.join(roots, "cls", "left").withColumn("root", F.coalesce("root", "cls"))
        members = stored(_still_open(members), "open")
    if members.isEmpty():
        return links
    pairs = stored(_small_pairs(members, percent).distinct(), "pairs")
    likely = stored(_likely(classes, pairs, percent), "likely")
    blocks = stored(_near_in_blocks(members, classes, percent), "blocks")
    asked = likely.union(blocks.select(F.col("cls").alias("a"), F.col("cls").alias("b")))
    sets = _sets(docs, classes, asked, k)
    in_blocks = blocks.join(sets, "cls").groupBy("bucket", "block", "part").applyInArrow(_linked_in_block(percent), "a binary, b binary")
    return links.union(stored(_confirmed(likely, sets, percent).union(in_blocks), "found"))


def _still_open(members: DataFrame) -> DataFrame:
    """Members of buckets that hold several components, with m, q and top: the bucket's members, those outside its
    largest component, and that component's root."""
    parts = members.groupBy("bucket", "root").agg(F.count("*").alias("c"))
    parts = parts.groupBy("bucket").agg(F.sum("c").alias("m"), F.count("*").alias("parts"), F.max(F.struct("c", "root")).alias("top"))
    parts = parts.where("parts > 1").select("bucket", "m", (F.col("m") - F.col("top.c")).alias("q"), F.col("top.root").alias("top"))
    return members.select("bucket", "band", "cls", "n", "root").join(parts, "bucket")


def _close(percent: int) -> Column:
    return F.least("n", "n2") * 100 >= percent * F.greatest("n", "n2")


def _pair() -> list[Column]:
    return [F.least("cls", "cls2").alias("a"), F.greatest("cls", "cls2").alias("b")]


def _leader_pairs(members: DataFrame, turn: int, percent: int) -> DataFrame:
    lead = members.groupBy("bucket").agg(F.min(F.struct(F.xxhash64("cls", F.lit(turn)), "cls", "n", "root")).alias("l"))
    lead = lead.select("bucket", F.col("l.cls").alias("cls2"), F.col("l.n").alias("n2"), F.col("l.root").alias("root2"))
    return members.join(lead, "bucket").where("root <> root2").where(_close(percent)).select(*_pair())


def _small_pairs(members: DataFrame, percent: int) -> DataFrame:
    """Pairs of different components in buckets of at most SMALL members: SMALL / 2 for each member at most."""
    few = members.where(F.col("m") <= SMALL)
    other = few.select("bucket", F.col("cls").alias("cls2"), F.col("n").alias("n2"), F.col("root").alias("root2"))
    return few.join(other, "bucket").where("root < root2").where(_close(percent)).select(*_pair())


def _near_in_blocks(members: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """bucket, block, part, asks, cls, root: members of large buckets that may have a link to another component.

    Every member outside a bucket's largest component asks; askers are cut into parts, members into blocks, and each
    part meets each block in a task of its own, by signature. A pair is looked at in the first band it shares.
    """
    many = members.where(F.col("m") > SMALL).join(classes.select("cls", "sig"), "cls")
    many = many.withColumn("blocks", F.ceil(F.col("m") / BLOCK)).withColumn("parts", F.ceil(F.col("q") / BLOCK))
    keys = ["bucket", "block", "part"]
    every = lambda c: F.explode(F.sequence(F.lit(0), F.col(c) - 1))
    cols = ["band", "cls", "n", "root", "sig"]
    data = many.withColumn("block", F.pmod(F.xxhash64("cls"), F.col("blocks"))).withColumn("part", every("parts")).select(*keys, *cols)
    asks = many.where("root <> top").withColumn("part", F.pmod(F.xxhash64("cls", F.lit(3)), F.col("parts"))).withColumn("block", every("blocks")).select(*keys, *cols)
    asks = asks.toDF(*keys, *cols)
    ddl = "bucket bigint, block bigint, part bigint, asks boolean, cls binary, root binary"
    return asks.groupBy(*keys).cogroup(data.groupBy(*keys)).applyInArrow(_near_block(percent), ddl)


def _signatures(t: pa.Table) -> np.ndarray:
    return np.frombuffer(b"".join(t["sig"].to_pylist()), np.uint32).reshape(len(t), -1)


def _near_block(percent: int):
    width = N_HASHES // BANDS

    def run(asks: pa.Table, data: pa.Table) -> pa.Table:
        keep_a, keep_d = np.zeros(len(asks), bool), np.zeros(len(data), bool)
        if len(asks) and len(data):
            band = asks["band"][0].as_py()
            sig_a, sig_d = _signatures(asks), _signatures(data)
            root_d, n_d = np.array(data["root"].to_pylist(), object), data["n"].to_numpy()
            for i, (root, n) in enumerate(zip(asks["root"].to_pylist(), asks["n"].to_pylist(), strict=True)):
                same = sig_d == sig_a[i]
                ok = (same.mean(axis=1) >= percent / 100 - SLACK) & (root_d != root)
                ok &= np.minimum(n, n_d) * 100 >= percent * np.maximum(n, n_d)
                if band and ok.any():
                    ok &= ~same[:, : band * width].reshape(len(data), band, width).all(axis=2).any(axis=1)
                keep_a[i] = ok.any()
                keep_d |= ok
        out = []
        for t, keep, side in ((asks, keep_a, True), (data, keep_d, False)):
            t = t.filter(pa.array(keep)) if len(t) else t
            t = t.append_column("asks", pa.array([side] * len(t), pa.bool_()))
            out.append(t.select(["bucket", "block", "part", "asks", "cls", "root"]))
        return pa.concat_tables(out)

    return run


def _linked_in_block(percent: int):
    """For each asker one link to each other component that it is linked with in this block."""

    def run(t: pa.Table) -> pa.Table:
        sides = t["asks"].to_pylist()
        cls, root, sets = t["cls"].to_pylist(), t["root"].to_pylist(), [np.frombuffer(x, np.uint64) for x in t["shingles"].to_pylist()]
        data = [i for i, s in enumerate(sides) if not s]
        out: list = [[], []]
        if data:
            size = np.array([len(sets[i]) for i in data])
            values = np.concatenate([sets[i] for i in data])
            owner = np.repeat(np.arange(len(data)), size)
            order = np.argsort(values, kind="stable")
            values, owner = values[order], owner[order]
            for i in (i for i, s in enumerate(sides) if s):
                x = sets[i]
                lo, hi = np.searchsorted(values, x, "left"), np.searchsorted(values, x, "right")
                c = hi - lo
                at = np.arange(c.sum()) + np.repeat(lo - (np.cumsum(c) - c), c)
                both = np.bincount(owner[at], minlength=len(data))
                seen = {root[i]}
                for j in np.flatnonzero(100 * both >= percent * (len(x) + size - both)):
                    d = data[j]
                    if root[d] not in seen:
                        seen.add(root[d])
                        out[0].append(min(cls[i], cls[d]))
                        out[1].append(max(cls[i], cls[d]))
        return pa.table({"a": pa.array(out[0], pa.binary()), "b": pa.array(out[1], pa.binary())})

    return run


def _likely(classes: DataFrame, pairs: DataFrame, percent: int) -> DataFrame:
    sig = classes.select("cls", "sig")
    signed = pairs.join(sig.toDF("a", "sig_a"), "a").join(sig.toDF("b", "sig_b"), "b")
    return signed.mapInArrow(_agreeing(percent / 100 - SLACK), "a binary, b binary")


def _sets(docs: DataFrame, classes: DataFrame, pairs: DataFrame, k: int) -> DataFrame:
    """cls, shingles of the classes in pairs, made from the texts of their representatives."""
    asked = pairs.select(F.col("a").alias("cls")).union(pairs.select(F.col("b").alias("cls"))).distinct()
    asked = stored(asked.join(classes.select("cls", "rep"), "cls"), "asked")
    rep = F.coalesce("rep", F.lit(0))
    sent = send(docs.sparkSession, bitmap(asked.select(F.pmod(rep + F.shiftright(rep, 33) * SPREAD, F.lit(BITMAP_BITS)).alias("at"))))
    sets = docs.mapInArrow(_set_rows(k, sent), "cls binary, shingles binary").join(asked.select("cls"), "cls", "left_semi")
    return stored(sets.groupBy("cls").agg(F.any_value("shingles").alias("shingles")), "sets")


def _confirmed(likely: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) that are links by their full sets."""
    full = likely.join(sets.toDF("a", "set_a"), "a").join(sets.toDF("b", "set_b"), "b")
    return full.mapInArrow(_linked(percent), "a binary, b binary")


def op4_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
