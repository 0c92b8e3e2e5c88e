"""The experiment workloads: accuracy by trees and rows, out-of-bag error, time by size, volume, shuffle bytes, ablation.

Each gives a tidy frame. Methods: hybrid (reduced features, weighted vote), classic, dynamic, library.
"""

from __future__ import annotations

import time
import uuid
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import classic, dynamic, library
from ..functions.hashing import mix
from ..operators.alike import put_together
from ..operators.binning import binned, fit_bins
from ..operators.model import Forest, fit_binned
from ..operators.spec import ForestSpec
from ..queries.training_sets import shared_bases
from ..session import shared_dir, stored
from . import cost as C
from . import measures as M

SPEC = ForestSpec(max_depth=5)


#: Spark adds up an Arrow batch's bytes at every row, which costs several times the rest of sending a narrow row. Up to so
#: many features a full batch of binned rows is small, and need not be measured.
BATCH_BYTES, NARROW = "spark.sql.execution.arrow.maxBytesPerBatch", 500

#: Splits of the rows whose forests grow at the same time: their jobs are short, and the driver is busy between them.
SIDE = 6


def split_rows(spark: SparkSession, sf_dir: str, data, seed: int = 42, n_bins: int = 8, frame: DataFrame | None = None) -> tuple[DataFrame, DataFrame, list]:
    """Binned training and test rows (four to one, by hash) and the bin rules, which only training rows shape. frame:
    the set's features, if they are stored already."""
    frame = stored(data.frame(spark, sf_dir), "features") if frame is None else frame
    test = mix(F.col("row_id"), F.lit(0), seed) % 5 == 0
    rules = fit_bins(frame.where(~test), list(data.features), n_bins)
    rows, slots = binned(frame, rules, "row_id", "target"), spark.sparkContext.defaultParallelism
    rows = stored(rows.repartition(slots) if rows.rdd.getNumPartitions() < slots else rows, "binned")
    return rows.where(~test), rows.where(test), rules


def fitted(method: str, train: DataFrame, rules: list, n_classes: int, spec: ForestSpec, alike: DataFrame | None = None):
    """alike: the training rows put together for the trees of spec, for the methods that draw weights by row and tree."""
    classes = list(range(n_classes))
    if method == "hybrid":
        return fit_binned(train, rules, classes, spec, alike=alike)
    if method == "classic":
        return classic.fit(train, rules, classes, spec, alike=alike)
    if method == "dynamic":
        return dynamic.fit(train, rules, classes, spec)
    return library.fit(train, n_classes, spec)


def decided(model, test: DataFrame, first: int | None = None) -> DataFrame:
    if isinstance(model, Forest):
        return model.predict(test, first, with_target=True)
    return library.predict(model, test)


def _accuracy(frame: DataFrame) -> float:
    return M.accuracy(frame).first()["accuracy"]


def accuracy_by_trees(spark: SparkSession, sf_dir: str, trees: list[int], methods: list[str], sets: list, seeds: list[int], dynamic_most: int = 10) -> DataFrame:
    """target, method, seed, trees, accuracy, majority. Our forests grow once and vote by their first trees; the
    library's are grown for each size; the dynamic forest, whose trees must wait for each other, to dynamic_most."""
    def one(data, frame: DataFrame, seed: int) -> list[tuple]:
        out = []
        train, test, rules = split_rows(spark, sf_dir, data, seed, frame=frame)
        top = max(counts := [r[0] for r in test.groupBy("target").count().select("count").collect()]) / max(1, sum(counts))
        most = max(trees)
        alike = put_together(train, SPEC.n_bins, len(rules), data.n_classes, most, seed) if {"hybrid", "classic"} & set(methods) else None
        for method in methods:
            sizes = [t for t in trees if method != "dynamic" or t <= dynamic_most]
            spec = SPEC.but(n_trees=max(sizes), seed=seed)
            model = None if method == "library" else fitted(method, train, rules, data.n_classes, spec, alike)
            for t in sizes:
                m = model or fitted(method, train, rules, data.n_classes, spec.but(n_trees=t))
                out.append((data.name, method, seed, t, _accuracy(decided(m, test, t)), top))
            model = m = None  # the driver holds one forest a set
            spark.sparkContext._jvm.System.gc()  # and not the plans and broadcasts of those before
        return out

    with ThreadPoolExecutor(SIDE) as pool:
        bases = shared_bases(spark, sf_dir, sets)
        frames = list(pool.map(lambda data: stored(data.frame(spark, sf_dir, bases), "features"), sets))
        parts = list(pool.map(lambda x: one(*x), [(d, f, seed) for d, f in zip(sets, frames, strict=True) for seed in seeds]))
    return spark.createDataFrame([r for part in parts for r in part], "target string, method string, seed int, trees int, accuracy double, majority double")


def share_of(rows: DataFrame, share: float) -> DataFrame:
    """A share of the rows by hash; a larger share holds every smaller one."""
    return rows.where(mix(F.col("row_id"), F.lit(1), 9) % 1000 < int(1000 * share))


def accuracy_by_rows(spark: SparkSession, sf_dir: str, shares: list[float], methods: list[str], data, n_trees: int = 10) -> DataFrame:
    """rows, method, accuracy: trained on growing shares of the training rows, judged on the same test rows."""
    out = []
    train, test, rules = split_rows(spark, sf_dir, data)
    for share in shares:
        own = stored(share_of(train, share), "share")
        n = own.count()
        for method in methods:
            out.append((n, method, _accuracy(decided(fitted(method, own, rules, data.n_classes, SPEC.but(n_trees=n_trees)), test))))
    return spark.createDataFrame(out, "rows bigint, method string, accuracy double")


def oob_by_trees(spark: SparkSession, sf_dir: str, scales: list[int], data) -> DataFrame:
    """scale, class (-1: all), max, min, mean of the out-of-bag error over 'the first t trees'."""
    train, _, rules = split_rows(spark, sf_dir, data)
    f = fit_binned(train, rules, list(range(data.n_classes)), SPEC.but(n_trees=max(scales)))
    counts = stored(f.oob_counts(train), "counts")
    error = (1 - F.sum("right") / F.sum("rows")).alias("oob_error")
    parts = []
    for s in scales:
        own = counts.where(F.col("first_t") <= s)
        parts.append(M.curve_summary(own.groupBy("first_t").agg(error)).select(F.lit(s).alias("scale"), F.lit(-1.0).alias("class"), "max", "min", "mean"))
        parts.append(M.curve_summary(own.groupBy("first_t", "target").agg(error), by=["target"]).select(F.lit(s).alias("scale"), F.col("target").alias("class"), "max", "min", "mean"))
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out


def time_by_size(spark: SparkSession, sf_dir: str, shares: list[float], methods: list[str], data, n_trees: int = 10) -> DataFrame:
    """rows, method, seconds to train on growing shares of the training rows; the first is run once before, to warm up."""
    out = []
    train, _, rules = split_rows(spark, sf_dir, data)
    for i, share in enumerate([shares[0], *shares]):
        own = stored(share_of(train, share), "share")
        n = own.count()
        for method in methods:
            at = time.perf_counter()
            fitted(method, own, rules, data.n_classes, SPEC.but(n_trees=n_trees))
            if i:
                out.append((n, method, time.perf_counter() - at))
    return spark.createDataFrame(out, "rows bigint, method string, seconds double")


def time_to_train(rows: DataFrame, rules: list, n_classes: int, methods: list[str], n_trees: int) -> list[tuple]:
    """(method, seconds to train on binned rows); all methods are run once before, to warm up."""
    out = []
    for again in (False, True):
        for method in methods:
            at = time.perf_counter()
            fitted(method, rows, rules, n_classes, SPEC.but(n_trees=n_trees))
            if again:
                out.append((method, time.perf_counter() - at))
    return out


def time_by_slots(spark: SparkSession, sf_dir: str, slots: list[int], methods: list[str], data, n_trees: int = 10) -> list[tuple]:
    """(slots, method, seconds), each number of slots in a session of its own process; one slot is the stand-alone run.
    The given session reads the tables and stores the binned training rows once; the others only train on these."""
    import base64
    import os
    import pickle
    import subprocess
    import sys
    from pathlib import Path

    train, _, rules = split_rows(spark, sf_dir, data)
    path = f"{shared_dir(spark)}/treeline-slots-{uuid.uuid4().hex}"
    train.write.parquet(path)
    hadoop = {k: v for k, v in spark.sparkContext.getConf().getAll() if k.startswith("spark.hadoop.")}  # a shared folder that needs settings
    root = str(Path(__file__).resolve().parents[2])
    env = {k: v for k, v in os.environ.items() if not k.startswith(("PYSPARK_GATEWAY", "PYSPARK_SUBMIT", "SPARK_LOCAL_DIRS", "_PYSPARK"))}
    env["PYTHONPATH"] = os.pathsep.join(x for x in (root, env.get("PYTHONPATH")) if x)
    code = (
        "import base64, pickle, sys; from treeline.session import session; from treeline.plans.workloads import time_to_train; "
        "n, conf, path, *rest = pickle.loads(base64.b64decode(sys.stdin.read())); "
        "s = session(f'local[{n}]', **conf, **{'spark.sql.shuffle.partitions': str(n), 'spark.ui.enabled': 'false'}); "
        "[print('ROW', m, t) for m, t in time_to_train(s.read.parquet(path), *rest)]"
    )
    out = []
    for n in slots:
        sent = base64.b64encode(pickle.dumps((n, hadoop, path, rules, data.n_classes, methods, n_trees))).decode()
        done = subprocess.run([sys.executable, "-c", code], input=sent, capture_output=True, text=True, env=env)
        if done.returncode:
            raise RuntimeError(done.stderr[-2000:])
        out += [(n, line.split()[1], float(line.split()[2])) for line in done.stdout.splitlines() if line.startswith("ROW")]
    return out


def generalisation_by_method(spark: SparkSession, sf_dir: str, methods: list[str], data, n_trees: int = 10) -> DataFrame:
    """method, train, test, gap: accuracy on the rows trained on and on others."""
    train, test, rules = split_rows(spark, sf_dir, data)
    out = []
    for method in methods:
        model = fitted(method, train, rules, data.n_classes, SPEC.but(n_trees=n_trees))
        r = M.generalisation_gap(decided(model, train), decided(model, test)).first()
        out.append((method, r["train"], r["test"], r["gap"]))
    return spark.createDataFrame(out, "method string, train double, test double, gap double")


def grid(spark: SparkSession, sf_dir: str, data, changes: list[dict]) -> DataFrame:
    """trees, selected, principal, bins, depth, accuracy of forests over a grid of specifications."""
    out = []
    for c in changes:
        train, test, rules = split_rows(spark, sf_dir, data, n_bins=c.get("n_bins", SPEC.n_bins))
        spec = SPEC.but(**c).sized(len(rules))
        f = fit_binned(train, rules, list(range(data.n_classes)), spec)
        out.append((spec.n_trees, spec.n_selected, spec.n_principal, spec.n_bins, spec.max_depth, _accuracy(decided(f, test))))
    return spark.createDataFrame(out, "trees int, selected int, principal int, bins int, depth int, accuracy double")


def volume_by_trees(spark: SparkSession, catalog: DataFrame, trees: list[int], bytes_per_cell: int = 8) -> DataFrame:
    return C.volume(catalog, trees).withColumn("bytes", F.col("cells") * bytes_per_cell)


def ablation(spark: SparkSession, sf_dir: str, data, seeds: list[int], n_trees: int = 10) -> DataFrame:
    """reduction, vote, criterion, seed, accuracy, oob: two by two by three."""
    out = []
    for seed in seeds:
        train, test, rules = split_rows(spark, sf_dir, data, seed)
        for reduction in (True, False):
            for criterion in ("gain_ratio", "gain", "gini"):
                f = fit_binned(train, rules, list(range(data.n_classes)), SPEC.but(n_trees=n_trees, reduction=reduction, criterion=criterion, seed=seed))
                oob = M.oob_curve(f.oob_votes(train), [n_trees]).first()["oob_error"]
                for vote in ("weighted", "direct"):
                    f.spec = f.spec.but(vote=vote)
                    out.append((reduction, vote, criterion, seed, _accuracy(decided(f, test)), oob))
    return spark.createDataFrame(out, "reduction boolean, vote string, criterion string, seed int, accuracy double, oob double")


def communication(spark: SparkSession, sf_dir: str, data, layouts: list[str], partitions: list[int], n_trees: int = 4) -> DataFrame:
    """layout, partitions, shuffle_write bytes of training, from the session's status store (no log needed). The
    training rows are made once: they lie in the tables' partitions, whatever the shuffles'."""
    out = []
    before = {c: spark.conf.get(c) for c in ("spark.sql.shuffle.partitions", BATCH_BYTES)}
    train, _, rules = split_rows(spark, sf_dir, data)
    train = stored(train, "train")
    try:
        if len(rules) <= NARROW:
            spark.conf.set(BATCH_BYTES, str(2**31 - 1))
        for p in partitions:
            spark.conf.set("spark.sql.shuffle.partitions", str(p))
            for layout in layouts:
                mark = _shuffled(spark)
                if layout == "library":
                    library.fit(train, data.n_classes, SPEC.but(n_trees=n_trees))
                else:
                    fit_binned(train, rules, list(range(data.n_classes)), SPEC.but(n_trees=n_trees, layout=layout, max_depth=3))
                out.append((layout, p, _shuffled(spark) - mark))
    finally:
        for c, value in before.items():
            spark.conf.set(c, value)
    return spark.createDataFrame(out, "layout string, partitions int, shuffle_write bigint")


def _shuffled(spark: SparkSession) -> int:
    """Bytes written to shuffles so far by all stages the status store still holds."""
    store = spark._jsc.sc().statusStore()
    spark._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    summary = store.executorList(False)
    return sum(summary.apply(i).totalShuffleWrite() for i in range(summary.size()))
