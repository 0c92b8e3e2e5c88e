"""Forests on streams: scoring rows as they come, and keeping a forest fresh batch by batch."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.model import Forest, fit_binned
from ..operators.spec import ForestSpec
from ..operators.voting import forest_predict
from ..session import shared_dir, stored


_STATE = "number bigint, next_tree int, paths array<string>, history array<struct<batch:bigint,tree:int,ca:double>>, done array<bigint>"


def score_stream(stream: DataFrame, forest: Forest, row_id: str) -> DataFrame:
    """row_id, prediction, score of a stream of wide rows: the forest is a static side, sent once."""
    rows = forest.rows(stream, row_id)
    return forest_predict(rows, forest.node_list, forest.spec.n_bins, forest.spec.task, forest.accuracy_of(), max(1, len(forest.classes)), forest.spec.normalise)


class IncrementalForest:
    """A forest of fixed size over a stream of binned rows (row_id, target, bins).

    Every batch first scores the trees on rows they have not seen (their accuracy so far decays by half each batch),
    then grows `fresh` trees on the rows held, which replace the trees of the least accuracy. Rows held are those of
    the last `window` batches, so the work of a batch does not grow with the stream.
    """

    def __init__(self, rules: list, classes: list, spec: ForestSpec, fresh: int = 2, window: int = 4, folder: str | None = None):
        """With a folder, the forest, the rows held and the number of the last batch are written there after every
        batch, and another object over the same folder goes on from there."""
        self.folder, self._paths, self._restored = folder, [], folder is None
        self.rules, self.classes, self.spec = rules, classes, spec
        self.fresh, self.window = fresh, window
        self.forest: Forest | None = None
        self.held: list[DataFrame] = []
        self.next_tree = 0
        self.history: list[tuple[int, int, float]] = []
        self._done: set[int] = set()

    def update(self, batch: DataFrame, number: int) -> None:
        self._restore(batch.sparkSession)
        if number in self._done:  # a batch that is run again after a failure
            return
        rows, path = self._kept(batch.select("row_id", "target", "bins"), number)
        if rows.isEmpty():
            self._done.add(number)
            return
        if self.forest is not None:
            self._score(rows, number)
        self.held, self._paths = [*self.held, rows][-self.window :], [*self._paths, path][-self.window :]
        data = self.held[0]
        for more in self.held[1:]:
            data = data.unionByName(more)
        n = self.spec.n_trees if self.forest is None else self.fresh
        new = fit_binned(data, self.rules, self.classes, self.spec.but(n_trees=n), first_tree=self.next_tree)
        self.next_tree += n
        if self.forest is None:
            self.forest = new
        else:
            stats = sorted(self.forest.stats_rows, key=lambda r: (r[3], -r[0]))
            gone = {r[0] for r in stats[: max(0, len(stats) + n - self.spec.n_trees)]}
            self.forest.node_list = [x for x in self.forest.node_list if x.tree not in gone] + new.node_list
            self.forest.stats_rows = [r for r in self.forest.stats_rows if r[0] not in gone] + new.stats_rows
        self._done.add(number)
        self._save(number)

    def _kept(self, rows: DataFrame, number: int) -> tuple[DataFrame, str]:
        if not self.folder:
            return stored(rows, "batch"), ""
        path = f"{self.folder}/rows-{number}"
        rows.write.mode("overwrite").parquet(path)
        return rows.sparkSession.read.schema(rows.schema).parquet(path), path

    def _save(self, number: int) -> None:
        """The model first, then the row that names it: a batch that fails in between is run again."""
        if self.folder:
            self.forest.save(f"{self.folder}/model-{number}")
            row = [(number, self.next_tree, self._paths, [(b, t, float(ca)) for b, t, ca in self.history], sorted(self._done))]
            frame = self.forest.spark.createDataFrame(row, _STATE)
            frame.coalesce(1).write.mode("overwrite").parquet(f"{self.folder}/state/{number:09d}")

    def _restore(self, spark) -> None:
        if self._restored:
            return
        self._restored = True
        top = spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/state")
        if not top.getFileSystem(spark._jsc.hadoopConfiguration()).exists(top):
            return
        last = spark.read.schema(_STATE).option("recursiveFileLookup", "true").parquet(f"{self.folder}/state").orderBy(F.desc("number")).first()
        if last is not None:
            self.forest = Forest.load(spark, f"{self.folder}/model-{last.number}")
            self.next_tree, self._paths, self._done = last.next_tree, list(last.paths), set(last.done)
            self.history = [(h.batch, h.tree, h.ca) for h in last.history]
            self.held = [spark.read.parquet(p) for p in self._paths]

    def _score(self, rows: DataFrame, number: int) -> None:
        from ..operators.voting import tree_predict

        votes = tree_predict(rows, self.forest.node_list, self.spec.n_bins, self.spec.task)
        now = {r.tree: r.ca for r in votes.groupBy("tree").agg(F.avg((F.col("prediction") == F.col("target")).cast("double")).alias("ca")).collect()}  # a row per tree
        self.forest.stats_rows = [(t, n, c, (ca + now.get(t, ca)) / 2) for t, n, c, ca in self.forest.stats_rows]
        self.history += [(number, t, ca) for t, ca in now.items()]

    def run(self, stream: DataFrame, after: Callable[[int], None] | None = None) -> None:
        def each(batch: DataFrame, number: int) -> None:
            self.update(batch, number)
            if after:
                after(number)

        check = f"{self.folder}/progress" if self.folder else f"{shared_dir(stream.sparkSession)}/treeline-incremental-{uuid.uuid4().hex}"
        stream.writeStream.foreachBatch(each).option("checkpointLocation", check).trigger(availableNow=True).start().awaitTermination()


def running_histogram(stream: DataFrame) -> DataFrame:
    """feature_id, bin, target, c over all rows so far (update mode)."""
    cells = stream.select("target", F.posexplode("bins").alias("feature_id", "bin"))
    return cells.groupBy("feature_id", "bin", "target").agg(F.count("*").alias("c"))
