"""SQL text, for DuckDB, of what the forest operators compute: one chain of named steps, cut where a query needs it."""

from __future__ import annotations

from ..functions.hashing import drawn_sql, mix_sql, poisson_sql
from ..operators.sampling import BLOCK_ROWS
from .training_sets import TrainingSet


def xl(x: str) -> str:
    return f"(CASE WHEN {x} > 0 THEN {x} * log2({x}) ELSE 0 END)"


def out(x: str, digits: int = 6) -> str:
    return f"round({x}, {digits}) + 0.0"


class Chain:
    """Named steps over one training set; text(...) puts a final SELECT after them."""

    def __init__(self, data: TrainingSet, n_bins: int = 8, n_trees: int = 5, seed: int = 42):
        self.data, self.n_bins, self.n_trees, self.seed = data, n_bins, n_trees, seed
        self.steps: list[tuple[str, str]] = []
        self._features()

    def add(self, name: str, sql: str) -> None:
        self.steps.append((name, sql))

    def text(self, final: str) -> str:
        return "WITH " + ",\n".join(f"{n} AS ({s})" for n, s in self.steps) + "\n" + final

    def _features(self) -> None:
        d, b = self.data, self.n_bins
        shares = ", ".join(str(i / b) for i in range(1, b))
        self.add("feats", d.sql)
        numbers = [f for f in d.features if f not in d.strings]
        self.add("cuts", "SELECT " + ", ".join(f"quantile_cont({f}::DOUBLE, [{shares}]) AS c_{f}" for f in numbers) + " FROM feats")
        joins, cols = "feats CROSS JOIN cuts", []
        for i, f in enumerate(d.features):
            if f in d.strings:
                self.add(f"codes_{f}", f"SELECT {f} AS v, row_number() OVER (ORDER BY count(*) DESC, {f}) - 1 AS code FROM feats WHERE {f} IS NOT NULL GROUP BY {f} QUALIFY code < {b - 1}")
                joins += f" LEFT JOIN codes_{f} k{i} ON k{i}.v = feats.{f}"
                cols.append(f"CASE WHEN feats.{f} IS NULL THEN -1 ELSE coalesce(k{i}.code, {b - 1}) END::INTEGER AS b{i}")
            else:
                cols.append(f"CASE WHEN feats.{f} IS NULL THEN -1 ELSE len(list_filter(c_{f}, lambda x: feats.{f}::DOUBLE > x)) END::INTEGER AS b{i}")
        self.add("bins", f"SELECT row_id, target, {', '.join(cols)} FROM {joins}")
        self.add("slices", " UNION ALL ".join(f"SELECT {i}::INTEGER AS feature_id, row_id, b{i} AS bin, target FROM bins" for i in range(len(d.features))))

    def weights(self, scope: str = "global") -> None:
        self.add("trees", f"SELECT range::INTEGER AS tree FROM range({self.n_trees})")
        if scope == "partition":
            self.add("sized", f"SELECT row_id, target, count(*) OVER (PARTITION BY row_id % 8) / {float(BLOCK_ROWS)} AS mean FROM bins")
            self.add("weights", f"SELECT row_id, target, tree, {drawn_sql('row_id', 'tree', 'mean', self.seed)} AS w FROM sized CROSS JOIN trees")
        else:
            self.add("weights", f"SELECT row_id, target, tree, {poisson_sql('row_id', 'tree', self.seed)} AS w FROM bins CROSS JOIN trees")

    def whole(self) -> None:
        """An unweighted histogram of the whole set, as tree 0."""
        self.add("h", "SELECT 0 AS tree, 0 AS node, feature_id, bin, target, count(*) AS c FROM slices GROUP BY ALL")
        self.gains("h", "g")

    def root(self) -> None:
        self.weights()
        self.add("h0", "SELECT tree, 0::BIGINT AS node, feature_id, bin, s.target, sum(w) AS c FROM slices s JOIN weights w USING (row_id) WHERE w > 0 GROUP BY ALL")
        self.gains("h0", "g0")

    def gains(self, h: str, g: str) -> None:
        key = "tree, node, feature_id"
        self.add(f"{g}_b", f"SELECT {key}, bin, sum(c) AS nb, sum({xl('c')}) AS sc, sum(c * c) AS sq FROM {h} GROUP BY ALL")
        self.add(f"{g}_t", f"SELECT {key}, target, sum(c) AS nt FROM {h} GROUP BY ALL")
        self.add(f"{g}_n", f"SELECT {key}, sum(nt) AS n, sum({xl('nt')}) AS st, sum(nt * nt) AS tq FROM {g}_t GROUP BY ALL")
        self.add(f"{g}_x", f"SELECT {key}, sum({xl('nb')}) AS sx, sum(sc) AS sb, sum(sq / nb) AS sg FROM {g}_b GROUP BY ALL")
        self.add(f"{g}_y", f"SELECT {key}, n, log2(n) - st / n AS h_target, (sx - sb) / n AS h_cond, log2(n) - sx / n AS split_info, greatest(sg / n - tq / (n * n), 0) AS gini FROM {g}_n JOIN {g}_x USING ({key})")
        self.add(f"{g}_z", f"SELECT *, greatest(h_target - h_cond, 0) AS gain FROM {g}_y")
        self.add(g, f"SELECT *, CASE WHEN split_info > 1e-12 THEN gain / split_info ELSE 0 END AS gain_ratio FROM {g}_z")

    def importance(self, g: str, name: str = "imp", criterion: str = "gain_ratio") -> None:
        total = f"sum({criterion}) OVER (PARTITION BY tree)"
        self.add(name, f"SELECT *, CASE WHEN {total} > 0 THEN {criterion} / {total} ELSE 1.0 / count(*) OVER (PARTITION BY tree) END AS importance FROM {g}")

    def select(self, n_principal: int, n_selected: int, shared: bool = False, criterion: str = "gain_ratio") -> None:
        if shared:
            self.add("gm", "SELECT t.tree, m.feature_id, m.gain_ratio FROM (SELECT DISTINCT tree FROM g0) t CROSS JOIN (SELECT feature_id, avg(gain_ratio) AS gain_ratio FROM g0 GROUP BY feature_id) m")
        self.importance("gm" if shared else "g0", criterion=criterion)
        self.add("ranked", "SELECT *, row_number() OVER (PARTITION BY tree ORDER BY round(importance, 10) DESC, feature_id) AS r FROM imp")
        key = mix_sql("feature_id", "tree", self.seed + 1)
        self.add("ranks", f"SELECT *, row_number() OVER (PARTITION BY tree ORDER BY CASE WHEN r <= {n_principal} THEN 0 ELSE 1 END, CASE WHEN r <= {n_principal} THEN r END, {key}, feature_id)::INTEGER AS rank FROM ranked")
        self.add("selected", f"SELECT tree, rank, feature_id, CASE WHEN r <= {n_principal} THEN 'principal' ELSE 'random' END AS origin FROM ranks WHERE rank <= {n_selected}")

    def every_feature(self) -> None:
        self.add("selected", "SELECT DISTINCT tree, feature_id FROM g0")

    def grow(self, depth: int, criterion: str = "gain_ratio", node_features: int = 0) -> None:
        """Steps a0, n0, best0, a1, ... and nodes; trees of at most this depth, one child per bin. node_features: how
        many features are drawn anew for each node, if any."""
        a = self.n_bins + 1
        self.add("a0", "SELECT tree, row_id, target, w, 0::BIGINT AS node FROM weights WHERE w > 0")
        for level in range(depth + 1):
            self.add(f"c{level}", f"SELECT tree, node, target, sum(w) AS c FROM a{level} GROUP BY ALL")
            self.add(f"n{level}", f"SELECT tree, node, sum(c) AS n, arg_max(target, c * 1000 - target)::DOUBLE AS prediction FROM c{level} GROUP BY ALL")
            if level == depth:
                break
            used = "".join(f" AND NOT EXISTS (SELECT 1 FROM path{level} u WHERE u.tree = g{level}s.tree AND u.node = g{level}s.node AND u.feature_id = g{level}s.feature_id)" for _ in [0] if level)
            self.add(f"hs{level}", f"SELECT a.tree, a.node, s.feature_id, s.bin, s.target, sum(a.w) AS c FROM slices s JOIN a{level} a USING (row_id) JOIN selected f ON f.tree = a.tree AND f.feature_id = s.feature_id GROUP BY ALL")
            self.gains(f"hs{level}", f"g{level}s")
            if node_features:
                key = mix_sql("(feature_id + node * 131)", "tree", self.seed + 2)
                self.add(f"drawn{level}", f"SELECT * FROM g{level}s WHERE true{used} QUALIFY row_number() OVER (PARTITION BY tree, node ORDER BY {key}, feature_id) <= {node_features}")
            scored, also = (f"drawn{level}", "") if node_features else (f"g{level}s", used)
            self.add(f"best{level}", f"SELECT tree, node, feature_id, {criterion} AS score FROM {scored} WHERE round({criterion}, 10) > 0 AND n >= 2{also} QUALIFY row_number() OVER (PARTITION BY tree, node ORDER BY round({criterion}, 10) DESC, feature_id) = 1")
            self.add(f"a{level + 1}", f"SELECT a.tree, a.row_id, a.target, a.w, a.node * {a} + s.bin + 2 AS node FROM a{level} a JOIN best{level} b USING (tree, node) JOIN slices s ON s.row_id = a.row_id AND s.feature_id = b.feature_id")
            before = f" UNION ALL SELECT c.tree, c.node, p.feature_id FROM (SELECT DISTINCT tree, node FROM a{level + 1}) c JOIN path{level} p ON p.tree = c.tree AND p.node = (c.node - 1) // {a}" if level else ""
            self.add(f"path{level + 1}", f"SELECT c.tree, c.node, b.feature_id FROM (SELECT DISTINCT tree, node FROM a{level + 1}) c JOIN best{level} b ON b.tree = c.tree AND b.node = (c.node - 1) // {a}{before}")
        parts = []
        for level in range(depth + 1):
            if level < depth:
                parts.append(f"SELECT n.tree, n.node, {level} AS depth, n.n, coalesce(b.feature_id, -1) AS feature_id, b.feature_id IS NULL AS is_leaf, n.prediction FROM n{level} n LEFT JOIN best{level} b USING (tree, node)")
            else:
                parts.append(f"SELECT tree, node, {level} AS depth, n, -1 AS feature_id, true AS is_leaf, prediction FROM n{level}")
        self.add("nodes", " UNION ALL ".join(parts))

    def predict(self, depth: int) -> None:
        """votes: row_id, target, tree, w, prediction of every tree on every row."""
        a = self.n_bins + 1
        self.add("p0", "SELECT row_id, target, tree, w, 0::BIGINT AS node FROM weights")
        for level in range(depth):
            self.add(
                f"p{level + 1}",
                f"SELECT p.row_id, p.target, p.tree, p.w, coalesce(c.node, p.node) AS node FROM p{level} p LEFT JOIN best{level} b ON b.tree = p.tree AND b.node = p.node "
                f"LEFT JOIN slices s ON s.row_id = p.row_id AND s.feature_id = b.feature_id LEFT JOIN n{level + 1} c ON c.tree = p.tree AND c.node = p.node * {a} + s.bin + 2",
            )
        self.add("votes", f"SELECT p.row_id, p.target, p.tree, p.w, n.prediction FROM p{depth} p JOIN nodes n USING (tree, node)")
        self.add("stats", "SELECT tree, count(*) AS oob_rows, sum((prediction = target)::BIGINT)::BIGINT AS oob_correct, avg((prediction = target)::INTEGER::DOUBLE) AS ca FROM votes WHERE w = 0 GROUP BY tree")

    def decide(self, kind: str, oob: bool = False, first: str = "", name: str = "decided") -> None:
        """row_id, target, prediction, score by direct or weighted vote."""
        weight = "1.0" if kind == "direct" else "coalesce(ca, 0)"
        where = " AND ".join(x for x in ("v.w = 0" if oob else "", first) if x) or "true"
        self.add(f"{name}_s", f"SELECT row_id, v.target, prediction, round(sum({weight}), 9) AS s FROM votes v LEFT JOIN stats USING (tree) WHERE {where} GROUP BY ALL")
        self.add(name, f"SELECT row_id, target, prediction, s AS score FROM {name}_s QUALIFY row_number() OVER (PARTITION BY row_id ORDER BY s DESC, prediction) = 1")


def forest_chain(data: TrainingSet, depth: int = 2, n_trees: int = 5, n_principal: int = 3, n_selected: int = 6, reduction: bool = True, criterion: str = "gain_ratio", shared: bool = False, node_features: int = 0) -> Chain:
    c = Chain(data, n_trees=n_trees)
    c.root()
    if reduction:
        c.select(n_principal, n_selected, shared, criterion)
    else:
        c.every_feature()
    c.grow(depth, criterion, node_features)
    c.predict(depth)
    return c
