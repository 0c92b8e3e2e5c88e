"""The Voronoi join against brute force, in many cells, chunks and blocks."""

import numpy as np
import pytest

from treeline.llm import knn


@pytest.mark.parametrize("pairs_sent", [200_000, 0])
def test_many_cells_and_blocks(spark, monkeypatch, pairs_sent):
    for name, v in (("CHUNK", 40), ("BLOCK", 9), ("PAIRS_SENT", pairs_sent)):
        monkeypatch.setattr(knn, name, v)
    rng = np.random.default_rng(5)
    middles = rng.normal(0, 3, (12, 5))
    x = (middles[rng.integers(0, 12, 1500)] + rng.normal(0, 0.4, (1500, 5))).round(1)
    x[700:760] = x[3]  # ties
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(5000 + i, [float(i), 1.0]) for i in range(8)] + [(5050, [2.0, 2.0])]
    got = knn.top_products(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), "vec_id % 50 = 0").collect()
    answers: dict = {}
    for r in got:
        answers.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    whole = {i: np.floor(np.array(v) * 256).astype(int) for i, v in rows}
    asked = [i for i in whole if i % 50 == 0]
    assert sorted(answers) == sorted(asked)
    for q in asked:
        best = sorted((-int(whole[q] @ v), i) for i, v in whole.items() if i != q and len(v) == len(whole[q]))[:5]
        assert sorted(answers[q]) == [(n + 1, i, -s) for n, (s, i) in enumerate(best)]


def test_blocks_are_bounded():
    pivots = knn.Pivots([np.array([float(i), 0.0]) for i in range(6)])
    blocks, n = knn._grouped(pivots, [(2, 0, 3000), (2, 1, 2000), (2, 2, 9000), (2, 3, 10), (2, 5, 20), (7, 0, 1)])
    assert n == 7 or n == 6
    size: dict = {}
    for (d, c), (first, parts) in blocks.items():
        for j in range(parts):
            size.setdefault(first + j, []).append((d, c))
    assert set(size) <= set(range(n)) and blocks[2, 2][1] == 3 and size[blocks[2, 2][0]] == [(2, 2)]
    assert blocks[2, 3][0] == blocks[2, 5][0] != blocks[7, 0][0]
