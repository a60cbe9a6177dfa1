"""Brute force and the lateral join without rows for all pairs."""

import numpy as np
import pandas as pd

from axisgrove.baselines import brute_knn
from axisgrove.operators import joins


def _frame(spark, ids, pts):
    return spark.createDataFrame(pd.DataFrame({"point_id": ids} | {f"c{j}": pts[:, j] for j in range(pts.shape[1])}))


def _expected(ids, pts, asked, at, k):
    out = []
    for q, x in zip(asked, at, strict=True):
        dist = ((x - pts) ** 2).sum(axis=1)
        out += [(int(q), r + 1, int(ids[i]), float(dist[i])) for r, i in enumerate(np.lexsort((ids, dist))[:k])]
    return sorted(out)


def test_brute_knn_makes_no_row_for_a_pair(spark):
    rng = np.random.default_rng(6)
    ids, pts = rng.permutation(6000) - 3000, rng.integers(0, 40, (6000, 2)).astype(float)  # many ties
    points = _frame(spark, ids, pts)
    for k, n in ((1, 50), (7, 50), (6500, 2)):
        got = brute_knn(points, _frame(spark, np.arange(n), pts[:n] + 0.5).withColumnRenamed("point_id", "query_id"), k)
        assert "NestedLoop" not in got._jdf.queryExecution().toString() and "Cartesian" not in got._jdf.queryExecution().toString()
        assert sorted(map(tuple, got.collect())) == _expected(ids, pts, np.arange(n), pts[:n] + 0.5, k)
    assert brute_knn(points, points.filter("false").withColumnRenamed("point_id", "query_id"), 3).count() == 0

def test_lateral_join_ranks_no_pairs(spark):
    rng = np.random.default_rng(7)
    ids, pts = np.arange(400), rng.integers(0, 30, (400, 1)).astype(float)
    points = _frame(spark, ids, pts)
    got = joins.knn_lateral(points.filter("point_id % 5 = 0"), points, 3)
    assert "NestedLoop" not in got._jdf.queryExecution().toString() and "Cartesian" not in got._jdf.queryExecution().toString()
    expected = [(q, i, d) for q, _, i, d in _expected(ids, pts, ids[::5], pts[::5], 3)]
    assert sorted(map(tuple, got.collect())) == sorted(expected)
