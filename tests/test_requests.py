"""Requests: equal ones are answered once, and few of them are compared with all points of a subtree at once."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from axisgrove.baselines import FullRebuildTree, LogForest
from axisgrove.model import TreeParams, plain
from axisgrove.operators import local, queries
from axisgrove.operators.tree import KdTree
from axisgrove.plans import storage


def _cloud(rng, n):
    pts = np.stack([rng.integers(0, 11, n) / 100, rng.random(n) * 1e5, rng.integers(0, 50, n).astype(float)], axis=1)
    pts[: n // 3] = pts[0]
    pts[n // 3 : n // 2] = pts[n // 2 : n // 2 + n // 2 - n // 3]  # pairs of copies
    return pts


def _frame(spark, key, pts):
    return spark.createDataFrame(pd.DataFrame({key: np.arange(len(pts))} | {f"c{j}": pts[:, j] for j in range(3)}))


def _nearest(pts, at, k):
    dist = ((at[:, None, 0] - pts[None, :, 0]) ** 2 + (at[:, None, 1] - pts[None, :, 1]) ** 2) + (at[:, None, 2] - pts[None, :, 2]) ** 2
    order = [np.lexsort((np.arange(len(pts)), row))[:k] for row in dist]
    return [(q, r + 1, int(p), float(dist[q, p])) for q, near in enumerate(order) for r, p in enumerate(near)]


@pytest.mark.parametrize("params", [TreeParams(), plain(store_boxes=True)])
def test_block_finds_what_the_walk_finds(monkeypatch, params):
    rng = np.random.default_rng(31)
    pts = _cloud(rng, 3000)
    tree = local.LocalTree.unpack(local.LocalTree.grow(pts, np.arange(3000)[::-1], params).pack())
    asked = np.concatenate([pts[:5], pts[2000:2200], rng.random((50, 3)) * [0.1, 1e5, 50]])
    passed = np.zeros((len(asked), 2), np.int64)
    walked = tree.knn(asked, 10, None, passed)
    monkeypatch.setattr(local, "BLOCK", (1 << 12, 1 << 40))
    assert tree.boxes == params.store_boxes
    for bound in (None, walked[0][:, 4]):
        dist, who = tree.knn(asked, 10, bound)
        near = walked[0] <= (np.inf if bound is None else bound[:, None])
        assert np.array_equal(dist, np.where(near, walked[0], np.inf)) and np.array_equal(who, np.where(near, walked[1], -1))


@pytest.mark.parametrize("make", [lambda p: KdTree.build(p, TreeParams(shard_rows=300)), lambda p: LogForest(p, plain(shard_rows=300), base=256)])
def test_equal_requests_are_answered_once(spark, monkeypatch, make):
    rng = np.random.default_rng(32)
    pts = _cloud(rng, 2000)
    at = np.tile(np.concatenate([pts[[0, 1, 1500]], [[0.05, -0.0, 3.0]]]), (25, 1))
    at[50:, 1] += 0.0  # 0.0 for -0.0
    asked, low, high = _frame(spark, "query_id", at), at - [0.02, 2e4, 9.0], at + [0.02, 2e4, 9.0]
    boxes = spark.createDataFrame(pd.DataFrame({"query_id": np.arange(len(at))} | {f"lo{j}": low[:, j] for j in range(3)} | {f"hi{j}": high[:, j] for j in range(3)})).withColumn("lo0", F.when(F.col("query_id") % 4 > 0, F.col("lo0")))
    tree, seen = make(_frame(spark, "point_id", pts)), []
    routed, counted = queries._routed, queries._counted_at_shards
    monkeypatch.setattr(queries, "_routed", lambda asked, *a, **b: seen.append(asked.count()) or routed(asked, *a, **b))
    monkeypatch.setattr(queries, "_counted_at_shards", lambda tree, asked: seen.append(asked.count()) or counted(tree, asked))
    assert sorted(map(tuple, tree.knn(asked, 10).collect())) == _nearest(pts, at, 10)
    low = boxes.fillna(-np.inf).orderBy("query_id").select("lo0", "lo1", "lo2").toPandas().to_numpy()
    assert sorted(map(tuple, tree.range_count(boxes).collect())) == [(i, int(((pts >= a) & (pts <= b)).all(axis=1).sum())) for i, (a, b) in enumerate(zip(low, high, strict=True))]
    assert seen and max(seen) <= 4


def test_points_are_not_moved_to_meet_a_small_batch(spark, monkeypatch):
    rng = np.random.default_rng(33)
    frame = _frame(spark, "point_id", _cloud(rng, 2000))
    batch = frame.filter("point_id % 7 = 0").withColumn("c1", F.when(F.col("point_id") % 2 == 0, F.col("c1")).otherwise(-1.0))
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        for most, hint in ((storage.BATCH_BYTES, True), (0, False)):
            monkeypatch.setattr(storage, "BATCH_BYTES", most)
            joined = frame.join(storage.few(batch), ["point_id", "c0", "c1", "c2"], "left_anti")
            assert ("BroadcastHashJoin" in joined._jdf.queryExecution().executedPlan().toString()) == hint
            for made in (FullRebuildTree(frame, plain(shard_rows=300)).delete(batch), LogForest(frame, plain(shard_rows=300), base=256).delete(batch)):
                assert sorted(r[0] for r in made.points().select("point_id").collect()) == [i for i in range(2000) if i % 14]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
