"""Box counts at the shards, by bit sets, and exact medians of several levels in a round."""

import numpy as np
import pandas as pd

from axisgrove.model import TreeParams, plain
from axisgrove.operators import local, queries
from axisgrove.operators.tree import KdTree


def _cloud(rng, n):
    pts = np.stack([rng.integers(0, 11, n) / 100, rng.random(n) * 1e5, rng.integers(0, 50, n).astype(float)], axis=1)
    pts[: n // 3] = pts[0]  # more copies of one point than a shard takes
    return pts


def _boxes(rng, pts, m):
    at, half = pts[rng.integers(0, len(pts), m)], rng.random((m, 3)) * [0.1, 9e4, 40]
    low, high = at - half, at + half
    low[0], high[0], low[1], high[1] = -np.inf, np.inf, 1.0, 0.0
    low[2] = high[2] = pts[0]
    return low, high


def test_boxes_counted_at_the_shards(spark, monkeypatch):
    def pairs(*_, **__):
        raise AssertionError("a row for a box and a shard")

    rng = np.random.default_rng(8)
    pts = _cloud(rng, 3000)
    low, high = _boxes(rng, pts, 300)
    frame = spark.createDataFrame(pd.DataFrame({"point_id": np.arange(3000)} | {f"c{j}": pts[:, j] for j in range(3)}))
    asked = spark.createDataFrame(pd.DataFrame({"query_id": np.arange(300)} | {f"lo{j}": low[:, j] for j in range(3)} | {f"hi{j}": high[:, j] for j in range(3)}))
    truth = [(i, int(((pts >= a) & (pts <= b)).all(axis=1).sum())) for i, (a, b) in enumerate(zip(low, high, strict=True))]
    tree = KdTree.build(frame, TreeParams(shard_rows=300))
    with monkeypatch.context() as held:
        held.setattr(queries, "_per_shard", pairs)
        assert sorted(map(tuple, tree.range_count(asked).collect())) == truth
        assert tree.range_count(asked.filter("false")).count() == 0
    monkeypatch.setattr(queries, "REQUEST_BYTES", 0)  # more boxes than a task takes: pairs by shuffling
    assert sorted(map(tuple, tree.range_count(asked).collect())) == truth


def test_bit_sets_count_like_a_walk():
    rng = np.random.default_rng(9)
    for n in (1, 63, 64, 65, 700):
        pts = _cloud(rng, n)
        low, high = _boxes(rng, pts, 400)
        keep = (low <= high).all(axis=1)
        assert (local.count_boxes(pts, low[keep], high[keep]) == [((pts >= a) & (pts <= b)).all(axis=1).sum() for a, b in zip(low[keep], high[keep], strict=True)]).all()


def test_levels_grow_the_same_tree_as_nodes(monkeypatch):
    rng = np.random.default_rng(10)
    pts = _cloud(rng, 2000)
    for params in (plain(store_boxes=True), plain(split_rule="cycle"), TreeParams()):
        pair = []
        for together in (local.TOGETHER, (1 << 40, 0)):
            monkeypatch.setattr(local, "TOGETHER", together)
            counters = local.Counters()
            pair.append((local.LocalTree.grow(pts, np.arange(2000), params, counters), counters))
            monkeypatch.undo()
        (a, one), (b, two) = pair
        assert one == two and all(np.array_equal(getattr(a, f), getattr(b, f)) for f in ("points", "ids", "dim", "val", "size", "skip", "box_low"))


def test_medians_of_several_levels_in_one_round(spark):
    rng = np.random.default_rng(11)
    pts = _cloud(rng, 3000)
    frame = spark.createDataFrame(pd.DataFrame({"point_id": np.arange(3000)} | {f"c{j}": pts[:, j] for j in range(3)}))
    one, many = KdTree.build(frame, plain(shard_rows=300)), KdTree.build(frame, plain(shard_rows=300, movement="eager"))
    splits = lambda t: sorted((t.top.dim[k], t.top.val[k], t.top.size[k]) for k in t._order() if t.top.left[k] >= 0)
    assert splits(one) == splits(many) and one.report.rounds < many.report.rounds and one.report.rounds <= 2
