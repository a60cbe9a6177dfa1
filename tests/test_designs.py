"""The rival designs at size: counts without pairs, pieces that a task can hold, medians without all values, all designs at once."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from axisgrove import catalog, comparison
from axisgrove.baselines import LogForest, SequentialTree, sequential
from axisgrove.model import plain
from axisgrove.operators import tree
from axisgrove.operators.tree import KdTree


def _cloud(rng, n):
    pts = np.stack([rng.integers(0, 11, n) / 100, rng.random(n) * 1e5, rng.integers(0, 50, n).astype(float)], axis=1)
    pts[: n // 3] = pts[0]
    return pts


def _frame(spark, ids, pts):
    return spark.createDataFrame(pd.DataFrame({"point_id": ids} | {f"c{j}": pts[:, j] for j in range(3)}))


def _boxes(spark, at):
    half = np.array([0.02, 2e4, 9.0])
    return spark.createDataFrame(pd.DataFrame({"query_id": np.arange(len(at))} | {f"lo{j}": at[:, j] - half[j] for j in range(3)} | {f"hi{j}": at[:, j] + half[j] for j in range(3)})), at - half, at + half


def test_forest_counts_marked_points_without_pairs(spark, monkeypatch):
    rng = np.random.default_rng(21)
    pts, ids = _cloud(rng, 3000), np.arange(3000)
    ids[1] = ids[0]  # two copies of one point, marked together
    frame = _frame(spark, ids, pts)
    forest = LogForest(frame, plain(shard_rows=300), base=256).delete(frame.filter("point_id % 7 = 0"))
    boxes, low, high = _boxes(spark, pts[:40])

    def pairs(*_, **__):
        raise AssertionError("a row for a box and a point")

    monkeypatch.setattr(KdTree, "range_report", pairs)
    left = pts[ids % 7 != 0]
    assert forest.dead_count and sorted(map(tuple, forest.range_count(boxes).collect())) == [(i, int(((left >= a) & (left <= b)).all(axis=1).sum())) for i, (a, b) in enumerate(zip(low, high, strict=True))]


def test_serial_style_in_pieces(spark, monkeypatch):
    rng = np.random.default_rng(22)
    pts, ids = _cloud(rng, 3000), np.arange(3000)
    frame, splits = _frame(spark, ids, pts), []
    for piece in (sequential.PIECE_BYTES, 24 * 400):
        monkeypatch.setattr(sequential, "PIECE_BYTES", piece)
        made = SequentialTree(frame.filter("point_id % 10 <> 3")).insert(frame.filter("point_id % 10 = 3")).delete(frame.filter("point_id % 10 < 2"))
        assert (len(made.tree.segments.held) > 1) == (piece < 1 << 20) and made.size == 2400
        assert made.report.found == 600 and made.point_deletes == 600
        assert sorted(r[0] for r in made.points().select("point_id").collect()) == ids[ids % 10 >= 2].tolist()
        splits.append(sorted(map(tuple, made.range_count(_boxes(spark, pts[:30])[0]).collect())))
    assert splits[0] == splits[1]


@pytest.mark.parametrize("rule", ["widest", "cycle"])
def test_medians_between_two_values_of_a_sample(spark, monkeypatch, rule):
    rng = np.random.default_rng(23)
    frame = _frame(spark, np.arange(6000), _cloud(rng, 6000))
    splits = lambda t: sorted((t.top.dim[k], t.top.val[k], t.top.size[k]) for k in t._order() if t.top.left[k] >= 0)
    whole = KdTree.build(frame, plain(shard_rows=300, split_rule=rule))
    # With 24,000 bytes, some ends are split further after all larger ones turned out to be one point.
    for most, sample in ((24000, 64), (1, 512), (1, 4)):
        monkeypatch.setattr(tree, "MEDIAN_BYTES", most)
        monkeypatch.setattr(tree, "MEDIAN_SAMPLE", sample)
        assert splits(KdTree.build(frame, plain(shard_rows=300, split_rule=rule))) == splits(whole)


def test_designs_at_the_same_time_agree(spark):
    rng = np.random.default_rng(24)
    pts = _cloud(rng, 1500)
    before = spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled", "false")
    got = comparison.side_by_side(_frame(spark, np.arange(1500), pts), lambda made, rows: made.range_count(_boxes(spark, pts[:10])[0]), 300)
    assert got.groupBy("query_id").agg(F.countDistinct("cnt").alias("n"), F.count("*").alias("m")).filter("n = 1 AND m = 4").count() == 10
    assert spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled", "false") == before


def test_years_of_the_window_need_no_join(spark):
    for year, batch in catalog._yearly(spark, "/root/testdata/sf0.001"):
        assert "Join" not in batch._jdf.queryExecution().toString()
        assert batch.count() == spark.read.parquet("/root/testdata/sf0.001/orders.parquet").filter(F.year("o_orderdate") == year).count()
