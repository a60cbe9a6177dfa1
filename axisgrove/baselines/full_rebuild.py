"""A tree of true medians that is built anew, from all points, by every update."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from axisgrove.model import Report, TreeParams, axes, normal_points, plain
from axisgrove.operators.tree import KdTree
from axisgrove.plans.storage import cut, few


class FullRebuildTree:
    def __init__(self, points: DataFrame, params: TreeParams | None = None):
        self.params = params or plain(store_boxes=True)
        self.held = cut(normal_points(points))
        self.tree = KdTree.build(self.held, self.params)
        self.report = Report(rebuilt=self.tree.size, rounds=self.tree.report.rounds, moved=self.tree.report.moved)

    build = classmethod(lambda cls, points, params=None: cls(points, params))

    def insert(self, batch: DataFrame) -> FullRebuildTree:
        return FullRebuildTree(self.held.unionByName(normal_points(batch)), self.params)

    def delete(self, batch: DataFrame) -> FullRebuildTree:
        """Takes out points of the same id and coordinates."""
        names = ["point_id", *axes(self.tree.top.d)]
        return FullRebuildTree(self.held.join(few(normal_points(batch).select(*names).distinct()), names, "left_anti"), self.params)

    @property
    def size(self) -> int:
        return self.tree.size

    def points(self) -> DataFrame:
        return self.tree.points().drop("shard_id")

    def knn(self, queries: DataFrame, k: int) -> DataFrame:
        return self.tree.knn(queries, k)

    def range_count(self, boxes: DataFrame) -> DataFrame:
        return self.tree.range_count(boxes)

    def range_report(self, boxes: DataFrame) -> DataFrame:
        return self.tree.range_report(boxes)

    def height(self) -> int:
        return self.tree.height()


def exact_root_median(points: DataFrame, column: str) -> DataFrame:
    """The element of rank n / 2 (from 0): where a plain build first splits this dimension."""
    return points.agg(F.expr(f"-percentile_disc(0.5) WITHIN GROUP (ORDER BY -{column})").alias("median"))
