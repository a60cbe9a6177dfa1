"""In the manner of a serial library: an insertion builds all anew, deletions are served one by one and nothing is rebalanced.

One task partitions everything that a task can hold. The tree of more points is the same, of true medians;
its lower parts then lie in several pieces, each with one task.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from axisgrove.model import Report, TreeParams, axes, dimensions_of, normal_points, plain
from axisgrove.operators.local import Counters, LocalTree
from axisgrove.operators.tree import KdTree, located, matrix, shard_of, shard_row
from axisgrove.plans.storage import SHARD_SCHEMA, cut


#: Bytes of coordinates that lie in one piece.
PIECE_BYTES = 1 << 24


class SequentialTree:
    def __init__(self, points: DataFrame, params: TreeParams | None = None, tree: KdTree | None = None):
        d = dimensions_of(points) if tree is None else tree.top.d
        self.params = (params or plain(store_boxes=True)).but(shard_rows=PIECE_BYTES // (8 * d), alpha=0.5)
        self.tree = tree or KdTree.build(normal_points(points), self.params)
        self.report = Report(rebuilt=self.tree.size)
        #: Deletions served so far, one by one.
        self.point_deletes = 0

    build = classmethod(lambda cls, points, params=None: cls(points, params))

    def insert(self, batch: DataFrame) -> SequentialTree:
        return SequentialTree(cut(self.points().unionByName(normal_points(batch))), self.params)

    def delete(self, batch: DataFrame) -> SequentialTree:
        tree, names, params = self.tree, axes(self.tree.top.d), self.params
        if not tree.segments.held:
            return self
        ends = {e: tree.top.shards[e] for e in tree.top.ends() if tree.top.shards[e]}
        asked = shard_of(located(normal_points(batch), tree.top), tree.top, ends).filter("shard_id IS NOT NULL").drop("node")

        def one_by_one(key, old, new):
            local = LocalTree.unpack(old.column("blob")[0].as_py()) if old.num_rows else LocalTree.grow(np.zeros((0, len(names))), np.zeros(0, np.int64), params)
            if new.num_rows:
                part = new.combine_chunks().to_batches()[0]
                local, found, _ = local.delete_one_by_one(part.column("point_id").to_numpy(), matrix(part, names), params)
                n = int(found.sum())
            else:
                n = 0
            return pa.Table.from_batches([shard_row(key[0].as_py(), local, Counters(), n)])

        made = tree.segments.read().groupBy("shard_id").cogroup(asked.groupBy("shard_id")).applyInArrow(one_by_one, SHARD_SCHEMA)
        report = Report()
        after = tree._rebuilt(tree.top.copy(), {}, asked, set(), report, made)
        out = SequentialTree(None, self.params, after)
        out.report, out.point_deletes = Report(found=report.found), self.point_deletes + batch.count()
        return out

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
