"""A forest of static trees of doubling size.

Slot i holds a tree of at most base * 2^i points, or none. A batch gathers the trees of all
lower slots until what is gathered fits the next slot, where one tree is built of it.
Deleted points are marked; trees of which less than half is alive are taken out and their
live points are inserted again, all together. Queries ask all trees and merge the answers.
Marked points are passed over: a tree with marks is asked for more neighbours than are
wanted, and again for twice as many where too few of those were alive.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from axisgrove.functions.geometry import dist2
from axisgrove.model import Report, TreeParams, axes, dimensions_of, normal_points, plain
from axisgrove.operators.queries import normal_boxes, once_each
from axisgrove.operators.tree import KdTree
from axisgrove.plans.storage import cut, few, numbered


class LogForest:
    def __init__(self, points: DataFrame | None = None, params: TreeParams | None = None, base: int | None = None, mode: str = "capacity"):
        self.params = params or plain()
        self.base = base or self.params.leaf_capacity << 6
        #: slot to tree; slot to its marks (point_id, c0, ..., copies); slot to the number of marked points.
        self.trees: dict[int, KdTree] = {}
        self.dead: dict[int, DataFrame] = {}
        self.dead_count: dict[int, int] = {}
        self.mode, self.d, self.spark, self.report = mode, None, None, Report()
        if points is not None:
            self._meet(points)._place(normal_points(points))

    build = classmethod(lambda cls, points, params=None: cls(points, params))

    def _meet(self, rows: DataFrame) -> LogForest:
        self.d, self.spark = self.d or dimensions_of(rows), rows.sparkSession
        return self

    def _copy(self) -> LogForest:
        other = LogForest(None, self.params, self.base, self.mode)
        other.trees, other.dead, other.dead_count = dict(self.trees), dict(self.dead), dict(self.dead_count)
        other.d, other.spark = self.d, self.spark
        return other

    @property
    def names(self) -> list[str]:
        return ["point_id", *axes(self.d)]

    def _alive(self, slot: int) -> DataFrame:
        rows = self.trees[slot].points().drop("shard_id")
        return rows.join(self.dead[slot].select(*self.names), self.names, "left_anti") if slot in self.dead else rows

    def _taken(self, slot: int) -> tuple[DataFrame, int]:
        """The live points of a slot, and how many; the slot is empty afterwards."""
        rows, n = self._alive(slot), self.trees[slot].size - self.dead_count.get(slot, 0)
        for held in (self.trees, self.dead, self.dead_count):
            held.pop(slot, None)
        return rows, n

    def _place(self, rows: DataFrame) -> LogForest:
        """Puts rows into the lowest slot that takes them and all live points of the slots below it."""
        n, slot = rows.count(), 0
        if not n:
            return self
        if self.mode == "exact":
            for s in list(self.trees):
                more, m = self._taken(s)
                rows, n = rows.unionByName(more), n + m
            return self._binary(rows, n)
        while n > self.base << slot or slot in self.trees:
            if slot in self.trees:
                more, m = self._taken(slot)
                rows, n = rows.unionByName(more), n + m
            if n <= self.base << slot:
                break
            slot += 1
        self.trees[slot] = KdTree.build(cut(rows), self.params)
        self.report.rebuilt += n
        return self

    def _binary(self, rows: DataFrame, n: int) -> LogForest:
        """Trees of exactly base * 2^i points, by the binary digits of n // base, and a buffer (slot -1) of the rest."""
        ordered, start = numbered(rows, "__r", "point_id"), 0
        for slot in reversed(range((n // self.base).bit_length())):
            if (n // self.base) >> slot & 1:
                size = self.base << slot
                self.trees[slot] = KdTree.build(ordered.filter((F.col("__r") >= start) & (F.col("__r") < start + size)).drop("__r"), self.params)
                start += size
        if start < n:
            self.trees[-1] = KdTree.build(ordered.filter(F.col("__r") >= start).drop("__r"), self.params)
        self.report.rebuilt += n
        return self

    def insert(self, batch: DataFrame) -> LogForest:
        return self._copy()._meet(batch)._place(normal_points(batch))

    def delete(self, batch: DataFrame) -> LogForest:
        """Marks the points of the same id and coordinates; only shards that the batch leads to are read."""
        other, asked = self._copy()._meet(batch), normal_points(batch)
        names = other.names
        asked = few(asked.select(*names).distinct())
        for s, tree in self.trees.items():
            here = tree.points_around(asked).select(*names)
            hit = here.join(asked, names, "left_semi").groupBy(*names).agg(F.count("*").alias("copies"))
            if s in self.dead:  # what was marked before is not marked again
                hit = hit.join(self.dead[s].select(*names), names, "left_anti").unionByName(self.dead[s])
            hit = cut(hit)
            n = hit.agg(F.sum("copies")).head()[0] or 0
            if n:
                other.dead[s], other.dead_count[s] = hit, n
        half = [s for s, n in other.dead_count.items() if 2 * (other.trees[s].size - n) < other.trees[s].size]
        if half:  # all of them leave before any point is placed again
            parts = [other._taken(s) for s in half]
            if any(n for _, n in parts):
                other._place(cut(reduce(DataFrame.unionByName, [rows for rows, n in parts if n])))
        return other

    @property
    def size(self) -> int:
        return sum(t.size for t in self.trees.values()) - sum(self.dead_count.values())

    def tree_sizes(self) -> dict[int, int]:
        return {s: t.size for s, t in sorted(self.trees.items())}

    def points(self) -> DataFrame:
        return self._union([self._alive(s) for s in self.trees], "point_id bigint, " + ", ".join(f"{c} double" for c in axes(self.d or 1)))

    def _union(self, parts: list[DataFrame], schema: str) -> DataFrame:
        return reduce(DataFrame.unionByName, parts) if parts else self.spark.createDataFrame([], schema)

    def _live_neighbours(self, slot: int, queries: DataFrame, k: int) -> DataFrame:
        """(query_id, point_id, dist2): the k nearest live points of one tree, or a few more."""
        tree, marks, coords = self.trees[slot], self.dead_count.get(slot, 0), axes(self.d)
        if not marks:
            return tree.knn(queries, k).drop("rank")
        asked = queries.select(F.col("query_id").cast("bigint").alias("query_id"), *[F.col(c).cast("double").alias(f"q_{c}") for c in coords])
        take, out, waiting = k + min(k, marks), [], cut(queries)
        copy = F.row_number().over(Window.partitionBy("query_id", "point_id", "dist2").orderBy("rank"))
        while True:
            found = cut(tree.knn(waiting, take))
            far = dist2([F.col(c) for c in coords], [F.col(f"q_{c}") for c in coords])
            marked = found.select("query_id", "point_id").distinct().join(self.dead[slot], "point_id").join(asked, "query_id")
            marked = marked.groupBy("query_id", "point_id", far.alias("dist2")).agg(F.sum("copies").alias("__gone"))
            live = found.withColumn("__copy", copy).join(marked, ["query_id", "point_id", "dist2"], "left").filter(F.col("__copy") > F.coalesce("__gone", F.lit(0)))
            live = cut(live.select("query_id", "point_id", "dist2"))
            # A query is done with k live points, or once the tree had no more to give.
            got = found.groupBy("query_id").agg(F.count("*").alias("__f")).filter(F.col("__f") == take)
            short = got.join(live.groupBy("query_id").agg(F.count("*").alias("__l")), "query_id", "left").filter(F.coalesce("__l", F.lit(0)) < k).select("query_id")
            short = cut(short)
            out.append(live.join(short, "query_id", "left_anti"))
            if short.isEmpty():
                return reduce(DataFrame.unionByName, out)
            waiting, take = cut(waiting.join(short, "query_id", "left_semi")), min(2 * take, k + marks)

    def knn(self, queries: DataFrame, k: int) -> DataFrame:
        coords = axes(self.d or 1)
        queries, given = once_each(queries.select(F.col("query_id").cast("bigint").alias("query_id"), *[F.col(c).cast("double").alias(c) for c in coords]), coords)
        found = self._union([self._live_neighbours(s, queries, k) for s in self.trees], "query_id bigint, point_id bigint, dist2 double")
        rank = F.row_number().over(Window.partitionBy("query_id").orderBy("dist2", "point_id"))
        return given(found.withColumn("rank", rank.cast("int")).filter(F.col("rank") <= k).select("query_id", "rank", "point_id", "dist2"))

    def _reported(self, slot: int, boxes: DataFrame) -> DataFrame:
        found = self.trees[slot].range_report(boxes)
        return found.join(self.dead[slot].select(*self.names), self.names, "left_anti").select(*found.columns) if slot in self.dead else found

    def range_report(self, boxes: DataFrame) -> DataFrame:
        return self._union([self._reported(s, boxes) for s in self.trees], "query_id bigint, point_id bigint, " + ", ".join(f"{c} double" for c in axes(self.d or 1)))

    def range_count(self, boxes: DataFrame) -> DataFrame:
        """Counts of all trees, less those of the marked points; no pair of a box and a point is made."""
        boxes, given = once_each(normal_boxes(boxes, self.d or 1), [*axes(self.d or 1, "lo"), *axes(self.d or 1, "hi")])
        counted = [tree.range_count(boxes) for tree in self.trees.values()]
        for marks in self.dead.values():
            rows = marks.withColumn("__j", F.explode(F.sequence(F.lit(1).cast("bigint"), "copies"))).select(*self.names)
            counted.append(KdTree.build(rows, self.params).range_count(boxes).withColumn("cnt", -F.col("cnt")))
        found = self._union(counted, "query_id bigint, cnt bigint").groupBy("query_id").agg(F.sum("cnt").alias("n"))
        return given(boxes.select("query_id").join(found, "query_id", "left").select("query_id", F.coalesce("n", F.lit(0)).cast("bigint").alias("cnt")))

    def height(self) -> int:
        return max([t.height() for t in self.trees.values()], default=0)
