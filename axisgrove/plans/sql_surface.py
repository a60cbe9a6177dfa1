"""Trees in SQL: temporary views of nodes, points and shards, table functions for candidates, and column functions."""

from __future__ import annotations

import numpy as np
from pyspark import cloudpickle
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from axisgrove.operators.tree import KdTree


def register(spark: SparkSession, tree: KdTree, name: str = "kd") -> None:
    """Views <name>_nodes, <name>_points, <name>_shards and table functions.

    ``SELECT * FROM kd_shards_in_box(array(lo..), array(hi..))`` gives the shards that a box meets,
    and whether it contains them; ``kd_shards_near(array(c..), dist2)`` those within a squared distance of
    a point; ``kd_tree_nodes(max_depth)`` the nodes of the top tier. All descend the top tier.
    Neighbours of the rows of a SELECT: ``knn_sql``.
    """
    tree.nodes().createOrReplaceTempView(f"{name}_nodes")
    tree.points().createOrReplaceTempView(f"{name}_points")
    tree.segments.read().select("shard_id", "size", "nodes", "height", "low", "high").createOrReplaceTempView(f"{name}_shards")
    packed = cloudpickle.dumps(tree.top.routes())

    class InBox:
        def __init__(self):
            self.routes = cloudpickle.loads(packed)

        def eval(self, lo, hi):
            (rows, nodes), (_, cut) = self.routes.boxes(np.array([lo], float), np.array([hi], float))
            for places, inside in ((self.routes.below(rows, nodes)[1], True), (cut, False)):
                for s in self.routes.shards[places].tolist():
                    yield s, inside

    class Near:
        def __init__(self):
            self.routes = cloudpickle.loads(packed)

        def eval(self, point, limit):
            _, places, far = self.routes.near(np.array([point], float), np.array([limit], float), np.array([-1]))
            yield from zip(self.routes.shards[places].tolist(), far.tolist(), strict=True)

    class TopNodes:
        def __init__(self):
            self.routes = cloudpickle.loads(packed)

        def eval(self, most):
            dim, val, left, right = self.routes.tree
            stack = [(0, 0)]
            while stack:
                k, depth = stack.pop()
                yield k, depth, int(dim[k]), float(val[k]), int(self.routes.size[k])
                if left[k] >= 0 and depth < most:
                    stack += [(int(right[k]), depth + 1), (int(left[k]), depth + 1)]

    spark.udtf.register(f"{name}_shards_in_box", udtf(InBox, returnType="shard_id bigint, inside boolean"))
    spark.udtf.register(f"{name}_shards_near", udtf(Near, returnType="shard_id bigint, dist2 double"))
    spark.udtf.register(f"{name}_tree_nodes", udtf(TopNodes, returnType="node_id bigint, depth int, dim int, val double, size bigint"))


def knn_sql(spark: SparkSession, tree: KdTree, queries_sql: str, k: int, view: str) -> None:
    """A view of the k nearest points of every row (query_id, c0, ...) of a SELECT: ``SELECT * FROM view`` answers them together."""
    tree.knn(spark.sql(queries_sql), k).createOrReplaceTempView(view)
