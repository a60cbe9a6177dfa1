"""What a tree looks like: nodes, balance, boxes, invariants."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from axisgrove.operators.local import LocalTree
from axisgrove.operators.tree import valued

NODE_SCHEMA = "shard_id bigint, number bigint, parent bigint, depth bigint, kind string, dim int, val double, size bigint, left_size bigint, right_size bigint, box_low array<double>, box_high array<double>"


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [pa.int64()] * 4 + [pa.string(), pa.int32(), pa.float64()] + [pa.int64()] * 3 + [pa.list_(pa.float64())] * 2
    columns = list(zip(*rows, strict=True)) if rows else [()] * 12
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=[c.split()[0] for c in NODE_SCHEMA.split(", ")])


def node_rows(tree) -> DataFrame:
    """Nodes of the shards (numbered in preorder) and of the top tier (shard_id -1). kind: interior, leaf,
    heavy (all points agree), shard (an end of the top tier)."""
    depth = {s: tree.top.depth(e) for e in tree.top.ends() for s in tree.top.shards[e]}
    above = np.zeros(max(depth, default=-1) + 1, np.int64)
    above[list(depth)] = list(depth.values())

    def work(batches):
        for batch in batches:
            for shard, above, blob in zip(*(batch.column(c).to_pylist() for c in ("shard_id", "above", "blob")), strict=True):
                local = LocalTree.unpack(blob)
                local.fit_boxes()
                depths, starts = local.depths(), local.starts()
                parent = np.full(len(local.dim), -1)
                for i in np.flatnonzero(local.dim >= 0):
                    parent[i + 1] = parent[local.right(i)] = i
                rows = []
                for i in range(len(local.dim)):
                    inner = local.dim[i] >= 0
                    box = local.box_low[i].tolist(), local.box_high[i].tolist()
                    kind = "interior" if inner else "heavy" if local.size[i] > 1 and box[0] == box[1] else "leaf"
                    sizes = (int(local.size[i + 1]), int(local.size[local.right(i)])) if inner else (0, 0)
                    rows.append((shard, i, int(parent[i]), above + int(depths[i]), kind, int(local.dim[i]), float(local.val[i]), int(local.size[i]), *sizes, *box))
                yield _batch(rows)

    inner = valued(tree.segments.read().select("shard_id", "blob"), "shard_id", {"above": above}).mapInArrow(work, NODE_SCHEMA)
    top = tree.top
    rows = []
    for k in tree._order():
        if top.left[k] >= 0:
            rows.append((-1, k, top.parent[k], top.depth(k), "interior", top.dim[k], top.val[k], top.size[k], top.size[top.left[k]], top.size[top.right[k]], None, None))
        else:
            rows.append((-1, k, top.parent[k], top.depth(k), "shard", -1, 0.0, top.size[k], 0, 0, None, None))
    return inner.unionByName(tree.spark.createDataFrame(rows, NODE_SCHEMA))


def balance_report(tree, alpha: float | None = None) -> DataFrame:
    """Interior nodes with the share of the smaller child, and whether that is within the slack."""
    a = tree.params.alpha if alpha is None else alpha
    low, high = F.least("left_size", "right_size"), F.greatest("left_size", "right_size")
    rows = tree.nodes().filter((F.col("kind") == "interior") & (F.col("size") > tree.params.leaf_capacity))
    return rows.select("shard_id", "number", "depth", "size", (low / F.col("size")).alias("smaller_share"), ((high - low <= 1) | (low.cast("decimal(20,0)") * 10000 >= F.col("size").cast("decimal(20,0)") * round(10000 * (0.5 - a)))).alias("balanced"))


def stats(tree) -> dict:
    """Size, height, nodes, shards, bytes of the shard rows."""
    size = tree.segments.read().agg(F.sum(F.octet_length("blob"))).head()[0] or 0
    return {"size": tree.size, "height": tree.height(), "nodes": sum(n for _, n in tree.heights.values()) + len(tree._order()), "shards": len(tree.segments.held), "bytes": size}


def split_error(tree) -> DataFrame:
    """How far the splits of the top tier miss the middle, as a share of the node."""
    rows = tree.nodes().filter((F.col("kind") == "interior") & (F.col("shard_id") == -1))
    return rows.select("number", "depth", "size", (F.abs(F.col("left_size") / F.col("size") - 0.5)).alias("error"))
