"""Column builders and Arrow functions on coordinates."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.functions import arrow_udf

from axisgrove.operators.local import descend


def dist2(one: list[Column], two: list[Column]) -> Column:
    """Squared distance: rounded products added from left to right, as everywhere in this library."""
    total = F.lit(0.0)
    for a, b in zip(one, two, strict=True):
        total = total + (a - b) * (a - b)
    return total


def box_contains(coords: list[Column], low: list[Column], high: list[Column]) -> Column:
    """Whether a point lies in a closed box; a conjunction of plain comparisons, so that it reaches the scan."""
    out = F.lit(True)
    for c, a, b in zip(coords, low, high, strict=True):
        out = out & (c >= a) & (c <= b)
    return out


def locate_column(top, names: list[str] | None = None) -> Column:
    """End node of a point by nested comparisons: native, for trees of up to a few hundred nodes."""
    names = names or [f"c{i}" for i in range(top.d)]

    def walk(k: int) -> Column:
        if top.left[k] < 0:
            return F.lit(k).cast("bigint")
        return F.when(F.col(names[top.dim[k]]) < F.lit(top.val[k]), walk(top.left[k])).otherwise(walk(top.right[k]))

    return walk(0)


def bucket_function(skeleton, d: int):
    """An Arrow function of d coordinate columns that gives the bucket of a skeleton."""
    arrays = (skeleton.dim, skeleton.val, skeleton.left, skeleton.right, skeleton.bucket)

    def bucket_of(points: np.ndarray) -> pa.Array:
        return pa.array(np.asarray(arrays[4])[descend(*arrays[:4], points)].astype(np.int64))

    @arrow_udf("bigint")
    def look_up(point: pa.Array) -> pa.Array:
        flat = point.flatten().to_numpy(zero_copy_only=False).astype(float)
        return bucket_of(flat.reshape(-1, d))

    return look_up


def interleaved(cells: list[Column], bits: int) -> Column:
    """Morton code of integer cells of ``bits`` bits each."""
    out = F.lit(0).cast("bigint")
    d = len(cells)
    for b in range(bits):
        for j, c in enumerate(cells):
            out = out.bitwiseOR(F.shiftleft(F.shiftright(c.cast("bigint"), b).bitwiseAND(F.lit(1).cast("bigint")), b * d + j))
    return out


def nearest(dist: Column, name: Column, k: int) -> Column:
    """Aggregate: the k least (distance, id) pairs of a group, in order. For groups of bounded size."""
    return F.slice(F.array_sort(F.collect_list(F.struct(dist.alias("dist2"), name.alias("point_id")))), 1, k)


def box_union(coords: list[Column]) -> Column:
    """Aggregate: the tight box of the points of a group."""
    return F.struct(F.array(*[F.min(c) for c in coords]).alias("low"), F.array(*[F.max(c) for c in coords]).alias("high"))
