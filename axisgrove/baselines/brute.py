"""Exact answers by comparing every request with every point: the truth that all else is held against."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from axisgrove.functions.geometry import box_contains
from axisgrove.model import axes, dimensions_of, normal_points
from axisgrove.operators.local import merge_nearest
from axisgrove.operators.tree import matrix, send


#: Requests that may be sent to every task; the comparison is for a small, stated set of them.
MOST_REQUESTS = 1_000_000


def _checked(requests: DataFrame) -> DataFrame:
    n = requests.count()
    if n > MOST_REQUESTS:
        raise ValueError(f"{n} requests are too many to compare with every point; at most {MOST_REQUESTS}, or use a tree")
    return requests


def _few(requests: DataFrame) -> DataFrame:
    """A broadcast of requests, whose number is checked before."""
    return F.broadcast(_checked(requests))


def brute_knn(points: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(query_id, rank, point_id, dist2): every task compares its points with a small set of requests, block by block,
    and gives the best k that it has for each; then the best k of these."""
    names, spark = axes(dimensions_of(points)), points.sparkSession
    asked = queries.select(F.col("query_id").cast("bigint").alias("query_id"), *[F.col(c).cast("double").alias(c) for c in names])
    held = send(spark, _checked(asked).toArrow())

    def work(batches):
        table = cloudpickle.loads(held.value)
        ids = table.column("query_id").to_numpy()
        at = [table.column(c).to_numpy() for c in names]
        best, who = np.full((len(ids), k), np.inf), np.full((len(ids), k), np.iinfo(np.int64).max)
        step = 64  # of points; few at first, when nearly all are among the best
        for batch in batches:
            coords, own = matrix(batch, names), batch.column("point_id").to_numpy()
            a = 0
            while a < len(own):
                some, name = coords[a : a + step], own[a : a + step]
                for c in range(0, len(ids), 32):
                    part = slice(c, c + 32)
                    dist = np.zeros((len(ids[part]), len(some)))
                    for j in range(len(names)):
                        gap = at[j][part][:, None] - some[None, :, j]
                        gap *= gap
                        dist += gap
                    rows, place = np.nonzero(dist <= best[part, -1][:, None])
                    if len(rows):
                        merge_nearest(best[part], who[part], rows, dist[rows, place], name[place])
                a, step = a + step, min(4096, 2 * step)
        rows, place = np.nonzero(~np.isinf(best))
        yield pa.RecordBatch.from_arrays([pa.array(ids[rows]), pa.array(who[rows, place]), pa.array(best[rows, place])], names=["query_id", "point_id", "dist2"])

    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    found = normal_points(points).select("point_id", *names).repartition(parts).mapInArrow(work, "query_id bigint, point_id bigint, dist2 double")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("dist2", "point_id"))
    return found.withColumn("rank", rank.cast("int")).filter(F.col("rank") <= k).select("query_id", "rank", "point_id", "dist2")


def brute_range(points: DataFrame, boxes: DataFrame) -> DataFrame:
    """(query_id, point_id, c0, ...) of the points in each closed box."""
    d = dimensions_of(points)
    inside = box_contains([F.col(c) for c in axes(d)], [F.col(c) for c in axes(d, "lo")], [F.col(c) for c in axes(d, "hi")])
    return normal_points(points).join(_few(boxes), inside).select("query_id", "point_id", *axes(d))


def brute_count(points: DataFrame, boxes: DataFrame) -> DataFrame:
    found = brute_range(points, boxes).groupBy("query_id").agg(F.count("*").alias("n"))
    return boxes.select("query_id").join(found, "query_id", "left").select("query_id", F.coalesce("n", F.lit(0)).cast("bigint").alias("cnt"))
