"""Points in Morton order, cut into runs with boxes: a quad- or octree along a space-filling curve, for 2 or 3 dimensions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from axisgrove.functions.geometry import box_contains, interleaved
from axisgrove.model import axes, dimensions_of, normal_points
from axisgrove.plans.storage import cut


class ZOrderTree:
    def __init__(self, points: DataFrame, bits: int = 16, runs: int | None = None):
        d = dimensions_of(points)
        if d > 3:
            raise ValueError("a space-filling curve is kept for at most three dimensions")
        names, clean = axes(d), normal_points(points)
        ends = clean.agg(*[F.min(c).alias(f"a_{c}") for c in names], *[F.max(c).alias(f"b_{c}") for c in names]).head()
        top = (1 << bits) - 1
        cells = [F.floor((F.col(c) - F.lit(ends[f"a_{c}"])) / F.lit(max(ends[f"b_{c}"] - ends[f"a_{c}"], 1e-300)) * top) if ends[f"a_{c}"] is not None else F.lit(0) for c in names]
        n = runs or int(points.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        self.d = d
        self.held = cut(clean.withColumn("code", interleaved(cells, bits)).repartitionByRange(n, "code").sortWithinPartitions("code").withColumn("run", F.spark_partition_id()))
        self.runs = cut(self.held.groupBy("run").agg(F.count("*").alias("size"), *[F.min(c).alias(f"a_{c}") for c in names], *[F.max(c).alias(f"b_{c}") for c in names]))

    def range_report(self, boxes: DataFrame) -> DataFrame:
        """Runs whose box meets the query's, then their points."""
        names = axes(self.d)
        meets = F.lit(True)
        for j, c in enumerate(names):
            meets = meets & (F.col(f"a_{c}") <= F.col(f"hi{j}")) & (F.col(f"b_{c}") >= F.col(f"lo{j}"))
        pairs = boxes.join(F.broadcast(self.runs.select("run", *[f"{e}_{c}" for c in names for e in "ab"])), meets).select("run", *boxes.columns)
        inside = box_contains([F.col(c) for c in names], [F.col(c) for c in axes(self.d, "lo")], [F.col(c) for c in axes(self.d, "hi")])
        return self.held.join(pairs, "run").filter(inside).select("query_id", "point_id", *names)

    def range_count(self, boxes: DataFrame) -> DataFrame:
        found = self.range_report(boxes).groupBy("query_id").agg(F.count("*").alias("n"))
        return boxes.select("query_id").join(found, "query_id", "left").select("query_id", F.coalesce("n", F.lit(0)).cast("bigint").alias("cnt"))
