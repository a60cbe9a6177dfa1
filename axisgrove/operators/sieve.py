"""The sieve: points to the buckets of a skeleton, with the count and offset matrices as tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from axisgrove.functions.geometry import bucket_function
from axisgrove.model import axes, dimensions_of
from axisgrove.operators.local import Skeleton


def bucket_column(skeleton: Skeleton, names: list[str]) -> Column:
    """Bucket of a point by nested comparisons (native)."""

    def walk(k: int) -> Column:
        if skeleton.dim[k] < 0:
            return F.lit(int(skeleton.bucket[k])).cast("bigint")
        return F.when(F.col(names[int(skeleton.dim[k])]) < F.lit(float(skeleton.val[k])), walk(int(skeleton.left[k]))).otherwise(walk(int(skeleton.right[k])))

    return walk(0)


def with_bucket(points: DataFrame, skeleton: Skeleton, how: str = "native") -> DataFrame:
    names = axes(dimensions_of(points))
    if how == "arrow":
        return points.withColumn("bucket", bucket_function(skeleton, len(names))(F.array(*[F.col(c).cast("double") for c in names])))
    return points.withColumn("bucket", bucket_column(skeleton, names))


def sieve_offsets(points: DataFrame, skeleton: Skeleton, chunk: Column | None = None) -> DataFrame:
    """(chunk, bucket, n, start): points of each chunk in each bucket, and where they begin in the output.

    ``start`` is the running sum in order of bucket, then chunk; empty cells are there, too.
    The chunk is the input partition unless a column is given. The tables are of size chunks x buckets.
    """
    held = with_bucket(points, skeleton).withColumn("chunk", (chunk if chunk is not None else F.spark_partition_id()).cast("bigint"))
    counts = held.groupBy("chunk", "bucket").agg(F.count("*").alias("n"))
    kind = counts.schema["bucket"].dataType
    grid = counts.select("chunk").distinct().withColumn("bucket", F.explode(F.sequence(F.lit(0).cast(kind), F.lit(skeleton.buckets - 1).cast(kind))))
    full = grid.join(counts, ["chunk", "bucket"], "left").withColumn("n", F.coalesce("n", F.lit(0)).cast("bigint"))
    # Running sums within each bucket, behind the totals of the buckets before: one row a bucket.
    ahead = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    totals = counts.groupBy("bucket").agg(F.sum("n").alias("all"))
    first = grid.select("bucket").distinct().join(totals, "bucket", "left").select("bucket", F.coalesce(F.sum("all").over(ahead), F.lit(0)).alias("first"))
    before = Window.partitionBy("bucket").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    inner = full.withColumn("inner", F.coalesce(F.sum("n").over(before), F.lit(0)))
    return inner.join(first, "bucket").select("chunk", "bucket", "n", (F.col("first") + F.col("inner")).cast("bigint").alias("start"))


@dataclass
class SieveResult:
    points: DataFrame
    counts: DataFrame


def sieve(points: DataFrame, skeleton: Skeleton, partitions: int | None = None, how: str = "count") -> SieveResult:
    """Points with ``bucket``, each bucket contiguous in one partition, in bucket order: one exchange by
    partition number ('count'), or a range partition and sort ('sort')."""
    held = with_bucket(points, skeleton)
    n = partitions or min(skeleton.buckets, int(points.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    if how == "sort":
        moved = held.repartitionByRange(n, "bucket").sortWithinPartitions("bucket")
    else:
        moved = held.repartitionById(n, (F.col("bucket") * n / skeleton.buckets).cast("int")).sortWithinPartitions("bucket")
    return SieveResult(moved, held.groupBy("bucket").agg(F.count("*").alias("n")))
