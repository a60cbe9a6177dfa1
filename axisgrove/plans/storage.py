"""Where trees live: Parquet folders of shards, one row a shard, never changed once written."""

from __future__ import annotations

import json
import tempfile
import threading
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

SHARD_SCHEMA = "shard_id bigint, size bigint, nodes bigint, height bigint, rebuilt bigint, moved bigint, rounds bigint, low array<double>, high array<double>, found bigint, absent_ids binary, absent_points binary, blob binary"


def shared_folder(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir; a temporary folder only where it is unset."""
    context = spark.sparkContext
    if not context.getCheckpointDir():
        shared = context.getConf().get("spark.checkpoint.dir")
        context.setCheckpointDir(shared or tempfile.mkdtemp(prefix="axisgrove-"))
    return context.getCheckpointDir()


#: Shuffle files go as soon as the table that they were made for is written.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
#: Tables are written from several threads; the setting goes back when the last one is done.
_writing, _writers = threading.Lock(), []


def cut(df: DataFrame) -> DataFrame:
    """The same rows without their lineage, from a Parquet table in the shared folder.

    Unlike a checkpoint it is compressed, read by column and of known size, and the plan above it
    inherits no constraints, whose number would multiply from one round of a loop to the next.
    """
    spark = df.sparkSession
    place = f"{shared_folder(spark)}/cut-{uuid.uuid4().hex}"
    with _writing:
        _writers.append(_writers[0] if _writers else spark.conf.get(_CLEANUP, "false"))
        spark.conf.set(_CLEANUP, "true")
    try:
        df.write.option("compression", "zstd").parquet(place)
    finally:
        with _writing:
            before = _writers.pop()
            if not _writers:
                spark.conf.set(_CLEANUP, before)
    out = spark.read.schema(df.schema).parquet(place)
    out.kept_at = place
    return out


def release(*made: DataFrame) -> None:
    """Deletes tables that ``cut`` has written; only for those that no later job reads."""
    for df in made:
        jvm = df.sparkSession._jvm
        path = jvm.org.apache.hadoop.fs.Path(df.kept_at)
        path.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(path, True)


#: A batch of up to so many bytes is sent to the points that it names; a larger one is joined by shuffling.
BATCH_BYTES = 8 << 20


def few(batch: DataFrame) -> DataFrame:
    """A batch of numbers without its lineage, with a hint to send it to all tasks where it was counted and is small."""
    batch = cut(batch)
    return F.broadcast(batch) if batch.count() * 8 * len(batch.columns) <= BATCH_BYTES else batch


def numbered(df: DataFrame, column: str, *order: str) -> DataFrame:
    """Adds the place of every row, from 0, in the order of some columns, without one task for all:
    rows are dealt out by range, counted by partition (one number each), and numbered within it."""
    parts = max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    held = cut(df.repartitionByRange(parts, *order).withColumn("__p", F.spark_partition_id()))
    count = {r["__p"]: r["count"] for r in held.groupBy("__p").count().collect()}
    before, at = [], 0
    for p in range(max(count, default=0) + 1):
        before.append(at)
        at += count.get(p, 0)
    place = F.row_number().over(Window.partitionBy("__p").orderBy(*order)) - 1
    return held.withColumn(column, place + F.array(*[F.lit(b).cast("bigint") for b in before])[F.col("__p")]).drop("__p")


def among(column: str, numbers: list[int], least: int = 8, most: int = 32) -> str:
    """SQL for a column of whole numbers that has one of some values: long runs by their ends (the longest, where they are many), the rest
    listed. One text, as a literal made by itself for each shard takes the driver a call each."""
    numbers = sorted(set(numbers))
    starts = [i for i, n in enumerate(numbers) if not i or n != numbers[i - 1] + 1]
    runs = sorted(((a, b) for a, b in zip(starts, [*starts[1:], len(numbers)]) if b - a >= least), key=lambda r: r[0] - r[1])[:most]
    inside = {i for a, b in runs for i in range(a, b)}
    alone = [str(n) for i, n in enumerate(numbers) if i not in inside]
    parts = [f"{column} BETWEEN {numbers[a]} AND {numbers[b - 1]}" for a, b in runs]
    return " OR ".join(parts + ([f"{column} IN ({', '.join(alone)})"] if alone else [])) or "false"


class Segments:
    """Which folder holds which shard. Writing returns a new object; old folders stay as they are."""

    def __init__(self, spark: SparkSession, home: str | None = None, held: dict[int, str] | None = None):
        self.spark, self.home, self.held = spark, home or f"{shared_folder(spark)}/tree-{uuid.uuid4().hex}", held or {}

    def write(self, shards: DataFrame, drop: set[int] = frozenset()) -> tuple[Segments, list]:
        """New shards take the place of those of the same number and of ``drop``; returns their statistics, too."""
        place = f"{self.home}/{uuid.uuid4().hex}"
        shards.write.parquet(place)
        # One short row a shard; blobs stay where they are.
        rows = self.spark.read.schema(SHARD_SCHEMA).parquet(place).drop("blob", "absent_ids", "absent_points").collect()
        held = {s: p for s, p in self.held.items() if s not in drop}
        held.update({r["shard_id"]: place for r in rows})
        return Segments(self.spark, self.home, held), rows

    def read(self, only: set[int] | None = None) -> DataFrame:
        """Shards, from the folders that hold them; other folders are not touched."""
        wanted = self.held if only is None else {s: self.held[s] for s in only if s in self.held}
        out = None
        for place in sorted(set(wanted.values())):
            part = self.spark.read.schema(SHARD_SCHEMA).parquet(place)
            here = [s for s, p in wanted.items() if p == place]
            if len(here) < sum(p == place for p in self.held.values()) or only is not None or len(set(self.held.values())) > 1:
                part = part.filter(among("shard_id", here))
            out = part if out is None else out.unionByName(part)
        return out if out is not None else self.spark.createDataFrame([], SHARD_SCHEMA)

    def manifest(self) -> str:
        return json.dumps({"home": self.home, "held": self.held})

    @classmethod
    def load(cls, spark: SparkSession, manifest: str) -> Segments:
        read = json.loads(manifest)
        return cls(spark, read["home"], {int(k): v for k, v in read["held"].items()})
