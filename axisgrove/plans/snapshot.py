"""Trees on disk: the shards are there already; a manifest and the top tier make a version."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from axisgrove.model import Report, TreeParams
from axisgrove.operators.top import TopTree
from axisgrove.operators.tree import KdTree
from axisgrove.plans.storage import Segments


def save(tree: KdTree, path: str, batch_id: int = -1) -> None:
    """Writes one line of JSON: parameters, top tier, which folder holds which shard, the last batch applied.

    A version is a file of its own, named by its batch; the newest that is complete counts, so a driver
    that is lost while it writes leaves the version before.
    """
    top = tree.top
    held = {k: getattr(top, k) for k in ("d", "dim", "val", "left", "right", "parent", "size", "next_shard")}
    held |= {k: {str(x): y for x, y in getattr(top, k).items()} for k in ("shards", "low", "high", "shard_size")}
    text = json.dumps({"top": held, "segments": tree.segments.manifest(), "params": tree.params.__dict__, "heights": {str(k): v for k, v in tree.heights.items()}, "batch_id": batch_id})
    tree.spark.createDataFrame([(text,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/version={batch_id + 1}")


def load(spark: SparkSession, path: str) -> tuple[KdTree, int]:
    """The tree, and the last batch that was applied to it."""
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    place = jvm.org.apache.hadoop.fs.Path(path)
    files = place.getFileSystem(conf)
    done = [str(x.getPath().getName()) for x in files.listStatus(place) if files.exists(jvm.org.apache.hadoop.fs.Path(x.getPath(), "_SUCCESS"))]
    newest = max(int(x.removeprefix("version=")) for x in done if x.startswith("version="))
    read = json.loads(spark.read.text(f"{path}/version={newest}", wholetext=True).head()[0])
    top = TopTree(read["top"]["d"])
    for k in ("dim", "val", "left", "right", "parent", "size", "next_shard"):
        setattr(top, k, read["top"][k])
    for k in ("shards", "low", "high", "shard_size"):
        setattr(top, k, {int(x): y for x, y in read["top"][k].items()})
    tree = KdTree(spark, top, Segments.load(spark, read["segments"]), TreeParams(**read["params"]), Report(), {int(k): tuple(v) for k, v in read["heights"].items()})
    return tree, read["batch_id"]


def payload(found: DataFrame, source: DataFrame, key: str) -> DataFrame:
    """Rows of a result with the columns of the table its points come from."""
    return found.join(source.withColumnRenamed(key, "point_id"), "point_id")


def compacted(tree: KdTree) -> KdTree:
    """All shards in one folder, after many small updates."""
    segments = Segments(tree.spark)
    segments, _ = segments.write(tree.segments.read().withColumn("found", F.lit(0).cast("bigint")))
    return KdTree(tree.spark, tree.top, segments, tree.params, Report(), dict(tree.heights))
