"""Like for like: the same operations on the same points for every design, and the balance of one tree over long streams."""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from axisgrove.baselines import FullRebuildTree, LogForest, SequentialTree
from axisgrove.model import TreeParams, plain
from axisgrove.operators.local import Counters, LocalTree
from axisgrove.operators.tree import KdTree
from axisgrove.plans.storage import cut

OURS = "weight-balanced"


def designs(shard_rows: int) -> dict[str, Callable]:
    """The tree and its three rivals, with shards of one size."""
    params = TreeParams(shard_rows=shard_rows)
    return {
        OURS: lambda p: KdTree.build(p, params),
        "log-method forest": lambda p: LogForest(p, plain(shard_rows=shard_rows, store_boxes=True)),
        "full rebuild": lambda p: FullRebuildTree(p, plain(shard_rows=shard_rows, store_boxes=True)),
        "serial style": SequentialTree,
    }


def updated(make: Callable, pts: DataFrame):
    """A design that was built, got 1 % more points (ids 3 modulo 100) and lost 1 % (ids 5 modulo 100)."""
    tree = make(pts.filter("pmod(point_id, 100) <> 3"))
    return tree.insert(pts.filter("pmod(point_id, 100) = 3")).delete(pts.filter("pmod(point_id, 100) = 5"))


def side_by_side(pts: DataFrame, ask: Callable, shard_rows: int) -> DataFrame:
    """``ask(tree, pts)`` of every design after the same updates, with its name in ``design``. Designs are built at the same
    time, so that the many short jobs of one do not leave the executors idle."""
    pts = cut(pts)
    with ThreadPoolExecutor(len(made := designs(shard_rows))) as pool:
        waiting = {name: pool.submit(lambda make=make: ask(updated(make, pts), pts)) for name, make in made.items()}
        parts = [found.result().withColumn("design", F.lit(name)) for name, found in waiting.items()]
    return reduce(DataFrame.unionByName, parts)


def measured(pts: DataFrame, asked: DataFrame, boxes: DataFrame, shard_rows: int, k: int = 10, runs: int = 1) -> list[dict]:
    """(design, operation, seconds): build, insert 1 %, delete 1 %, k-NN and box counts, each timed by itself.

    No tree is shared between designs, and none is built within a query's time. Updates start from
    the same tree in every run; results are written nowhere.
    """
    pts, asked, boxes = cut(pts), cut(asked), cut(boxes)
    more = cut(pts.filter("pmod(point_id, 100) = 3").withColumn("point_id", F.col("point_id") + 10**12))
    less = cut(pts.filter("pmod(point_id, 100) = 5"))
    spend = lambda df: df.write.format("noop").mode("overwrite").save()
    out = []
    for name, make in designs(shard_rows).items():
        tree = make(pts)
        steps = {"build": lambda make=make: make(pts), "insert 1 %": lambda tree=tree: tree.insert(more), "delete 1 %": lambda tree=tree: tree.delete(less), f"{k}-nn": lambda tree=tree: spend(tree.knn(asked, k)), "range count": lambda tree=tree: spend(tree.range_count(boxes))}
        for step, run in steps.items():
            start = time.perf_counter()
            for _ in range(runs):
                run()
            out.append({"design": name, "operation": step, "seconds": (time.perf_counter() - start) / runs})
    return out


def ratios(rows: list[dict]) -> list[dict]:
    """Every rival's seconds over ours, by operation, and the geometric mean over operations."""
    ours = {r["operation"]: r["seconds"] for r in rows if r["design"] == OURS}
    out = [r | {"ratio": r["seconds"] / ours[r["operation"]]} for r in rows]
    for name in dict.fromkeys(r["design"] for r in rows):
        own = [r["ratio"] for r in out if r["design"] == name]
        out.append({"design": name, "operation": "geometric mean", "seconds": None, "ratio": math.exp(sum(map(math.log, own)) / len(own))})
    return out


def minutes(events: DataFrame) -> DataFrame:
    """(point_id, c0, c1, shuffled) of every minute that has events: its number, the mean value in hundredths (from an exact
    sum), and a hash. All events are read; how many points that makes goes by the time they span."""
    at = F.expr("timestampdiff(MINUTE, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts)")
    cents = F.sum(F.round(F.col("value") * 100).cast("bigint")) / F.count("value")
    found = events.filter("ts IS NOT NULL AND value IS NOT NULL").groupBy(at.alias("point_id")).agg(cents.cast("double").alias("c1"))
    return found.select("point_id", F.col("point_id").cast("double").alias("c0"), "c1", F.xxhash64("point_id", F.lit(5)).alias("shuffled"))


def stream_order(kind: str, at: np.ndarray, shuffled: np.ndarray) -> np.ndarray:
    """'in time', 'tenth first' (a tenth at random, then the rest in time) or 'shuffled': the order in which points come."""
    if kind == "in time":
        return np.argsort(at, kind="stable")
    if kind == "shuffled":
        return np.lexsort((at, shuffled))
    first = shuffled % 10 == 0
    return np.lexsort((np.where(first, shuffled, at), ~first))


def balance_study(events: DataFrame, kinds=("in time", "tenth first", "shuffled"), slacks=(0.01, 0.03, 0.1, 0.2, 0.3, 0.4, 0.5), batches: int = 200, every: int = 10, probes: int = 100) -> DataFrame:
    """(stream, slack, batches, rebuild_ratio, moved_ratio, height, balanced_height, visits_mean, visits_max).

    The points are the minutes of the events. Each (stream, slack) is a task that inserts the batches into one
    local tree. After every ``every`` batches the nodes that 1-NN queries pass are divided by those of a tree of
    medians over the same points; the figures are the geometric mean and the maximum of that.
    """
    cases = [(k, a) for k in kinds for a in slacks]
    fields = "stream string, slack double, batches int, rebuild_ratio double, moved_ratio double, height int, balanced_height int, visits_mean double, visits_max double"

    def run(key, table):
        kind, alpha = cases[key[0].as_py()]
        at, n = table.column("point_id").to_numpy(), table.num_rows
        order = stream_order(kind, at, table.column("shuffled").to_numpy())
        rows, ids = np.stack([table.column(c).to_numpy() for c in ("c0", "c1")], axis=1)[order], at[order]
        params, counters, asked = TreeParams(alpha=alpha), Counters(), np.random.default_rng(99).integers(0, n, probes)
        tree, slower, even = LocalTree.grow(np.zeros((0, 2)), np.zeros(0, np.int64), params), [], None
        for b in range(batches):
            own = slice(b * n // batches, (b + 1) * n // batches)
            tree = tree.insert(rows[own], ids[own], params, counters)
            if own.stop and ((b + 1) % every == 0 or b + 1 == batches):
                even = LocalTree.grow(rows[: own.stop], ids[: own.stop], plain())
                passed = []
                for t in (tree, even):
                    visits = np.zeros((probes, 2), np.int64)
                    t.knn(rows[asked % own.stop], 1, None, visits)
                    passed.append(visits.sum())
                slower.append(passed[0] / passed[1])
        values = [kind, alpha, batches, counters.rebuilt / n, counters.moved / n, int(tree.depths().max()), int(even.depths().max()), math.exp(np.mean(np.log(slower))), max(slower)]
        kinds_ = [pa.string(), pa.float64(), pa.int32(), pa.float64(), pa.float64(), pa.int32(), pa.int32(), pa.float64(), pa.float64()]
        return pa.table([pa.array([v], k) for v, k in zip(values, kinds_, strict=True)], names=[f.split()[0] for f in fields.split(", ")])

    spark = events.sparkSession
    dealt = minutes(events).crossJoin(F.broadcast(spark.range(len(cases)).withColumnRenamed("id", "case")))
    # A partition for every case.
    return dealt.repartitionById(len(cases), F.col("case").cast("int")).groupBy("case").applyInArrow(run, fields)
