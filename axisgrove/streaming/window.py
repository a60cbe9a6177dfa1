"""Sliding windows of batches: as a loop over frames, and over a stream with foreachBatch."""

from __future__ import annotations

from collections.abc import Callable, Iterable

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from axisgrove.model import TreeParams
from axisgrove.operators.tree import KdTree
from axisgrove.plans import snapshot


def run_window(batches: Iterable[tuple[object, DataFrame]], width: int, probe: Callable[[object, object], None], make=None):
    """Inserts each batch, takes out the one of ``width`` steps before, and calls ``probe(name, tree)``.

    ``make`` builds the first tree from a frame (KdTree by default; the baselines fit, too).
    Returns the last tree.
    """
    make = make or (lambda points: KdTree.build(points, TreeParams()))
    tree, held = None, []
    for name, batch in batches:
        tree = make(batch) if tree is None else tree.insert(batch)
        held.append(batch)
        if len(held) > width:
            tree = tree.delete(held.pop(0))
        probe(name, tree)
    return tree


class StreamingTree:
    """Keeps a tree up to date from a stream of points with a day; days older than the window are taken out.

    foreachBatch may repeat a batch after a failure: the number of the last batch that was
    applied is kept with the tree, and a repeated one is passed over. With ``home``, a folder that
    outlives the driver, tree and number are saved after every batch, and a new driver goes on from there.
    """

    def __init__(self, days: int, params: TreeParams | None = None, home: str | None = None):
        self.days, self.params, self.home, self.tree, self.last, self.newest = days, params or TreeParams(), home, None, -1, None

    @classmethod
    def restored(cls, spark, days: int, home: str) -> StreamingTree:
        tree, last = snapshot.load(spark, home)
        held = cls(days, tree.params, home)
        held.tree, held.last = tree, last
        high = [h[0] for h in tree.top.high.values()]
        held.newest = int(max(high) // held.edge(1)) if high else None
        return held

    def apply(self, batch: DataFrame, batch_id: int) -> None:
        """One micro-batch of (point_id, c0, ..., day)."""
        if batch_id <= self.last:
            return
        batch = batch.persist()
        try:
            newest = batch.agg(F.max("day")).head()[0]
            if newest is not None:
                self.newest = newest if self.newest is None else max(self.newest, newest)
                fresh = batch.filter(F.col("day") > self.newest - self.days).drop("day")
                self.tree = KdTree.build(fresh, self.params) if self.tree is None else self.tree.insert(fresh)
                self._expire()
        finally:
            batch.unpersist()
        self.last = batch_id
        if self.home and self.tree is not None:
            snapshot.save(self.tree, self.home, batch_id)

    def _expire(self) -> None:
        """Coordinate 0 is in days or seconds; ``edge`` says where the window begins on it. Only shards that
        reach below that are read."""
        edge = float(self.edge(self.newest - self.days + 1))
        reach = {s for s, low in self.tree.top.low.items() if low[0] < edge}
        if reach:
            self.tree = self.tree.delete(self.tree.points(reach).filter(F.col("c0") < F.lit(edge)).drop("shard_id"))

    def edge(self, day: int) -> float:
        return float(day) * 86400.0

    def start(self, stream: DataFrame, checkpoint: str):
        return stream.writeStream.foreachBatch(self.apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def tumbling(stream: DataFrame, time: str, length: str, late: str, *aggregates) -> DataFrame:
    """Aggregates by event-time windows; rows later than the watermark are dropped."""
    return stream.withWatermark(time, late).groupBy(F.window(time, length).alias("w")).agg(*aggregates)


def sliding(stream: DataFrame, time: str, length: str, step: str, late: str, *aggregates) -> DataFrame:
    return stream.withWatermark(time, late).groupBy(F.window(time, length, step).alias("w")).agg(*aggregates)


def sessions(stream: DataFrame, time: str, gap: str, late: str, key: str, *aggregates) -> DataFrame:
    return stream.withWatermark(time, late).groupBy(F.session_window(time, gap).alias("w"), key).agg(*aggregates)


def shard_counts(stream: DataFrame) -> DataFrame:
    """A running count of arrivals a shard, kept as state: (shard_id, total) on every change."""

    def count(key, frames, state: GroupState):
        total = state.get[0] if state.exists else 0
        for frame in frames:
            total += len(frame)
        state.update((total,))
        yield pd.DataFrame({"shard_id": [key[0]], "total": [total]})

    return stream.groupBy("shard_id").applyInPandasWithState(count, "shard_id bigint, total bigint", "total bigint", "update", GroupStateTimeout.NoTimeout)
