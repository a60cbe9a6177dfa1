"""The distributed tree: construction in rounds of several levels, batch updates by partial rebuilding, queries.

Two tiers. Nodes above the shards are in a ``TopTree``; every shard is one row that holds a
``LocalTree``. A round samples every open bucket, draws a skeleton of several levels from
each sample and counts the points of the new buckets; when all buckets fit a shard, the
points are moved once, straight to their shard.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from axisgrove.model import Report, TreeParams, axes, dimensions_of, is_balanced, normal_points
from axisgrove.functions.geometry import locate_column
from axisgrove.operators.local import Counters, LocalTree, Skeleton, descend
from axisgrove.operators.top import TopTree
from axisgrove.plans.storage import SHARD_SCHEMA, Segments, cut

#: Requests that one task answers against one shard at a time.
CHUNK = 4096
#: Open ends of at most so many bytes of coordinates are split at true medians by one task each, all levels in one round.
MEDIAN_BYTES = 1 << 26
#: Larger ones find each median between two values of a sample of about so many points.
MEDIAN_SAMPLE = 4096
#: Points that a task moves to their shards and builds, one shard after the other.
DEALT = 1 << 17
_FIELDS = [c.split()[0] for c in SHARD_SCHEMA.split(", ")]


def matrix(batch: pa.RecordBatch, names: list[str]) -> np.ndarray:
    return np.stack([batch.column(c).to_numpy(zero_copy_only=False).astype(float) for c in names], axis=1) if batch.num_rows else np.zeros((0, len(names)))


def send(spark: SparkSession, value):
    """A broadcast of a value whose classes executors may not know."""
    return spark.sparkContext.broadcast(cloudpickle.dumps(value))


def located(points: DataFrame, top: TopTree, column: str = "node", how: str = "arrow") -> DataFrame:
    """Adds the end node of every point: by Arrow batches, or natively by nested comparisons (small trees)."""
    d = top.d
    if how == "native":
        return points.withColumn(column, locate_column(top))
    held = send(points.sparkSession, top.arrays())
    names = axes(d)

    def work(batches):
        arrays = cloudpickle.loads(held.value)
        for batch in batches:
            yield batch.append_column(column, pa.array(descend(*arrays, matrix(batch, names)), pa.int64()))

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in points.schema)
    return points.mapInArrow(work, f"{kinds}, `{column}` bigint")


def valued(rows: DataFrame, key: str, values: dict[str, np.ndarray], base: int = 0) -> DataFrame:
    """Adds columns with ``values[name][key - base]``: arrays go to tasks once, and a row looks its place up directly."""
    held = send(rows.sparkSession, values)

    def work(batches):
        arrays = cloudpickle.loads(held.value)
        for batch in batches:
            at = batch.column(key).to_numpy(zero_copy_only=False) - base
            for name, v in arrays.items():
                batch = batch.append_column(name, pa.array(v[at]))
            yield batch

    kinds = [f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema]
    names = {"i": "bigint", "f": "double", "b": "boolean"}
    return rows.mapInArrow(work, ", ".join(kinds + [f"`{c}` {names[v.dtype.kind]}" for c, v in values.items()]))


def by_node(top: TopTree, found: dict[int, object], rest, kind) -> np.ndarray:
    """One value a node of the top tier: those of ``found``, elsewhere ``rest``."""
    out = np.full(len(top.dim), rest, dtype=kind)
    out[list(found)] = list(found.values())
    return out


def hash_order(params: TreeParams):
    """Sampling order of rows: fixed by id, whatever the partitions."""
    return F.xxhash64("point_id", F.lit(params.seed))


def draw_sample(points: DataFrame, s: int, seed: int = 1, how: str = "hash", n: int | None = None) -> DataFrame:
    """``s`` rows. 'hash': those of least hash, no row twice; 'replace': as often as drawn with replacement.

    With the number of rows known, a threshold first removes nearly all others, so that
    what is sorted is small.
    """
    order = F.xxhash64("point_id", F.lit(seed))
    if how == "hash":
        held, by = points.withColumn("__o", order), ["__o", *points.columns]
        if n and n > 8 * s:
            # Low hashes are expected to be four times as many as are wanted; if they are not enough, all are sorted.
            low = held.filter(F.col("__o") < F.lit(int(4 * s / n * 2**64) - 2**63))
            held = low if low.limit(s).count() == s else held
        return held.orderBy(*by).limit(s).drop("__o")
    share = F.pmod(order, F.lit(1 << 30)) / float(1 << 30)
    total = n if n is not None else points.count()
    # Copies of a row in a sample with replacement follow a Poisson law of mean s / n.
    mean = s / max(1, total)
    steps, p, acc = [], math.exp(-mean), 0.0
    for k in range(1, 40):
        acc += p
        steps.append(F.when(share >= acc, 1).otherwise(0))
        p *= mean / k
    copies = sum(steps[1:], steps[0])
    return points.withColumn("__k", copies).filter("__k > 0").withColumn("__j", F.explode(F.sequence(F.lit(1), F.col("__k")))).orderBy(F.xxhash64("point_id", "__j", F.lit(seed + 1))).limit(s).drop("__k", "__j")


def _grow_shards(dealt: DataFrame, d: int, params: TreeParams) -> DataFrame:
    """One row a shard from points with ``shard_id``: a single exchange, then one shard in memory at a time."""
    names = axes(d)

    def row(shard: int, points: np.ndarray, ids: np.ndarray):
        counters = Counters()
        tree = LocalTree.grow(points, ids, params, counters)
        return shard_row(shard, tree, counters)

    def work(batches):
        now, points, ids = None, [], []
        for batch in batches:
            shard = batch.column("shard_id").to_numpy(zero_copy_only=False)
            p, i = matrix(batch, names), batch.column("point_id").to_numpy(zero_copy_only=False)
            edges = [0, *(np.flatnonzero(np.diff(shard)) + 1).tolist(), len(shard)]
            for a, b in zip(edges, edges[1:], strict=False):
                if a == b:
                    continue
                if now is not None and shard[a] != now:
                    yield row(now, np.concatenate(points), np.concatenate(ids))
                    points, ids = [], []
                now = int(shard[a])
                points.append(p[a:b])
                ids.append(i[a:b])
        if now is not None:
            yield row(now, np.concatenate(points), np.concatenate(ids))

    return dealt.sortWithinPartitions("shard_id").mapInArrow(work, SHARD_SCHEMA)


def shard_row(shard: int, tree: LocalTree, counters: Counters, found: int = 0, absent_ids: bytes = b"", absent_points: bytes = b"") -> pa.RecordBatch:
    n = len(tree.ids)
    low = tree.points.min(axis=0).tolist() if n else []
    high = tree.points.max(axis=0).tolist() if n else []
    height = int(tree.depths().max()) if len(tree.dim) else 0
    values = [shard, n, len(tree.dim), height, counters.rebuilt, counters.moved, counters.rounds, low, high, found, absent_ids, absent_points, tree.pack()]
    kinds = [pa.int64()] * 7 + [pa.list_(pa.float64())] * 2 + [pa.int64()] + [pa.binary()] * 3
    return pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(values, kinds, strict=True)], names=_FIELDS)


def counted(points: DataFrame, top: TopTree, only: list[int]) -> dict[int, int]:
    """How many points come to each of some ends; tasks give one number an end."""
    held, names = send(points.sparkSession, (top.arrays(), by_node(top, dict.fromkeys(only, True), False, bool))), axes(top.d)

    def work(batches):
        arrays, wanted = cloudpickle.loads(held.value)
        total = np.zeros(len(wanted), np.int64)
        for batch in batches:
            total += np.bincount(descend(*arrays, matrix(batch, names)), minlength=len(wanted))
        some = np.flatnonzero(wanted & (total > 0))
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(total[some])], names=["node", "n"])

    found = points.select(*names).mapInArrow(work, "node bigint, n bigint").groupBy("node").agg(F.sum("n").alias("n"))
    return {r["node"]: r["n"] for r in found.collect()}


def _least(points: DataFrame, s: int, seed: int, n: int, names: list[str]) -> np.ndarray:
    """The rows of ``draw_sample``, collected: rows above a threshold are sorted only where those below are too few."""
    held, by = points.withColumn("__o", F.xxhash64("point_id", F.lit(seed))), ["__o", *points.columns]
    low = held.filter(F.col("__o") < F.lit(int(4 * s / n * 2**64) - 2**63)) if n > 8 * s else held
    rows = low.orderBy(*by).limit(s).select(*names).toPandas()
    if len(rows) < min(s, n) and n > 8 * s:
        rows = held.orderBy(*by).limit(s).select(*names).toPandas()
    return rows.to_numpy(dtype=float)


def _bucket_skeletons(points: DataFrame, open_: dict[int, int], top: TopTree, params: TreeParams) -> dict[int, tuple[Skeleton | None, list[int] | None]]:
    """A skeleton for every open end, from a sample of its points (None where it does not split), and the points of its
    buckets where they are known by then. One bucket's sample is drawn on the driver; the samples of many are turned
    into skeletons where they are, and only those come back."""
    largest = max(open_.values())
    # No more levels than it takes to bring the largest bucket down to a shard.
    levels = min(params.levels, max(1, math.ceil(math.log2(largest / params.shard_rows) + 0.5)))
    params = params.but(levels=levels)
    names, s = axes(top.d), params.base_cutoff
    depth = {k: top.depth(k) for k in open_}
    if params.sampler == "exact":
        most = MEDIAN_BYTES // (8 * top.d)
        if params.movement == "eager" or largest > most:
            return _median_splits(points, {k: n for k, n in open_.items() if params.movement == "eager" or n > most}, top, params)
        return _median_skeletons(points, open_, top, params)
    if len(open_) == 1:
        (k,) = open_
        here = points if len(top.dim) == 1 else located(points, top).filter(F.col("node") == k).drop("node")
        return {k: (Skeleton.from_sample(_least(here, s, params.seed, open_[k], names), params.levels, params.split_rule, depth[k]), None)}
    need = by_node(top, {k: min(1.0, 2.0 * s / max(1, n)) for k, n in open_.items()}, 0.0, float)
    share = F.pmod(hash_order(params), F.lit(1 << 30)) / float(1 << 30)
    held = send(points.sparkSession, (top.arrays(), need))

    def pick(batches):
        arrays, need = cloudpickle.loads(held.value)
        for batch in batches:
            node = descend(*arrays, matrix(batch, names))
            own = np.flatnonzero(batch.column("__share").to_numpy() < need[node])
            yield pa.RecordBatch.from_arrays([pa.array(node[own]), *[batch.column(c).take(pa.array(own)) for c in names]], names=["node", *names])

    # No more than the largest share of any end is looked at by place.
    sample = points.withColumn("__share", share).filter(F.col("__share") < F.lit(float(need.max()))).select("__share", *names)
    sample = sample.mapInArrow(pick, "node bigint, " + ", ".join(f"{c} double" for c in names))

    def draw(key, table):
        k = key[0].as_py()
        points = np.stack([table.column(c).to_numpy() for c in names], axis=1)
        made = Skeleton.from_sample(points, params.levels, params.split_rule, depth[k])
        return pa.table({"node": pa.array([k], pa.int64()), "blob": pa.array([cloudpickle.dumps(made)], pa.binary())})

    made = sample.groupBy("node").applyInArrow(draw, "node bigint, blob binary").collect()
    return {k: (None, None) for k in open_} | {r["node"]: (cloudpickle.loads(r["blob"]), None) for r in made}


def _runs(node: np.ndarray, wanted: np.ndarray):
    """(node, its rows) for the wanted nodes of a batch."""
    order = np.argsort(node, kind="stable")
    order = order[wanted[node[order]]]
    edge = np.flatnonzero(np.diff(node[order], prepend=-1))
    for a, b in zip(edge.tolist(), [*edge[1:].tolist(), len(order)], strict=False):
        yield int(node[order[a]]), order[a:b]


def _median_splits(points: DataFrame, open_: dict[int, int], top: TopTree, params: TreeParams) -> dict[int, tuple[Skeleton | None, list[int] | None]]:
    """One true median for every open end, in two passes: extents and a sample, which gives the dimension and two values
    that the median lies between; then the number of points below these and the values between. Where it
    does not lie there, all values of the end are taken. Tasks and the driver hold numbers of an end, and of its points the few between."""
    names, spark = axes(top.d), points.sparkSession
    depth = {k: top.depth(k) for k in open_}
    share = by_node(top, {k: MEDIAN_SAMPLE / max(1, n) for k, n in open_.items()}, 0.0, float)
    held = send(spark, (top.arrays(), share))

    def looked(batches):
        arrays, share = cloudpickle.loads(held.value)
        low, high, some = {}, {}, {}
        rng = np.random.default_rng(params.seed)
        for batch in batches:
            at = matrix(batch, names)
            for k, own in _runs(descend(*arrays, at), share > 0):
                here = at[own]
                low[k] = np.minimum(low.get(k, np.inf), here.min(axis=0))
                high[k] = np.maximum(high.get(k, -np.inf), here.max(axis=0))
                some.setdefault(k, []).append(here[rng.random(len(here)) < share[k]])
        for k in low:
            yield pa.RecordBatch.from_arrays([pa.array([k]), *[pa.array([v.tobytes()], pa.binary()) for v in (low[k], high[k], np.concatenate(some[k]))]], names=["node", "low", "high", "some"])

    def between(key, table):
        k = key[0].as_py()
        read = lambda c: np.concatenate([np.frombuffer(x, float).reshape(-1, len(names)) for x in table.column(c).to_pylist()])
        low, high, some = read("low").min(axis=0), read("high").max(axis=0), read("some")
        start = depth[k] % len(names) if params.split_rule == "cycle" else int(np.argmax(high - low))
        order = [(start + j) % len(names) for j in range(len(names))] if params.split_rule == "cycle" else [start]
        dim = next((j for j in order if high[j] > low[j]), -1)
        x, gap = np.sort(some[:, dim]), 2 * math.isqrt(len(some)) + 1
        a, b = (x[len(x) // 2 - gap], x[len(x) // 2 + gap]) if len(x) > 4 * gap else (-np.inf, np.inf)
        return pa.table({"node": pa.array([k]), "dim": pa.array([dim]), "least": pa.array([low[dim]]), "a": pa.array([float(a)]), "b": pa.array([float(b)])})

    coords = points.select(*names)
    found = coords.mapInArrow(looked, "node bigint, low binary, high binary, some binary").groupBy("node").applyInArrow(between, "node bigint, dim bigint, least double, a double, b double").collect()
    waiting = {r["node"]: (r["dim"], r["least"], r["a"], r["b"]) for r in found if r["dim"] >= 0}
    out: dict[int, tuple[Skeleton | None, list[int] | None]] = {k: (None, None) for k in open_}
    while waiting:
        asked = send(spark, (top.arrays(), by_node(top, {k: v[0] for k, v in waiting.items()}, -1, np.int64), waiting))

        def gathered(batches):
            arrays, dim, limits = cloudpickle.loads(asked.value)
            below, above = dict.fromkeys(limits, 0), dict.fromkeys(limits, np.inf)
            inside: dict[int, list] = {}
            for batch in batches:
                at = matrix(batch, names)
                for k, own in _runs(descend(*arrays, at), dim >= 0):
                    _, _, a, b = limits[k]
                    x = at[own, dim[k]]
                    below[k] += int((x < a).sum())
                    more = x[x > b]
                    if len(more):
                        above[k] = min(above[k], more.min())
                    inside.setdefault(k, []).append(x[(x >= a) & (x <= b)])
            for k in inside:
                value, many = np.unique(np.concatenate(inside[k]), return_counts=True)
                value, many = np.append(value, [-np.inf, np.inf, above[k]]), np.append(many, [below[k], 0, 0])
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(value), k)), pa.array(value), pa.array(many)], names=["node", "value", "many"])

        def pick(key, table):
            k = key[0].as_py()
            value, place = np.unique(table.column("value").to_numpy(), return_inverse=True)
            many = np.bincount(place, table.column("many").to_numpy(), len(value)).astype(np.int64)
            ends, rank = np.cumsum(many), open_[k] // 2
            at = int(np.searchsorted(ends, rank, "right"))
            # Values without a number lie beyond the upper limit, those before the first beyond the lower.
            known = 0 < at < len(value)
            if known and value[at] == waiting[k][1]:
                at += 1
            return pa.table({"node": pa.array([k]), "value": pa.array([value[at] if known else None], pa.float64()), "left": pa.array([int(ends[at - 1]) if known else None], pa.int64())})

        got = coords.mapInArrow(gathered, "node bigint, value double, many bigint").groupBy("node").applyInArrow(pick, "node bigint, value double, left bigint").collect()
        for r in got:
            if r["value"] is not None:
                out[r["node"]] = Skeleton.from_splits([(waiting[r["node"]][0], r["value"])]), [r["left"], open_[r["node"]] - r["left"]]
        waiting = {r["node"]: (*waiting[r["node"]][:2], -np.inf, np.inf) for r in got if r["value"] is None}
    return out


def _median_skeletons(points: DataFrame, open_: dict[int, int], top: TopTree, params: TreeParams) -> dict[int, tuple[Skeleton | None, list[int] | None]]:
    """The skeletons that rounds of true medians would come to, each from all points of an end in one task."""
    names, depth = axes(top.d), {k: top.depth(k) for k in open_}
    held = send(points.sparkSession, (top.arrays(), by_node(top, dict.fromkeys(open_, True), False, bool)))

    def here(batches):
        arrays, wanted = cloudpickle.loads(held.value)
        for batch in batches:
            node = descend(*arrays, matrix(batch, names))
            own = pa.array(np.flatnonzero(wanted[node]))
            yield pa.RecordBatch.from_arrays([pa.array(node).take(own), *[batch.column(c).take(own) for c in names]], names=["node", *names])

    def draw(key, table):
        k = key[0].as_py()
        points = np.stack([table.column(c).to_numpy() for c in names], axis=1)
        made = Skeleton.from_sample(points, 1 << 30, params.split_rule, depth[k], params.shard_rows)
        many = None if made is None else np.bincount(made.locate(points), minlength=made.buckets).tolist()
        return pa.table({"node": pa.array([k], pa.int64()), "blob": pa.array([cloudpickle.dumps((made, many))], pa.binary())})

    dealt = points.select(*names).mapInArrow(here, "node bigint, " + ", ".join(f"{c} double" for c in names))
    made = dealt.groupBy("node").applyInArrow(draw, "node bigint, blob binary").collect()
    return {k: (None, None) for k in open_} | {r["node"]: cloudpickle.loads(r["blob"]) for r in made}


def refine(rows: DataFrame, top: TopTree, open_: dict[int, int], params: TreeParams, report: Report) -> tuple[DataFrame, list[int]]:
    """Splits the open ends of ``top`` (node to number of points) until they fit a shard, gives them
    shard numbers, and returns the points with ``shard_id``, dealt, and the numbers. All ends advance together."""
    fresh = sorted(open_)
    waiting = {k: n for k, n in open_.items() if n > params.shard_rows}
    counts = dict(open_)
    stuck: set[int] = set()
    # Every round finds the ends anew from the points themselves, not through the rounds before.
    held = rows.select("point_id", *axes(top.d))
    while waiting:
        skeletons = _bucket_skeletons(held, waiting, top, params)
        grown: list[int] = []
        new: dict[int, int] = {}
        whole = params.sampler == "exact" and params.movement != "eager" and max(waiting.values()) <= MEDIAN_BYTES // (8 * top.d)
        for k, (skeleton, many) in sorted(skeletons.items()):
            if skeleton is None:
                stuck.add(k)  # all points agree, as far as a sample can tell
            else:
                ends = top.graft(k, skeleton)
                grown += ends
                if many is not None:
                    new.update(zip(ends, many, strict=True))
                counts.pop(k)
                fresh.remove(k)
        report.rounds += 1
        if not grown:  # others may wait that were not tried
            waiting = {k: n for k, n in waiting.items() if k not in stuck}
            continue
        report.scanned += sum(waiting.values())
        if params.movement == "eager":
            held = cut(located(held, top).repartition("node")).drop("node")
            report.moved += sum(waiting.values())
        if missing := [k for k in grown if k not in new]:
            new |= counted(held, top, missing)
        counts.update({k: new.get(k, 0) for k in grown})
        fresh += grown
        if whole:  # all levels were made: where an end is still too large, its points agree
            stuck |= {k for k in grown if counts[k] > params.shard_rows}
        waiting = {k: counts[k] for k in fresh if counts[k] > params.shard_rows and k not in stuck}
    pieces: dict[int, list[int]] = {}
    for k in fresh:
        many = max(1, math.ceil(counts[k] / params.shard_rows)) if k in stuck else 1
        pieces[k] = top.new_shards(many)
        top.shards[k] = pieces[k]
    report.moved += sum(counts[k] for k in fresh)
    return deal(held, top, pieces, sum(counts[k] for k in fresh)), [s for k in fresh for s in pieces[k]]


def shard_of(rows: DataFrame, top: TopTree, pieces: dict[int, list[int]], spread: bool = True) -> DataFrame:
    """Adds shard_id for points with ``node``: the shards of an end are numbered in a row, and an id names one of
    them, or with ``spread`` off the first; null for ends without any."""
    first = by_node(top, {k: s[0] for k, s in pieces.items()}, -1, np.int64)
    many = by_node(top, {k: len(s) for k, s in pieces.items()}, 1, np.int64)
    own = F.pmod(F.xxhash64("point_id", F.lit(3)), F.col("__many")) if spread else F.lit(0)
    return valued(rows, "node", {"__first": first, "__many": many}).withColumn("shard_id", F.when(F.col("__first") >= 0, F.col("__first") + own)).drop("__first", "__many")


def deal(points: DataFrame, top: TopTree, pieces: dict[int, list[int]], size: int) -> DataFrame:
    """Points with ``shard_id``, shards to partitions in order: neighbours share one, none is split, none is hashed onto another."""
    names, shards = ["point_id", *axes(top.d)], np.array(sorted(s for p in pieces.values() for s in p))
    n = max(1, min(len(shards), max(int(points.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-size // DEALT))))
    place = np.zeros(int(shards[-1] - shards[0]) + 1, np.int32)
    place[shards - shards[0]] = np.arange(len(shards)) * n // len(shards)
    first = by_node(top, {k: s[0] for k, s in pieces.items()}, -1, np.int64)
    many = by_node(top, {k: len(s) for k, s in pieces.items()}, 1, np.int64)
    held = send(points.sparkSession, (top.arrays(), first, many, place, int(shards[0])))

    def work(batches):
        arrays, first, many, place, base = cloudpickle.loads(held.value)
        for batch in batches:
            node = descend(*arrays, matrix(batch, names[1:]))
            shard = first[node] + batch.column("__spread").to_numpy() % many[node]
            yield pa.RecordBatch.from_arrays([pa.array(place[shard - base]), pa.array(shard), *[batch.column(c) for c in names]], names=["__place", "shard_id", *names])

    # An id names one of the shards that a point fills, as in shard_of.
    spread = F.xxhash64("point_id", F.lit(3)) if many.max() > 1 else F.lit(0).cast("bigint")
    dealt = points.select(spread.alias("__spread"), *names).mapInArrow(work, "__place int, shard_id bigint, point_id bigint, " + ", ".join(f"{c} double" for c in names[1:]))
    return dealt.repartitionById(n, F.col("__place")).drop("__place")


class KdTree:
    """A version of a tree. Updates return a new version; old ones stay valid."""

    def __init__(self, spark: SparkSession, top: TopTree, segments: Segments, params: TreeParams, report: Report, heights: dict[int, tuple[int, int]]):
        self.spark, self.top, self.segments, self.params, self.report, self.heights = spark, top, segments, params, report, heights

    # --- construction -----------------------------------------------------------

    @classmethod
    def build(cls, points: DataFrame, params: TreeParams | None = None) -> KdTree:
        """The tree of points (point_id, c0, c1, ...). Rows with a null, NaN or infinite coordinate are left out."""
        params = params or TreeParams()
        clean = normal_points(points)
        top = TopTree(dimensions_of(clean))
        empty = cls(points.sparkSession, top, Segments(points.sparkSession), params, Report(), {})
        return empty._rebuilt(top, {0: clean.count()}, clean, set(), Report())

    def _rebuilt(self, top: TopTree, open_: dict[int, int], rows: DataFrame, gone: set[int], report: Report, also: DataFrame | None = None) -> KdTree:
        """Open ends grown anew from ``rows``, together with other new shard rows; the next version."""
        made = also
        if open_:
            dealt, _ = refine(rows, top, open_, self.params, report)
            grown = _grow_shards(dealt, top.d, self.params)
            made = grown if made is None else made.unionByName(grown)
        if made is None:
            return KdTree(self.spark, top, self.segments, self.params, report, dict(self.heights))
        before = set(self.segments.held)
        segments, stats = self.segments.write(made, gone)
        top = top.copy()
        heights = {s: h for s, h in self.heights.items() if s not in gone}
        for s in gone:
            top.shard_size.pop(s, None)
            top.low.pop(s, None)
            top.high.pop(s, None)
        for r in stats:
            s = r["shard_id"]
            top.shard_size[s], heights[s] = r["size"], (r["height"], r["nodes"])
            if r["size"]:
                top.low[s], top.high[s] = list(r["low"]), list(r["high"])
            report.rebuilt += r["rebuilt"]
            report.moved += r["moved"]
            report.found += r["found"]
        report.shards_written = len(stats)
        report.shards_kept = len(before & set(segments.held) - {r["shard_id"] for r in stats})
        top.sum_up()
        return KdTree(self.spark, top, segments, self.params, report, heights)

    @classmethod
    def build_incremental(cls, batches, params: TreeParams | None = None) -> KdTree:
        """Starts empty and inserts the batches one by one."""
        tree = None
        for batch in batches:
            tree = cls.build(batch, params) if tree is None else tree.insert(batch)
        return tree

    # --- updates ----------------------------------------------------------------

    def _plan(self, after: dict[int, int]) -> tuple[list[int], list[int]]:
        """From the points that ends will have: the topmost nodes to rebuild, and the ends to patch."""
        size = {}
        for k in reversed(self._order()):
            size[k] = after.get(k, self.top.size[k]) if self.top.left[k] < 0 else size[self.top.left[k]] + size[self.top.right[k]]
        touched = set()
        for k in after:
            while k >= 0 and k not in touched:
                touched.add(k)
                k = self.top.parent[k]
        rebuild, patch, stack = [], [], [0] if touched else []
        while stack:
            k = stack.pop()
            if self.top.left[k] < 0:
                (rebuild if size[k] > self.params.shard_rows or not self.top.shards[k] or len(self.top.shards[k]) > 1 else patch).append(k)
            elif size[k] > self.params.leaf_capacity and not is_balanced(size[self.top.left[k]], size[self.top.right[k]], self.params.alpha) or size[k] <= self.params.leaf_capacity:
                rebuild.append(k)
            else:
                stack += [c for c in (self.top.right[k], self.top.left[k]) if c in touched]
        return rebuild, patch

    def _order(self) -> list[int]:
        out, stack = [], [0]
        while stack:
            k = stack.pop()
            out.append(k)
            if self.top.left[k] >= 0:
                stack += [self.top.left[k], self.top.right[k]]
        return out

    def insert(self, batch: DataFrame, on_conflict: str = "bag") -> KdTree:
        """The tree with a batch more. 'bag' keeps every row; 'ignore' leaves out rows whose id and
        coordinates are there already; 'replace' first deletes those."""
        clean = normal_points(batch)
        if on_conflict == "replace":
            return self.delete(clean).insert(clean)
        if on_conflict == "ignore":
            names = ["point_id", *axes(self.top.d)]
            clean = clean.dropDuplicates(names)
            clean = clean.join(self.points_around(clean).select(*names), names, "left_anti")
        rows = cut(located(clean, self.top))
        delta = {r["node"]: r["count"] for r in rows.groupBy("node").count().collect()}
        if not delta:
            return KdTree(self.spark, self.top, self.segments, self.params, Report(shards_kept=len(self.segments.held)), dict(self.heights))
        rebuild, patch = self._plan({k: self.top.size[k] + n for k, n in delta.items()})
        return self._apply(rows, delta, rebuild, patch)

    def _apply(self, rows: DataFrame, delta: dict[int, int], rebuild: list[int], patch: list[int]) -> KdTree:
        top, report, params = self.top.copy(), Report(), self.params
        below = {k: self.top.ends(k) for k in rebuild}
        open_ = {k: self.top.size[k] + sum(delta.get(e, 0) for e in below[k]) for k in rebuild}
        gone = {s for k in rebuild for s in top.close(k)}
        under = {e for k in rebuild for e in below[k]}
        report.rebuilt = sum(open_.values())
        source = None
        if rebuild:
            source = valued(rows, "node", {"__under": by_node(self.top, dict.fromkeys(under, True), False, bool)}).filter("__under").drop("node", "__under")
            if gone:
                source = source.unionByName(self.points(gone).drop("shard_id"))
        also = None
        patched = {k: self.top.shards[k][0] for k in patch if delta.get(k)}
        if patched:
            names = axes(top.d)
            part = valued(rows, "node", {"shard_id": by_node(self.top, patched, -1, np.int64)}).filter("shard_id >= 0")

            def patch_shard(key, old, new):
                counters = Counters()
                tree = LocalTree.unpack(old.column("blob")[0].as_py()) if old.num_rows else LocalTree.grow(np.zeros((0, len(names))), np.zeros(0, np.int64), params)
                points = np.stack([new.column(c).to_numpy() for c in names], axis=1).astype(float)
                tree = tree.insert(points, new.column("point_id").to_numpy(), params, counters)
                return pa.Table.from_batches([shard_row(key[0].as_py(), tree, counters)])

            # A shard that is patched stays below shard_rows points, and so does its share of the batch.
            also = self.segments.read(set(patched.values())).groupBy("shard_id").cogroup(part.groupBy("shard_id")).applyInArrow(patch_shard, SHARD_SCHEMA)
        return self._rebuilt(top, open_, source, gone | set(patched.values()) - set(patched.values()), report, also)

    def delete(self, batch: DataFrame, match: str = "id", copies: str = "one") -> KdTree:
        """The tree without the points that a batch names, by id and coordinates or by coordinates alone
        ('coords': one copy a request, smallest id first, or with copies='all' every copy).

        Round one matches the requests in their shards and takes the points out; round two
        rebuilds, from what is left, the topmost nodes that are out of balance by then.
        Requests that found nothing are in the report: absent (point_id, c0, ...).
        """
        names, params, d = axes(self.top.d), self.params, self.top.d
        rows = located(normal_points(batch), self.top)
        ends = {e: self.top.shards[e] for e in self.top.ends() if self.top.shards[e]}
        if not ends:
            report = Report(absent=rows.drop("node"))
            return KdTree(self.spark, self.top, self.segments, params, report, dict(self.heights))
        # Ids name the one of several shards of a point; by coordinates such shards are asked one after the other.
        rows = cut(shard_of(rows, self.top, ends, match == "id"))
        if match == "coords" and any(len(s) > 1 for s in ends.values()):
            return self._delete_heavy(rows, copies)
        touched = {r["shard_id"] for r in rows.filter(F.col("shard_id").isNotNull()).select("shard_id").distinct().collect()}
        if not touched:
            return KdTree(self.spark, self.top, self.segments, params, Report(absent=rows.drop("node", "shard_id")), dict(self.heights))

        def take_out(key, old, new):
            counters = Counters()
            tree = LocalTree.unpack(old.column("blob")[0].as_py()) if old.num_rows else LocalTree.grow(np.zeros((0, len(names))), np.zeros(0, np.int64), params)
            points = np.stack([new.column(c).to_numpy() for c in names], axis=1).astype(float)
            ids = new.column("point_id").to_numpy()
            gone, found = tree.match(ids if match == "id" else None, points, copies == "all")
            tree = tree.delete(gone, params, counters)
            return pa.Table.from_batches([shard_row(key[0].as_py(), tree, counters, int(gone.sum()), ids[~found].astype(np.int64).tobytes(), points[~found].tobytes())])

        also = self.segments.read(touched).groupBy("shard_id").cogroup(rows.groupBy("shard_id")).applyInArrow(take_out, SHARD_SCHEMA)
        report = Report()
        once = self._rebuilt(self.top.copy(), {}, rows, set(), report, also)
        report.absent = once._absent(touched, d).unionByName(rows.filter(F.col("shard_id").isNull()).select("point_id", *names))
        after = {e: once.top.size[e] for e, s in ends.items() if touched & set(s)}
        rebuild, _ = once._plan(after)
        rebuild = [k for k in rebuild if self.top.left[k] >= 0]
        if not rebuild:
            return once
        twice = once._apply(once.points(set()).drop("shard_id").withColumn("node", F.lit(0).cast("bigint")), {}, rebuild, [])
        final = twice.report
        final.found, final.absent, final.rebuilt, final.moved = report.found, report.absent, final.rebuilt + report.rebuilt, final.moved + report.moved
        final.shards_written += report.shards_written
        return twice

    def _absent(self, shards: set[int], d: int) -> DataFrame:
        names = axes(d)

        def work(batches):
            for batch in batches:
                for ids, points in zip(batch.column("absent_ids").to_pylist(), batch.column("absent_points").to_pylist(), strict=True):
                    p = np.frombuffer(points or b"", float).reshape(-1, d)
                    yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(ids or b"", np.int64)), *[pa.array(p[:, j]) for j in range(d)]], names=["point_id", *names])

        return self.segments.read(shards).select("absent_ids", "absent_points").mapInArrow(work, "point_id bigint, " + ", ".join(f"{c} double" for c in names))

    def _delete_heavy(self, rows: DataFrame, copies: str) -> KdTree:
        """By coordinates where a point fills several shards: requests are numbered against the copies by id."""
        from pyspark.sql import Window

        names = axes(self.top.d)
        asked = rows.groupBy(*names).agg(F.count("*").alias("asked"))
        held = self.points_around(rows.drop("node", "shard_id")).join(asked, names).withColumn("turn", F.row_number().over(Window.partitionBy(*names).orderBy("point_id")))
        victims = held if copies == "all" else held.filter("turn <= asked")
        return self.delete(victims.select("point_id", *names), "id")

    # --- reading ----------------------------------------------------------------

    def points(self, only: set[int] | None = None) -> DataFrame:
        """shard_id, point_id, c0, ... of all points, or of those of some shards."""
        names, d = axes(self.top.d), self.top.d

        def work(batches):
            for batch in batches:
                for shard, blob in zip(batch.column("shard_id").to_pylist(), batch.column("blob").to_pylist(), strict=True):
                    tree = LocalTree.unpack(blob)
                    for a in range(0, len(tree.ids), 1 << 16):
                        own = slice(a, a + (1 << 16))
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(tree.ids[own]), shard)), pa.array(tree.ids[own]), *[pa.array(tree.points[own, j].copy()) for j in range(d)]], names=["shard_id", "point_id", *names])

        return self.segments.read(only).select("shard_id", "blob").mapInArrow(work, "shard_id bigint, point_id bigint, " + ", ".join(f"{c} double" for c in names))

    def points_around(self, rows: DataFrame) -> DataFrame:
        """All points of the shards that hold the places of ``rows``; no other shard is read."""
        ends = [r["node"] for r in located(rows, self.top).select("node").distinct().collect()]
        return self.points({s for e in ends for s in self.top.shards[e]})

    def subtree_points(self, node: int) -> DataFrame:
        """All points below a node of the top tier, from its shards alone."""
        return self.points({s for e in self.top.ends(node) for s in self.top.shards[e]})

    def nodes(self) -> DataFrame:
        """Every node: shard_id and number (preorder; shard -1 for the top tier), depth, kind, dim, val, size, left and right sizes."""
        from axisgrove.operators.inspection import node_rows

        return node_rows(self)

    @property
    def size(self) -> int:
        return self.top.size[0]

    def height(self) -> int:
        return max([self.top.depth(e) + max([self.heights.get(s, (0, 0))[0] for s in self.top.shards[e]], default=0) for e in self.top.ends()], default=0)

    def knn(self, queries: DataFrame, k: int, max_radius: float | None = None) -> DataFrame:
        from axisgrove.operators.queries import knn

        return knn(self, queries, k, max_radius)

    def knn_self(self, k: int, exclude_self: bool = False) -> DataFrame:
        """The nearest points of every point of the tree."""
        from pyspark.sql import Window

        q = self.points().withColumnRenamed("point_id", "query_id").drop("shard_id")
        if not exclude_self:
            return self.knn(q, k)
        found = self.knn(q, k + 1).filter("point_id <> query_id")
        rank = F.row_number().over(Window.partitionBy("query_id").orderBy("rank")).cast("int")
        return found.withColumn("rank", rank).filter(F.col("rank") <= k)

    def range_count(self, boxes: DataFrame) -> DataFrame:
        from axisgrove.operators.queries import range_count

        return range_count(self, boxes)

    def range_report(self, boxes: DataFrame) -> DataFrame:
        from axisgrove.operators.queries import range_report

        return range_report(self, boxes)
