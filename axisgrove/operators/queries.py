"""k nearest neighbours and box queries on a distributed tree.

Requests are routed by descending the top tier, grouped by shard in chunks of bounded size, joined
with the shard's row and answered together inside it. Only shards that are asked for are read; few
requests go to the shards, where they stay. A box that contains a whole node is answered from its size alone.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from axisgrove.model import axes
from axisgrove.operators.local import LocalTree
from axisgrove.operators.tree import CHUNK, KdTree, matrix, send
from axisgrove.plans.storage import cut


#: Requests of up to so many bytes are sent to all tasks, which read shards; more are joined by shuffling.
REQUEST_BYTES = 32 << 20
#: Second searches of more shards a request than this are done in two waves, of the nearest NEAREST shards first.
MANY, NEAREST = 8, 4
#: Requests meet so many shards at a time while they are routed.
ROUTED = 1 << 20
#: Boxes that a task routes in a run.
RUN = 1024


def _slices(rows: int, routes):
    """(from, length) of runs of requests whose pairs with all shards are bounded."""
    step = min(4096, max(16, ROUTED // max(1, len(routes.shards))))
    return [(at, step) for at in range(0, rows, step)]


def _per_shard(requests: DataFrame, tree: KdTree, columns: list[str], answer, schema: str, load: dict[int, int] | None = None) -> DataFrame:
    """``answer(local_tree, request_table, shard)`` for requests (shard_id, ...) in chunks of about CHUNK a shard.

    How many requests each shard gets is one number a shard on the driver; it says which shards
    are read, whether requests or shards are moved, and which go to several tasks.
    """
    load = _load(requests) if load is None else load
    if not load:
        return requests.sparkSession.createDataFrame([], schema)
    busy = [(s, -(-n // CHUNK)) for s, n in load.items() if n > CHUNK]
    chunk = F.lit(0).cast("bigint")
    if busy:
        split = requests.sparkSession.createDataFrame(busy, "__s bigint, __many bigint")
        requests = requests.join(F.broadcast(split), F.col("shard_id") == F.col("__s"), "left")
        chunk = F.pmod(F.xxhash64("query_id", F.lit(9)), F.coalesce("__many", F.lit(1)))
    packed = requests.withColumn("__chunk", chunk).groupBy("shard_id", "__chunk").agg(F.collect_list(F.struct(*columns)).alias("requests"))

    def work(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                tree = LocalTree.unpack(batch.column("blob")[i].as_py())
                part = batch.column("requests").slice(i, 1).flatten()
                asked = {c: part.field(j).to_numpy(zero_copy_only=False) for j, c in enumerate(columns)}
                yield from answer(tree, asked, batch.column("shard_id")[i].as_py())

    shards = tree.segments.read(set(load) if len(load) < len(tree.segments.held) else None).select("shard_id", "blob")
    if not busy and sum(load.values()) * 8 * (len(columns) + 1) <= REQUEST_BYTES:
        packed = F.broadcast(packed)
    return shards.join(packed, "shard_id").select("shard_id", "requests", "blob").mapInArrow(work, schema)


def _load(requests: DataFrame) -> dict[int, int]:
    return {r["shard_id"]: r["count"] for r in requests.groupBy("shard_id").count().collect()}


def _stack(asked: dict, names: list[str]) -> np.ndarray:
    return np.stack([asked[c].astype(float) for c in names], axis=1)


def once_each(asked: DataFrame, names: list[str]) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """Requests that ask the same are answered once: the requests of least id, one for each different value of ``names``, and what gives
    their answers to the others, too. Where fewer than half are repeats, all are asked as they are."""
    asked = cut(asked)
    n, different = asked.agg(F.count("*"), F.countDistinct(F.struct(*names))).head()
    if 2 * different > n:
        return asked, lambda found: found
    least = cut(asked.groupBy(*names).agg(F.min("query_id").alias("query_id"), *[F.first(c).alias(c) for c in asked.columns if c not in ("query_id", *names)]).select(*asked.columns))
    alike = least.select(F.col("query_id").alias("__least"), *[F.col(c).alias(f"__{c}") for c in names])
    alike = asked.select(F.col("query_id").alias("__asked"), *names).join(alike, [F.col(c).eqNullSafe(F.col(f"__{c}")) for c in names]).select("__asked", "__least")

    def given(found: DataFrame) -> DataFrame:
        rest = [c for c in found.columns if c != "query_id"]
        return found.join(alike, F.col("query_id") == F.col("__least")).select(F.col("__asked").alias("query_id"), *rest)

    return least, given


_NEAR = "query_id bigint, point_id bigint, dist2 double"


def _search(requests: DataFrame, tree: KdTree, k: int, load: dict[int, int] | None = None) -> DataFrame:
    names = axes(tree.top.d)

    def answer(local, asked, shard):
        dist, who = local.knn(_stack(asked, names), k, asked["bound"].astype(float))
        rows, place = np.nonzero(~np.isinf(dist))
        yield pa.RecordBatch.from_arrays([pa.array(asked["query_id"][rows]), pa.array(who[rows, place]), pa.array(dist[rows, place])], names=["query_id", "point_id", "dist2"])

    return _per_shard(requests, tree, ["query_id", *names, "bound"], answer, _NEAR, load)


def _routed(queries: DataFrame, tree: KdTree, k: int, fan_out: bool, nearest: tuple[int, int] | None = None) -> DataFrame:
    """(query_id, coordinates, bound, shard_id): the shards of the lowest node with k points around a
    query, or with ``fan_out`` all others whose box comes within the bound. ``nearest`` (from, to) takes
    of each query's shards, the nearest first, only those places."""
    names = axes(tree.top.d)
    held = send(queries.sparkSession, tree.top.routes())

    def work(batches):
        routes = cloudpickle.loads(held.value)
        for whole in batches:
            for at, step in _slices(whole.num_rows, routes):
                batch = whole.slice(at, step)
                points, bound = matrix(batch, names), batch.column("bound").to_numpy(zero_copy_only=False)
                home = routes.home(points, k)
                if fan_out:
                    rows, place, dist = routes.near(points, bound, home)
                    if nearest:
                        order = np.lexsort((place, dist, rows))
                        rows, place = rows[order], place[order]
                        first = np.searchsorted(rows, rows)
                        keep = (np.arange(len(rows)) - first >= nearest[0]) & (np.arange(len(rows)) - first < nearest[1])
                        rows, place = rows[keep], place[keep]
                else:
                    rows, place = routes.below(np.arange(len(points)), home)
                yield batch.take(pa.array(rows)).append_column("shard_id", pa.array(routes.shards[place]))

    kinds = "query_id bigint, " + ", ".join(f"{c} double" for c in names) + ", bound double, shard_id bigint"
    return queries.select("query_id", *names, "bound").mapInArrow(work, kinds)


def _best(found: DataFrame, k: int) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("dist2", "point_id"))
    return found.withColumn("rank", rank.cast("int")).filter(F.col("rank") <= k).select("query_id", "rank", "point_id", "dist2")


def knn(tree: KdTree, queries: DataFrame, k: int, max_radius: float | None = None) -> DataFrame:
    """(query_id, rank, point_id, dist2) of the k nearest points of every query, exactly; ties by id.

    First the shards of the lowest node around the query that holds k points are searched;
    the k-th distance found bounds the others, which are searched where their box comes
    within it (ties included); where that leaves many, the nearest few first, which narrows the
    bound. ``max_radius`` leaves out points farther away.
    """
    if k < 1:
        raise ValueError("k must be at least 1")
    names = axes(tree.top.d)
    limit = float("inf") if max_radius is None else float(max_radius) ** 2
    if not tree.size:
        return queries.sparkSession.createDataFrame([], "query_id bigint, rank int, point_id bigint, dist2 double")
    asked = queries.select(F.col("query_id").cast("bigint").alias("query_id"), *[F.col(c).cast("double").alias(c) for c in names]).withColumn("bound", F.lit(limit))
    asked, given = once_each(asked, names)
    first = cut(_best(_search(_routed(asked, tree, k, False), tree, k), k))
    if len(tree.segments.held) == 1:
        return given(first)

    def narrowed(found: DataFrame) -> DataFrame:
        reach = found.filter(F.col("rank") == k).select(F.col("query_id").alias("__q"), F.col("dist2").alias("__r"))
        return asked.join(reach, F.col("query_id") == F.col("__q"), "left").withColumn("bound", F.least("bound", F.coalesce("__r", F.lit(float("inf"))))).drop("__q", "__r")

    again = _routed(narrowed(first), tree, k, True)
    load = _load(again)
    if sum(load.values()) <= MANY * first.select("query_id").distinct().count():
        return given(_best(first.drop("rank").unionByName(_search(again, tree, k, load)), k))
    # The nearest shards of a query are the same for any bound that they are within.
    close = _search(_routed(narrowed(first), tree, k, True, (0, NEAREST)), tree, k)
    first = cut(_best(first.drop("rank").unionByName(close), k))
    rest = _search(_routed(narrowed(first), tree, k, True, (NEAREST, 1 << 62)), tree, k)
    return given(_best(first.drop("rank").unionByName(rest), k))


def _classified(boxes: DataFrame, tree: KdTree, whole: bool) -> DataFrame:
    """(query_id, lo.., hi.., shard_id, inside, cnt, contained): a row for every shard that a box cuts, and for
    what it contains either one row a node (shard_id null, points in cnt, shards in contained) or,
    with ``whole``, one a shard."""
    d = tree.top.d
    low_names, high_names = axes(d, "lo"), axes(d, "hi")
    held = send(boxes.sparkSession, tree.top.routes())

    def work(batches):
        routes = cloudpickle.loads(held.value)

        def laid(batch, rows, shards, inside, count, contained):
            out = batch.take(pa.array(rows))
            for name, v in (("shard_id", shards), ("inside", pa.array(np.full(len(rows), inside))), ("cnt", pa.array(count)), ("contained", pa.array(contained))):
                out = out.append_column(name, v)
            return out

        for every in batches:
            for at, step in _slices(every.num_rows, routes):
                batch = every.slice(at, step)
                (rows, nodes), (r, place) = routes.boxes(matrix(batch, low_names), matrix(batch, high_names))
                yield laid(batch, r, pa.array(routes.shards[place]), False, np.zeros(len(r), np.int64), np.zeros(len(r), np.int64))
                if whole:
                    rows, place = routes.below(rows, nodes)
                    yield laid(batch, rows, pa.array(routes.shards[place]), True, routes.shard_size[place], np.ones(len(rows), np.int64))
                else:
                    yield laid(batch, rows, pa.nulls(len(rows), pa.int64()), True, routes.size[nodes], routes.stop[nodes] - routes.start[nodes])

    kinds = "query_id bigint, " + ", ".join(f"{c} double" for c in [*low_names, *high_names])
    return boxes.mapInArrow(work, kinds + ", shard_id bigint, inside boolean, cnt bigint, contained bigint")


def normal_boxes(boxes: DataFrame, d: int) -> DataFrame:
    """query_id and double bounds; a null bound is open."""
    return boxes.select(
        F.col("query_id").cast("bigint").alias("query_id"),
        *[F.coalesce(F.col(c).cast("double"), F.lit(float("-inf"))).alias(c) for c in axes(d, "lo")],
        *[F.coalesce(F.col(c).cast("double"), F.lit(float("inf"))).alias(c) for c in axes(d, "hi")],
    )


def range_count(tree: KdTree, boxes: DataFrame) -> DataFrame:
    """(query_id, cnt) of every closed box; 0 for empty and inverted ones. Nodes inside a box are counted by their size, their shards not read."""
    d = tree.top.d
    asked = normal_boxes(boxes, d)
    if not tree.size:
        return asked.select("query_id", F.lit(0).cast("bigint").alias("cnt"))
    low_names, high_names = axes(d, "lo"), axes(d, "hi")
    asked, given = once_each(asked, [*low_names, *high_names])
    if asked.count() * 8 * (2 * d + 1) <= REQUEST_BYTES:
        return given(_counted_at_shards(tree, asked))
    pairs = _classified(asked, tree, False)

    def answer(local, asked, shard):
        yield pa.RecordBatch.from_arrays([pa.array(asked["query_id"]), pa.array(local.ranges(_stack(asked, low_names), _stack(asked, high_names), False))], names=["query_id", "cnt"])

    known = pairs.filter("inside").groupBy("query_id").agg(F.sum("cnt").alias("cnt"))
    partial = _per_shard(pairs.filter("NOT inside"), tree, ["query_id", *low_names, *high_names], answer, "query_id bigint, cnt bigint")
    return given(_summed(asked, known.unionByName(partial)))


def _summed(asked: DataFrame, counts: DataFrame) -> DataFrame:
    total = counts.groupBy("query_id").agg(F.sum("cnt").alias("__cnt")).withColumnRenamed("query_id", "__q")
    return asked.select("query_id").join(total, F.col("query_id") == F.col("__q"), "left").select("query_id", F.coalesce("__cnt", F.lit(0)).cast("bigint").alias("cnt"))


def _counted_at_shards(tree: KdTree, asked: DataFrame) -> DataFrame:
    """range_count where all boxes fit a task: they are sent to the shards, so no pair of a box and a shard is ever a
    row, and a task gives one count for each box that has some of its points."""
    spark, d = tree.spark, tree.top.d
    low_names, high_names = axes(d, "lo"), axes(d, "hi")
    boxes = asked.toArrow()
    held, ways = send(spark, boxes), send(spark, tree.top.routes())

    def laid():
        table = cloudpickle.loads(held.value)
        return table.column("query_id").to_numpy(), *(np.stack([table.column(c).to_numpy() for c in names], axis=1) for names in (low_names, high_names))

    def route(batches):
        """Of runs of boxes: the points of whole nodes (cnt), and the shards that some box cuts (shard_id)."""
        (ids, low, high), routes = laid(), cloudpickle.loads(ways.value)
        counts, seen = np.zeros(len(ids), np.int64), np.zeros(len(routes.shards), bool)
        for batch in batches:
            for start in batch.column("id").to_pylist():
                end = min(start + RUN, len(ids))
                for at, step in _slices(end - start, routes):
                    own = slice(start + at, min(start + at + step, end))
                    (rows, nodes), (_, place) = routes.boxes(low[own], high[own])
                    np.add.at(counts[own], rows, routes.size[nodes])
                    seen[place] = True
        some, near = np.flatnonzero(counts), routes.shards[seen]
        gap = lambda n: pa.nulls(n, pa.int64())
        yield pa.RecordBatch.from_arrays([pa.concat_arrays(x) for x in ((pa.array(ids[some]), gap(len(near))), (pa.array(counts[some]), gap(len(near))), (gap(len(some)), pa.array(near)))], names=["query_id", "cnt", "shard_id"])

    def count(batches):
        (ids, low, high), routes = laid(), cloudpickle.loads(ways.value)
        counts, usable = np.zeros(len(ids), np.int64), (low <= high).all(axis=1)
        place = {s: i for i, s in enumerate(routes.shards.tolist())}
        ends = np.flatnonzero((routes.left < 0) & (routes.stop > routes.start))
        ends = ends[np.argsort(routes.start[ends])]
        end = np.repeat(ends, routes.stop[ends] - routes.start[ends])
        for batch in batches:
            for shard, blob in zip(batch.column("shard_id").to_pylist(), batch.column("blob"), strict=True):
                at = place[shard]
                meets, whole = usable.copy(), np.ones(len(ids), bool)
                for j in range(d):
                    meets &= (low[:, j] <= routes.shard_high[at, j]) & (routes.shard_low[at, j] <= high[:, j])
                    whole &= (low[:, j] <= routes.low[end[at], j]) & (routes.high[end[at], j] <= high[:, j])
                own = np.flatnonzero(meets & ~whole)  # whole nodes are counted where boxes are routed
                counts[own] += LocalTree.unpack(blob.as_py()).ranges(low[own], high[own], False)
        some = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(counts[some])], names=["query_id", "cnt"])

    if not boxes.num_rows:
        return asked.select("query_id", F.lit(0).cast("bigint").alias("cnt"))
    runs = spark.range(0, boxes.num_rows, RUN, max(1, min(spark.sparkContext.defaultParallelism, -(-boxes.num_rows // RUN))))
    routed = cut(runs.mapInArrow(route, "query_id bigint, cnt bigint, shard_id bigint"))
    near = {r[0] for r in routed.filter("shard_id IS NOT NULL").select("shard_id").distinct().collect()}
    known = routed.filter("shard_id IS NULL").drop("shard_id")
    if not near:
        return _summed(asked, known)
    shards = tree.segments.read(near if len(near) < len(tree.segments.held) else None).select("shard_id", "blob")
    return _summed(asked, known.unionByName(shards.mapInArrow(count, "query_id bigint, cnt bigint")))




def range_report(tree: KdTree, boxes: DataFrame) -> DataFrame:
    """(query_id, point_id, c0, ...) of all points in each closed box; shards inside a box are given out unsearched."""
    d = tree.top.d
    names, low_names, high_names = axes(d), axes(d, "lo"), axes(d, "hi")
    schema = "query_id bigint, point_id bigint, " + ", ".join(f"{c} double" for c in names)
    if not tree.size:
        return boxes.sparkSession.createDataFrame([], schema)
    pairs = _classified(normal_boxes(boxes, d), tree, True)

    def answer(local, asked, shard):
        inside = asked["inside"].astype(bool)
        low, high = _stack(asked, low_names), _stack(asked, high_names)
        low[inside], high[inside] = -np.inf, np.inf
        for a in range(0, len(low), 64):
            q, p = local.ranges(low[a : a + 64], high[a : a + 64], True)
            yield pa.RecordBatch.from_arrays([pa.array(asked["query_id"][a + q]), pa.array(local.ids[p]), *[pa.array(local.points[p, j]) for j in range(d)]], names=["query_id", "point_id", *names])

    return _per_shard(pairs, tree, ["query_id", *low_names, *high_names, "inside"], answer, schema)


def visit_counts(tree: KdTree, requests: DataFrame, k: int | None = None) -> DataFrame:
    """(query_id, leaves, interiors, shards_read, shards_contained): nodes passed by box queries, or by k-NN in the home shards."""
    d = tree.top.d
    names, low_names, high_names = axes(d), axes(d, "lo"), axes(d, "hi")
    schema = "query_id bigint, leaves bigint, interiors bigint"

    def answer(local, asked, shard):
        visits = np.zeros((len(asked["query_id"]), 2), np.int64)
        if k is None:
            local.ranges(_stack(asked, low_names), _stack(asked, high_names), False, visits)
        else:
            local.knn(_stack(asked, names), k, asked["bound"].astype(float), visits)
        yield pa.RecordBatch.from_arrays([pa.array(asked["query_id"]), pa.array(visits[:, 0]), pa.array(visits[:, 1])], names=["query_id", "leaves", "interiors"])

    if k is None:
        pairs = _classified(normal_boxes(requests, d), tree, False)
        seen = _per_shard(pairs.filter("NOT inside"), tree, ["query_id", *low_names, *high_names], answer, schema)
        contained = pairs.groupBy("query_id").agg(F.sum("contained").alias("contained"))
    else:
        pairs = _routed(requests.withColumn("bound", F.lit(float("inf"))), tree, k, False)
        seen = _per_shard(pairs, tree, ["query_id", *names, "bound"], answer, schema)
        contained = pairs.groupBy("query_id").agg(F.lit(0).cast("bigint").alias("contained"))
    total = seen.groupBy("query_id").agg(F.sum("leaves").alias("leaves"), F.sum("interiors").alias("interiors"), F.count("*").alias("shards_read"))
    out = requests.select(F.col("query_id").cast("bigint").alias("query_id")).join(total, "query_id", "left").join(contained, "query_id", "left")
    return out.select("query_id", *[F.coalesce(c, F.lit(0)).cast("bigint").alias(c if c != "contained" else "shards_contained") for c in ("leaves", "interiors", "shards_read", "contained")])
