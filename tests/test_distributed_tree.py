"""The distributed tree and its rivals against brute force on small frames."""

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from axisgrove.baselines import FullRebuildTree, LogForest, SequentialTree
from axisgrove.model import TreeParams, plain, rejects
from axisgrove.operators import inspection
from axisgrove.operators.local import Skeleton
from axisgrove.operators.sieve import sieve_offsets
from axisgrove.operators.tree import KdTree, draw_sample
from axisgrove.plans.storage import numbered
from axisgrove.sources.tables import uniform_points, walk_points

SMALL = TreeParams(shard_rows=300)
SF = "/root/testdata/sf0.001"


def frame(spark, points, ids=None):
    data = {"point_id": np.arange(len(points)) if ids is None else ids} | {f"c{j}": points[:, j] for j in range(points.shape[1])}
    return spark.createDataFrame(pd.DataFrame(data), "point_id bigint, " + ", ".join(f"c{j} double" for j in range(points.shape[1])))


def ids_of(df):
    return sorted(r[0] for r in df.select("point_id").collect())


@pytest.fixture(scope="module")
def cloud(spark):
    return uniform_points(spark, 2000, 2, seed=4).cache()


def test_same_tree_for_any_partitioning(spark, cloud):
    one, two = KdTree.build(cloud.repartition(1), SMALL), KdTree.build(cloud.repartition(7), SMALL)
    pick = lambda t: t.nodes().select("shard_id", "number", "dim", "val", "size").orderBy("shard_id", "number").collect()
    assert pick(one) == pick(two)


def test_queries_agree_with_all_rivals(spark, cloud):
    asked = cloud.filter("point_id % 97 = 0").withColumnRenamed("point_id", "query_id")
    boxes = asked.selectExpr("query_id", "c0 - 90000 AS lo0", "c0 + 90000 AS hi0", "c1 - 90000 AS lo1", "c1 + 90000 AS hi1")
    near, count = None, None
    for make in (lambda p: KdTree.build(p, SMALL), lambda p: KdTree.build(p, SMALL.but(store_boxes=True)), lambda p: FullRebuildTree.build(p, plain(shard_rows=300)), lambda p: LogForest(p, plain(), base=256), SequentialTree.build):
        tree = make(cloud.filter("point_id % 2 = 0")).insert(cloud.filter("point_id % 2 = 1"))
        tree = tree.delete(cloud.filter("point_id % 5 = 0"))
        a = sorted(map(tuple, tree.knn(asked, 4).select("query_id", "rank", "point_id", "dist2").collect()))
        b = sorted(map(tuple, tree.range_count(boxes).collect()))
        near, count = near or a, count or b
        assert a == near and b == count and tree.size == 1600


def test_neighbours_with_any_id(spark):
    rng = np.random.default_rng(3)
    ids = np.unique(np.concatenate([[-(2**63), -(2**63) + 1, -(2**62) - 1, -(2**62), -1, 0, 2**63 - 1], rng.integers(-(2**63), 2**63 - 1, 1500, dtype=np.int64)]).astype(np.int64))
    pts = rng.integers(0, 30, (len(ids), 2)).astype(float)
    asked = rng.integers(-5, 35, (60, 2)).astype(float)
    tree = KdTree.build(frame(spark, pts, ids), SMALL)
    assert len(tree.segments.held) > 1 and (ids < -(2**62)).sum() > 300
    queries = frame(spark, asked).withColumnRenamed("point_id", "query_id")
    for k in (1, 7, 2000):
        expected = []
        for q in range(len(asked)):
            dist = ((pts - asked[q]) ** 2).sum(axis=1)
            expected += [(q, r + 1, int(ids[i]), float(dist[i])) for r, i in enumerate(np.lexsort((ids, dist))[:k])]
        assert sorted(map(tuple, tree.knn(queries, k).select("query_id", "rank", "point_id", "dist2").collect())) == expected


def test_edges(spark):
    empty = KdTree.build(frame(spark, np.zeros((0, 2))), SMALL)
    assert empty.size == 0 and empty.points().count() == 0
    q = spark.createDataFrame([(1, 0.0, 0.0)], "query_id bigint, c0 double, c1 double")
    assert empty.knn(q, 3).count() == 0
    with pytest.raises(ValueError):
        empty.knn(q, 0)
    tree = empty.insert(frame(spark, np.ones((1000, 2))))
    assert tree.size == 1000 and tree.knn(q, 3).count() == 3
    assert len([s for s in tree.top.shards.values() for _ in s]) >= 4  # one point, several shards
    few = tree.delete(spark.range(3).selectExpr("id + 5000 AS point_id", "1.0D AS c0", "1.0D AS c1"), match="coords")
    assert ids_of(few.points()) == list(range(3, 1000))
    bad = spark.createDataFrame([(1, None), (2, float("nan")), (3, float("inf")), (4, -0.0)], "point_id bigint, c0 double")
    assert ids_of(KdTree.build(bad, SMALL).points()) == [4] and ids_of(rejects(bad)) == [1, 2, 3]


def test_balance_after_adversarial_stream(spark):
    walk = walk_points(spark, 1500, 2, restart=0.01).cache()
    tree = KdTree.build_incremental([walk.filter(f"point_id >= {a} AND point_id < {a + 500}") for a in (0, 500, 1000)], SMALL)
    assert inspection.balance_report(tree).filter("NOT balanced").count() == 0
    assert ids_of(tree.points()) == list(range(1500))


def test_untouched_shards_keep_their_files(spark, cloud):
    tree = KdTree.build(cloud, SMALL)
    after = tree.insert(cloud.filter("c0 < 100000 AND c1 < 100000").withColumn("point_id", F.col("point_id") + 10**6).limit(3))
    kept = [s for s, p in tree.segments.held.items() if after.segments.held.get(s) == p]
    assert len(kept) >= len(tree.segments.held) - 3


def test_offsets_worked_example(spark):
    rows = [(0, 0, 25.0), (1, 0, 3.0), (2, 0, 12.0), (3, 1, 31.0), (4, 1, 8.0), (5, 1, 22.0)]
    pts = spark.createDataFrame(rows, "point_id bigint, chunk bigint, c0 double")
    got = sieve_offsets(pts, Skeleton.from_splits([(0, 20.0), (0, 10.0), (0, 30.0)]), F.col("chunk")).orderBy("chunk", "bucket").collect()
    assert [r["n"] for r in got] == [1, 1, 1, 0, 1, 0, 1, 1] and [r["start"] for r in got] == [0, 2, 3, 5, 1, 3, 4, 5]


def test_sample_is_independent_of_layout(spark, cloud):
    assert ids_of(draw_sample(cloud.repartition(9), 100, n=2000)) == ids_of(draw_sample(cloud.coalesce(1), 100))


def test_sample_is_of_least_hash(spark, cloud):
    hashed = sorted((r["h"], r["point_id"]) for r in cloud.select(F.xxhash64("point_id", F.lit(1)).alias("h"), "point_id").collect())
    for s in (1, 10, 100, 1999, 5000):
        assert ids_of(draw_sample(cloud, s, n=2000)) == sorted(i for _, i in hashed[:s])
    twice = cloud.withColumn("point_id", F.col("point_id") % 3)  # three hashes, all far apart: the threshold passes none or many
    assert draw_sample(twice, 50, n=2000).count() == 50


def test_numbered(spark, cloud):
    got = numbered(cloud.select("point_id", "c0"), "place", "c0", "point_id").collect()
    assert [r["place"] for r in sorted(got, key=lambda r: (r["c0"], r["point_id"]))] == list(range(2000))
    assert numbered(cloud.filter("false"), "place", "c0").count() == 0


@pytest.mark.parametrize("mode", ["capacity", "exact"])
def test_forest_over_random_updates(spark, mode):
    """Against a plain list of points, through insertions, deletions, repeated ids and an emptied forest."""
    rng = np.random.default_rng(17)
    held: list[tuple] = []
    forest = LogForest(None, plain(shard_rows=200), base=64, mode=mode)
    queries = [(q, float(rng.integers(0, 40)), float(rng.integers(0, 40))) for q in range(8)]
    asked = spark.createDataFrame(queries, "query_id bigint, c0 double, c1 double")
    boxes = asked.selectExpr("query_id", "c0 - 6 AS lo0", "c0 + 6 AS hi0", "c1 - 6 AS lo1", "c1 + 6 AS hi1")
    make = lambda rows: spark.createDataFrame(rows, "point_id bigint, c0 double, c1 double")
    fresh = lambda n: [(int(rng.integers(0, 400)), float(rng.integers(0, 40)), float(rng.integers(0, 40))) for _ in range(n)]
    for step in ("i300", "i260", "d0.3", "d0.75", "i90", "d1.0", "i50", "d0.5"):
        if step[0] == "i":
            rows = fresh(int(step[1:]))
            held, forest = held + rows, forest.insert(make(rows))
        else:
            gone = [p for p in held if rng.random() < float(step[1:])]
            held, forest = [p for p in held if p not in set(gone)], forest.delete(make([*gone, (9999, 1.0, 1.0)]))
        assert forest.size == len(held) and sorted(map(tuple, forest.points().collect())) == sorted(held), step
        near, count = [], []
        for q, x, y in queries:
            best = sorted(((p[1] - x) ** 2 + (p[2] - y) ** 2, p[0]) for p in held)[:4]
            near += [(q, r + 1, i, d) for r, (d, i) in enumerate(best)]
            count.append((q, sum(x - 6 <= p[1] <= x + 6 and y - 6 <= p[2] <= y + 6 for p in held)))
        assert sorted(map(tuple, forest.knn(asked, 4).collect())) == near, step
        assert sorted(map(tuple, forest.range_count(boxes).collect())) == count, step
        assert forest.range_report(boxes).count() == sum(n for _, n in count), step


@pytest.mark.parametrize("name", ["knn10_e3", "range_count_o2", "delete_bag_copies_l2d", "insert_10pct_o2", "window_steps_events", "as_of_join_events"])
def test_catalog_against_duckdb(spark, name):
    from axisgrove import catalog

    con = duckdb.connect()
    for t in ("orders", "lineitem", "events"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    got = catalog.QUERIES[name](spark, SF).toPandas()
    expected = con.execute(catalog.ORACLE[name]).df()
    cols = sorted(got.columns)
    assert cols == sorted(expected.columns)
    key = lambda df: sorted(repr(tuple("null" if pd.isna(v) else v if isinstance(v, str) else float(v) for v in r)) for r in df[cols].astype(object).itertuples(index=False))
    assert key(got) == key(expected)


WHOLE = {f"build_{v}_knn5_e3_1pct": ("e3", 5) for v in ("levels1", "exact1", "cycle", "eager", "boxes")}
WHOLE |= {"knn100_e3_1pct": ("e3", 100), "knn10_l9_1pct": ("l9", 10), "brute_knn10_o2_1pct": ("o2", 10), "snapshot_reload_knn_o2_1pct": ("o2", 5), "insert_10pct_knn_1pct": ("e3", 10), "window_year_knn_o2_1pct": ("o2", 10)}
WHOLE |= {f"{b}_insert_knn10_e3_1pct": ("e3", 10) for b in ("fullrebuild", "logforest", "sequential")}
WHOLE |= dict.fromkeys(("as_of_join_events_all", "as_of_join_by_user_all", "json_coordinate_events_all"))


def test_every_due_row_is_asked(spark):
    """The forms that ask all due rows: the same rows as SQL, and an answer for every row with id % 100 = 0 (or every event)."""
    from axisgrove import catalog
    from axisgrove.sources.tables import point_sql

    con = duckdb.connect()
    for t in ("orders", "lineitem", "events", "part"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    for name, what in WHOLE.items():
        got = catalog.QUERIES[name](spark, SF)
        rows = list(map(tuple, got.collect()))
        expected = con.execute(f"SELECT {', '.join(got.columns)} FROM ({catalog.ORACLE[name]})").fetchall()
        assert sorted(map(repr, rows)) == sorted(map(repr, expected)), name
        if what is None:
            assert len(rows) == con.execute("SELECT count(*) FROM events").fetchone()[0], name
        else:
            due = con.execute(f"SELECT point_id FROM ({point_sql(what[0])}) WHERE point_id % 100 = 0").fetchall()
            at = got.columns.index("query_id")
            assert sorted(r[at] for r in rows) == sorted(q for (q,) in due for _ in range(what[1])), name


@pytest.mark.parametrize(("query", "rival"), [("fullrebuild_range_report_e3", "FullRebuildTree"), ("logforest_range_report_e3", "LogForest"), ("logforest_tree_sizes", "LogForest"), ("window5_year_sizes_o2_fullrebuild", "FullRebuildTree"), ("window5_year_sizes_o2_logforest", "LogForest")])
def test_rivals_of_the_catalog_store_boxes(spark, monkeypatch, query, rival):
    from axisgrove import catalog

    class Asked(Exception):
        pass

    class Recorder:
        def __init__(self, points, params, **more):
            raise Asked(params)

        build = classmethod(lambda cls, points, params: cls(points, params))

    monkeypatch.setattr(catalog, rival, Recorder)
    with pytest.raises(Asked) as found:
        catalog.QUERIES[query](spark, "/root/testdata/sf0.01")
    assert found.value.args[0].store_boxes


def test_rivals_of_the_workloads_store_boxes(spark, cloud):
    from axisgrove import workloads

    for name in ("full rebuild", "log-method forest"):
        made = workloads.DESIGNS[name](cloud)
        trees = list(made.trees.values()) if name == "log-method forest" else [made.tree]
        assert made.params.store_boxes and all(t.params.store_boxes for t in trees)


def test_real_data_workload_covers_the_survey(spark, monkeypatch):
    from axisgrove import workloads

    monkeypatch.setattr(workloads, "DESIGNS", {"weight-balanced": workloads.DESIGNS["weight-balanced"]})
    monkeypatch.setattr(workloads, "timed", lambda run, runs=1: float(run() is None))
    rows = list(workloads.w8(spark, SF))
    sets = {"R1 v10", "R2 l2d", "R2 v7", "R3 v16", "R4 l3", "R5 l5", "R5 e3", "R6 o2"}
    assert {(r["parameter"], r["operation"]) for r in rows} == {(s, o) for s in sets for o in ("build", "1-nn of all points", "10-nn of all points", "range report")}


def test_shards_are_asked_for_by_runs(spark):
    """Shards next to each other are named by their ends, so no plan holds a literal for each; the same shards are found."""
    from axisgrove.plans.storage import among

    rng = np.random.default_rng(5)
    for some in ([], [4], [-3, -2, 7], list(range(40)), [*range(10, 30), 50, 52, *range(60, 75)], rng.choice(400, 150, replace=False).tolist()):
        found = spark.range(-5, 400).filter(among("id", some))
        assert sorted(r[0] for r in found.collect()) == sorted(some)
    pts = spark.range(6000).selectExpr("id AS point_id", "CAST(id AS DOUBLE) AS c0", "CAST(id * 7 % 6000 AS DOUBLE) AS c1")
    tree = KdTree.build(pts, TreeParams(shard_rows=64))
    assert len(tree.segments.held) > 60
    read = tree.segments.read(set(tree.segments.held))
    assert read.select("shard_id").distinct().count() == len(tree.segments.held)
    assert len(read._jdf.queryExecution().optimizedPlan().toJSON().split("catalyst.expressions.Literal")) < 10
