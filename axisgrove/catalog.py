"""All queries of the engine, each with its DuckDB twin where SQL can say the same."""

from __future__ import annotations

import math
import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from axisgrove import comparison
from axisgrove.baselines import FullRebuildTree, LogForest, SequentialTree, ZOrderTree, brute_count, brute_knn, brute_range
from axisgrove.baselines.full_rebuild import exact_root_median
from axisgrove.functions.geometry import box_union, dist2, nearest
from axisgrove.model import TreeParams, axes, plain
from axisgrove.operators import inspection, joins, queries
from axisgrove.operators.local import Skeleton
from axisgrove.operators.sieve import sieve, sieve_offsets, with_bucket
from axisgrove.operators.tree import KdTree, draw_sample
from axisgrove.plans.snapshot import compacted, load, payload, save
from axisgrove.plans.sql_surface import register
from axisgrove.plans.storage import cut, shared_folder
from axisgrove.sources.tables import LINE_ID, as_queries, boxes_around, dimensions, point_sql, points, read_batch, table, uniform_points, walk_points, write_report
from axisgrove.streaming.window import StreamingTree, run_window, sessions, shard_counts, sliding, tumbling

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}

#: Points of a shard in the queries: small enough that the tables given make several shards.
PARAMS = TreeParams(shard_rows=4096)
#: Half-widths of the boxes around every 500th point.
HALF = {"o1": [20000], "o2": [40000, 200], "l2": [5, 8000], "l3": [5, 0.02, 0.02], "l5": [12, 0.03, 0.03, 25000, 600], "l9": [20, 0.05, 0.05, 40000, 1200, 200000, 1200, 500, 25], "e2": [2e5, 20], "e3": [4e5, 30, 40], "c2": [1500, 5], "p2": [6, 120], "v5": [0.1] * 5, "l2d": [0.01, 0.01]}
#: All rows that a k-NN search is due for (Q-NN-in of FIXTURES.md); the searches whose own SQL asks fewer have a second form with it, named ..._1pct.
PERCENT = "point_id % 100 = 0"
_trees: dict = {}


def tree_of(spark: SparkSession, sf_dir: str, name: str, params: TreeParams = PARAMS, where: str = "true") -> KdTree:
    """A tree over a point set; kept, so that the queries of one session build it once."""
    key = (spark.sparkContext.applicationId, sf_dir, name, params, where)
    if key not in _trees:
        _trees[key] = KdTree.build(points(spark, sf_dir, name).filter(where), params)
    return _trees[key]


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLE[name] = sql
        return f

    return add


# --- pieces of SQL ------------------------------------------------------------------


def d2_sql(d: int, a: str = "p", b: str = "q") -> str:
    return " + ".join(f"({b}.c{i} - {a}.c{i}) * ({b}.c{i} - {a}.c{i})" for i in range(d))


def knn_sql(pts: str, asked: str, d: int, k: int, extra: str = "true") -> str:
    return f"""WITH p AS ({pts}), q AS ({asked}), x AS (SELECT q.query_id, p.point_id, {d2_sql(d)} AS dist2 FROM q CROSS JOIN p),
    r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist2, point_id) AS rank FROM x WHERE {extra})
    SELECT query_id, rank::INT AS rank, point_id, dist2 FROM r WHERE rank <= {k}"""


def asked_sql(name: str, where: str) -> str:
    d = dimensions(name)
    return f"SELECT point_id AS query_id, {', '.join(axes(d))} FROM ({point_sql(name)}) WHERE {where}"


def box_sql(name: str, where: str = "point_id % 500 = 7") -> str:
    h = HALF[name]
    return f"SELECT point_id AS query_id, {', '.join(f'c{i} - {float(x)!r}::DOUBLE AS lo{i}, c{i} + {float(x)!r}::DOUBLE AS hi{i}' for i, x in enumerate(h))} FROM ({point_sql(name)}) WHERE {where}"


def inside_sql(d: int) -> str:
    return " AND ".join(f"p.c{i} >= b.lo{i} AND p.c{i} <= b.hi{i}" for i in range(d))


def count_sql(pts: str, boxes: str, d: int) -> str:
    return f"WITH p AS ({pts}), b AS ({boxes}) SELECT b.query_id, count(p.point_id) AS cnt FROM b LEFT JOIN p ON {inside_sql(d)} GROUP BY b.query_id"


def report_sql(pts: str, boxes: str, d: int) -> str:
    return f"WITH p AS ({pts}), b AS ({boxes}) SELECT b.query_id, p.point_id, {', '.join(f'p.c{i}' for i in range(d))} FROM b JOIN p ON {inside_sql(d)}"


def boxes_of(spark, sf_dir, name, where="point_id % 500 = 7") -> DataFrame:
    return boxes_around(points(spark, sf_dir, name).filter(where), HALF[name])


# --- construction -------------------------------------------------------------------


def _construction() -> None:
    for name in ("o2", "e3", "l3", "v10"):
        def roundtrip(spark, sf_dir, name=name):
            return tree_of(spark, sf_dir, name).points().drop("shard_id")

        query(f"build_points_roundtrip_{name}", point_sql(name))(roundtrip)
    for label, params in {"levels1": PARAMS.but(levels=1), "exact1": plain(shard_rows=4096), "cycle": PARAMS.but(split_rule="cycle"), "eager": PARAMS.but(movement="eager"), "boxes": PARAMS.but(store_boxes=True)}.items():
        for suffix, where in (("", "point_id % 500 = 7"), ("_1pct", PERCENT)):
            def variant(spark, sf_dir, params=params, where=where):
                return tree_of(spark, sf_dir, "e3", params).knn(as_queries(points(spark, sf_dir, "e3").filter(where)), 5)

            query(f"build_{label}_knn5_e3{suffix}", knn_sql(point_sql("e3"), asked_sql("e3", where), 3, 5))(variant)

    @query("build_size_audit", f"SELECT count(*) AS points, count(*) AS leaf_points FROM ({point_sql('e3')})")
    def build_size_audit(spark, sf_dir):
        nodes = tree_of(spark, sf_dir, "e3").nodes().filter("shard_id >= 0")
        return nodes.agg(F.sum(F.when(F.col("number") == 0, F.col("size"))).alias("points"), F.sum(F.when(F.col("kind") != "interior", F.col("size"))).alias("leaf_points"))

    @query("build_leaf_cap", "SELECT 0::BIGINT AS too_large, 0::BIGINT AS wrong_sums")
    def build_leaf_cap(spark, sf_dir):
        nodes = tree_of(spark, sf_dir, "l3").nodes()
        return nodes.agg(F.count_if((F.col("kind") == "leaf") & (F.col("size") > 32)).alias("too_large"), F.count_if((F.col("kind") == "interior") & (F.col("size") != F.col("left_size") + F.col("right_size"))).alias("wrong_sums"))

    @query("build_balance_violations", "SELECT 0::BIGINT AS violations")
    def build_balance_violations(spark, sf_dir):
        return inspection.balance_report(tree_of(spark, sf_dir, "o2")).agg(F.count_if(~F.col("balanced")).alias("violations"))

    @query("build_balance_violations_plain", "SELECT 0::BIGINT AS violations")
    def build_balance_violations_plain(spark, sf_dir):
        return inspection.balance_report(tree_of(spark, sf_dir, "o2", plain(shard_rows=4096)), alpha=0.01).filter("size > 200").agg(F.count_if(~F.col("balanced")).alias("violations"))

    @query("plain_root_split_o2", f"SELECT c0 AS median FROM (SELECT c0, row_number() OVER (ORDER BY c0) AS r, count(*) OVER () AS n FROM ({point_sql('o2')})) WHERE r = n // 2 + 1")
    def plain_root_split_o2(spark, sf_dir):
        return exact_root_median(points(spark, sf_dir, "o2"), "c0")

    @query("one_dim_order_o1", f"SELECT count(*) AS points, 0::BIGINT AS out_of_order FROM ({point_sql('o1')})")
    def one_dim_order_o1(spark, sf_dir):
        tree = tree_of(spark, sf_dir, "o1")
        ends = tree.nodes().filter("shard_id >= 0 AND kind <> 'interior'").select("shard_id", "number", F.col("box_low")[0].alias("a"), F.col("box_high")[0].alias("b"), "size")
        # Within a shard leaf by leaf; between shards, one row each, in the order of the top tier.
        inner = ends.withColumn("before", F.lag("b").over(Window.partitionBy("shard_id").orderBy("number")))
        inner = inner.groupBy("shard_id").agg(F.sum("size").alias("n"), F.count_if(F.col("a") < F.col("before")).alias("wrong"), F.min("a").alias("a"), F.max("b").alias("b"))
        place = spark.createDataFrame([(s, i) for i, s in enumerate(s for e in tree.top.ends() for s in tree.top.shards[e])], "shard_id bigint, place bigint")
        outer = inner.join(place, "shard_id").withColumn("before", F.lag("b").over(Window.orderBy("place")))
        return outer.agg(F.sum("n").alias("points"), (F.sum("wrong") + F.count_if(F.col("a") < F.col("before"))).alias("out_of_order"))

    @query("heavy_leaf_l2d", f"SELECT c0, c1, count(*) AS multiplicity FROM ({point_sql('l2d')}) GROUP BY c0, c1")
    def heavy_leaf_l2d(spark, sf_dir):
        leaves = tree_of(spark, sf_dir, "l2d").nodes().filter("shard_id >= 0 AND kind <> 'interior'")
        return leaves.groupBy(F.col("box_low")[0].alias("c0"), F.col("box_low")[1].alias("c1")).agg(F.sum("size").alias("multiplicity"))

    @query("dup_multiplicity_l3", f"SELECT c0, c1, c2, count(*) AS multiplicity FROM ({point_sql('l3')}) GROUP BY c0, c1, c2 HAVING count(*) > 1")
    def dup_multiplicity_l3(spark, sf_dir):
        return tree_of(spark, sf_dir, "l3").points().groupBy("c0", "c1", "c2").agg(F.count("*").alias("multiplicity")).filter("multiplicity > 1")

    @query("node_box_tight_e3", f"SELECT min(c0) AS lo0, max(c0) AS hi0, min(c1) AS lo1, max(c1) AS hi1, min(c2) AS lo2, max(c2) AS hi2, count(*) AS size FROM ({point_sql('e3')})")
    def node_box_tight_e3(spark, sf_dir):
        roots = tree_of(spark, sf_dir, "e3").nodes().filter("shard_id >= 0 AND number = 0")
        return roots.agg(*[f(F.col(c)[i]).alias(f"{n}{i}") for i in range(3) for n, c, f in (("lo", "box_low", F.min), ("hi", "box_high", F.max))], F.sum("size").alias("size"))

    fixed = [(1, 30.0), (0, 1e6), (2, 50.0)]
    bucket = "CASE WHEN c1 < 30 THEN CASE WHEN c0 < 1e6 THEN 0 ELSE 1 END ELSE CASE WHEN c2 < 50 THEN 2 ELSE 3 END END"
    query("bucket_lookup_fixed", f"SELECT point_id, ({bucket})::BIGINT AS bucket FROM ({point_sql('e3')})")(lambda spark, sf_dir: with_bucket(points(spark, sf_dir, "e3"), Skeleton.from_splits(fixed), "arrow").select("point_id", "bucket"))
    query("bucket_lookup_native", f"SELECT point_id, ({bucket})::BIGINT AS bucket FROM ({point_sql('e3')})")(lambda spark, sf_dir: with_bucket(points(spark, sf_dir, "e3"), Skeleton.from_splits(fixed)).select("point_id", "bucket"))
    query("sieve_counts_fixed", f"SELECT ({bucket})::BIGINT AS bucket, count(*) AS n FROM ({point_sql('e3')}) GROUP BY 1")(lambda spark, sf_dir: sieve(points(spark, sf_dir, "e3"), Skeleton.from_splits(fixed)).counts)
    offsets = f"""WITH h AS (SELECT point_id % 16 AS chunk, ({bucket})::BIGINT AS bucket FROM ({point_sql('e3')})), c AS (SELECT chunk, bucket, count(*) AS n FROM h GROUP BY ALL),
    g AS (SELECT k.chunk, b.bucket, coalesce(c.n, 0)::BIGINT AS n FROM (SELECT DISTINCT chunk FROM c) k CROSS JOIN (SELECT unnest(range(4)) AS bucket) b LEFT JOIN c ON c.chunk = k.chunk AND c.bucket = b.bucket)
    SELECT chunk, bucket, n, coalesce(sum(n) OVER (ORDER BY bucket, chunk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start FROM g"""
    query("sieve_offsets_fixed", offsets)(lambda spark, sf_dir: sieve_offsets(points(spark, sf_dir, "e3"), Skeleton.from_splits(fixed), F.col("point_id") % 16))
    for how in ("count", "sort"):
        def sieved(spark, sf_dir, how=how):
            moved = sieve(points(spark, sf_dir, "e3"), Skeleton.from_splits(fixed), 4, how).points.withColumn("at", F.spark_partition_id())
            return moved.groupBy("bucket").agg(F.count("*").alias("n"), F.countDistinct("at").alias("partitions"))

        query(f"sieve_{how}_contiguous", f"SELECT ({bucket})::BIGINT AS bucket, count(*) AS n, 1::BIGINT AS partitions FROM ({point_sql('e3')}) GROUP BY 1")(sieved)
    query("sample_hash_e3", "SELECT 256::BIGINT AS drawn, 256::BIGINT AS different")(lambda spark, sf_dir: draw_sample(points(spark, sf_dir, "e3"), 256).agg(F.count("*").alias("drawn"), F.countDistinct("point_id").alias("different")))
    query("sample_replace_e3")(lambda spark, sf_dir: draw_sample(points(spark, sf_dir, "e3"), 256, how="replace"))
    query("generator_uniform", "SELECT 5000::BIGINT AS n")(lambda spark, sf_dir: KdTree.build(uniform_points(spark, 5000, 3), PARAMS).points().agg(F.count("*").alias("n")))
    query("generator_walk", "SELECT 5000::BIGINT AS n")(lambda spark, sf_dir: KdTree.build(walk_points(spark, 5000, 2), PARAMS).points().agg(F.count("*").alias("n")))


# --- queries ------------------------------------------------------------------------


def _searches() -> None:
    for name, k, where in (("e3", 1, "point_id % 100 = 0"), ("e3", 10, "point_id % 100 = 0"), ("e3", 100, "point_id % 500 = 0"), ("o2", 10, "point_id % 100 = 0"), ("v16", 10, "point_id % 20 = 0"), ("v64", 10, "point_id % 50 = 0"), ("v12", 10, "point_id % 50 = 0"), ("l9", 10, "point_id % 600 = 0"), ("c2", 10, "point_id % 50 = 0"), ("k2", 3, "point_id % 10 = 0"), ("e3", 100, PERCENT), ("l9", 10, PERCENT)):
        def near(spark, sf_dir, name=name, k=k, where=where):
            return tree_of(spark, sf_dir, name).knn(as_queries(points(spark, sf_dir, name).filter(where)), k)

        known = f"knn{k}_{name}" in QUERIES
        query(f"knn{k}_{name}{'_1pct' if known else ''}", knn_sql(point_sql(name), asked_sql(name, where), dimensions(name), k))(near)
    query("knn_first_percent_e3", knn_sql(point_sql("e3"), f"SELECT point_id AS query_id, c0, c1, c2 FROM (SELECT *, row_number() OVER (ORDER BY point_id) AS r, count(*) OVER () AS n FROM ({point_sql('e3')})) WHERE r * 100 <= n", 3, 10))(lambda spark, sf_dir: tree_of(spark, sf_dir, "e3").knn(as_queries(points(spark, sf_dir, "e3").join(points(spark, sf_dir, "e3").agg(F.percentile("point_id", 0.0101).alias("m")), F.col("point_id") < F.col("m")).drop("m")).orderBy("query_id").limit(points(spark, sf_dir, "e3").count() // 100), 10))
    query("knn_self_p2", knn_sql(point_sql("p2"), asked_sql("p2", "true"), 2, 5))(lambda spark, sf_dir: tree_of(spark, sf_dir, "p2", PARAMS.but(shard_rows=512)).knn_self(5))
    query("knn_self_others_s", f"""WITH p AS ({point_sql('s')}), x AS (SELECT q.point_id AS query_id, p.point_id, {d2_sql(1)} AS dist2 FROM p q CROSS JOIN p WHERE p.point_id <> q.point_id),
    r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist2, point_id) AS rank FROM x) SELECT query_id, rank::INT AS rank, point_id, dist2 FROM r WHERE rank <= 2""")(lambda spark, sf_dir: tree_of(spark, sf_dir, "s").knn_self(2, exclude_self=True))
    query("knn_ood_d2_g2", knn_sql(point_sql("d2"), asked_sql("g2", "true"), 2, 10))(lambda spark, sf_dir: tree_of(spark, sf_dir, "d2", PARAMS.but(shard_rows=256)).knn(as_queries(points(spark, sf_dir, "g2")), 10))
    grid = "SELECT (i * 10 + j)::BIGINT AS query_id, i * 50000.0::DOUBLE AS c0, j * 300.0::DOUBLE AS c1 FROM range(10) a(i) CROSS JOIN range(10) b(j)"
    query("knn_ood_grid_o2", knn_sql(point_sql("o2"), grid, 2, 10))(lambda spark, sf_dir: tree_of(spark, sf_dir, "o2").knn(spark.range(100).selectExpr("id AS query_id", "CAST(id DIV 10 AS DOUBLE) * 50000.0D AS c0", "CAST(id % 10 AS DOUBLE) * 300.0D AS c1"), 10))
    query("knn_k_gt_n_s", knn_sql(point_sql("s"), asked_sql("s", "point_id % 10 = 0"), 1, 5000))(lambda spark, sf_dir: tree_of(spark, sf_dir, "s").knn(as_queries(points(spark, sf_dir, "s").filter("point_id % 10 = 0")), 5000))
    query("knn_radius_capped", knn_sql(point_sql("o2"), asked_sql("o2", "point_id % 100 = 0"), 2, 10, "dist2 <= 250000.0::DOUBLE"))(lambda spark, sf_dir: tree_of(spark, sf_dir, "o2").knn(as_queries(points(spark, sf_dir, "o2").filter("point_id % 100 = 0")), 10, 500.0))
    for suffix, where in (("", "point_id % 500 = 0"), ("_1pct", PERCENT)):
        query(f"brute_knn10_o2{suffix}", knn_sql(point_sql("o2"), asked_sql("o2", where), 2, 10))(lambda spark, sf_dir, where=where: brute_knn(points(spark, sf_dir, "o2"), as_queries(points(spark, sf_dir, "o2").filter(where)), 10))
    for name in ("o2", "l3", "v5", "e3"):
        where = "point_id % 50 = 7" if name == "v5" else "point_id % 500 = 7"
        def report(spark, sf_dir, name=name, where=where):
            return tree_of(spark, sf_dir, name).range_report(boxes_of(spark, sf_dir, name, where))

        query(f"range_report_{name}", report_sql(point_sql(name), box_sql(name, where), dimensions(name)))(report)
    for name in ("o1", "o2", "l2", "l3", "l5", "l9", "e3", "c2", "p2", "l2d"):
        def counted(spark, sf_dir, name=name):
            return tree_of(spark, sf_dir, name).range_count(boxes_of(spark, sf_dir, name))

        query(f"range_count_{name}", count_sql(point_sql(name), box_sql(name), dimensions(name)))(counted)

    def counted_boxes(spark, sf_dir):
        return tree_of(spark, sf_dir, "e3", PARAMS.but(store_boxes=True)).range_count(boxes_of(spark, sf_dir, "e3"))

    query("range_count_stored_boxes_e3", count_sql(point_sql("e3"), box_sql("e3"), 3))(counted_boxes)
    for label, (lo, hi) in {"empty": ((5.0, 5.0), (4.0, 9.0)), "open": ((None, None), (None, 1000.0)), "point": ((-math.inf, 0.0), (math.inf, 0.0))}.items():
        as_sql = lambda x, inf: f"'{inf}'::DOUBLE" if x is None or math.isinf(x) else f"{x!r}::DOUBLE"
        box = "SELECT 1::BIGINT AS query_id, " + ", ".join(f"{as_sql(a, '-inf')} AS lo{i}, {as_sql(b, 'inf')} AS hi{i}" for i, (a, b) in enumerate(zip(lo, hi, strict=True)))

        def edge(spark, sf_dir, lo=lo, hi=hi):
            return tree_of(spark, sf_dir, "o2").range_count(spark.createDataFrame([(1, lo[0], hi[0], lo[1], hi[1])], "query_id bigint, lo0 double, hi0 double, lo1 double, hi1 double"))

        query(f"range_count_{label}_box", count_sql(point_sql("o2"), box, 2))(edge)
    query("brute_count_o2", count_sql(point_sql("o2"), box_sql("o2"), 2))(lambda spark, sf_dir: brute_count(points(spark, sf_dir, "o2"), boxes_of(spark, sf_dir, "o2")))
    query("brute_range_o2", report_sql(point_sql("o2"), box_sql("o2"), 2))(lambda spark, sf_dir: brute_range(points(spark, sf_dir, "o2"), boxes_of(spark, sf_dir, "o2")))
    query("zorder_range_count_o2", count_sql(point_sql("o2"), box_sql("o2"), 2))(lambda spark, sf_dir: ZOrderTree(points(spark, sf_dir, "o2")).range_count(boxes_of(spark, sf_dir, "o2")))

    @query("range_rollup_nation", f"""WITH p AS ({point_sql('c2')}), b AS ({box_sql('c2', 'point_id % 100 = 7')}), h AS (SELECT p.point_id FROM b JOIN p ON {inside_sql(2)})
    SELECT r_name, n_name, count(*) AS hits FROM h JOIN customer ON c_custkey = point_id JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)""")
    def range_rollup_nation(spark, sf_dir):
        hits = tree_of(spark, sf_dir, "c2").range_report(boxes_of(spark, sf_dir, "c2", "point_id % 100 = 7"))
        rows = payload(hits.select("point_id"), table(spark, sf_dir, "customer"), "c_custkey")
        dims = table(spark, sf_dir, "nation").join(F.broadcast(table(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
        return rows.join(F.broadcast(dims), F.col("c_nationkey") == F.col("n_nationkey")).rollup("r_name", "n_name").agg(F.count("*").alias("hits"))

    @query("subtree_points_o2", f"SELECT count(*) AS n FROM ({point_sql('o2')})")
    def subtree_points_o2(spark, sf_dir):
        tree = tree_of(spark, sf_dir, "o2")
        top = tree.top
        children = [top.left[0], top.right[0]] if top.left[0] >= 0 else [0]
        parts = [tree.subtree_points(c).agg(F.count("*").alias("n")) for c in children]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out.agg(F.sum("n").alias("n"))


# --- updates ------------------------------------------------------------------------


def _updates() -> None:
    for f in (1, 10, 100, 1000):
        label = {1: "001pct", 10: "01pct", 100: "1pct", 1000: "10pct"}[f]

        def inserted(spark, sf_dir, f=f):
            base = tree_of(spark, sf_dir, "o2", PARAMS, f"pmod(point_id, 10000) >= {f}")
            return base.insert(points(spark, sf_dir, "o2").filter(f"pmod(point_id, 10000) < {f}")).points().drop("shard_id")

        def deleted(spark, sf_dir, f=f):
            gone = points(spark, sf_dir, "o2").filter(f"pmod(point_id, 10000) < {f}")
            return tree_of(spark, sf_dir, "o2").delete(gone).points().drop("shard_id")

        query(f"insert_{label}_o2", point_sql("o2"))(inserted)
        query(f"delete_{label}_o2", f"SELECT * FROM ({point_sql('o2')}) WHERE point_id % 10000 >= {f}")(deleted)

    @query("insert_empty", f"SELECT count(*) AS n FROM ({point_sql('o2')})")
    def insert_empty(spark, sf_dir):
        return tree_of(spark, sf_dir, "o2").insert(points(spark, sf_dir, "o2").filter("false")).points().agg(F.count("*").alias("n"))

    for suffix, where in (("", "point_id % 200 = 0"), ("_1pct", PERCENT)):
        def insert_10pct_knn(spark, sf_dir, where=where):
            base = tree_of(spark, sf_dir, "e3", PARAMS, "point_id % 10 <> 3")
            return base.insert(points(spark, sf_dir, "e3").filter("point_id % 10 = 3")).knn(as_queries(points(spark, sf_dir, "e3").filter(where)), 10)

        query(f"insert_10pct_knn{suffix}", knn_sql(point_sql("e3"), asked_sql("e3", where), 3, 10))(insert_10pct_knn)

    @query("insert_larger_than_tree", f"SELECT count(*) AS n, sum(point_id)::BIGINT AS ids FROM ({point_sql('o2')})")
    def insert_larger_than_tree(spark, sf_dir):
        base = tree_of(spark, sf_dir, "o2", PARAMS, "point_id % 10 = 0")
        return base.insert(points(spark, sf_dir, "o2").filter("point_id % 10 <> 0")).points().agg(F.count("*").alias("n"), F.sum("point_id").alias("ids"))

    @query("insert_on_conflict_ignore", f"SELECT count(*) AS n FROM ({point_sql('o2')})")
    def insert_on_conflict_ignore(spark, sf_dir):
        base = tree_of(spark, sf_dir, "o2", PARAMS, "point_id % 10 <> 0")
        return base.insert(points(spark, sf_dir, "o2").filter("point_id % 5 = 0"), on_conflict="ignore").points().agg(F.count("*").alias("n"))

    @query("insert_balance_kept", "SELECT 0::BIGINT AS violations")
    def insert_balance_kept(spark, sf_dir):
        base = tree_of(spark, sf_dir, "e2", PARAMS, "c0 < 1296000")
        return inspection.balance_report(base.insert(points(spark, sf_dir, "e2").filter("c0 >= 1296000"))).agg(F.count_if(~F.col("balanced")).alias("violations"))

    @query("delete_absent_report", f"SELECT point_id + 1000000000 AS point_id, c0, c1 FROM ({point_sql('o2')}) WHERE point_id % 50 = 0")
    def delete_absent_report(spark, sf_dir):
        real = points(spark, sf_dir, "o2")
        asked = real.filter("point_id % 40 = 0").unionByName(real.filter("point_id % 50 = 0").withColumn("point_id", F.col("point_id") + 1000000000))
        return tree_of(spark, sf_dir, "o2").delete(asked).report.absent

    @query("delete_all", "SELECT 0::BIGINT AS n, 0::BIGINT AS size")
    def delete_all(spark, sf_dir):
        tree = tree_of(spark, sf_dir, "p2").delete(points(spark, sf_dir, "p2"))
        return tree.points().agg(F.count("*").alias("n"), F.lit(tree.size).cast("bigint").alias("size"))

    bag = point_sql("l2d")
    wanted = "SELECT c0, c1, 3 AS copies FROM p WHERE c0 = 0.05 AND c1 = 0.03 GROUP BY c0, c1"

    @query("delete_bag_copies_l2d", f"WITH p AS ({bag}), w AS ({wanted}), n AS (SELECT p.*, row_number() OVER (PARTITION BY p.c0, p.c1 ORDER BY point_id) AS r FROM p) SELECT n.point_id, n.c0, n.c1 FROM n LEFT JOIN w ON n.c0 = w.c0 AND n.c1 = w.c1 WHERE w.copies IS NULL OR r > copies")
    def delete_bag_copies_l2d(spark, sf_dir):
        three = spark.range(3).selectExpr("id AS point_id", "0.05D AS c0", "0.03D AS c1")
        return tree_of(spark, sf_dir, "l2d", PARAMS.but(shard_rows=1 << 14)).delete(three, match="coords").points().drop("shard_id")

    @query("delete_every_copy_l2d", f"SELECT * FROM ({bag}) WHERE NOT (c0 = 0.05 AND c1 = 0.03)")
    def delete_every_copy_l2d(spark, sf_dir):
        one = spark.range(1).selectExpr("id AS point_id", "0.05D AS c0", "0.03D AS c1")
        return tree_of(spark, sf_dir, "l2d", PARAMS.but(shard_rows=1 << 14)).delete(one, match="coords", copies="all").points().drop("shard_id")

    @query("insert_then_delete_identity", point_sql("p2"))
    def insert_then_delete_identity(spark, sf_dir):
        more = points(spark, sf_dir, "p2").filter("point_id % 3 = 0").withColumn("point_id", F.col("point_id") + 1000000)
        return tree_of(spark, sf_dir, "p2").insert(more).delete(more).points().drop("shard_id")

    @query("incremental_range_count_e3", count_sql(point_sql("e3"), box_sql("e3"), 3))
    def incremental_range_count_e3(spark, sf_dir):
        batches = [points(spark, sf_dir, "e3").filter(f"point_id % 5 = {i}") for i in range(5)]
        return KdTree.build_incremental(batches, PARAMS).range_count(boxes_of(spark, sf_dir, "e3"))

    for suffix, where in (("", "point_id % 500 = 0"), ("_1pct", PERCENT)):
        def snapshot_reload_knn_o2(spark, sf_dir, suffix=suffix, where=where):
            path = f"{shared_folder(spark)}/manifest-{abs(hash(sf_dir))}{suffix}"
            save(compacted(tree_of(spark, sf_dir, "o2")), path, 3)
            return load(spark, path)[0].knn(as_queries(points(spark, sf_dir, "o2").filter(where)), 5)

        query(f"snapshot_reload_knn_o2{suffix}", knn_sql(point_sql("o2"), asked_sql("o2", where), 2, 5))(snapshot_reload_knn_o2)


def _yearly(spark, sf_dir):
    # The second coordinate is the day, so its year needs no second reading.
    rows = points(spark, sf_dir, "o2").withColumn("year", F.year(F.date_add(F.lit("1995-01-01").cast("date"), F.col("c1").cast("int"))))
    return [(y, rows.filter(F.col("year") == y).drop("year")) for y in range(1995, 2002)]


def _windows() -> None:
    in_window = "SELECT o_orderkey, year(o_orderdate) AS y FROM orders"
    for label, make in {"": lambda p: KdTree.build(p, PARAMS), "_fullrebuild": lambda p: FullRebuildTree.build(p, plain(shard_rows=4096, store_boxes=True)), "_logforest": lambda p: LogForest.build(p, plain(shard_rows=4096, store_boxes=True)), "_sequential": SequentialTree.build}.items():
        for width in (5, 3) if not label else (5,):
            def sizes(spark, sf_dir, make=make, width=width):
                seen = []
                run_window(_yearly(spark, sf_dir), width, lambda y, t: seen.append((y, t.size)), make)
                return spark.createDataFrame(seen, "year int, size bigint")

            query(f"window{width}_year_sizes_o2{label}", f"WITH o AS ({in_window}) SELECT s.y::INT AS year, count(*) AS size FROM (SELECT unnest(range(1995, 2002)) AS y) s JOIN o ON o.y <= s.y AND o.y > s.y - {width} GROUP BY s.y")(sizes)

    for suffix, where in (("", "point_id % 200 = 0"), ("_1pct", PERCENT)):
        def last_knn(spark, sf_dir, where=where):
            tree = run_window(_yearly(spark, sf_dir), 5, lambda y, t: None, lambda p: KdTree.build(p, PARAMS))
            return tree.knn(as_queries(points(spark, sf_dir, "o2").filter(where)), 10)

        query(f"window_year_knn_o2{suffix}", knn_sql(f"SELECT p.* FROM ({point_sql('o2')}) p JOIN orders ON o_orderkey = point_id WHERE year(o_orderdate) > 1996", asked_sql("o2", where), 2, 10))(last_knn)


# --- baselines ----------------------------------------------------------------------


def _baselines() -> None:
    base, batch = "pmod(point_id, 10) <> 3", "pmod(point_id, 10) = 3"
    makers = {"fullrebuild": lambda p: FullRebuildTree.build(p, plain(shard_rows=4096, store_boxes=True)), "logforest": lambda p: LogForest.build(p, plain(shard_rows=4096, store_boxes=True)), "sequential": SequentialTree.build}
    kept: dict = {}
    for label, make in makers.items():
        def held(spark, sf_dir, label=label, make=make):
            key = (spark.sparkContext.applicationId, sf_dir, label)
            if key not in kept:
                kept[key] = make(points(spark, sf_dir, "e3").filter(base))
            return kept[key]

        def near(spark, sf_dir, held=held, where="point_id % 200 = 0"):
            return held(spark, sf_dir).insert(points(spark, sf_dir, "e3").filter(batch)).knn(as_queries(points(spark, sf_dir, "e3").filter(where)), 10)

        def left(spark, sf_dir, held=held):
            return held(spark, sf_dir).delete(points(spark, sf_dir, "e3").filter("pmod(point_id, 10) < 2")).points()

        def counts(spark, sf_dir, held=held):
            return held(spark, sf_dir).delete(points(spark, sf_dir, "e3").filter("pmod(point_id, 10) < 2")).range_count(boxes_of(spark, sf_dir, "e3"))

        def reports(spark, sf_dir, held=held):
            return held(spark, sf_dir).range_report(boxes_of(spark, sf_dir, "e3"))

        some = f"SELECT * FROM ({point_sql('e3')}) WHERE point_id % 10 <> 3"
        fewer = f"SELECT * FROM ({some}) WHERE point_id % 10 >= 2"
        query(f"{label}_insert_knn10_e3", knn_sql(point_sql("e3"), asked_sql("e3", "point_id % 200 = 0"), 3, 10))(near)
        query(f"{label}_insert_knn10_e3_1pct", knn_sql(point_sql("e3"), asked_sql("e3", PERCENT), 3, 10))(lambda spark, sf_dir, near=near: near(spark, sf_dir, where=PERCENT))
        query(f"{label}_after_delete_e3", fewer)(left)
        query(f"{label}_delete_range_count_e3", count_sql(fewer, box_sql("e3"), 3))(counts)
        query(f"{label}_range_report_e3", report_sql(some, box_sql("e3"), 3))(reports)

    @query("logforest_tree_sizes", "WITH n AS (SELECT count(*) // 512 AS b, count(*) % 512 AS rest FROM events), s AS (SELECT i AS slot, 512 * (1 << i) AS size FROM n, range(40) t(i) WHERE (b >> i) & 1 = 1 UNION ALL SELECT -1, rest FROM n WHERE rest > 0) SELECT slot::INT AS slot, size::BIGINT AS size FROM s")
    def logforest_tree_sizes(spark, sf_dir):
        forest = LogForest(points(spark, sf_dir, "e3").filter("point_id % 2 = 0"), plain(shard_rows=4096, store_boxes=True), base=512, mode="exact")
        sizes = forest.insert(points(spark, sf_dir, "e3").filter("point_id % 2 <> 0")).tree_sizes()
        return spark.createDataFrame(list(sizes.items()), "slot int, size bigint")


# --- all designs side by side ---------------------------------------------------------


def _comparison() -> None:
    labels = list(comparison.designs(PARAMS.shard_rows))
    listed = f"(SELECT unnest([{', '.join(repr(x) for x in labels)}]) AS design)"
    for name in ("o2", "e3", "l5", "l9", "l2d"):
        d = dimensions(name)
        left = f"SELECT * FROM ({point_sql(name)}) WHERE point_id % 100 <> 5"

        def together(ask, spark, sf_dir, name=name):
            return comparison.side_by_side(points(spark, sf_dir, name), ask, PARAMS.shard_rows)

        query(f"designs_range_count_{name}", f"SELECT design, query_id, cnt FROM {listed}, ({count_sql(left, box_sql(name), d)})")(lambda spark, sf_dir, name=name, together=together: together(lambda tree, pts: tree.range_count(boxes_around(pts.filter("point_id % 500 = 7"), HALF[name])), spark, sf_dir))
        query(f"designs_knn10_{name}", f"SELECT design, query_id, rank, point_id, dist2 FROM {listed}, ({knn_sql(left, asked_sql(name, PERCENT), d, 10)})")(lambda spark, sf_dir, together=together: together(lambda tree, pts: tree.knn(as_queries(pts.filter(PERCENT)), 10), spark, sf_dir))

    @query("design_ratios_e3")
    def design_ratios(spark, sf_dir):
        """Seconds of every design and operation, and their ratios to the weight-balanced tree."""
        pts = points(spark, sf_dir, "e3")
        rows = comparison.ratios(comparison.measured(pts, as_queries(pts.filter(PERCENT)), boxes_of(spark, sf_dir, "e3"), PARAMS.shard_rows))
        return spark.createDataFrame([(r["design"], r["operation"], r["seconds"], r["ratio"]) for r in rows], "design string, operation string, seconds double, ratio double")

    query("balance_study")(lambda spark, sf_dir: comparison.balance_study(table(spark, sf_dir, "events")))

    @query("balance_study_order", "SELECT unnest(['in time', 'shuffled', 'tenth first']) AS stream, true AS work_falls, true AS height_rises")
    def balance_study_order(spark, sf_dir):
        """Whether from the least to the greatest slack rebuilt points become fewer and the tree not lower, by stream."""
        found = comparison.balance_study(table(spark, sf_dir, "events"), slacks=(0.01, 0.1, 0.5), batches=60)
        at = lambda c, a: F.max(F.when(F.col("slack") == a, F.col(c)))
        falls = (at("rebuild_ratio", 0.01) > at("rebuild_ratio", 0.1)) & (at("rebuild_ratio", 0.1) > at("rebuild_ratio", 0.5))
        return found.groupBy("stream").agg(falls.alias("work_falls"), (at("height", 0.01) <= at("height", 0.5)).alias("height_rises"))


# --- measures (no SQL twin: they count what the engine does) -------------------------


def _measures() -> None:
    @query("ablation_rounds")
    def ablation_rounds(spark, sf_dir):
        """Rounds and rows moved for several levels a round, one level from samples, and one level at medians."""
        rows = []
        for label, params in {"several levels, sampled": PARAMS.but(shard_rows=512), "one level, sampled": PARAMS.but(shard_rows=512, levels=1, movement="eager"), "one level, medians": plain(shard_rows=512, movement="eager")}.items():
            r = KdTree.build(points(spark, sf_dir, "e3"), params).report
            rows.append((label, r.rounds, r.scanned, r.moved))
        return spark.createDataFrame(rows, "strategy string, rounds int, scanned bigint, moved bigint")

    @query("stats_visits_bb_vs_plain")
    def stats_visits(spark, sf_dir):
        out = None
        for label, params in {"plain": PARAMS, "boxes": PARAMS.but(store_boxes=True)}.items():
            seen = queries.visit_counts(tree_of(spark, sf_dir, "e3", params), boxes_of(spark, sf_dir, "e3")).withColumn("variant", F.lit(label))
            out = seen if out is None else out.unionByName(seen)
        return out

    @query("alpha_sweep_rebuild")
    def alpha_sweep_rebuild(spark, sf_dir):
        """Rebuilt points over size, height and mean visits of 1-NN, by slack, for points that come in order
        of time (type 1) or a tenth at random first (type 2)."""
        rows = []
        pts = points(spark, sf_dir, "e3")
        for kind in (1, 2):
            part = F.when(F.pmod(F.xxhash64("point_id"), F.lit(10)) == 0, 0).otherwise(1 + F.floor(F.col("c0") / (30 * 86400 / 5))) if kind == 2 else 1 + F.floor(F.col("c0") / (30 * 86400 / 5))
            dealt = cut(pts.withColumn("part", part.cast("int")))
            for alpha in (0.03, 0.1, 0.3, 0.5):
                tree, rebuilt = None, 0
                for b in range(6):
                    batch = dealt.filter(F.col("part") == b).drop("part")
                    if batch.isEmpty():
                        continue
                    tree = KdTree.build(batch, PARAMS.but(alpha=alpha)) if tree is None else tree.insert(batch)
                    rebuilt += tree.report.rebuilt
                probe = as_queries(pts.filter("point_id % 500 = 0"))
                seen = queries.visit_counts(tree, probe, 1).agg(F.avg(F.col("leaves") + F.col("interiors"))).head()[0]
                rows.append((kind, alpha, rebuilt / tree.size, tree.height(), float(seen)))
        return spark.createDataFrame(rows, "stream_type int, alpha double, rebuild_ratio double, height int, visits double")

    query("balance_report")(lambda spark, sf_dir: inspection.balance_report(tree_of(spark, sf_dir, "e3")))
    query("split_error_e3")(lambda spark, sf_dir: inspection.split_error(tree_of(spark, sf_dir, "e3")))
    query("tree_stats")(lambda spark, sf_dir: spark.createDataFrame([(n, *inspection.stats(tree_of(spark, sf_dir, n)).values()) for n in ("o2", "e3", "l3")], "name string, size bigint, height int, nodes bigint, shards int, bytes bigint"))
    query("leaf_occupancy_cube")(lambda spark, sf_dir: tree_of(spark, sf_dir, "l3").nodes().filter("shard_id >= 0").cube("kind", "depth").agg(F.count("*").alias("nodes"), F.sum("size").alias("points")))


# --- operators around the methods -----------------------------------------------------


def _operators() -> None:
    @query("range_join_boxes", report_sql(point_sql("p2"), box_sql("p2", "point_id % 100 = 7"), 2))
    def range_join_boxes(spark, sf_dir):
        return joins.range_join(boxes_of(spark, sf_dir, "p2", "point_id % 100 = 7"), points(spark, sf_dir, "p2"), PARAMS)

    @query("radius_join_p2", f"WITH p AS ({point_sql('p2')}), q AS (SELECT * FROM p WHERE point_id % 50 = 0), x AS (SELECT q.point_id AS query_id, p.point_id, {d2_sql(2)} AS dist2 FROM q CROSS JOIN p) SELECT * FROM x WHERE dist2 <= 400.0")
    def radius_join_p2(spark, sf_dir):
        pts = points(spark, sf_dir, "p2")
        return joins.radius_join(pts.filter("point_id % 50 = 0"), pts, 20.0, PARAMS)

    @query("knn_join_c2_s", knn_sql(point_sql("c1"), asked_sql("s", "true"), 1, 3))
    def knn_join_c2_s(spark, sf_dir):
        return joins.knn_join(points(spark, sf_dir, "s"), points(spark, sf_dir, "c1"), 3, PARAMS)

    @query("knn_lateral_s", f"SELECT query_id, point_id, dist2 FROM ({knn_sql(point_sql('s'), asked_sql('s', 'point_id % 5 = 0'), 1, 2)})")
    def knn_lateral_s(spark, sf_dir):
        pts = points(spark, sf_dir, "s")
        return joins.knn_lateral(pts.filter("point_id % 5 = 0"), pts, 2)

    @query("closest_pair_s", f"WITH p AS ({point_sql('s')}) SELECT q.point_id AS a, p.point_id AS b, {d2_sql(1)} AS dist2 FROM p q JOIN p ON q.point_id < p.point_id ORDER BY dist2, a, b LIMIT 1")
    def closest_pair_s(spark, sf_dir):
        return joins.closest_pair(points(spark, sf_dir, "s"), PARAMS)

    as_of = "SELECT q.event_id, (SELECT max_by(e.event_id, (e.ts, e.event_id)) FROM events e WHERE e.event_type = 'purchase' AND e.ts <= q.ts{by}) AS right_id FROM events q WHERE q.event_id % 20 = 0"
    every = as_of.removesuffix(" WHERE q.event_id % 20 = 0")

    def as_of_all(spark, sf_dir, where="event_id % 20 = 0"):
        ev = table(spark, sf_dir, "events")
        right = ev.filter("event_type = 'purchase'").select(F.col("ts").alias("rts"), F.col("event_id").alias("right_id"))
        return joins.as_of_join(ev.filter(where).select("event_id", "ts"), right, "ts", "rts").select("event_id", "right_id")

    query("as_of_join_events", as_of.format(by=""))(as_of_all)
    query("as_of_join_events_all", every.format(by=""))(lambda spark, sf_dir: as_of_all(spark, sf_dir, "true"))

    def as_of_user(spark, sf_dir, where="event_id % 20 = 0"):
        ev = table(spark, sf_dir, "events")
        right = ev.filter("event_type = 'purchase'").select("user_id", F.col("ts").alias("rts"), F.col("event_id").alias("right_id"))
        return joins.as_of_join(ev.filter(where).select("event_id", "ts", "user_id"), right, "ts", "rts", ["user_id"]).select("event_id", "right_id")

    query("as_of_join_by_user", as_of.format(by=" AND e.user_id = q.user_id"))(as_of_user)
    query("as_of_join_by_user_all", every.format(by=" AND e.user_id = q.user_id"))(lambda spark, sf_dir: as_of_user(spark, sf_dir, "true"))

    @query("labelled_documents_semi_anti", "SELECT d.source, count(*) FILTER (l.doc_id IS NOT NULL) AS labelled, count(*) FILTER (l.doc_id IS NULL) AS unlabelled FROM documents d LEFT JOIN labels l USING (doc_id) GROUP BY d.source")
    def labelled_documents(spark, sf_dir):
        docs, labels = table(spark, sf_dir, "documents").select("doc_id", "source"), table(spark, sf_dir, "labels").select("doc_id")
        some = docs.join(labels, "doc_id", "left_semi").select("source", F.lit(1).alias("l"), F.lit(0).alias("u"))
        rest = docs.join(labels, "doc_id", "left_anti").select("source", F.lit(0).alias("l"), F.lit(1).alias("u"))
        return some.unionByName(rest).groupBy("source").agg(F.sum("l").alias("labelled"), F.sum("u").alias("unlabelled"))

    @query("set_operations_l2d", f"WITH p AS (SELECT c0, c1 FROM ({point_sql('l2d')})), a AS (SELECT * FROM p WHERE c0 <= 0.06), b AS (SELECT * FROM p WHERE c0 >= 0.04) SELECT 'distinct' AS op, count(*) AS n FROM (SELECT DISTINCT * FROM p) UNION ALL SELECT 'except', count(*) FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b) UNION ALL SELECT 'intersect', count(*) FROM (SELECT * FROM a INTERSECT ALL SELECT * FROM b) UNION ALL SELECT 'union', count(*) FROM (SELECT * FROM a UNION ALL SELECT * FROM b)")
    def set_operations(spark, sf_dir):
        p = points(spark, sf_dir, "l2d").select("c0", "c1")
        a, b = p.filter("c0 <= 0.06"), p.filter("c0 >= 0.04")
        parts = {"distinct": p.distinct(), "except": a.exceptAll(b), "intersect": a.intersectAll(b), "union": a.unionByName(b)}
        out = None
        for name, df in parts.items():
            row = df.agg(F.count("*").alias("n")).select(F.lit(name).alias("op"), "n")
            out = row if out is None else out.unionByName(row)
        return out

    @query("point_set_statistics_e2", f"SELECT count(*) AS n, count(DISTINCT c1) AS values, min(c1) AS low, max(c1) AS high, round(stddev_samp(c1), 6) AS spread, max_by(point_id, (c1, point_id)) AS largest, min_by(point_id, (c1, point_id)) AS smallest, bit_xor(point_id) AS checksum FROM ({point_sql('e2')})")
    def point_set_statistics(spark, sf_dir):
        pts = points(spark, sf_dir, "e2")
        key = F.struct("c1", "point_id")
        return pts.agg(F.count("*").alias("n"), F.countDistinct("c1").alias("values"), F.min("c1").alias("low"), F.max("c1").alias("high"), F.round(F.stddev_samp("c1"), 6).alias("spread"), F.max_by("point_id", key).alias("largest"), F.min_by("point_id", key).alias("smallest"), F.bit_xor("point_id").alias("checksum"))

    @query("grouping_sets_nation", "SELECT c_mktsegment, c_nationkey, count(*) AS n, grouping(c_mktsegment)::INT AS g1, grouping(c_nationkey)::INT AS g2 FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())")
    def grouping_sets_nation(spark, sf_dir):
        return spark.sql("SELECT c_mktsegment, c_nationkey, count(*) AS n, CAST(grouping(c_mktsegment) AS INT) AS g1, CAST(grouping(c_nationkey) AS INT) AS g2 FROM {c} GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())", c=table(spark, sf_dir, "customer"))

    @query("window_steps_events", "WITH d AS (SELECT date_diff('day', TIMESTAMP '2024-01-01', ts) AS day, count(*) AS n FROM events GROUP BY 1) SELECT day::INT AS day, n, lag(n) OVER (ORDER BY day) AS before, (sum(n) OVER (ORDER BY day RANGE BETWEEN 4 PRECEDING AND CURRENT ROW))::BIGINT AS in_window, rank() OVER (ORDER BY n DESC, day)::INT AS place, ntile(4) OVER (ORDER BY day)::INT AS quarter FROM d")
    def window_steps(spark, sf_dir):
        days = table(spark, sf_dir, "events").groupBy(F.expr("CAST(timestampdiff(DAY, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts) AS INT)").alias("day")).agg(F.count("*").alias("n"))
        by = Window.orderBy("day")
        return days.select("day", "n", F.lag("n").over(by).alias("before"), F.sum("n").over(by.rangeBetween(-4, 0)).alias("in_window"), F.rank().over(Window.orderBy(F.desc("n"), "day")).alias("place"), F.ntile(4).over(by).alias("quarter"))

    as_json = "SELECT event_id AS point_id, CAST(json_extract_string(props, '$.k') AS DOUBLE) AS c0, value AS c1 FROM events"

    @query("json_coordinate_events", f"{as_json} WHERE event_id % 10 = 0")
    def json_coordinate(spark, sf_dir, where="event_id % 10 = 0"):
        ev = table(spark, sf_dir, "events").filter(where)
        return ev.select(F.col("event_id").alias("point_id"), F.get_json_object("props", "$.k").cast("double").alias("c0"), F.col("value").alias("c1"))

    query("json_coordinate_events_all", as_json)(lambda spark, sf_dir: json_coordinate(spark, sf_dir, "true"))

    @query("embedding_arrays", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS norm2, len(embedding)::INT AS d FROM embeddings")
    def embedding_arrays(spark, sf_dir):
        v = table(spark, sf_dir, "embeddings")
        return v.select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")), 4).alias("norm2"), F.size("embedding").alias("d"))

    @query("top_k_orders", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
    def top_k_orders(spark, sf_dir):
        return table(spark, sf_dir, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice")

    @query("line_ids_unique", f"SELECT count(*) AS n, count(DISTINCT {LINE_ID}) AS ids FROM lineitem")
    def line_ids_unique(spark, sf_dir):
        return points(spark, sf_dir, "l2").agg(F.count("*").alias("n"), F.countDistinct("point_id").alias("ids"))

    @query("sql_shards_in_box_e3", f"SELECT count(*) AS n FROM ({point_sql('e3')}) WHERE c0 BETWEEN 100000 AND 900000 AND c1 BETWEEN 10 AND 60 AND c2 BETWEEN 20 AND 90")
    def sql_shards_in_box(spark, sf_dir):
        register(spark, tree_of(spark, sf_dir, "e3"), "kd")
        return spark.sql("SELECT count(*) AS n FROM kd_points JOIN kd_shards_in_box(array(100000D, 10D, 20D), array(900000D, 60D, 90D)) USING (shard_id) WHERE c0 BETWEEN 100000 AND 900000 AND c1 BETWEEN 10 AND 60 AND c2 BETWEEN 20 AND 90")

    @query("nearest_aggregate_s", f"SELECT query_id, rank, point_id, dist2 FROM ({knn_sql(point_sql('s'), asked_sql('s', 'point_id % 5 = 0'), 1, 3)})")
    def nearest_aggregate(spark, sf_dir):
        pts = points(spark, sf_dir, "s")
        asked = pts.filter("point_id % 5 = 0").select(F.col("point_id").alias("query_id"), F.col("c0").alias("q0"))
        far = pts.join(F.broadcast(asked), F.lit(True)).groupBy("query_id").agg(nearest(dist2([F.col("q0")], [F.col("c0")]), F.col("point_id"), 3).alias("near"))
        return far.select("query_id", F.posexplode("near").alias("pos", "n")).select("query_id", (F.col("pos") + 1).alias("rank"), "n.point_id", "n.dist2")

    @query("box_union_aggregate_e3", f"SELECT e.event_type, min(c0) AS lo0, max(c0) AS hi0, min(c1) AS lo1, max(c1) AS hi1 FROM ({point_sql('e3')}) p JOIN events e ON e.event_id = p.point_id GROUP BY e.event_type")
    def box_union_aggregate(spark, sf_dir):
        kinds = table(spark, sf_dir, "events").select("event_id", "event_type")
        rows = points(spark, sf_dir, "e3").join(kinds, F.col("point_id") == F.col("event_id")).groupBy("event_type").agg(box_union([F.col("c0"), F.col("c1")]).alias("b"))
        return rows.select("event_type", F.col("b.low")[0].alias("lo0"), F.col("b.high")[0].alias("hi0"), F.col("b.low")[1].alias("lo1"), F.col("b.high")[1].alias("hi1"))

    for kind in ("csv", "json", "orc", "parquet"):
        def from_files(spark, sf_dir, kind=kind):
            place = f"{shared_folder(spark)}/boxes-{kind}-{uuid.uuid4().hex}"
            write_report(boxes_of(spark, sf_dir, "o2"), place, kind)
            return tree_of(spark, sf_dir, "o2").range_count(read_batch(spark, place, kind, 2, "box", "query_id"))

        query(f"boxes_from_{kind}", count_sql(point_sql("o2"), box_sql("o2"), 2))(from_files)

    @query("batch_size_sweep_e3")
    def batch_size_sweep(spark, sf_dir):
        """Shards written, points moved and points in rebuilt subtrees by size of the inserted batch."""
        rows = []
        base = tree_of(spark, sf_dir, "e3", PARAMS.but(shard_rows=1024), "pmod(point_id, 10000) >= 5000")
        for f in (1, 10, 100, 1000, 5000):
            t = base.insert(points(spark, sf_dir, "e3").filter(f"pmod(point_id, 10000) < {f}"))
            rows.append((f / 10000, t.size - base.size, t.report.shards_written, t.report.shards_kept, t.report.moved, t.report.rebuilt))
        return spark.createDataFrame(rows, "share double, inserted bigint, shards_written int, shards_kept int, moved bigint, rebuilt bigint")

    @query("output_size_sweep_l3")
    def output_size_sweep(spark, sf_dir):
        """Points found and nodes passed by half-width of the box, as a share of each axis."""
        pts = points(spark, sf_dir, "l3").filter("point_id % 2000 = 7")
        out = None
        for share in (0.01, 0.1, 0.4):
            boxes = boxes_around(pts, [50 * share, 0.1 * share, 0.08 * share])
            tree = tree_of(spark, sf_dir, "l3")
            part = tree.range_count(boxes).join(queries.visit_counts(tree, boxes), "query_id").withColumn("share", F.lit(share))
            out = part if out is None else out.unionByName(part)
        return out.groupBy("share").agg(F.avg("cnt").alias("points"), F.avg("leaves").alias("leaves"), F.avg("interiors").alias("interiors"), F.avg("shards_contained").alias("shards_contained"))

    @query("growth_of_work")
    def growth_of_work(spark, sf_dir):
        """Rounds, rows moved and height by number of points."""
        rows = []
        for n in (2000, 8000, 32000):
            t = KdTree.build(uniform_points(spark, n, 3), PARAMS.but(shard_rows=1024))
            rows.append((n, t.report.rounds, t.report.scanned, t.report.moved, t.height(), len(t.segments.held)))
        return spark.createDataFrame(rows, "n int, rounds int, scanned bigint, moved bigint, height int, shards int")

    @query("stream_sessions_by_user", """WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS head FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
    s AS (SELECT user_id, ts, sum(head) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, floor(epoch(min(ts)))::BIGINT AS start, count(*) AS n FROM s GROUP BY user_id, k""")
    def stream_sessions(spark, sf_dir):
        got = streamed(spark, sf_dir, "sessions", lambda s: sessions(s.withColumn("t", F.to_timestamp(F.col("ts").cast("string"))), "t", "6 hours", "1 day", "user_id", F.count("*").alias("n")))
        return got.select("user_id", F.unix_seconds("w.start").alias("start"), "n")

    @query("stream_without_duplicates", "SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM events")
    def stream_without_duplicates(spark, sf_dir):
        twice = lambda s: s.withColumn("t", F.to_timestamp(F.col("ts").cast("string"))).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
        got = streamed(spark, sf_dir, "single", lambda s: twice(s).withWatermark("t", "1 day").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), "append")
        return got.agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("ids"))

    @query("stream_shard_counts", f"SELECT (CASE WHEN c1 < 30 THEN 0 ELSE 1 END)::BIGINT AS shard_id, count(*) AS total FROM ({point_sql('e2')}) GROUP BY 1")
    def stream_shard_counts(spark, sf_dir):
        got = streamed(spark, sf_dir, "counts", lambda s: shard_counts(s.select(F.when(F.col("value") < 30, 0).otherwise(1).cast("bigint").alias("shard_id"))), "update")
        return got.groupBy("shard_id").agg(F.max("total").alias("total"))

    def streamed(spark, sf_dir, name, build, mode="complete"):
        schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
        stream = spark.readStream.schema(schema).option("pathGlobFilter", "events*.parquet").parquet(sf_dir)
        out = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
        # Results go to files, one folder a batch; of complete results the last batch has all.
        write = lambda batch, number: batch.write.parquet(f"{out}/rows/batch={number}")
        q = build(stream).writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{out}/state").trigger(availableNow=True).start()
        q.awaitTermination()
        rows = spark.read.parquet(f"{out}/rows")
        return (rows.filter(F.col("batch") == rows.agg(F.max("batch")).head()[0]) if mode == "complete" else rows).drop("batch")

    day = "epoch(date_trunc('day', ts))::BIGINT"

    @query("stream_tumbling_day", f"SELECT {day} AS start, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1")
    def stream_tumbling(spark, sf_dir):
        got = streamed(spark, sf_dir, "tumbling", lambda s: tumbling(s.withColumn("t", F.to_timestamp(F.col("ts").cast("string"))), "t", "1 day", "1 day", F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")))
        return got.select(F.unix_seconds("w.start").alias("start"), "n", "total")

    @query("stream_sliding_five_days", f"SELECT (s.d + 86400 * k)::BIGINT AS start, count(*) AS n FROM (SELECT {day} AS d FROM events) s, range(-4, 1) t(k) GROUP BY 1")
    def stream_sliding(spark, sf_dir):
        got = streamed(spark, sf_dir, "sliding", lambda s: sliding(s.withColumn("t", F.to_timestamp(F.col("ts").cast("string"))), "t", "5 days", "1 day", "1 day", F.count("*").alias("n")))
        return got.select(F.unix_seconds("w.start").alias("start"), "n")

    @query("window_day_range_e2", f"WITH p AS ({point_sql('e2')}), w AS (SELECT * FROM p WHERE c0 >= 25 * 86400.0), b AS (SELECT 1::BIGINT AS query_id) SELECT b.query_id, count(w.point_id) AS cnt FROM b LEFT JOIN w ON c1 BETWEEN 20 AND 80 GROUP BY b.query_id")
    def window_day_range(spark, sf_dir):
        """A tree fed by a stream with foreachBatch that keeps the last five of the thirty days."""
        schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
        stream = spark.readStream.schema(schema).option("pathGlobFilter", "events*.parquet").parquet(sf_dir)
        seconds = F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts) / CAST(1000000 AS DOUBLE)")
        rows = stream.select(F.col("event_id").alias("point_id"), seconds.alias("c0"), F.col("value").alias("c1"), F.floor(seconds / 86400).cast("int").alias("day"))
        held = StreamingTree(5, PARAMS)
        held.start(rows, f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}").awaitTermination()
        box = spark.createDataFrame([(1, None, None, 20.0, 80.0)], "query_id bigint, lo0 double, hi0 double, lo1 double, hi1 double")
        return held.tree.range_count(box)


for _part in (_construction, _searches, _updates, _windows, _baselines, _comparison, _measures, _operators):
    _part()
