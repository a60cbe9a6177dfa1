"""The experiment workloads with times and counters: python -m axisgrove.workloads [--sf-dir DIR] [--cpus N] NAME...

Each workload gives rows (workload, design, operation, parameter, seconds, and what the
engine counted). Seconds are means of ``RUNS`` runs after one warm-up, results written nowhere.
"""

from __future__ import annotations

import argparse
import json
import math
import subprocess
import sys
import time
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from axisgrove.baselines import FullRebuildTree, LogForest, SequentialTree
from axisgrove.catalog import HALF, PARAMS, boxes_of
from axisgrove.model import plain
from axisgrove.operators import queries
from axisgrove.operators.tree import KdTree
from axisgrove.plans.storage import cut
from axisgrove.sources.tables import as_queries, boxes_around, points, uniform_points, walk_points
from axisgrove.streaming.window import run_window

RUNS = 3
DESIGNS: dict[str, Callable] = {
    "weight-balanced": lambda p: KdTree.build(p, PARAMS),
    "weight-balanced with boxes": lambda p: KdTree.build(p, PARAMS.but(store_boxes=True)),
    "log-method forest": lambda p: LogForest(p, plain(shard_rows=PARAMS.shard_rows, store_boxes=True)),
    "full rebuild": lambda p: FullRebuildTree(p, plain(shard_rows=PARAMS.shard_rows, store_boxes=True)),
    "serial style": SequentialTree,
}


def timed(run: Callable, runs: int = RUNS) -> float:
    run()
    start = time.perf_counter()
    for _ in range(runs):
        run()
    return round((time.perf_counter() - start) / runs, 3)


def spent(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def _row(workload, design, operation, parameter, seconds, **counted) -> dict:
    return {"workload": workload, "design": design, "operation": operation, "parameter": parameter, "seconds": seconds} | counted


def _report(tree) -> dict:
    r = getattr(tree, "report", None)
    return {"rounds": r.rounds, "moved": r.moved, "rebuilt": r.rebuilt, "shards_written": r.shards_written, "shards_kept": r.shards_kept} if r else {}


def _life(workload: str, name: str, pts: DataFrame, shares: tuple[float, ...], k: int, half: list[float], designs=None) -> Iterator[dict]:
    """Build, insert and delete shares of the points, nearest neighbours of 1 %, and boxes."""
    pts = cut(pts)
    asked = as_queries(pts.filter("pmod(point_id, 100) = 0"))
    boxes = boxes_around(pts.filter("pmod(point_id, 500) = 7"), half)
    for label, make in (designs or DESIGNS).items():
        yield _row(workload, label, "build", name, timed(lambda make=make: make(pts)))
        tree = make(pts)
        for f in shares:
            part = cut(pts.filter(f"pmod(point_id, 10000) < {int(f * 10000)}"))
            fresh = cut(part.withColumn("point_id", F.col("point_id") + 10**12))
            yield _row(workload, label, "insert", f"{name} {f:g}", timed(lambda tree=tree, fresh=fresh: tree.insert(fresh)), **_report(tree.insert(fresh)))
            yield _row(workload, label, "delete", f"{name} {f:g}", timed(lambda tree=tree, part=part: tree.delete(part)), **_report(tree.delete(part)))
        yield _row(workload, label, f"{k}-nn", name, timed(lambda tree=tree: spent(tree.knn(asked, k))))
        yield _row(workload, label, "range report", name, timed(lambda tree=tree: spent(tree.range_report(boxes))))
        yield _row(workload, label, "range count", name, timed(lambda tree=tree: spent(tree.range_count(boxes))))


def w1(spark, sf):
    for name in ("o2", "e2"):
        yield from _life("W1", name, points(spark, sf, name), (0.0001, 0.001, 0.01, 0.1), 10, HALF[name])


def w2(spark, sf):
    n = points(spark, sf, "e2").count()
    for d in (2, 3, 5, 9):
        for kind, make in (("uniform", uniform_points), ("walk", walk_points)):
            yield from _life("W2", f"{kind} {d}-D", make(spark, n, d), (0.01,), 10, [2.0**20 * 0.05 ** (1 / d) / 2] * d)


def w3(spark, sf):
    yield from _life("W3", "12-D", points(spark, sf, "v12"), (0.01,), 10, [0.15] * 12)


def w4(spark, sf):
    yield from _life("W4", "e3", points(spark, sf, "e3"), (0.0001, 0.001, 0.01, 0.1, 0.5, 1.0), 10, HALF["e3"], {k: DESIGNS[k] for k in ("weight-balanced", "log-method forest", "full rebuild")})


def w5(spark, sf):
    pts = cut(points(spark, sf, "e3"))
    asked = as_queries(pts.filter("pmod(point_id, 100) = 0"))
    for label, make in DESIGNS.items():
        tree = make(pts)
        for k in (1, 10, 100):
            yield _row("W5", label, "k-nn", k, timed(lambda tree=tree, k=k: spent(tree.knn(asked, k))))


def w6(spark, sf):
    tree, asked = KdTree.build(points(spark, sf, "d2"), PARAMS), as_queries(points(spark, sf, "g2"))
    yield _row("W6", "weight-balanced", "10-nn of other points", "d2, g2", timed(lambda: spent(tree.knn(asked, 10))))


def w7(spark, sf):
    for name in ("l2", "l3"):
        pts = cut(points(spark, sf, name))
        centres = pts.filter("pmod(point_id, 2000) = 7")
        for label, make in DESIGNS.items():
            tree = make(pts)
            for share in (0.001, 0.01, 0.1, 1.0):
                boxes = boxes_around(centres, [h * share * 4 for h in HALF[name]])
                found = boxes.count() and tree.range_count(boxes).agg(F.avg("cnt")).head()[0]
                yield _row("W7", label, "range report", f"{name} {share:g}", timed(lambda tree=tree, boxes=boxes: spent(tree.range_report(boxes))), mean_output=found)
                yield _row("W7", label, "range count", f"{name} {share:g}", timed(lambda tree=tree, boxes=boxes: spent(tree.range_count(boxes))), mean_output=found)


def w8(spark, sf):
    """Real data: build, neighbours of all points, boxes around every 500th point (every 50th of the embeddings)."""
    for paper, name in (("R1", "v10"), ("R2", "l2d"), ("R2", "v7"), ("R3", "v16"), ("R4", "l3"), ("R5", "l5"), ("R5", "e3"), ("R6", "o2")):
        pts = cut(points(spark, sf, name))
        made = name.startswith("v")
        boxes = boxes_around(pts.filter("pmod(point_id, 50) = 7" if made else "pmod(point_id, 500) = 7"), [0.1] * int(name[1:]) if made else HALF[name])
        for label, make in DESIGNS.items():
            yield _row("W8", label, "build", f"{paper} {name}", timed(lambda make=make: make(pts)))
            tree = make(pts)
            for k in (1, 10):
                yield _row("W8", label, f"{k}-nn of all points", f"{paper} {name}", timed(lambda tree=tree, k=k: spent(tree.knn(as_queries(pts), k)), 1))
            yield _row("W8", label, "range report", f"{paper} {name}", timed(lambda tree=tree: spent(tree.range_report(boxes))))


def w9(spark, sf):
    from axisgrove.catalog import _yearly

    years = [(y, cut(b)) for y, b in _yearly(spark, sf)]
    asked = as_queries(points(spark, sf, "o2").filter("pmod(point_id, 200) = 0"))
    for label, make in DESIGNS.items():
        seen: list = []

        def probe(year, tree, seen=seen):
            start = time.perf_counter()
            spent(tree.knn(asked, 10))
            seen.append((year, time.perf_counter() - start, tree.size))

        start = time.perf_counter()
        run_window(years, 5, probe, make)
        total = time.perf_counter() - start - sum(s for _, s, _ in seen)
        for year, seconds, size in seen:
            yield _row("W9", label, "10-nn after the step", year, round(seconds, 3), size=size)
        yield _row("W9", label, "all updates", "1995-2001", round(total, 3))


def w10(spark, sf):
    for n in (10_000, 40_000, 160_000):
        t = KdTree.build(uniform_points(spark, n, 3), PARAMS)
        yield _row("W10", "weight-balanced", "build", n, None, **_report(t), height=t.height())


def w11(spark, sf):
    for name in ("o2", "l3", "e3", "v5"):
        for label in ("weight-balanced", "weight-balanced with boxes"):
            tree = DESIGNS[label](points(spark, sf, name))
            boxes = cut(boxes_of(spark, sf, name, "pmod(point_id, 50) = 7" if name == "v5" else "pmod(point_id, 500) = 7"))
            seen = queries.visit_counts(tree, boxes).agg(F.avg("leaves").alias("leaves"), F.avg("interiors").alias("interiors")).head()
            yield _row("W11", label, "range report", name, timed(lambda tree=tree, boxes=boxes: spent(tree.range_report(boxes))), leaves=seen["leaves"], interiors=seen["interiors"])


def w12(spark, sf):
    for name in ("e3", "l3"):
        pts = cut(points(spark, sf, name))
        for label, params in {"several levels, sampled": PARAMS, "one level, sampled": PARAMS.but(levels=1), "one level, medians": plain(shard_rows=PARAMS.shard_rows)}.items():
            t = KdTree.build(pts, params)
            yield _row("W12", label, "build", name, timed(lambda pts=pts, params=params: KdTree.build(pts, params)), **_report(t))


def _stream(workload, spark, pts, part, alphas, designs=None) -> Iterator[dict]:
    dealt = cut(pts.withColumn("part", part.cast("int")))
    count = dealt.agg(F.max("part")).head()[0] + 1
    batches = [cut(dealt.filter(F.col("part") == b).drop("part")) for b in range(count)]
    probe = cut(as_queries(pts.filter("pmod(point_id, 500) = 0")))
    whole = timed(lambda: KdTree.build(pts, PARAMS), 1)
    for alpha in alphas:
        tree, rebuilt, seconds, slower = None, 0, 0.0, []
        for b in batches:
            start = time.perf_counter()
            tree = KdTree.build(b, PARAMS.but(alpha=alpha)) if tree is None else tree.insert(b)
            seconds += time.perf_counter() - start
            rebuilt += tree.report.rebuilt
            even = KdTree.build(tree.points().drop("shard_id"), plain(shard_rows=PARAMS.shard_rows))
            passed = [queries.visit_counts(t, probe, 1).agg(F.avg(F.col("leaves") + F.col("interiors"))).head()[0] for t in (tree, even)]
            slower.append(passed[0] / passed[1])
        yield _row(workload, "weight-balanced", "incremental", f"alpha {alpha}", round(seconds, 3), rebuild_ratio=rebuilt / tree.size, update_over_build=seconds / whole, height=tree.height(), visits_geometric_mean=math.exp(sum(map(math.log, slower)) / len(slower)), visits_max=max(slower))


def w13(spark, sf, batches: int = 10):
    pts = cut(points(spark, sf, "e3"))
    yield from _stream("W13", spark, pts, F.floor(F.col("c0") / (31 * 86400 / batches)), (0.01, 0.03, 0.1, 0.2, 0.3, 0.4, 0.5))


def w14(spark, sf, batches: int = 10):
    pts = cut(points(spark, sf, "e3"))
    first = F.pmod(F.xxhash64("point_id"), F.lit(10)) == 0
    yield from _stream("W14", spark, pts, F.when(first, 0).otherwise(1 + F.floor(F.col("c0") / (31 * 86400 / (batches - 1)))), (0.01, 0.03, 0.1, 0.2, 0.3, 0.4, 0.5))


def w15(spark, sf):
    pts = points(spark, sf, "e3")
    slack = {f"weight-balanced, slack {a}": (lambda p, a=a: KdTree.build(p, PARAMS.but(alpha=a))) for a in (0.03, 0.1, 0.3)}
    yield from _life("W15", "e3", pts, (0.01, 0.1), 10, HALF["e3"], slack | {k: DESIGNS[k] for k in ("log-method forest", "full rebuild")})


def w16(spark, sf):
    """Self-relative speed-up: the same run in sessions of 1, 2 and 4 threads."""
    base = None
    for cpus in (1, 2, 4):
        made = subprocess.run([sys.executable, "-m", "axisgrove.workloads", "--sf-dir", sf, "--cpus", str(cpus), "SCALE"], capture_output=True, text=True, check=True)
        rows = [json.loads(x) for x in made.stdout.splitlines() if x.startswith("{")]
        base = base or {r["operation"]: r["seconds"] for r in rows}
        for r in rows:
            yield r | {"workload": "W16", "parameter": cpus, "speed_up": round(base[r["operation"]] / r["seconds"], 2)}


def scale(spark, sf):
    yield from (r for r in _life("SCALE", "e3", points(spark, sf, "e3"), (0.01,), 10, HALF["e3"], {"weight-balanced": DESIGNS["weight-balanced"]}))


def w17(spark, sf):
    tree = KdTree.build(points(spark, sf, "o1"), PARAMS)
    yield _row("W17", "weight-balanced", "one dimension: leaves in sorted order", "o1", None, height=tree.height(), **_report(tree))


WORKLOADS = {f.__name__.upper(): f for f in (w1, w2, w3, w4, w5, w6, w7, w8, w9, w10, w11, w12, w13, w14, w15, w16, w17, scale)}


def main() -> None:
    parser = argparse.ArgumentParser()
    parser.add_argument("--sf-dir", default="/root/testdata/sf0.01")
    parser.add_argument("--cpus", default="8")
    parser.add_argument("names", nargs="+", choices=sorted(WORKLOADS))
    args = parser.parse_args()
    spark = SparkSession.builder.master(f"local[{args.cpus}]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in args.names:
        for row in WORKLOADS[name](spark, args.sf_dir):
            print(json.dumps(row), flush=True)


if __name__ == "__main__":
    main()
