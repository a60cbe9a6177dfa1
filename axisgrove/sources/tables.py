"""Point sets on the given tables, query sets, update batches and generators.

A point set is one SELECT that gives point_id, c0, c1, ...; the same text serves Spark and
DuckDB but for date arithmetic, which ``{days:x}`` and ``{seconds:x}`` stand for.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from axisgrove.model import axes

_DIALECT = {
    "spark": {"days": "CAST(datediff({x}, DATE'1995-01-01') AS DOUBLE)", "seconds": "timestampdiff(MICROSECOND, TIMESTAMP_NTZ'2024-01-01 00:00:00', {x}) / CAST(1000000 AS DOUBLE)", "item": "CAST({x}[{i}] AS DOUBLE)", "words": "CAST(size(split({x}, ' ')) AS DOUBLE)", "chars": "CAST(length({x}) AS DOUBLE)"},
    "duckdb": {"days": "CAST(date_diff('day', DATE '1995-01-01', {x}::DATE) AS DOUBLE)", "seconds": "date_diff('microsecond', TIMESTAMP '2024-01-01 00:00:00', {x}) / CAST(1000000 AS DOUBLE)", "item": "CAST({x}[{j}] AS DOUBLE)", "words": "CAST(len(string_split({x}, ' ')) AS DOUBLE)", "chars": "CAST(len({x}) AS DOUBLE)"},
}

#: The unique key of lineitem as one number: order, line, part and supplier in fixed fields.
LINE_ID = "((l_orderkey * 8 + l_linenumber) * 1048576 + l_partkey) * 65536 + l_suppkey"

POINT_SETS = {
    "o1": "SELECT o_orderkey AS point_id, o_totalprice AS c0 FROM orders",
    "o2": "SELECT o_orderkey AS point_id, o_totalprice AS c0, {days:o_orderdate} AS c1 FROM orders",
    "l2": f"SELECT {LINE_ID} AS point_id, l_quantity AS c0, l_extendedprice AS c1 FROM lineitem",
    "l2d": f"SELECT {LINE_ID} AS point_id, l_discount AS c0, l_tax AS c1 FROM lineitem",
    "l3": f"SELECT {LINE_ID} AS point_id, l_quantity AS c0, l_discount AS c1, l_tax AS c2 FROM lineitem",
    "l5": f"SELECT {LINE_ID} AS point_id, l_quantity AS c0, l_discount AS c1, l_tax AS c2, l_extendedprice AS c3, {{days:l_shipdate}} AS c4 FROM lineitem",
    "l9": f"SELECT {LINE_ID} AS point_id, l_quantity AS c0, l_discount AS c1, l_tax AS c2, l_extendedprice AS c3, {{days:l_shipdate}} AS c4, o_totalprice AS c5, {{days:o_orderdate}} AS c6, p_retailprice AS c7, CAST(p_size AS DOUBLE) AS c8 FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey",
    "e2": "SELECT event_id AS point_id, {seconds:ts} AS c0, value AS c1 FROM events",
    "e3": "SELECT event_id AS point_id, {seconds:ts} AS c0, value AS c1, CAST(user_id AS DOUBLE) AS c2 FROM events",
    "c1": "SELECT c_custkey AS point_id, c_acctbal AS c0 FROM customer",
    "c2": "SELECT c_custkey AS point_id, c_acctbal AS c0, CAST(c_nationkey AS DOUBLE) AS c1 FROM customer",
    "p2": "SELECT p_partkey AS point_id, CAST(p_size AS DOUBLE) AS c0, p_retailprice AS c1 FROM part",
    "s": "SELECT s_suppkey AS point_id, s_acctbal AS c0 FROM supplier",
    "d2": "SELECT doc_id AS point_id, CAST(n_chars AS DOUBLE) AS c0, {words:text} AS c1 FROM documents",
    "g2": "SELECT page_id AS point_id, {chars:url} AS c0, {chars:html} AS c1 FROM pages",
    "k2": "SELECT conv_id * 1024 + turn AS point_id, CAST(turn AS DOUBLE) AS c0, {chars:text} AS c1 FROM conversations",
}
DIMENSIONS = {"o1": 1, "o2": 2, "l2": 2, "l2d": 2, "l3": 3, "l5": 5, "l9": 9, "e2": 2, "e3": 3, "c1": 1, "c2": 2, "p2": 2, "s": 1, "d2": 2, "g2": 2, "k2": 2}
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def dimensions(name: str) -> int:
    return int(name[1:]) if re.fullmatch(r"v\d+", name) else DIMENSIONS[name]


def point_sql(name: str, dialect: str = "duckdb") -> str:
    """The SELECT of a point set. ``v<D>``: the first D numbers of the embeddings."""
    words = _DIALECT[dialect]
    if re.fullmatch(r"v\d+", name):
        coords = ", ".join(words["item"].format(x="embedding", i=i, j=i + 1) + f" AS c{i}" for i in range(int(name[1:])))
        return f"SELECT vec_id AS point_id, {coords} FROM embeddings"
    return re.sub(r"\{(\w+):(\w+)\}", lambda m: words[m[1]].format(x=m[2]), POINT_SETS[name])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def points(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A point set, read with only the columns it needs."""
    sql = point_sql(name, "spark")
    used = [t for t in TABLES if re.search(rf"\b(?:FROM|JOIN) {t}\b", sql)]
    args = {t: table(spark, sf_dir, t) for t in used}
    return spark.sql(re.sub(r"\b(FROM|JOIN) (\w+)\b", lambda m: f"{m[1]} {{{m[2]}}}", sql), **args)


def as_queries(pts: DataFrame) -> DataFrame:
    return pts.withColumnRenamed("point_id", "query_id")


def boxes_around(pts: DataFrame, half: list[float]) -> DataFrame:
    """Closed boxes of fixed half-widths around points."""
    return pts.select(F.col("point_id").alias("query_id"), *[(F.col(f"c{i}") - F.lit(float(h))).alias(f"lo{i}") for i, h in enumerate(half)], *[(F.col(f"c{i}") + F.lit(float(h))).alias(f"hi{i}") for i, h in enumerate(half)])


def uniform_points(spark: SparkSession, n: int, d: int, seed: int = 1, bits: int = 20) -> DataFrame:
    """Hash-made points, the same for any number of partitions."""
    coords = [F.pmod(F.xxhash64("id", F.lit(j), F.lit(seed)), F.lit(1 << bits)).cast("double").alias(f"c{j}") for j in range(d)]
    return spark.range(n).select(F.col("id").alias("point_id"), *coords)


def walk_points(spark: SparkSession, n: int, d: int, restart: float = 0.001, seed: int = 1, bits: int = 20, step: int = 8) -> DataFrame:
    """Clusters: blocks of 1 / restart ids, each a walk of hashed steps from a hashed origin."""
    block = (F.col("id") * F.lit(restart)).cast("bigint")
    rows = spark.range(n).withColumn("block", block)
    run = Window.partitionBy("block").orderBy("id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    coords = []
    for j in range(d):
        origin = F.pmod(F.xxhash64("block", F.lit(j), F.lit(seed)), F.lit(1 << bits))
        move = F.pmod(F.xxhash64("id", F.lit(j), F.lit(seed + 1)), F.lit(2 * step + 1)) - step
        coords.append((origin + F.sum(move).over(run)).cast("double").alias(f"c{j}"))
    return rows.select(F.col("id").alias("point_id"), *coords)


def read_batch(spark: SparkSession, path: str, kind: str, d: int, prefix: str = "c", key: str = "point_id") -> DataFrame:
    """Points or boxes from CSV, JSON, ORC or Parquet files with a declared schema."""
    names = axes(d) if prefix == "c" else [*axes(d, "lo"), *axes(d, "hi")]
    schema = f"{key} bigint, " + ", ".join(f"{c} double" for c in names)
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if kind == "csv" else reader.format(kind).load(path)


def write_report(df: DataFrame, path: str, kind: str = "json") -> None:
    """A result as CSV, JSON, ORC, Parquet or nowhere ('noop')."""
    if kind == "noop":
        df.write.format("noop").mode("overwrite").save()
    else:
        df.write.mode("overwrite").option("header", True).format(kind).save(path)
