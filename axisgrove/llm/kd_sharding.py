"""Shards of equal bytes as the leaves of a k-d tree over document metadata.

A node is split at the weighted (by bytes) median of the metadata dimension that is widest
in it, relative to the dimension's extent in the whole table, until leaves reach the target
bytes. Medians are exact: all nodes of a level are narrowed down together by histograms of
``BINS`` cells, each one aggregation. The tree (a few numbers a node) is all that comes to
the driver; rows find their leaf by comparisons with literals, without a join or shuffle.

The dimensions given here are functions of the text, so that equal texts meet in one leaf.
Where the rows of one median value weigh more than a share (``tolerance``) of their node, the value
is divided by text checksum. A group of equal texts stays together unless it alone weighs more than
that: then the law (bytes near equal) can't be kept without dividing it, and it is divided by id.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from axisgrove.llm.common import cut, set_aside, table

#: Cells of a histogram in the search for a median.
BINS = 4096
#: Part of a node's bytes that may be misplaced to keep equal values together.
TOLERANCE = 0.004
#: Rows that one task numbers.
ROWS_PER_RUN = 500_000
DIMENSIONS = ("size", "beyond_ascii", "lines", "spaces", "digits")
TIES = ("text_crc32", "doc_id")
MEASURES = ("size", "text_crc32", "beyond_ascii", "lines", "spaces", "digits")


def text_metadata(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",), text: str = "text") -> DataFrame:
    """``keep``, size (UTF-8 bytes plus one), text_crc32, beyond_ascii (bytes past one a character), lines, spaces, digits."""
    whole = F.coalesce(F.col(text), F.lit(""))
    size = F.octet_length(whole).cast("bigint")
    return docs.select(
        *keep,
        (size + 1).alias("size"),
        F.crc32(whole.cast("binary")).alias("text_crc32"),
        (size - F.length(whole)).alias("beyond_ascii"),
        (F.length(whole) - F.length(F.replace(whole, F.lit("\n"), F.lit(""))) + 1).cast("bigint").alias("lines"),
        (F.length(whole) - F.length(F.replace(whole, F.lit(" "), F.lit("")))).cast("bigint").alias("spaces"),
        (F.length(whole) - F.length(F.translate(whole, "0123456789", ""))).cast("bigint").alias("digits"),
    )


@dataclass
class Split:
    """Rows at or before the boundary, in the order of ``columns``, go to the lower child."""

    columns: list[str] = field(default_factory=list)
    values: list[int] = field(default_factory=list)

    def above(self) -> Column:
        out = F.lit(False)
        for name, value in reversed(list(zip(self.columns, self.values, strict=True))):
            x = F.coalesce(F.col(name).cast("bigint"), F.lit(-(2**62)))
            out = (x > value) | ((x == value) & out)
        return out


class KdTree:
    """Splits by heap number (root 1, children 2i and 2i + 1)."""

    def __init__(self, depth: int):
        self.depth, self.splits = depth, {}

    def node(self, level: int, at: int = 1) -> Column:
        """Heap number of a row's node on a level."""
        if level == 0:
            return F.lit(at)
        return F.when(self.splits[at].above(), self.node(level - 1, 2 * at + 1)).otherwise(self.node(level - 1, 2 * at))

    def leaf(self) -> Column:
        return (self.node(self.depth) - F.lit(2**self.depth)).cast("int")


def _by_node(values: dict[int, int | str], kind: str) -> Column:
    """The number of a row's node as a literal look-up."""
    return F.element_at(F.create_map(*[x for k, v in values.items() for x in (F.lit(k), F.lit(v).cast(kind))]), F.col("__node"))


def _boundaries(rows: DataFrame, ranges: dict[int, tuple[Column, int, int, float]], weight: str) -> dict[int, tuple[int, float, float]]:
    """For nodes with (column, least, most, goal): the value at which the running weight
    reaches the goal, the weight before it and its own weight."""
    low = {k: r[1] for k, r in ranges.items()}
    high = {k: r[2] for k, r in ranges.items()}
    before = dict.fromkeys(ranges, 0.0)
    found: dict[int, tuple[int, float, float]] = {}
    names = sorted({r[0] for r in ranges.values()})
    open_ = set(ranges)
    while open_:
        which = {k: ranges[k][0] for k in open_}
        x = F.coalesce(*[F.when(_by_node(which, "string") == n, F.coalesce(F.col(n).cast("bigint"), F.lit(-(2**62)))) for n in names])
        width = {k: max(1, -(-(high[k] - low[k] + 1) // BINS)) for k in open_}
        part = rows.filter(F.col("__node").isin(sorted(open_))).withColumn("__x", x).withColumn("__low", _by_node({k: low[k] for k in open_}, "bigint"))
        part = part.filter((F.col("__x") >= F.col("__low")) & (F.col("__x") <= _by_node({k: high[k] for k in open_}, "bigint")))
        cell = F.expr("(__x - __low) div __width")
        part = part.withColumn("__width", _by_node({k: width[k] for k in open_}, "bigint")).groupBy("__node", cell.alias("cell")).agg(F.sum(weight).alias("w"))
        cells: dict[int, list] = {}
        for r in part.collect():  # at most BINS rows a node
            cells.setdefault(r["__node"], []).append((r["cell"], r["w"]))
        for k in sorted(open_):
            for cell_no, w in sorted(cells.get(k, [])):
                if before[k] + w >= ranges[k][3] or cell_no == max(cells[k])[0]:
                    low[k] += cell_no * width[k]
                    high[k] = min(high[k], low[k] + width[k] - 1)
                    if width[k] == 1:
                        found[k] = (low[k], before[k], w)
                        open_.discard(k)
                    break
                before[k] += w
            else:
                found[k] = (low[k], before[k], 0.0)
                open_.discard(k)
    return found


def grow(rows: DataFrame, depth: int, dimensions=DIMENSIONS, ties=TIES, weight: str = "size", tolerance: float = TOLERANCE) -> KdTree:
    """The tree of ``depth`` levels over rows that hold the dimensions, ties and weight as integers."""
    tree = KdTree(depth)
    wide = None
    value = {c: F.coalesce(F.col(c).cast("bigint"), F.lit(-(2**62))) for c in {*dimensions, *ties}}
    extent = [f(value[c]).alias(f"{n}_{c}") for c in value for n, f in (("lo", F.min), ("hi", F.max))]
    for level in range(depth):
        here = rows.withColumn("__node", tree.node(level))
        stats = {r["__node"]: r for r in here.groupBy("__node").agg(F.sum(weight).alias("w"), *extent).collect()}
        if wide is None:
            wide = {c: max(1, stats[1][f"hi_{c}"] - stats[1][f"lo_{c}"]) if stats else 1 for c in dimensions}
        for k in range(2**level, 2 ** (level + 1)):
            tree.splits[k] = Split()
        goal = {k: s["w"] / 2 for k, s in stats.items()}
        slack = {k: s["w"] * tolerance for k, s in stats.items()}
        widest = {k: max(dimensions, key=lambda c, s=s: ((s[f"hi_{c}"] - s[f"lo_{c}"]) / wide[c], -dimensions.index(c))) for k, s in stats.items()}
        pending = {k: (widest[k], s[f"lo_{widest[k]}"], s[f"hi_{widest[k]}"], goal[k]) for k, s in stats.items()}
        done_before = dict.fromkeys(stats, 0.0)
        for step in range(len(ties) + 1):
            if not pending:
                break
            cond = F.lit(False)
            for k in pending:
                inside = F.col("__node") == k
                for c, v in zip(tree.splits[k].columns, tree.splits[k].values, strict=True):
                    inside = inside & (value[c] == v)
                cond = cond | inside
            found = _boundaries(here.filter(cond) if step else here, pending, weight)
            following = {}
            for k, (v, before, own) in found.items():
                name = pending[k][0]
                lower, upper = done_before[k] + before, done_before[k] + before + own
                rest = [c for c in ties if c not in [*tree.splits[k].columns, name]]
                miss = min(goal[k] - lower, upper - goal[k])
                tree.splits[k].columns.append(name)
                if miss > slack[k] and rest:
                    tree.splits[k].values.append(v)
                    done_before[k] = lower
                    c = rest[0]
                    following[k] = (c, stats[k][f"lo_{c}"], stats[k][f"hi_{c}"], goal[k] - lower)
                else:
                    tree.splits[k].values.append(v if upper - goal[k] <= goal[k] - lower else v - 1)
            pending = following
    return tree


def depth_for(total: int, target_bytes: int) -> int:
    """Levels until leaves reach the target bytes."""
    depth = 0
    while total > target_bytes << depth:
        depth += 1
    return depth


def with_slots(rows: DataFrame, shard: str = "shard", order: tuple[str, ...] = ("doc_id", "text_crc32", "size")) -> DataFrame:
    """Gapless ``slot`` numbers from 0 within each shard, in ``order``.

    Rows are dealt out by range of (shard, order), counted a run, and numbered within runs
    behind the counts of the runs before; no shard meets in one task.
    """
    runs = max(1, -(-rows.count() // ROWS_PER_RUN), int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    dealt = cut(rows.repartitionByRange(runs, shard, *order).withColumn("__run", F.spark_partition_id()))
    ahead = Window.partitionBy(shard).orderBy("__run").rowsBetween(Window.unboundedPreceding, -1)
    counts = dealt.groupBy(shard, "__run").count().select(shard, "__run", F.coalesce(F.sum("count").over(ahead), F.lit(0)).alias("__ahead"))
    within = Window.partitionBy(shard, "__run").orderBy(*order)
    numbered = dealt.withColumn("__n", F.row_number().over(within))
    # One row a run and shard, each standing for up to ROWS_PER_RUN rows.
    numbered = numbered.join(counts, [shard, "__run"])
    return numbered.withColumn("slot", (F.col("__ahead") + F.col("__n") - 1).cast("bigint")).drop("__run", "__ahead", "__n")


def kd_shards(docs: DataFrame, shards: int | None = 16, target_bytes: int | None = None, keep: tuple[str, ...] = ("doc_id",), text: str = "text", tolerance: float = TOLERANCE) -> tuple[DataFrame, KdTree]:
    """Metadata rows with ``shard``, and the tree. Kept columns that have the name of a measure or of
    ``shard`` come back with ``_in`` added; ``doc_id`` must be among them.

    ``shards`` (a power of two) or ``target_bytes`` fixes the depth. A null text has no
    bytes and counts one; null ids come first; equal rows are told apart by nothing and
    stay together; long texts are measured whole; an empty table gives an empty result and a tree of one-sided splits.
    """
    docs = set_aside(docs.select(*keep, F.col(text).alias("__text")), [*MEASURES, "shard"])
    rows = cut(text_metadata(docs, tuple(c for c in docs.columns if c != "__text"), "__text"))
    if target_bytes:
        depth = depth_for(rows.agg(F.sum("size")).head()[0] or 0, target_bytes)
    else:
        depth = (shards or 1).bit_length() - 1
        if 1 << depth != (shards or 1):
            raise ValueError("the number of shards must be a power of two")
    tree = grow(rows, depth, tolerance=tolerance)
    return rows.withColumn("shard", tree.leaf()), tree


def with_shard(docs: DataFrame, tree: KdTree, text: str = "text") -> DataFrame:
    """The documents with ``size`` and ``shard``; every row finds its leaf where it is. Columns that have the name
    of a measure or of ``shard`` come back with ``_in`` added; nulls, ties, repeats and empty tables as in ``kd_shards``.
    """
    docs = set_aside(docs.withColumn("__text", F.col(text)), [*MEASURES, "shard"])
    others = [c for c in docs.columns if c != "__text"]
    return text_metadata(docs, tuple(others), "__text").withColumn("shard", tree.leaf()).select(*[F.col(f"`{c}`") for c in others], "size", "shard")


def write_shards(docs: DataFrame, tree: KdTree, path: str, text: str = "text") -> None:
    """The documents as Parquet, one folder a shard; rows go straight to the shard's files."""
    with_shard(docs, tree, text).drop("size").write.partitionBy("shard").parquet(path)


def op6_kd_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in 16 shards of near equal bytes."""
    rows, _ = kd_shards(table(spark, sf_dir, "documents"), 16)
    numbered = with_slots(rows.select("doc_id", "size", "text_crc32", "shard"))
    return numbered.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
