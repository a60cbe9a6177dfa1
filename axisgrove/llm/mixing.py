"""Mixing sources to target weights by Pareto order sampling.

Every source gets a target amount of words. A document's expected number of copies is
its source's target over its source's size (times its relative importance, where given);
the whole part of that number is taken for certain, and the fraction left is an inclusion
probability p. Documents are ranked by (u / (1 - u)) / (p / (1 - p)) with u a fixed
pseudo-random number of the document, and the smallest ranks are taken until the words
that the source still lacks are reached.

No source is ever sorted as a whole: ranks fall into log-spaced cells, words are summed by
(source, cell), a running sum over the cells of a source finds the cell in which its
target is reached, and only the documents of that one cell are ordered.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from axisgrove.llm.common import cut, keeping, set_aside, table

#: Weights of the sources in order of their names, repeating.
WEIGHTS = (5, 2, 1)
#: Share of all words that the mix takes, and most copies of a source.
SHARE, MOST = 1.5, 2
#: Cells of rank for each doubling: a cell holds under a thousandth of a source.
CELLS_PER_DOUBLING = 1024


@keeping
def with_sizes(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id", "source")) -> DataFrame:
    """``keep`` and ``size``: the number of words between ASCII white space (null or empty: 0), of whole
    texts however long; repeated rows stay; an empty table gives no rows.
    A kept column that has the name of a result comes back with ``_in`` added.
    """
    fields = docs.select(*keep, text)
    schema = ", ".join(f"`{c}` {fields.schema[c].dataType.simpleString()}" for c in keep) + ", size bigint"

    def count(batches):
        for batch in batches:
            words = pc.count_substring_regex(batch.column(text), r"[^\x20\x09-\x0D]+")
            columns = [batch.column(c) for c in keep]
            yield pa.RecordBatch.from_arrays([*columns, pc.fill_null(words, 0).cast(pa.int64())], names=[*keep, "size"])

    return fields.mapInArrow(count, schema)


def word_count(text: Column) -> Column:
    """The number of words between ASCII white space (null or empty: 0), counted by the JVM: no text goes through Python.

    Every word becomes one letter with the white space after it; only white space ahead of the first can be left.
    """
    letters = F.regexp_replace(text, r"[^\x20\x09-\x0D]++[\x20\x09-\x0D]*+", "x")
    return F.coalesce(F.length(F.ltrim(letters, F.lit(" \t\n\v\f\r"))), F.lit(0)).cast("bigint")


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """source, source_size, target: words to take from each source.

    One row a source comes in. Sources in code-point order, null last, have ``weights`` in
    turn. A target is the source's weight times a common level, but at most ``most`` times
    its size; sources that stop there come first in the order of size over weight, so the
    level follows from running sums. The windows run over the sources only.
    """
    listed = Window.orderBy(F.col("source").asc_nulls_last())
    pattern = F.array(*[F.lit(int(w)) for w in weights])
    ranked = sizes.withColumn("weight", F.element_at(pattern, ((F.row_number().over(listed) - 1) % len(weights)) + 1))
    by_cap = Window.orderBy((F.col("source_size") * F.lit(most) / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before = by_cap.rowsBetween(Window.unboundedPreceding, -1)
    after = by_cap.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    everything = Window.partitionBy()
    level = (F.sum("source_size").over(everything) * F.lit(float(share)) - F.coalesce(F.sum(F.col("source_size") * most).over(before), F.lit(0))) / F.sum("weight").over(after)
    ranked = ranked.withColumn("level", level).withColumn("open", F.col("level") * F.col("weight") <= F.col("source_size") * most)
    #: Once a source stays below its cap, so do all that follow, at the level found there.
    found = F.min(F.when(F.col("open"), F.struct(F.col("source_size") * F.lit(most) / F.col("weight"), F.col("level")).alias("x"))).over(everything)
    ranked = ranked.withColumn("found", found)
    cap = (F.col("source_size") * most).cast("double")
    level = F.col("found").getField("level")
    return ranked.select("source", "source_size", F.when(level.isNull(), cap).otherwise(F.least(level * F.col("weight"), cap)).alias("target"))


def uniform(key: Column, seed: str) -> Column:
    """A number in (0, 1) fixed by the key: 52 bits of an MD5 digest, centred."""
    digits = F.substring(F.md5(F.concat(F.lit(seed + ":"), F.coalesce(key.cast("string"), F.lit("null")))), 1, 13)
    return (F.conv(digits, 16, 10).cast("double") + F.lit(0.5)) / F.lit(4503599627370496.0)


_INNER = ("__mass", "__s", "__source", "__expected", "__whole", "__p", "__u", "__rank", "__cell", "__c", "__before", "__edge", "__lacking", "__some", "__all", "__upto")


def pareto_mix(sized: DataFrame, weights=WEIGHTS, share: float = SHARE, most: int = MOST, seed: str = "mix", importance: str | None = None) -> DataFrame:
    """``sized`` (doc_id, source, size and more) plus source_size, target, copies, taken.

    ``importance`` names a column of positive numbers: expected copies are in proportion
    to it within the source (a number above ``most`` is cut to ``most``); without it all
    documents of a source expect the same.

    Nulls: a null source is a source of its own, a null id a key like any other; a document without
    words takes none. Repeated ids get the same random number and are told apart by size,
    so ties are taken in a fixed order. An empty table gives an empty mix. Reruns agree. Columns of ``sized``
    that have the name of a result, or of an inner column (two underscores ahead), come back with ``_in`` added.
    """
    sized = set_aside(sized, ["source_size", "target", "copies", "taken", *_INNER])
    w = F.col(importance).cast("double") if importance else F.lit(1.0)
    totals = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.sum(F.col("size") * w).alias("__mass"))
    goal = targets(totals.select("source", "source_size"), weights, share, most).join(totals.select(F.col("source").alias("__s"), "__mass"), F.col("source").eqNullSafe(F.col("__s"))).drop("__s")
    # One row a source, as a table of known size: it is sent along where it is small; else all documents would be moved to meet it.
    goal = cut(goal)
    docs = sized.join(goal.withColumnRenamed("source", "__source"), F.col("source").eqNullSafe(F.col("__source")), "left").drop("__source")
    rate = F.when(F.col("source_size") > 0, F.col("target") / (F.col("__mass") if importance else F.col("source_size"))).otherwise(F.lit(0.0))
    docs = docs.withColumn("__expected", F.least(rate * w, F.lit(float(most))))
    docs = docs.withColumn("__whole", F.floor("__expected")).withColumn("__p", F.col("__expected") - F.col("__whole"))
    u = uniform(F.col("doc_id"), seed)
    docs = docs.withColumn("__u", u).withColumn("__rank", F.when(F.col("__p") > 0, (F.col("__u") / (1 - F.col("__u"))) / (F.col("__p") / (1 - F.col("__p")))))
    docs = docs.withColumn("__cell", F.floor(F.log2("__rank") * CELLS_PER_DOUBLING))
    cells = cut(docs.groupBy("source", "__cell").agg(F.sum("size").alias("__words"), F.sum(F.col("size") * F.col("__whole")).alias("__sure"), F.max("target").alias("__target")))
    run = Window.partitionBy("source").orderBy(F.col("__cell").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    lacking = (F.col("__target") - F.sum("__sure").over(Window.partitionBy("source"))).alias("__lacking")
    cells = cells.select(F.col("source").alias("__source"), F.col("__cell").alias("__c"), "__words", F.coalesce(F.sum("__words").over(run), F.lit(0)).alias("__before"), lacking)
    # Only a document in the cell where the target is reached must be ordered.
    over = F.col("__c").isNotNull() & (F.col("__before") + F.col("__words") > F.col("__lacking"))
    reached = cut(cells.groupBy("__source").agg(F.min(F.when(over, F.struct("__c", "__before"))).alias("__edge"), F.first("__lacking").alias("__lacking")))
    docs = docs.join(reached, F.col("source").eqNullSafe(F.col("__source")), "left")
    edge_cell = F.col("__edge").getField("__c")
    docs = docs.withColumn("__some", F.coalesce(F.col("__cell") == edge_cell, F.lit(False)))
    docs = docs.withColumn("__all", F.coalesce((F.col("__cell") < edge_cell) | edge_cell.isNull(), F.lit(False)) & F.col("__cell").isNotNull())
    base = [c for c in sized.columns]
    plain = docs.filter(~F.col("__some")).select(*base, "source_size", "target", (F.col("__whole") + F.col("__all").cast("long")).alias("copies"))
    inner = Window.partitionBy("source").orderBy("__rank", "doc_id", "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    edge = docs.filter("__some").withColumn("__upto", F.col("__edge").getField("__before") + F.sum("size").over(inner))
    # A document is taken while that brings the words nearer to the target than leaving it.
    edge = edge.select(*base, "source_size", "target", (F.col("__whole") + (2 * F.col("__upto") - F.col("size") <= 2 * F.col("__lacking")).cast("long")).alias("copies"))
    return plain.unionByName(edge).withColumn("copies", F.col("copies").cast("long")).withColumn("taken", F.col("size") * F.col("copies"))


def op1_pareto_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The mix of all documents at the fixed weights and share."""
    sized = cut(with_sizes(table(spark, sf_dir, "documents")))
    return pareto_mix(sized).select("doc_id", "size", "source_size", "target", "taken")


OP1_SQL = r"""
WITH s AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size FROM documents),
g AS (SELECT source, sum(size)::BIGINT AS source_size FROM s GROUP BY source),
w AS (SELECT *, [5, 2, 1][1 + ((row_number() OVER (ORDER BY source COLLATE C ASC NULLS LAST) - 1) % 3)::INT] AS weight FROM g),
o AS (SELECT *, row_number() OVER (ORDER BY source_size * 2 / weight, source ASC NULLS LAST) AS k FROM w),
l AS (SELECT a.*, ((SELECT sum(source_size) FROM o) * 1.5::DOUBLE
          - coalesce((SELECT sum(b.source_size * 2) FROM o b WHERE b.k < a.k), 0)) / (SELECT sum(b.weight) FROM o b WHERE b.k >= a.k) AS level FROM o a),
f AS (SELECT level FROM l WHERE level * weight <= source_size * 2 ORDER BY k LIMIT 1),
t AS (SELECT source, source_size, CASE WHEN (SELECT count(*) FROM f) = 0 THEN (source_size * 2)::DOUBLE
          ELSE least((SELECT level FROM f) * weight, (source_size * 2)::DOUBLE) END AS target FROM l),
d AS (SELECT s.*, source_size, target, CASE WHEN source_size > 0 THEN least(target / source_size, 2.0::DOUBLE) ELSE 0 END AS e,
          (('0x' || substr(md5('mix:' || coalesce(doc_id::VARCHAR, 'null')), 1, 13))::UBIGINT::DOUBLE + 0.5::DOUBLE) / 4503599627370496.0::DOUBLE AS u
      FROM s JOIN t ON s.source IS NOT DISTINCT FROM t.source),
r AS (SELECT *, floor(e)::BIGINT AS whole, (u / (1 - u)) / nullif((e - floor(e)) / (1 - (e - floor(e))), 0) AS odds FROM d),
c AS (SELECT *, sum(size) OVER (PARTITION BY source ORDER BY odds NULLS LAST, doc_id, size ROWS UNBOUNDED PRECEDING) AS upto,
          target - sum(size * whole) OVER (PARTITION BY source) AS lacking FROM r)
SELECT doc_id, size, source_size, target, (size * (whole + CASE WHEN odds IS NOT NULL AND 2 * upto - size <= 2 * lacking THEN 1 ELSE 0 END))::BIGINT AS taken FROM c
"""
