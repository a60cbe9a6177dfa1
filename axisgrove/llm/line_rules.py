"""Quality rules with cross-document line frequency. Built-in column functions only.

Lines are normalised (lower case, runs of digits as 0, white space as one space) and
hashed; the distinct documents that hold a line are counted for each host (the source of a
document); a line in more documents than the host's limit is boilerplate and is removed,
and documents of which too little is left are rejected. Exact copies count as one document,
so copying a document does not turn its own lines into boilerplate.

All that depends on (host, text) alone is kept once for each such pair, which is also how
the hosts and texts that hold a large share of all rows are reduced before any shuffle.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from axisgrove.llm.common import cut, keeping, table

SPACE = r"[\x20\x09-\x0D]+"
WINDOW = 8
LEAST_WORDS, MOST_REPEATED = 20, 30
#: A line is boilerplate in more than so many documents of its host, and more than this share of them (in thousandths).
LEAST_DOCUMENTS, SHARE_PER_MILLE = 20, 20
#: A document is depleted with fewer words left than LEAST_WORDS, or than this share (in tenths).
KEPT_TENTHS = 3
#: Boilerplate lines, and texts that hold some, that are sent to every task; longer lists are joined by shuffling.
BROADCAST_LINES, BROADCAST_TEXTS = 200_000, 100_000
#: Hashes of boilerplate lines that such texts may hold together, to be sent: 8 bytes each.
BROADCAST_HASHES = 1_000_000


def let(value: Column, use) -> Column:
    """``use(value)`` with the value computed once."""
    return F.transform(F.array(value), use)[0]


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(text, SPACE), "")


def _repeated(hashes: Column) -> Column:
    """Words covered by windows that stand twice or more; ``hashes`` has one number a window."""

    def covered(places: Column) -> Column:
        start = F.struct(F.lit(0).cast("bigint").alias("n"), F.lit(-1).cast("bigint").alias("end"))
        step = lambda a, p: F.struct((a["n"] + p + WINDOW - F.greatest(p, a["end"])).alias("n"), (p + WINDOW).alias("end"))
        return F.aggregate(F.array_sort(places), start, step)["n"]

    def twins(ranked: Column) -> Column:
        last = F.size(ranked) - 1
        same = lambda e, i, j: ranked[F.greatest(F.lit(0), F.least(j, last))]["h"] == e["h"]
        kept = F.filter(ranked, lambda e, i: ((i > 0) & same(e, i, i - 1)) | ((i < last) & same(e, i, i + 1)))
        return F.transform(kept, lambda e: e["i"])

    ranked = F.array_sort(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.cast("bigint").alias("i"))))
    return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), F.lit(0).cast("bigint")).otherwise(covered(let(ranked, twins)))


def _windows(words: Column) -> Column:
    """A number for every run of WINDOW words."""
    hashed = F.transform(words, lambda w: F.xxhash64(w))
    runs = let(hashed, lambda h: F.transform(F.sequence(F.lit(1), F.size(h) - (WINDOW - 1)), lambda i: F.xxhash64(F.slice(h, i, WINDOW))))
    return F.when(F.size(words) >= WINDOW, runs).otherwise(F.array().cast("array<bigint>"))


def base_rules(docs: DataFrame, keep: list, text: str = "text") -> DataFrame:
    """``keep`` and n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed."""
    whole = F.coalesce(F.col(text), F.lit(""))
    df = docs.select(*keep, whole.alias("__t"), words_of(whole).alias("__w"))
    df = df.withColumn("__h", _windows(F.col("__w")))
    df = df.select(
        *[c for c in df.columns if c not in ("__t", "__w", "__h")],
        F.size("__w").cast("bigint").alias("n_words"),
        F.length(F.array_join("__w", "")).cast("bigint").alias("word_chars"),
        (F.length("__t") - F.length(F.regexp_replace("__t", r"[#*$%&|<>]", ""))).cast("bigint").alias("n_symbols"),
        let(F.filter(F.split(F.col("__t"), "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")), lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("bigint").alias("n_dup_lines"),
        let(F.col("__h"), _repeated).alias("n_repeat_words"),
    )
    return df.withColumn("base_failed", (F.col("n_words") < LEAST_WORDS) | (100 * F.col("n_repeat_words") > MOST_REPEATED * F.col("n_words")))


def normal_line(line: Column) -> Column:
    return F.lower(F.regexp_replace(F.trim(F.regexp_replace(line, SPACE, " ")), "[0-9]+", "0"))


def _identity(text: Column) -> list[Column]:
    whole = F.coalesce(text, F.lit(""))
    return [F.xxhash64(whole).alias("__x"), F.hash(whole, F.octet_length(whole)).alias("__y")]


def boilerplate(docs: DataFrame, text: str = "text", host: str = "source", least: int = LEAST_DOCUMENTS, per_mille: int = SHARE_PER_MILLE) -> DataFrame:
    """For every (host, text) that holds boilerplate: __host, __x, __y (its identity), removed
    (words in such lines) and lines (their hashes)."""
    whole = F.coalesce(F.col(text), F.lit(""))
    filled = F.filter(F.split(whole, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    made = F.transform(filled, lambda x: F.struct(F.xxhash64(normal_line(x)).alias("h"), F.size(words_of(x)).alias("n")))
    # A null host is a host of its own.
    once = cut(docs.select(F.col(host).alias("__host"), *_identity(F.col(text)), made.alias("lines")).dropDuplicates(["__host", "__x", "__y"]))
    hosts = once.groupBy("__host").agg(F.count("*").alias("documents")).withColumnRenamed("__host", "__h")
    held = once.select("__host", F.explode(F.array_distinct(F.transform("lines", lambda x: x["h"]))).alias("line"))
    counts = held.groupBy("__host", "line").agg(F.count("*").alias("n")).filter(F.col("n") > least)
    over = counts.join(hosts, F.col("__host").eqNullSafe(F.col("__h"))).filter(F.col("n") * 1000 > F.col("documents") * per_mille)
    over = cut(over.select(F.col("__host").alias("__bad_host"), F.col("line").alias("__bad")))
    side = F.broadcast(over) if over.count() <= BROADCAST_LINES else over
    each = once.select("__host", "__x", "__y", F.explode("lines").alias("line"))
    hit = each.join(side, F.col("__host").eqNullSafe(F.col("__bad_host")) & (F.col("line.h") == F.col("__bad")))
    return hit.groupBy("__host", "__x", "__y").agg(F.sum("line.n").cast("bigint").alias("removed"), F.collect_set("line.h").alias("lines"))


@keeping
def judged(docs: DataFrame, keep: list[str], text: str = "text", host: str = "source", with_text: bool = False) -> DataFrame:
    """``keep``, the base measures, removed (words in boilerplate lines), kept; with
    ``with_text`` also clean_text, without the boilerplate lines (null stays null).

    A null or empty text has no words and fails the base rules; lines are compared without
    regard to ties or order; repeated rows are judged alike; a text counts whole, however long; an empty table gives no rows.
    A kept column that has the name of a result comes back with ``_in`` added.
    """
    bad = boilerplate(docs, text, host).select(F.col("__host").alias("__bh"), F.col("__x").alias("__bx"), F.col("__y").alias("__by"), "removed", *([F.col("lines").alias("__bad")] if with_text else []))
    bad = cut(bad)
    texts, hashes = bad.agg(F.count("*"), F.sum(F.size("__bad")) if with_text else F.lit(0)).head()
    if texts <= BROADCAST_TEXTS and (hashes or 0) <= BROADCAST_HASHES:
        bad = F.broadcast(bad)
    base = base_rules(docs, [*keep, F.col(host).alias("_host"), *[c.alias(f"_id{i}") for i, c in enumerate(_identity(F.col(text)))], *([F.col(text).alias("_text")] if with_text else [])], text)
    df = base.join(bad, F.col("_host").eqNullSafe(F.col("__bh")) & (F.col("_id0") == F.col("__bx")) & (F.col("_id1") == F.col("__by")), "left")
    df = df.withColumn("removed", F.coalesce("removed", F.lit(0)).cast("bigint"))
    left = F.col("n_words") - F.col("removed")
    df = df.withColumn("kept", ~F.col("base_failed") & (left >= LEAST_WORDS) & (left * 10 >= F.col("n_words") * KEPT_TENTHS))
    measures = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "removed", "kept"]
    if with_text:
        lines = F.filter(F.split(F.col("_text"), "\n"), lambda x: ~F.array_contains("__bad", F.xxhash64(normal_line(x))))
        df = df.withColumn("clean_text", F.when(F.col("__bad").isNull(), F.col("_text")).otherwise(F.array_join(lines, "\n")))
        measures.append("clean_text")
    return df.select(*keep, *measures)


def op7_line_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Base measures and verdict of every document."""
    return judged(table(spark, sf_dir, "documents"), ["doc_id"]).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


OP7_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, source, coalesce(text, '') AS t FROM documents),
w AS (SELECT *, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS ws FROM d),
g AS (SELECT k, unnest(range(1, len(ws) - 6)) AS i, ws FROM w),
r AS (SELECT k, i, count(*) OVER (PARTITION BY k, array_to_string(ws[i : i + 7], ' ')) AS c FROM g),
rep AS (SELECT k, count(DISTINCT p) AS n FROM (SELECT k, unnest(range(i, i + 8)) AS p FROM r WHERE c > 1) GROUP BY k),
l AS (SELECT k, source, t, unnest(string_split(t, chr(10))) AS line FROM d),
lf AS (SELECT *, lower(regexp_replace(trim(regexp_replace(line, '[\x20\x09-\x0D]+', ' ', 'g')), '[0-9]+', '0', 'g')) AS norm,
    len(regexp_extract_all(line, '[^\x20\x09-\x0D]+')) AS n FROM l WHERE regexp_matches(line, '[^\x20\x09-\x0D]')),
dup AS (SELECT k, count(*) - count(DISTINCT line) AS n FROM lf GROUP BY k),
h AS (SELECT source, count(DISTINCT t) AS documents FROM d GROUP BY source),
f AS (SELECT source, norm, count(DISTINCT t) AS c FROM lf GROUP BY source, norm),
o AS (SELECT f.source, norm FROM f JOIN h ON f.source IS NOT DISTINCT FROM h.source WHERE c > 20 AND c * 1000 > documents * 20),
rm AS (SELECT k, sum(n) AS n FROM lf JOIN o ON lf.source IS NOT DISTINCT FROM o.source AND lf.norm = o.norm GROUP BY k),
b AS (SELECT doc_id, len(ws)::BIGINT AS n_words, len(array_to_string(ws, ''))::BIGINT AS word_chars,
    (len(t) - len(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols, coalesce(dup.n, 0)::BIGINT AS n_dup_lines,
    coalesce(rep.n, 0)::BIGINT AS n_repeat_words, coalesce(rm.n, 0) AS removed
  FROM w LEFT JOIN dup USING (k) LEFT JOIN rep USING (k) LEFT JOIN rm USING (k))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
    n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed,
    NOT (n_words < 20 OR 100 * n_repeat_words > 30 * n_words) AND n_words - removed >= 20 AND (n_words - removed) * 10 >= n_words * 3 AS kept
FROM b
"""
