"""Quotation linking in conversations. Built-in column functions only.

A message's lines carry quote levels (leading ``>`` marks, spaces between them allowed).
Runs of lines of one level are passages; a passage is normalised (lower case, white space
as one space) and hashed. A quoted passage is linked to the earliest message of the same
conversation that says it unquoted, before the quoting message. A message replies to the
latest message that it quotes; replies are followed to the first message of their thread
by doubling, and messages are ordered by thread, then turn, with the quotes taken out.

Only the earliest turn of each (conversation, passage) takes part in the join, so a
passage that is said or quoted very often meets one row. Nothing is gathered by conversation.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from axisgrove.llm.common import cut, set_aside, table

MARK = r"^(?:[ \t]*>)+[ \t]?"
SPACE = r"[\x20\x09-\x0D]+"


def _normal(passage: Column) -> Column:
    return F.trim(F.lower(F.regexp_replace(passage, SPACE, " ")))


def passages(text: Column) -> Column:
    """Runs of lines of one quote level: array of (level, passage). Blank lines end a run."""

    def line(x: Column) -> Column:
        marks = F.regexp_extract(x, MARK, 0)
        rest = F.regexp_replace(x, MARK, "")
        return F.struct(F.length(F.regexp_replace(marks, "[^>]", "")).alias("level"), rest.alias("rest"))

    lines = F.filter(F.transform(F.split(text, r"\r?\n"), line), lambda x: F.lit(True))

    def runs(rows: Column) -> Column:
        blank = lambda r: ~r["rest"].rlike(r"[^\x20\x09-\x0D]")
        first = lambda r, i: ~blank(r) & ((i == 0) | blank(rows[F.greatest(i - 1, F.lit(0))]) | (rows[F.greatest(i - 1, F.lit(0))]["level"] != r["level"]))
        starts = F.filter(F.transform(rows, lambda r, i: F.when(first(r, i), i)), lambda i: i.isNotNull())

        def cut_at(at: Column) -> Column:
            stop = lambda k: F.when(k + 1 < F.size(at), at[k + 1]).otherwise(F.size(rows))
            return F.transform(at, lambda i, k: F.struct(rows[i]["level"].alias("level"), F.array_join(F.transform(F.slice(rows, i + 1, stop(k) - i), lambda r: r["rest"]), "\n").alias("passage")))

        return F.transform(F.array(starts), cut_at)[0]

    return F.transform(F.array(lines), runs)[0]


def unquoted(text: Column) -> Column:
    """The text without its quoted lines, trimmed."""
    kept = F.filter(F.split(text, r"\r?\n"), lambda x: ~x.rlike(MARK))
    return F.regexp_replace(F.array_join(kept, "\n"), r"^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$", "")


def linked(messages: DataFrame, conversation: str = "conv_id", turn: str = "turn", text: str = "text") -> DataFrame:
    """Every message with own_text, n_quoted (quoted passages), n_linked, reply_to (turn),
    thread (first turn of its thread) and depth (replies up to there).

    Null or empty texts quote and say nothing; messages without conversation or turn are
    linked with nothing and are their own thread; messages that share a turn share its
    passages and its reply; repeated rows stay; texts of any length are taken whole; an empty table gives
    no rows. Columns that have the name of a result, or of an inner column
    (two underscores ahead), come back with ``_in`` added.
    """
    messages = set_aside(messages, ["own_text", "n_quoted", "n_linked", "reply_to", "thread", "depth", "__c", "__t", "__to", "__n", "__root", "__depth"])
    whole = F.coalesce(F.col(text), F.lit(""))
    named = messages.select(F.col(conversation).alias("c"), F.col(turn).alias("t"), passages(whole).alias("p")).filter(F.col("c").isNotNull() & F.col("t").isNotNull())
    each = cut(named.select("c", "t", F.explode("p").alias("p")).select("c", "t", (F.col("p.level") > 0).alias("quoted"), F.xxhash64(_normal(F.col("p.passage"))).alias("h"), F.hash(_normal(F.col("p.passage"))).alias("g")))
    said = each.filter(~F.col("quoted")).groupBy("c", "h", "g").agg(F.min("t").alias("first"))
    quotes = each.filter("quoted").groupBy("c", "t", "h", "g").agg(F.count("*").alias("n"))
    found = quotes.join(said, ["c", "h", "g"]).filter(F.col("first") < F.col("t"))
    replies = cut(found.groupBy("c", "t").agg(F.max("first").alias("to"), F.sum("n").cast("bigint").alias("n_linked")))
    # A reply goes to an earlier turn, so threads are trees; each step doubles the way up.
    up = replies.select("c", "t", F.col("to").alias("root"), F.lit(1).cast("bigint").alias("depth"))
    while True:
        above = up.select(F.col("c").alias("c2"), F.col("t").alias("t2"), F.col("root").alias("root2"), F.col("depth").alias("depth2"))
        ahead = up.join(above, (F.col("c") == F.col("c2")) & (F.col("root") == F.col("t2")), "left")
        if ahead.filter(F.col("t2").isNotNull()).isEmpty():
            break
        up = cut(ahead.select("c", "t", F.coalesce("root2", "root").alias("root"), (F.col("depth") + F.coalesce("depth2", F.lit(0))).alias("depth")))
    known = replies.join(up, ["c", "t"]).select(F.col("c").alias("__c"), F.col("t").alias("__t"), F.col("to").alias("__to"), F.col("n_linked").alias("__n"), F.col("root").alias("__root"), F.col("depth").alias("__depth"))
    df = messages.join(known, (F.col(conversation) == F.col("__c")) & (F.col(turn) == F.col("__t")), "left")
    quoted = F.size(F.filter(passages(F.coalesce(F.col(text), F.lit(""))), lambda p: p["level"] > 0)).cast("bigint")
    added = {
        "own_text": unquoted(F.coalesce(F.col(text), F.lit(""))),
        "n_quoted": quoted,
        "n_linked": F.coalesce("__n", F.lit(0)).cast("bigint"),
        "reply_to": F.col("__to"),
        "thread": F.coalesce("__root", F.col(turn)),
        "depth": F.coalesce("__depth", F.lit(0)).cast("bigint"),
    }
    return df.select(*[F.col(f"`{x}`") for x in messages.columns], *[v.alias(k) for k, v in added.items()])


def in_reply_order(found: DataFrame, conversation: str = "conv_id", turn: str = "turn") -> DataFrame:
    """The messages globally sorted into reply-ordered conversations."""
    return found.orderBy(conversation, "thread", turn)


def op3_quotations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All messages without quotes, with their links (reply_to -1: none) and their place in reply order."""
    found = linked(table(spark, sf_dir, "conversations"))
    return found.select("conv_id", "turn", "role", F.col("own_text").alias("text"), "n_quoted", "n_linked", F.coalesce("reply_to", F.lit(-1)).alias("reply_to"), "thread", "depth")


OP3_SQL = r"""
WITH RECURSIVE m AS (SELECT row_number() OVER () AS k, *, regexp_split_to_array(coalesce(text, ''), '\r?\n') AS lines FROM conversations),
l AS (SELECT k, conv_id, turn, unnest(range(1, len(lines) + 1)) AS i, unnest(lines) AS line FROM m),
q AS (SELECT *, len(regexp_replace(regexp_extract(line, '^(?:[ \t]*>)+[ \t]?'), '[^>]', '', 'g')) AS lvl, regexp_replace(line, '^(?:[ \t]*>)+[ \t]?', '') AS rest FROM l),
z AS (SELECT *, NOT regexp_matches(rest, '[^\x20\x09-\x0D]') AS blank FROM q),
y AS (SELECT *, CASE WHEN NOT blank AND (lag(blank) OVER w OR lag(lvl) OVER w IS DISTINCT FROM lvl) THEN 1 ELSE 0 END AS head FROM z WINDOW w AS (PARTITION BY k ORDER BY i)),
x AS (SELECT *, sum(head) OVER (PARTITION BY k ORDER BY i) AS run FROM y),
p AS (SELECT k, any_value(conv_id) AS c, any_value(turn) AS t, first(lvl ORDER BY i) AS lvl, trim(lower(regexp_replace(string_agg(rest, chr(10) ORDER BY i), '[\x20\x09-\x0D]+', ' ', 'g'))) AS h FROM x WHERE run > 0 GROUP BY k, run),
f AS (SELECT a.c, a.t, max(b.t) AS reply_to, sum(a.n) AS n FROM (SELECT c, t, h, count(*) AS n FROM p WHERE lvl > 0 GROUP BY ALL) a
    JOIN (SELECT c, h, min(t) AS t FROM p WHERE lvl = 0 GROUP BY ALL) b ON a.c = b.c AND a.h = b.h AND b.t < a.t GROUP BY a.c, a.t),
u AS (SELECT c, t, reply_to AS root, 1 AS depth FROM f UNION ALL SELECT u.c, u.t, f.reply_to, depth + 1 FROM u JOIN f ON u.c = f.c AND u.root = f.t),
r AS (SELECT c, t, min(root) AS root, max(depth) AS depth FROM u GROUP BY c, t),
n AS (SELECT k, count(*) FILTER (lvl > 0) AS n FROM p GROUP BY k)
SELECT conv_id, turn, role, regexp_replace(array_to_string(list_filter(lines, lambda x: NOT regexp_matches(x, '^(?:[ \t]*>)+')), chr(10)), '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g') AS text,
    coalesce(n.n, 0)::BIGINT AS n_quoted, coalesce(f.n, 0)::BIGINT AS n_linked, coalesce(f.reply_to, -1) AS reply_to, coalesce(r.root, turn) AS thread, coalesce(r.depth, 0)::BIGINT AS depth
FROM m LEFT JOIN n USING (k) LEFT JOIN f ON m.conv_id = f.c AND m.turn = f.t LEFT JOIN r ON m.conv_id = r.c AND m.turn = r.t
"""
