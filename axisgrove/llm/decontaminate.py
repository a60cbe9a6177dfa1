"""Benchmark decontamination as a prefix-filtered set join over item-sized windows.

Windows of benchmark items are runs of consecutive words; a document holds a window when
all its words stand there in order (containment 1). Words are ordered by how rare they are
in the whole corpus, counted first; for containment 1 the necessary prefix of a window is
its single rarest word, so only places of a document where such a word stands are joined
with the windows it leads. What is left passes a length and position bound (the window
must fit into the document around that place) and is verified word for word, rarest first.

The benchmark side is held in blocks of at most ``BLOCK_BYTES`` of text; a larger
benchmark makes more passes over the documents instead of a larger broadcast.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from axisgrove.llm.common import cut, keeping, table
from axisgrove.llm.words import ALNUM, Words, slices

WIDTH = 10
#: Benchmark text that one pass may hold in each worker.
BLOCK_BYTES = 8 << 20
#: Candidates that are expanded at a time.
_CANDIDATES = 1 << 18


class WindowIndex:
    """Distinct windows of a block of items, keyed by their rarest word."""

    def __init__(self, items: list[tuple], width: int):
        words = Words(pa.array([t for _, t in items], pa.string()), ALNUM, lower=True)
        packed = words.packed()
        self.vocabulary = pc.unique(packed)
        ids = pc.index_in(packed, value_set=self.vocabulary).to_numpy(zero_copy_only=False).astype(np.int32) if len(packed) else np.zeros(0, np.int32)
        owners: dict[tuple, set] = {}
        for k, (item, _) in enumerate(items):
            own = ids[words.first[k] : words.first[k + 1]].tolist()
            size = min(width, len(own))
            for i in range(len(own) - size + 1 if size else 0):
                owners.setdefault(tuple(own[i : i + size]), set()).add(str(item))
        self.windows = list(owners)
        self.items = [sorted(owners[w]) for w in self.windows]

    def order(self, counts: np.ndarray) -> None:
        """Choose each window's prefix word by the corpus counts of the vocabulary."""
        n, width = len(self.windows), max(map(len, self.windows), default=0)
        self.size = np.array([len(w) for w in self.windows], dtype=np.int64)
        #: For each window the places of its words, rarest first, and the words there; padded by repeating the first.
        self.places, self.expected = np.zeros((n, width), np.int64), np.zeros((n, width), np.int32)
        for i, w in enumerate(self.windows):
            by = sorted(range(len(w)), key=lambda j: (counts[w[j]], w[j], j))
            by += by[:1] * (width - len(w))
            self.places[i], self.expected[i] = by, [w[j] for j in by]
        lead = self.expected[:, 0] if n else np.zeros(0, np.int32)
        self.by_lead = np.argsort(lead, kind="stable")
        self.heads = np.searchsorted(lead[self.by_lead], np.arange(len(self.vocabulary) + 1))

    def occurrences(self, ids: np.ndarray, first: np.ndarray):
        """(text, start, window) of every occurrence, in chunks; ids are vocabulary numbers, -1 for other words."""
        leads = np.diff(self.heads)
        spots = np.flatnonzero((ids >= 0) & (np.append(leads, 0)[ids] > 0))
        text = np.searchsorted(first, spots, side="right") - 1
        many = leads[ids[spots]]
        ends = np.cumsum(many)
        done = 0
        while done < len(spots):
            upto = max(int(np.searchsorted(ends, (ends[done - 1] if done else 0) + _CANDIDATES, side="right")), done + 1)
            here, count, owner = spots[done:upto], many[done:upto], text[done:upto]
            nth = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
            window = self.by_lead[np.repeat(self.heads[ids[here]], count) + nth]
            start = np.repeat(here, count) - self.places[window, 0]
            owner = np.repeat(owner, count)
            fits = (start >= first[owner]) & (start + self.size[window] <= first[owner + 1])
            window, start, owner = window[fits], start[fits], owner[fits]
            for j in range(1, self.places.shape[1]):
                same = ids[start + self.places[window, j]] == self.expected[window, j]
                window, start, owner = window[same], start[same], owner[same]
            yield owner, start, window
            done = upto


def _vocabulary_ids(words: Words, vocabulary) -> np.ndarray:
    if not len(words.start) or not len(vocabulary):
        return np.full(len(words.start), -1, dtype=np.int32)
    return pc.fill_null(pc.index_in(words.packed(), value_set=vocabulary), -1).to_numpy(zero_copy_only=False).astype(np.int32)


def _corpus_counts(docs: DataFrame, text: str, index: WindowIndex) -> np.ndarray:
    """How often each word of the vocabulary stands in all documents."""
    spark = docs.sparkSession
    held = spark.sparkContext.broadcast(index.vocabulary)

    def count(batches):
        total = np.zeros(len(held.value), dtype=np.int64)
        for batch in batches:
            for part in slices(batch, text):
                ids = _vocabulary_ids(Words(part.column(text), ALNUM, lower=True), held.value)
                total += np.bincount(ids[ids >= 0], minlength=len(total))
        found = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(found), pa.array(total[found])], names=["word", "n"])

    counts = np.zeros(len(index.vocabulary), dtype=np.int64)
    for row in docs.select(text).mapInArrow(count, "word bigint, n bigint").groupBy("word").agg(F.sum("n").alias("n")).collect():
        counts[row.word] = row.n
    return counts


def _covered(starts: np.ndarray, stops: np.ndarray, n: int) -> np.ndarray:
    step = np.zeros(n + 1, dtype=np.int64)
    np.add.at(step, starts, 1)
    np.add.at(step, stops, -1)
    return np.cumsum(step[:-1]) > 0


@keeping
def contaminated_words(docs: DataFrame, items: DataFrame, keep: list[str], text: str = "text", item_id: str = "item_id", item_text: str = "text", width: int = WIDTH, with_text: bool = False) -> DataFrame:
    """``keep`` of every document, n_words, hits array<struct<start,stop>> (word spans that
    windows cover, merged) and items array<string> (ids of the items found, sorted);
    ``with_text`` keeps the text, too.

    Nulls and texts without words have no words and no hits; a null item text gives no
    window; a null item id counts as "None"; repeated rows are judged each alone; empty
    tables give no rows, or no hits; a text is searched whole, however long.
    A kept column that has the name of a result comes back with ``_in`` added.
    """
    spark = docs.sparkSession
    bytes_ = items.agg(F.sum(F.octet_length(item_text))).head()[0] or 0
    blocks = max(1, math.ceil(2 * bytes_ / BLOCK_BYTES)) if bytes_ > BLOCK_BYTES else 1
    fields = docs.select(*keep, text)
    kept = ", ".join(f"`{c}` {fields.schema[c].dataType.simpleString()}" for c in keep)
    added = "n_words bigint, hits array<struct<start:bigint,stop:bigint>>, items array<string>"
    out = fields.withColumns({"n_words": F.lit(0).cast("bigint"), "hits": F.array().cast("array<struct<start:bigint,stop:bigint>>"), "items": F.array().cast("array<string>")})
    for block in range(blocks):
        part = items.filter(F.pmod(F.xxhash64(item_id, item_text), F.lit(blocks)) == block) if blocks > 1 else items
        index = WindowIndex([tuple(r) for r in part.select(item_id, item_text).filter(F.col(item_text).isNotNull()).collect()], width)
        index.order(_corpus_counts(docs, text, index))
        held = spark.sparkContext.broadcast(cloudpickle.dumps(index))
        last = block == blocks - 1 and not with_text

        def find(batches, held=held, last=last):
            index = cloudpickle.loads(held.value)
            for batch in batches:
                for part in slices(batch, text):
                    words = Words(part.column(text), ALNUM, lower=True)
                    ids = _vocabulary_ids(words, index.vocabulary)
                    earlier_hits, earlier_items = part.column("hits").to_pylist(), part.column("items").to_pylist()
                    starts, stops = [], []
                    found: dict[int, set] = {}
                    for i, spans in enumerate(earlier_hits):
                        starts += [np.array([s["start"] for s in spans], dtype=np.int64) + words.first[i]] if spans else []
                        stops += [np.array([s["stop"] for s in spans], dtype=np.int64) + words.first[i]] if spans else []
                        if earlier_items[i]:
                            found[i] = set(earlier_items[i])
                    for owner, start, window in index.occurrences(ids, words.first):
                        starts.append(start)
                        stops.append(start + index.size[window])
                        pairs = np.unique(np.stack([owner, window], axis=1), axis=0) if len(owner) else []
                        for o, w in pairs:
                            found.setdefault(int(o), set()).update(index.items[w])
                    hit = _covered(np.concatenate(starts or [np.zeros(0, np.int64)]), np.concatenate(stops or [np.zeros(0, np.int64)]), len(ids))
                    spans: list[list] = [[] for _ in range(part.num_rows)]
                    for i in found:
                        own = np.concatenate([[False], hit[words.first[i] : words.first[i + 1]], [False]]).astype(np.int8)
                        edge = np.diff(own)
                        spans[i] = [{"start": a, "stop": b} for a, b in zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist(), strict=True)]
                    columns = [part.column(c) for c in keep] + ([] if last else [part.column(text)])
                    columns += [pa.array(words.counts()), pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))), pa.array([sorted(found.get(i, ())) for i in range(part.num_rows)], pa.list_(pa.string()))]
                    yield pa.RecordBatch.from_arrays(columns, names=[*keep, *([] if last else [text]), "n_words", "hits", "items"])

        out = out.mapInArrow(find, ", ".join(x for x in (kept, "" if last else f"`{text}` string", added) if x))
        if block < blocks - 1:
            out = cut(out)
    return out


def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words of every document that benchmark windows cover, and which items they are of."""
    found = contaminated_words(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), ["doc_id"])
    n_hit = F.aggregate("hits", F.lit(0).cast("bigint"), lambda total, s: total + s["stop"] - s["start"])
    return found.select(
        "doc_id",
        "n_words",
        n_hit.alias("n_hit"),
        F.size("items").cast("bigint").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"),
        (F.size("hits") > 0).alias("contaminated"),
    )


OP8_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
bw AS (SELECT item_id, least(10, len(w)) AS l, unnest(range(1, (len(w) - least(10, len(w)) + 2)::BIGINT)) AS i, w FROM b WHERE len(w) > 0),
win AS (SELECT DISTINCT item_id, l, array_to_string(w[i : i + l - 1], ' ') AS t FROM bw),
dw AS (SELECT k, l, w, unnest(range(1, greatest(1, len(w) - l + 2)::BIGINT)) AS i FROM d, (SELECT DISTINCT l FROM win)),
occ AS (SELECT k, i, dw.l, item_id FROM (SELECT k, l, i, array_to_string(w[i : i + l - 1], ' ') AS t FROM dw) dw JOIN win ON win.l = dw.l AND win.t = dw.t),
hit AS (SELECT k, count(DISTINCT p) AS n FROM (SELECT k, unnest(range(i, i + l)) AS p FROM occ) GROUP BY k),
its AS (SELECT k, count(*) AS n, sha256(string_agg(x, ',' ORDER BY x)) AS s FROM (SELECT DISTINCT k, item_id::VARCHAR AS x FROM occ) GROUP BY k)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(hit.n, 0)::BIGINT AS n_hit, coalesce(its.n, 0)::BIGINT AS n_items,
    coalesce(its.s, sha256('')) AS items_sha256, coalesce(hit.n, 0) > 0 AS contaminated
FROM d LEFT JOIN hit USING (k) LEFT JOIN its USING (k)
"""
