"""Removal of repeated byte strings by suffix sorting with difference covers, block by block.

All strings of ``length`` bytes that also start earlier (in a document of smaller id, or
earlier in the same one) are found; what they cover is removed. Strings in different surroundings are compared
byte by byte in the sorting. Equal runs and whole copies are taken as equal by their hashes, of 128 bits
for a run (its anchor and all its bytes) and 96 for a text, not byte by byte.

A suffix array of the whole corpus is never held. Windows are dealt out by their anchor (see
``anchors``), which equal windows share, so that equal suffixes meet:

1. Anchors that stand twice or more are found; windows with another anchor are unique.
2. Runs of windows with one anchor whose bytes are all equal are settled by comparing
   hashes of whole runs: all but the first repeat it. This takes most repeats.
3. For the first runs of anchors that stand in different surroundings, the bytes go to the
   anchor's task. Those that share with no other neither half of what lies around the anchor go, as equal
   windows hold one of the halves. There the suffixes are sorted one bucket (a range of their leading bytes)
   at a time. Suffixes that agree on those bytes are ordered by ranks, computed before, of
   the suffixes at places of a difference cover: for any two places some shift below the
   cover's period brings both into the cover. Neighbours that share ``length`` bytes are repeats.

An anchor in very many surroundings is split: its windows are dealt out one by one, by
hash, before the same sorting.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from axisgrove.llm.anchors import GRAM, runs_of_texts
from axisgrove.llm.common import cut, keeping, release, table
from axisgrove.llm.packing import bit_filter, whole_groups, within
from axisgrove.llm.words import mix64, multipliers, slices, text_bytes

LENGTH = 100
#: Period of the difference cover, and the cover: every shift is a difference of two members.
PERIOD, COVER = 7, (0, 1, 3)
#: Suffixes that are sorted at a time.
BUCKET = 1 << 20
#: Surroundings of one anchor beyond which its windows are dealt out one by one.
CROWDED = 20_000
#: Texts and removed spans that may be sent to every task; more are joined by shuffling.
BROADCAST_TEXTS, BROADCAST_SPANS = 200_000, 1_000_000
#: Text that makes one bucket of anchors.
_BYTES_A_BUCKET = 64 << 20

_LAST = 2**63 - 1


# --- suffix sorting -----------------------------------------------------------------


def _leading(data: np.ndarray, size: int) -> np.ndarray:
    """The 8 bytes from each of the first ``size`` places, as a number that sorts like them."""
    return np.ndarray(shape=(size,), dtype=">u8", buffer=data, strides=(1,)).astype(np.uint64)


def cover_ranks(lead: np.ndarray, size: int) -> np.ndarray:
    """Ranks of the suffixes at the places of the cover; no two are equal.

    Ranks of PERIOD bytes come from the leading bytes; a rank of twice as many bytes is the
    rank of a pair, whose second member lies one or more periods on and so is in the cover too.
    Place p with p % PERIOD == COVER[c] has number (p // PERIOD) * len(COVER) + c.
    """
    blocks = -(-size // PERIOD)
    places = (np.arange(blocks)[:, None] * PERIOD + np.array(COVER)).ravel()
    places = places[places < size]
    rank = np.empty(len(places), dtype=np.uint64)
    # A rank is the number of lesser places and one; only places that share theirs with others are ranked again.
    shared = np.arange(len(places))
    keys, least = lead[places] >> np.uint64(8 * (8 - PERIOD)), np.ones(len(places), np.uint64)
    reach = PERIOD
    while len(shared):
        order = np.argsort(keys, kind="stable")
        keys, shared, least = keys[order], shared[order], least[order]
        fresh = np.concatenate([[True], keys[1:] != keys[:-1]])
        heads = np.maximum.accumulate(np.where(fresh, np.arange(len(keys)), 0))
        within = np.maximum.accumulate(np.where(np.concatenate([[True], least[1:] != least[:-1]]), np.arange(len(keys)), 0))
        rank[shared] = least + (heads - within).astype(np.uint64)
        shared = shared[~(fresh & np.concatenate([fresh[1:], [True]]))]
        if reach > 2 * size:
            break
        least, on = rank[shared], shared + reach // PERIOD * len(COVER)
        after = np.zeros(len(shared), dtype=np.uint64)
        after[on < len(rank)] = rank[on[on < len(rank)]]
        keys = least << np.uint64(32) | after
        reach *= 2
    return rank


#: Number of a residue within the cover, and for two residues the least shift that brings both into it.
_NUMBER = {r: c for c, r in enumerate(COVER)}
_SHIFT = [[next(d for d in range(PERIOD) if (r + d) % PERIOD in _NUMBER and (s + d) % PERIOD in _NUMBER) for s in range(PERIOD)] for r in range(PERIOD)]


def _rank_at(rank: np.ndarray, places: np.ndarray) -> np.ndarray:
    number = np.array([_NUMBER.get(r, 0) for r in range(PERIOD)])
    return rank[places // PERIOD * len(COVER) + number[places % PERIOD]]


def _sort_ties(places: np.ndarray, group: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """Order of suffixes within groups that agree on PERIOD bytes; ``group`` is ascending.

    Suffixes of one residue are sorted by the cover rank at one shift. That order is also
    the order at every other shift, so the place of a suffix among those of another residue
    is found by bisection at the shift that the two residues have in common.
    """
    residue = places % PERIOD
    classes = []
    for r in range(PERIOD):
        rows = np.flatnonzero(residue == r)
        classes.append(rows[np.lexsort((_rank_at(rank, places[rows] + _SHIFT[r][r]), group[rows]))])
    position = np.zeros(len(places), dtype=np.int64)
    wide = np.uint64(32)
    for r, mine in enumerate(classes):
        for s, other in enumerate(classes):
            if not len(mine) or not len(other):
                continue
            if r == s:
                position[mine] += np.arange(len(mine))
                continue
            shift = _SHIFT[r][s]
            theirs = group[other].astype(np.uint64) << wide | _rank_at(rank, places[other] + shift)
            own = group[mine].astype(np.uint64) << wide | _rank_at(rank, places[mine] + shift)
            position[mine] += np.searchsorted(theirs, own, side="right" if s < r else "left")
    order = np.empty(len(places), dtype=np.int64)
    order[position] = np.arange(len(places))
    return order


def _agree(data: np.ndarray, one: np.ndarray, two: np.ndarray, length: int) -> np.ndarray:
    """Whether ``length`` bytes from the places of ``one`` and ``two`` are equal."""
    lanes = np.ndarray(shape=(len(data) - 7,), dtype="<u8", buffer=data, strides=(1,))
    alive = np.arange(len(one))
    for at in [*range(0, length - 7, 8), length - 8]:
        alive = alive[lanes[one[alive] + at] == lanes[two[alive] + at]]
    out = np.zeros(len(one), dtype=bool)
    out[alive] = True
    return out


def repeated_windows(data: np.ndarray, places: np.ndarray, length: int, bucket: int = BUCKET):
    """Classes of equal windows: (place indices, class numbers) of all that have a twin, bucket by bucket.

    ``data`` must run on for at least 2 * PERIOD + 8 bytes behind its text, ``places`` are
    window starts at least ``length`` bytes before that end.
    """
    size = len(data) - 8
    lead = _leading(data, size)
    rank = cover_ranks(lead, size)
    head = lead[places]
    bounds = np.sort(head)[:: max(1, bucket)][1:] if len(places) > bucket else np.zeros(0, np.uint64)
    which = np.searchsorted(bounds, head, side="right")
    for b in range(len(bounds) + 1):
        rows = np.flatnonzero(which == b) if len(bounds) else np.arange(len(places))
        rows = rows[np.argsort(head[rows], kind="stable")]
        keys = head[rows]
        same = keys[1:] == keys[:-1]
        tied = np.concatenate([[False], same]) | np.concatenate([same, [False]]) if len(rows) else np.zeros(0, bool)
        rows = rows[tied]
        if not len(rows):
            continue
        group = np.cumsum(np.concatenate([[0], head[rows][1:] != head[rows][:-1]]))
        rows = rows[_sort_ties(places[rows], group, rank)]
        at = places[rows]
        twin = _agree(data, at[:-1], at[1:], length)
        number = np.cumsum(np.concatenate([[True], ~twin])) - 1
        many = np.bincount(number)[number] > 1
        if many.any():
            yield rows[many], number[many]


# --- distribution -------------------------------------------------------------------


def _identity(text: str) -> dict:
    whole = F.coalesce(F.col(text), F.lit(""))
    return {"__x": F.xxhash64(whole), "__y": F.hash(whole, F.octet_length(whole))}


def _texts(part: pa.RecordBatch, column: str):
    data, offsets = text_bytes(part.column(column))
    return [data[a:b] for a, b in zip(offsets, offsets[1:], strict=False)]


def _repeated_anchors(docs: DataFrame, text: str, length: int, buckets: int) -> DataFrame:
    """(anchor): anchors that stand at least twice. Hashes travel as packed runs by bucket."""

    def mark(batches):
        for batch in batches:
            for part in slices(batch, text):
                anchor, n = np.unique(runs_of_texts(*text_bytes(part.column(text)), length, False)[3], return_counts=True)
                anchor = np.repeat(anchor, np.minimum(n, 2))
                cuts = np.searchsorted(anchor, np.array([(b << 64) // buckets for b in range(1, buckets)], dtype=np.uint64)) if buckets > 1 else []
                blobs = [(b, x.tobytes()) for b, x in enumerate(np.split(anchor, cuts)) if len(x)]
                yield pa.RecordBatch.from_arrays([pa.array([b for b, _ in blobs], pa.int32()), pa.array([x for _, x in blobs], pa.binary())], names=["bucket", "packed"])

    def count(batches):
        for held in whole_groups(batches, "bucket"):
            keys = held.column("bucket").to_numpy()
            blobs = held.column("packed").to_pylist()
            for b in np.unique(keys).tolist():
                anchor = np.sort(np.frombuffer(b"".join(x for x, k in zip(blobs, keys.tolist(), strict=True) if k == b), dtype=np.uint64))
                twice = anchor[1:][anchor[1:] == anchor[:-1]]
                yield pa.RecordBatch.from_arrays([pa.array(np.unique(twice).view(np.int64))], names=["anchor"])

    packed = docs.select(text).mapInArrow(mark, "bucket int, packed binary")
    return packed.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(count, "anchor bigint")


_RUN = "anchor bigint, whole bigint, doc bigint, x bigint, y int, start bigint, n bigint"
_RUN_COLUMNS = [c.split()[0] for c in _RUN.split(", ")]


def _runs_within(docs: DataFrame, text: str, length: int, bits: bytes) -> DataFrame:
    """Runs whose anchor passes a filter. ``settled`` ones repeat a run of the same slice."""
    held = docs.sparkSession.sparkContext.broadcast(bits)

    def work(batches):
        bits = np.frombuffer(held.value, dtype=np.uint8)
        for batch in batches:
            for part in slices(batch, text):
                doc, x, y = (part.column(c).to_numpy(zero_copy_only=False) for c in ("__doc", "__x", "__y"))
                owner, start, n, anchor, whole, _ = runs_of_texts(*text_bytes(part.column(text)), length)
                keep = np.flatnonzero(within(bits, anchor))
                owner, start, n, a, w = owner[keep], start[keep], n[keep], anchor[keep].view(np.int64), whole[keep].view(np.int64)
                arrays = [a, w, doc[owner], x[owner], y[owner].astype(np.int32), start, n]
                order = np.lexsort((start, y[owner], x[owner], doc[owner], w, a))
                a, w = a[order], w[order]
                settled = np.zeros(len(a), dtype=bool)
                settled[order[1:]] = (a[1:] == a[:-1]) & (w[1:] == w[:-1])
                first = order[np.maximum.accumulate(np.where(settled[order], 0, np.arange(len(order))))] if len(order) else order
                # A repeated row is the same document: it repeats nothing.
                twin = np.zeros(len(a), dtype=bool)
                twin[order] = (doc[owner[order]] == doc[owner[first]]) & (x[owner[order]] == x[owner[first]]) & (y[owner[order]] == y[owner[first]]) & (start[order] == start[first])
                yield pa.RecordBatch.from_arrays([*map(pa.array, arrays), pa.array(settled & ~twin)], names=[*_RUN_COLUMNS, "settled"])

    return docs.select("__doc", "__x", "__y", text).mapInArrow(work, _RUN + ", settled boolean")


def _name(whole, x, start):
    """A number for one run of one text, of hashes that differ in their low bits (columns)."""
    return whole.bitwiseXOR(x).bitwiseXOR(start)


def _bytes_of(docs: DataFrame, text: str, length: int, bits: bytes) -> DataFrame:
    """Runs whose name (see ``_name``) passes a filter, with their bytes and the anchor's place in these."""
    held = docs.sparkSession.sparkContext.broadcast(bits)

    def work(batches):
        bits = np.frombuffer(held.value, dtype=np.uint8)
        for batch in batches:
            for part in slices(batch, text):
                doc, x, y = (part.column(c).to_numpy(zero_copy_only=False) for c in ("__doc", "__x", "__y"))
                data, offsets = text_bytes(part.column(text))
                owner, start, n, anchor, whole, place = runs_of_texts(data, offsets, length)
                keep = np.flatnonzero(within(bits, whole ^ x[owner].view(np.uint64) ^ start.view(np.uint64)))
                owner, start, n, anchor, place = owner[keep], start[keep], n[keep], anchor[keep].view(np.int64), place[keep].astype(np.int32)
                at = offsets[owner] + start
                pieces = [data[a:b].tobytes() for a, b in zip(at.tolist(), (at + n + length - 1).tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([*map(pa.array, (anchor, doc[owner], x[owner], y[owner].astype(np.int32), start, n, place)), pa.array(pieces, pa.binary())], names=["anchor", "doc", "x", "y", "start", "n", "place", "bytes"])

    return docs.select("__doc", "__x", "__y", text).mapInArrow(work, "anchor bigint, doc bigint, x bigint, y int, start bigint, n bigint, place int, bytes binary")


def _judge_runs(candidates: DataFrame) -> DataFrame:
    """Runs with ``repeats`` (a run of equal bytes came first) or else first of their bytes, where
    the anchor has other surroundings too. Streams in sorted order, with one row in memory."""

    def work(batches):
        state = None  # anchor, whole, the first run's identity; a first run that waits for a second kind
        waiting = None
        for batch in batches:
            if not batch.num_rows:
                continue
            anchor, whole, doc, x, y, start = (batch.column(c).to_numpy(zero_copy_only=False) for c in _RUN_COLUMNS[:6])
            fresh_anchor = np.concatenate([[state is None or state[0] != anchor[0]], anchor[1:] != anchor[:-1]])
            fresh = fresh_anchor | np.concatenate([[state is None or state[1] != whole[0]], whole[1:] != whole[:-1]])
            lead = np.maximum.accumulate(np.where(fresh, np.arange(len(fresh)), -1))
            same = np.zeros(len(fresh), dtype=bool)
            known = lead >= 0
            same[known] = (doc[known] == doc[lead[known]]) & (x[known] == x[lead[known]]) & (y[known] == y[lead[known]]) & (start[known] == start[lead[known]])
            if not known.all():
                d, xx, yy, s = state[2]
                rest = ~known
                same[rest] = (doc[rest] == d) & (x[rest] == xx) & (y[rest] == yy) & (start[rest] == s)
            firsts = np.flatnonzero(fresh)
            # An anchor's first run is of interest once a second kind of run follows it.
            alone = fresh_anchor[firsts] & ~np.concatenate([fresh_anchor[firsts][1:] == False, [False]])  # noqa: E712
            several = firsts[~alone]
            out = [batch.filter(pa.array(~fresh & ~same)).append_column("repeats", pa.array(np.ones(int((~fresh & ~same).sum()), bool)))]
            if len(firsts):
                if waiting is not None and not fresh_anchor[firsts[0]]:
                    out.append(waiting)
                waiting = None
                last = firsts[-1]
                if alone[-1]:  # it may yet be followed in the next batch
                    waiting = batch.slice(int(last), 1).append_column("repeats", pa.array([False]))
            out.append(batch.take(pa.array(several)).append_column("repeats", pa.array(np.zeros(len(several), bool))))
            f = int(lead[-1])
            state = (anchor[-1], whole[-1], (doc[f], x[f], y[f], start[f]) if f >= 0 else state[2])
            yield from out

    keys = ["anchor", "whole", "doc", "x", "y", "start"]
    return candidates.select(*_RUN_COLUMNS).repartition("anchor").sortWithinPartitions(*keys).mapInArrow(work, _RUN + ", repeats boolean")


def _shared(data: np.ndarray, at: np.ndarray, size: int, here: np.ndarray, key: np.ndarray) -> np.ndarray:
    """Which of the rows ``here`` agree with another of the same key on the ``size`` bytes from ``at``."""
    lanes = np.ndarray(shape=(len(data) - 7,), dtype="<u8", buffer=data, strides=(1,))
    rows, out = np.flatnonzero(here), np.zeros(len(at), dtype=bool)
    steps = [*range(0, size - 7, 8), size - 8]
    with np.errstate(over="ignore"):
        name = key[rows].view(np.uint64) * multipliers(1, 903)[0]
        for step, weight in zip(steps, multipliers(len(steps), 904), strict=True):
            name = mix64(name + lanes[at[rows] + step] * weight)
    _, number, often = np.unique(name, return_inverse=True, return_counts=True)
    out[rows[often[number] > 1]] = True
    return out


def _trimmed(data: np.ndarray, base: np.ndarray, n: np.ndarray, place: np.ndarray, key: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """(first, stop) of the windows of each segment that may have a twin.

    Equal windows hold the anchor at one place, and either the half of what is around it that lies before it or
    the other half behind it: segments that share neither with another of their anchor are left out, and those that share
    one of the two keep the windows that hold it. Segments without a place (-1) are left as they are.
    """
    before = (length - GRAM) // 2
    behind = length - GRAM - before + 1
    known = (place >= 0) & (before >= 8)  # fewer bytes than a lane are not compared
    first, stop = np.zeros(len(n), dtype=np.int64), n.copy()
    # Windows that start before ``split`` have the bytes before the anchor, the others those behind it.
    split = np.clip(place - before + 1, 0, n)
    stop[known & ~_shared(data, base + place + GRAM, behind, known & (split < n), key)] = 0
    right = stop > 0
    left = _shared(data, base + place - before, before, known & (split > 0), key)
    first = np.where(known, np.where(left, 0, np.where(right, split, 0)), first)
    stop = np.where(known, np.where(right, n, np.where(left, split, 0)), n)
    return first, stop


def _sorted_repeats(segments: DataFrame, length: int) -> DataFrame:
    """(doc, x, y, start, n): windows that repeat an earlier one, from segments (key, doc, x, y, start, n, place, bytes)."""

    def work(batches):
        for held in whole_groups(batches, "key"):
            key, doc, x, y, start, n, place = (held.column(c).to_numpy() for c in ("key", "doc", "x", "y", "start", "n", "place"))
            data, ends = text_bytes(held.column("bytes"))
            data = np.concatenate([data, np.zeros(length + 4 * PERIOD + 8, np.uint8)])
            first, stop = _trimmed(data, ends[:-1], n, place.astype(np.int64), key, length)
            some = np.flatnonzero(stop > first)
            if not len(some):
                continue
            # Only what the windows that are left hold goes on.
            doc, x, y, start, n, begin = doc[some], x[some], y[some], start[some] + first[some], (stop - first)[some], (ends[:-1] + first)[some]
            size = n + length - 1
            base = np.cumsum(size) - size
            data = np.concatenate([data[np.repeat(begin - base, size) + np.arange(int(size.sum()))], np.zeros(4 * PERIOD + 8, np.uint8)])
            owner = np.repeat(np.arange(len(n)), n)
            inner = np.arange(len(owner)) - np.repeat(np.cumsum(n) - n, n)
            gone = np.zeros(len(owner), dtype=bool)
            for rows, number in repeated_windows(data, base[owner] + inner, length):
                o = owner[rows]
                order = np.lexsort((start[o] + inner[rows], y[o], x[o], doc[o], number))
                later = np.concatenate([[False], number[order][1:] == number[order][:-1]])
                gone[rows[order[later]]] = True
            # A stretch of removed windows is cut where a segment ends.
            heads = np.flatnonzero(gone & np.concatenate([[True], (owner[1:] != owner[:-1]) | ~gone[:-1]]))
            stops = np.flatnonzero(gone & np.concatenate([(owner[1:] != owner[:-1]) | ~gone[1:], [True]])) + 1
            o = owner[heads]
            yield pa.RecordBatch.from_arrays([pa.array(v) for v in (doc[o], x[o], y[o], start[o] + inner[heads], stops - heads)], names=["doc", "x", "y", "start", "n"])

    dealt = segments.select("key", "doc", "x", "y", "start", "n", "place", "bytes").repartition("key").sortWithinPartitions("key", "doc", "x", "y", "start")
    return dealt.mapInArrow(work, "doc bigint, x bigint, y int, start bigint, n bigint")


def _windows_apart(segments: DataFrame, length: int) -> DataFrame:
    """Segments of crowded anchors as single windows, keyed by a hash of their bytes; others as they are."""

    def work(batches):
        weights = multipliers(length, 900)
        for batch in batches:
            crowded = batch.column("surroundings").to_numpy(zero_copy_only=False) > CROWDED
            plain = batch.filter(pa.array(~crowded))
            yield plain.select(["key", "doc", "x", "y", "start", "n", "place", "bytes"])
            for row in batch.filter(pa.array(crowded)).to_pylist():
                data = np.frombuffer(row["bytes"], np.uint8)
                windows = np.lib.stride_tricks.sliding_window_view(data, length)
                with np.errstate(over="ignore"):
                    keys = mix64((windows.astype(np.uint64) * weights).sum(axis=1)).view(np.int64)
                m = len(keys)
                yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array([row["doc"]] * m, pa.int64()), pa.array([row["x"]] * m, pa.int64()), pa.array([row["y"]] * m, pa.int32()), pa.array(row["start"] + np.arange(m)), pa.array(np.ones(m, np.int64)), pa.array(np.full(m, -1, np.int32)), pa.array([w.tobytes() for w in windows], pa.binary())], names=["key", "doc", "x", "y", "start", "n", "place", "bytes"])

    return segments.mapInArrow(work, "key bigint, doc bigint, x bigint, y int, start bigint, n bigint, place int, bytes binary")


def _merged(spans: list[dict], size: int, length: int) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for a, n in sorted((s["start"], s["n"]) for s in spans or ()):
        b = min(size, a + n + length - 1)
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


@keeping
def without_repeats(docs: DataFrame, keep: list[str], doc_id: str = "doc_id", text: str = "text", length: int = LENGTH) -> DataFrame:
    """``keep``, n_bytes, removed array<struct<start,stop>> (byte spans, merged) and kept (the bytes left).

    A null text is empty; null ids come after all others; equal rows are one document, which
    does not repeat itself, and are judged alike; documents that share an id but not the
    text are ordered by a hash of it; texts shorter than ``length`` keep all, longer ones are taken
    whole; an empty table gives no rows. A kept column that has the name of a result comes back with ``_in`` added.
    """
    named = docs.withColumns({**_identity(text), "__doc": F.coalesce(F.col(doc_id).cast("bigint"), F.lit(_LAST))})
    # Exact copies of a whole text are known without looking into it; their list is sent along where it is short.
    twins = cut(named.groupBy("__x", "__y").agg(F.min("__doc").alias("__first"), F.max("__doc").alias("__last"), F.first(F.octet_length(text)).alias("size")).filter("__first < __last").select("__x", "__y", "__first"))
    listed = F.broadcast(twins) if twins.count() <= BROADCAST_TEXTS else twins
    copied = named.join(listed, ["__x", "__y"], "left").withColumn("__copy", F.coalesce(F.col("__doc") > F.col("__first"), F.lit(False))).drop("__first")
    own = copied.filter(~F.col("__copy") & (F.octet_length(text) >= length))
    total = docs.agg(F.sum(F.octet_length(text))).head()[0] or 0
    buckets = max(64, total // _BYTES_A_BUCKET)
    bits = bit_filter(_repeated_anchors(own, text, length, buckets), "anchor")
    candidates = cut(_runs_within(own, text, length, bits))
    judged = cut(_judge_runs(candidates.filter("NOT settled")))
    firsts = judged.filter("NOT repeats")
    kinds = firsts.groupBy("anchor").agg(F.count("*").alias("surroundings"))
    wanted = cut(firsts.join(kinds, "anchor").select(F.col("doc").alias("d"), F.col("x").alias("x1"), F.col("y").alias("y1"), F.col("start").alias("s"), F.col("whole").alias("w"), "surroundings"))
    pieces = _bytes_of(own, text, length, bit_filter(wanted.select(_name(F.col("w"), F.col("x1"), F.col("s")).alias("name")), "name"))
    pieces = pieces.join(wanted, (F.col("doc") == F.col("d")) & (F.col("x") == F.col("x1")) & (F.col("y") == F.col("y1")) & (F.col("start") == F.col("s")))
    pieces = pieces.withColumn("key", F.col("anchor")).dropDuplicates(["doc", "x", "y", "start"])
    found = _sorted_repeats(_windows_apart(pieces.select("key", "surroundings", "doc", "x", "y", "start", "n", "place", "bytes"), length), length)
    span = ["doc", "x", "y", "start", "n"]
    spans = candidates.filter("settled").select(*span).unionByName(judged.filter("repeats").select(*span)).unionByName(found)
    spans = cut(spans.groupBy(F.col("doc").alias("__d"), F.col("x").alias("__x1"), F.col("y").alias("__y1")).agg(F.collect_set(F.struct("start", "n")).alias("__spans")).withColumn("__many", F.size("__spans")))
    release(candidates, judged, wanted)
    side = F.broadcast(spans) if (spans.agg(F.sum("__many")).head()[0] or 0) <= BROADCAST_SPANS else spans
    marked = copied.join(side.drop("__many"), (F.col("__doc") == F.col("__d")) & (F.col("__x") == F.col("__x1")) & (F.col("__y") == F.col("__y1")), "left")

    kinds = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep)

    def work(batches):
        for batch in batches:
            for part in slices(batch, text):
                copies, spans = part.column("__copy").to_pylist(), part.column("__spans").to_pylist()
                removed, left, sizes = [], [], []
                for data, copy, own in zip(_texts(part, text), copies, spans, strict=True):
                    gone = ([(0, len(data))] if len(data) >= length else []) if copy else _merged(own, len(data), length)
                    at, rest = 0, []
                    for a, b in gone:
                        rest.append(data[at:a].tobytes())
                        at = b
                    rest.append(data[at:].tobytes())
                    removed.append([{"start": a, "stop": b} for a, b in gone])
                    left.append(b"".join(rest))
                    sizes.append(len(data))
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), pa.array(sizes, pa.int64()), pa.array(removed, pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))), pa.array(left, pa.binary())], names=[*keep, "n_bytes", "removed", "kept"])

    return marked.select(*keep, *([text] if text not in keep else []), "__copy", "__spans").mapInArrow(work, ", ".join(x for x in (kinds, "n_bytes bigint, removed array<struct<start:bigint,stop:bigint>>, kept binary") if x))


def op2_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What repeated strings of 100 bytes take from every document."""
    found = without_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"), ["doc_id"])
    gone = F.aggregate("removed", F.lit(0).cast("bigint"), lambda n, s: n + s["stop"] - s["start"])
    return found.select("doc_id", "n_bytes", gone.alias("n_removed"), F.size("removed").cast("bigint").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))
