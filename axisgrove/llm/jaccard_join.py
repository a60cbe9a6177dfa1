"""Exact Jaccard join on word n-grams: size bands, bitmap signatures, sorted-array checks.

A document is the set of hashes of its shingles; documents with equal sets are one node.
Linked nodes A and B share at least m of the first |A| - ceil(t |A|) + m shingles of A,
whatever common order is taken, and the same holds for B; m grows with the size (one in
twenty). Our order is by hash, with shingles that were counted often put last, so
that passages which many documents share lead to no candidates between them.

1. Shingles often seen are listed (a bounded list; it shapes the order, not the result).
2. Prefixes of all nodes are joined on shingles that at least two nodes hold; a node with
   too few of those is linked with nothing and goes.
3. For the sets of what stays, the leading shingles are chosen again, the rarest first. Nodes that
   share those, directly or through others, go with their sets to one tile of bounded bytes;
   what is too large for one is dealt to many (see ``_links``).
4. Within a tile, pairs that are not connected yet are tried: sizes must lie in the band that
   the threshold allows, and bits in which two signatures differ bound the overlap from above.
5. What remains is decided by intersecting the sorted arrays, in the tile. Only links that
   join two groups leave it, fewer than it has nodes, so no group becomes all of its pairs.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from axisgrove.llm.common import cut, keeping, release, table
from axisgrove.llm.components import components
from axisgrove.llm.packing import bit_filter, whole_groups, within
from axisgrove.llm.words import SPACED, Words, mix64, shingle_hashes, slices

WIDTH, PERCENT = 4, 85
#: Most shingles that are put last in the order.
FREQUENT = 1 << 16
#: Shingles that are counted together when looking for frequent ones, and the least count there.
COUNTED, LEAST_COUNT = 1 << 22, 4
#: Sets and signatures in a tile.
TILE_BYTES = 8 << 20
#: Signature bits: a power of two, twice the size of the set or more, within these bounds.
LEAST_BITS, MOST_BITS = 64, 4096
#: Nodes whose keys may be sent to every task; more are joined by shuffling.
BROADCAST_NODES = 300_000
#: Prefix shingles that one bucket of the packed comparison holds.
PACKED_ROWS = 1 << 22


def shared_least(n: int) -> int:
    """m for a set of n shingles."""
    return 1 + n // 20


def _sets(part: pa.RecordBatch, text: str, width: int):
    """Sorted distinct shingle hashes of each text of a batch."""
    words = Words(part.column(text), SPACED, lower=True)
    found, owner = shingle_hashes(words, width)
    if len(owner) and np.any(np.diff(owner) < 0):
        order = np.argsort(owner, kind="stable")
        found, owner = found[order], owner[order]
    ends = np.searchsorted(owner, np.arange(part.num_rows + 1))
    return [np.unique(found[ends[i] : ends[i + 1]]) for i in range(part.num_rows)]


def _node(own: np.ndarray) -> int:
    """A 64-bit name of a set, as a signed number."""
    with np.errstate(over="ignore"):
        total = np.array([np.sum(mix64(own ^ np.uint64(0x5851F42D4C957F2D))) + np.uint64(len(own))], dtype=np.uint64)
    return int(mix64(total).view(np.int64)[0])


def _signature(own: np.ndarray) -> bytes:
    """Bits of the shingles of a set."""
    bits = LEAST_BITS
    while bits < len(own) * 2 and bits < MOST_BITS:
        bits *= 2
    marked = np.zeros(bits, dtype=bool)
    marked[(own & np.uint64(bits - 1)).astype(np.int64)] = True
    return np.packbits(marked, bitorder="little").tobytes()


def frequent_shingles(docs: DataFrame, text: str, width: int, most: int = FREQUENT) -> np.ndarray:
    """At most ``most`` shingles that stand in many documents, least frequent first.

    Each task counts its shingles in large runs and reports those seen several times; the
    counts are added up. Missing one costs time later, never a link.
    """

    def count(batches):
        held: list[np.ndarray] = []
        seen: set[int] = set()
        size = 0

        def report():
            found, n = np.unique(np.concatenate(held), return_counts=True)
            often = n >= LEAST_COUNT
            return pa.RecordBatch.from_arrays([pa.array(found[often].view(np.int64)), pa.array(n[often].astype(np.int64))], names=["shingle", "n"])

        for batch in batches:
            for part in slices(batch, text):
                for own in _sets(part, text, width):
                    if not len(own) or (name := _node(own)) in seen:
                        continue
                    seen.add(name)
                    held.append(own)
                    size += len(own)
                    if size >= COUNTED:
                        yield report()
                        held, size = [], 0
                        seen.clear()
        if held:
            yield report()

    counts = docs.select(text).mapInArrow(count, "shingle bigint, n bigint").groupBy("shingle").agg(F.sum("n").alias("n"))
    listed = cut(counts.orderBy(F.desc("n"), "shingle").limit(most)).orderBy(F.desc("n"), "shingle").collect()
    return np.array([r["shingle"] for r in reversed(listed)], dtype=np.int64).view(np.uint64)


def sketches(docs: DataFrame, keep: list[str], text: str, width: int, percent: int, often: np.ndarray) -> DataFrame:
    """``keep``, key (hash of the text), node, n_shingles, prefix (array of shingles)."""
    fields = docs.select(*keep, F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("__key"), text)
    ranks = np.argsort(often, kind="stable")
    held = docs.sparkSession.sparkContext.broadcast((often[ranks].tobytes(), ranks.tobytes()))

    def work(batches):
        often, rank = np.frombuffer(held.value[0], dtype=np.uint64), np.frombuffer(held.value[1], dtype=np.int64)
        likely = np.zeros(1 << 20, dtype=bool)
        likely[(often >> np.uint64(44)).astype(np.int64)] = True
        for batch in batches:
            for part in slices(batch, text):
                nodes, sizes, heads = [], [], []
                for own in _sets(part, text, width):
                    n = len(own)
                    first = n - (percent * n + 99) // 100 + shared_least(n) if n else 0
                    place = np.zeros(n, dtype=np.int64)
                    maybe = np.flatnonzero(likely[(own >> np.uint64(44)).astype(np.int64)])
                    if len(maybe):
                        at = np.minimum(np.searchsorted(often, own[maybe]), len(often) - 1)
                        same = often[at] == own[maybe]
                        place[maybe[same]] = rank[at[same]] + 1
                    cold = own[place == 0][:first]
                    if len(cold) < first:
                        cold = np.concatenate([cold, own[np.argsort(place, kind="stable")[len(cold) : first]]])
                    nodes.append(_node(own) if n else 0)
                    sizes.append(n)
                    heads.append(cold)
                ends = np.zeros(len(heads) + 1, dtype=np.int32)
                np.cumsum([len(h) for h in heads], out=ends[1:])
                prefix = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([*heads, np.zeros(0, np.uint64)]).view(np.int64)))
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), part.column("__key"), pa.array(nodes, pa.int64()), pa.array(sizes, pa.int64()), prefix], names=[*keep, "key", "node", "n_shingles", "prefix"])

    kinds = ", ".join(f"`{c}` {fields.schema[c].dataType.simpleString()}" for c in keep)
    return fields.mapInArrow(work, ", ".join(x for x in (kinds, "key bigint, node bigint, n_shingles bigint, prefix array<bigint>") if x))


def _shared_heads(nodes: DataFrame, percent: int) -> DataFrame:
    """(shingle, node) of the leading shingles that more than one node holds, and of few others, for nodes
    that have enough shared shingles in their prefix to be linked with any.

    First every slice packs, for each shingle, the least and the greatest node that holds
    it, so a shingle that very many nodes hold is two numbers a slice; where the two differ
    over all slices, the shingle is shared. A bitmap of those then picks the rows, where a node's
    whole prefix is at hand, so that nodes with too few go before anything is moved.
    """
    total = nodes.agg(F.sum(F.size("prefix"))).head()[0] or 0
    buckets = max(64, total // PACKED_ROWS)
    limits = np.array([(b << 64) // buckets for b in range(1, buckets)], dtype=np.uint64)

    def flat(batch):
        lists = batch.column("prefix")
        shingle = lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
        return shingle, np.repeat(np.arange(batch.num_rows), np.diff(lists.offsets.to_numpy()))

    def pack(batches):
        for batch in batches:
            shingle, row = flat(batch)
            node = batch.column("node").to_numpy()[row]
            order = np.lexsort((node, shingle))
            shingle, node = shingle[order], node[order]
            first = np.concatenate([[True], shingle[1:] != shingle[:-1]]) if len(shingle) else np.zeros(0, bool)
            last = np.concatenate([first[1:], [True]]) if len(shingle) else first
            keep = first | (last & ~first & (node != node[np.maximum.accumulate(np.where(first, np.arange(len(first)), 0))] if len(first) else last))
            # Six bytes of either: shingles that agree on those only pass the filter, which is harmless.
            pairs = np.concatenate([(x >> np.uint64(16)).astype("<u8")[:, None].view(np.uint8)[:, :6] for x in (shingle[keep], node[keep].view(np.uint64))], axis=1)
            parts = np.split(pairs, np.searchsorted(shingle[keep], limits))
            blobs = [(b, np.ascontiguousarray(x).tobytes()) for b, x in enumerate(parts) if len(x)]
            yield pa.RecordBatch.from_arrays([pa.array([b for b, _ in blobs], pa.int32()), pa.array([x for _, x in blobs], pa.binary())], names=["bucket", "packed"])

    def compare(batches):
        for held in whole_groups(batches, "bucket"):
            keys, blobs = held.column("bucket").to_numpy(), held.column("packed").to_pylist()
            for b in np.unique(keys).tolist():
                packed = np.frombuffer(b"".join(x for x, k in zip(blobs, keys.tolist(), strict=True) if k == b), dtype=np.uint8).reshape(-1, 2, 6)
                pairs = np.zeros((len(packed), 2, 8), dtype=np.uint8)
                pairs[:, :, :6] = packed
                pairs = pairs.view("<i8").reshape(-1, 2)
                pairs = pairs[np.argsort(pairs[:, 0], kind="stable")]
                heads = np.flatnonzero(np.concatenate([[True], pairs[1:, 0] != pairs[:-1, 0]]))
                apart = np.minimum.reduceat(pairs[:, 1], heads) != np.maximum.reduceat(pairs[:, 1], heads)
                yield pa.RecordBatch.from_arrays([pa.array(pairs[heads[apart], 0])], names=["shingle"])

    packed = nodes.select("node", "prefix").mapInArrow(pack, "bucket int, packed binary")
    shared = packed.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(compare, "shingle bigint")
    held = nodes.sparkSession.sparkContext.broadcast(bit_filter(shared, "shingle"))  # of shingles without their last two bytes

    def pick(batches):
        bits = np.frombuffer(held.value, dtype=np.uint8)
        for batch in batches:
            shingle, row = flat(batch)
            n = batch.column("n").to_numpy()
            keep = within(bits, shingle >> np.uint64(16))
            # The smaller of the m of a node and of the smallest partner it may have.
            keep &= (np.bincount(row[keep], minlength=len(n)) >= shared_least(percent * n // 100))[row]
            place = np.arange(len(row)) - (batch.column("prefix").offsets.to_numpy()[:-1] - batch.column("prefix").offsets.to_numpy()[0])[row]
            # Linked nodes share one of the shingles that lead (m = 1), so the others need not be tried.
            keep &= place < (n - (percent * n + 99) // 100 + 1)[row]
            yield pa.RecordBatch.from_arrays([pa.array(shingle[keep].view(np.int64)), pa.array(batch.column("node").to_numpy()[row[keep]])], names=["shingle", "node"])

    return nodes.mapInArrow(pick, "shingle bigint, node bigint").distinct()


def _full_sets(docs: DataFrame, text: str, width: int, wanted: DataFrame) -> DataFrame:
    """node, n, shingles, signature of the texts whose key is in ``wanted``."""
    held = docs.select(F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("key"), text)
    side = F.broadcast(wanted) if wanted.count() <= BROADCAST_NODES else wanted

    def work(batches):
        seen: set[int] = set()  # of the listed texts only
        for batch in batches:
            for part in slices(batch, text):
                own = {_node(x): x for x in _sets(part, text, width)}
                names = [k for k in own if k not in seen]
                seen.update(names)
                own = [own[k] for k in names]
                yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array([len(x) for x in own], pa.int64()), pa.array([x.tobytes() for x in own], pa.binary()), pa.array([_signature(x) for x in own], pa.binary())], names=["node", "n", "shingles", "signature"])

    return held.join(side, "key", "left_semi").select(text).mapInArrow(work, "node bigint, n bigint, shingles binary, signature binary").dropDuplicates(["node"])


def _linked(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    """Exact: 100 |a and b| >= percent |a or b|, by sorted arrays."""
    small, large = (a, b) if len(a) <= len(b) else (b, a)
    at = np.searchsorted(large, small)
    at[at == len(large)] = len(large) - 1
    both = int(np.count_nonzero(large[at] == small))
    return 100 * both >= percent * (len(a) + len(b) - both)


class _Signatures:
    """Signatures of many rows as one matrix of bytes for each length, and each folded once."""

    def __init__(self, signatures: list[bytes]):
        self.length = np.array([len(x) for x in signatures], dtype=np.int64)
        self.row = np.zeros(len(signatures), dtype=np.int64)
        self.full, self.half = {}, {}
        for size in np.unique(self.length).tolist():
            rows = np.flatnonzero(self.length == size)
            self.row[rows] = np.arange(len(rows))
            self.full[size] = np.frombuffer(b"".join(signatures[r] for r in rows), np.uint8).reshape(-1, size)
            self.half[size] = self.full[size][:, : size // 2] | self.full[size][:, size // 2 :]

    def differing(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Bits in which rows i and j differ; of lengths further apart than a factor of two, none are counted."""
        out = np.zeros(len(i), dtype=np.int64)
        one, two = self.length[i], self.length[j]
        for size in self.full:
            for of, x, y, left, right in ((one == size) & (two == size), self.full, self.full, size, size), ((one == size) & (two == 2 * size), self.full, self.half, size, 2 * size), ((one == 2 * size) & (two == size), self.half, self.full, 2 * size, size):
                at = np.flatnonzero(of)
                for k in range(0, len(at), 1 << 15):
                    part = at[k : k + (1 << 15)]
                    out[part] = np.bitwise_count(x[left][self.row[i[part]]] ^ y[right][self.row[j[part]]]).sum(axis=1)
        return out


def _joined(tile: pa.Table, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Node pairs (a, b) that join the groups of one tile, as many as groups vanish.

    ``tile`` has node, n, group, half, shingles, signature. Rows of one group are connected already;
    where rows of both halves are there, only pairs across them are tried. Each row is compared with
    smaller ones within the band of sizes, first with one row of every group; what the
    signatures allow is decided by intersecting the sorted arrays.
    """
    nodes, sizes = tile.column("node").to_numpy(), tile.column("n").to_numpy()
    order = np.lexsort((nodes, sizes))
    nodes, sizes, group, half = nodes[order], sizes[order], tile.column("group").to_numpy()[order], tile.column("half").to_numpy()[order]
    _, first, group = np.unique(group, return_index=True, return_inverse=True)
    sided = len(half) > 0 and bool((half != half[0]).any())
    signatures, arrays = tile.column("signature").to_pylist(), tile.column("shingles").to_pylist()
    signatures = _Signatures([signatures[k] for k in order])
    arrays = [np.frombuffer(arrays[k], dtype=np.uint64) for k in order]
    lowest = np.searchsorted(sizes, -(-percent * sizes // 100))

    def linked(i: int, j: np.ndarray) -> np.ndarray:
        """Which rows of ``j`` are linked with row ``i``."""
        total = sizes[i] + sizes[j]
        j = j[(100 + percent) * ((total - signatures.differing(np.full(len(j), i), j)) // 2) >= percent * total]
        return j[[_linked(arrays[x], arrays[i], percent) for x in j.tolist()]] if len(j) else j

    for i in range(1, len(nodes)):
        near = np.arange(lowest[i], i)
        if sided:
            near = near[half[near] != half[i]]
        for heads in True, False:
            near = near[group[near] != group[i]]
            if not len(near):
                break
            found = linked(i, near[len(near) - 1 - np.unique(group[near][::-1], return_index=True)[1]] if heads else near)
            found = found[np.unique(group[found], return_index=True)[1]]
            if len(found):
                group[np.isin(group, group[found])] = group[i]
    # A star for each group that came about: a node of every one that is in it now, and the least of those.
    least = np.full(len(first), np.iinfo(np.int64).max)
    np.minimum.at(least, group[first], nodes[first])
    head = least[group[first]]
    return nodes[first][head != nodes[first]], head[head != nodes[first]]


def joined_tiles(rows: DataFrame, percent: int) -> DataFrame:
    """Links (a, b) that connect what is linked within each tile of ``rows`` (tile, node, n, group, half, shingles, signature)."""

    def work(batches):
        for held in whole_groups(batches, "tile"):
            keys = held.column("tile").to_numpy()
            cuts = [0, *(np.flatnonzero(np.diff(keys)) + 1).tolist(), len(keys)]
            for x, y in zip(cuts, cuts[1:], strict=False):
                if y - x > 1:
                    a, b = _joined(held.slice(x, y - x), percent)
                    yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

    return rows.select("tile", "node", "n", "group", "half", "shingles", "signature").repartition("tile").sortWithinPartitions("tile").mapInArrow(work, "a bigint, b bigint")


def _rows_of_use(rows: DataFrame, percent: int) -> DataFrame:
    """(tile, node, n, group, half): of each tile the rows that their signatures allow to be linked with a row of another
    group there, and of the other half where both are there; tiles that are left with the same rows are one.

    Only signatures travel for this, a small part of the sets, which ``joined_tiles`` then needs for few rows.
    """

    def work(batches):
        for held in whole_groups(batches, "tile"):
            tile, node, n, group, half = (held.column(c).to_numpy() for c in ("tile", "node", "n", "group", "half"))
            first = np.concatenate([[True], tile[1:] != tile[:-1]])
            heads = np.flatnonzero(first)
            which = np.cumsum(first) - 1
            sided = (np.minimum.reduceat(half, heads) != np.maximum.reduceat(half, heads))[which]
            behind = np.arange(len(tile)) - heads[which]
            signatures = _Signatures(held.column("signature").to_pylist())
            keep, i, back = np.zeros(len(tile), dtype=bool), np.flatnonzero(behind > 0), 1
            while len(i):
                j = i - back  # sorted by size, so j is not the larger one
                a = i[(100 * n[j] >= percent * n[i]) & (group[i] != group[j]) & (~sided[i] | (half[i] != half[j]))]
                total = n[a] + n[a - back]
                a = a[(100 + percent) * ((total - signatures.differing(a, a - back)) // 2) >= percent * total]
                keep[a] = keep[a - back] = True
                back += 1
                i = i[behind[i] >= back]
            kept = np.flatnonzero(keep)
            with np.errstate(over="ignore"):
                name = mix64(mix64(node[kept].view(np.uint64)) + half[kept].astype(np.uint64))
                sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(name)])
                ends = np.searchsorted(which[kept], np.arange(len(heads) + 1))
                name = mix64(sums[ends[1:]] - sums[ends[:-1]])[which[kept]]
            yield pa.RecordBatch.from_arrays([pa.array(name.view(np.int64)), *(pa.array(x[kept]) for x in (node, n, group, half))], names=["tile", "node", "n", "group", "half"])

    dealt = rows.select("tile", "node", "n", "group", "half", "signature").repartition("tile").sortWithinPartitions("tile", "n")
    return dealt.mapInArrow(work, "tile bigint, node bigint, n bigint, group bigint, half int").distinct()


def _neighbourhoods(live: DataFrame, sizes: DataFrame, tile_bytes: int) -> DataFrame:
    """(label, node, n, bytes, tiles) of nodes that share shingles of ``live`` (shingle, node), directly or through others."""
    first = live.groupBy("shingle").agg(F.min("node").alias("first"))
    label = components(live.join(first, "shingle").select(F.col("node").alias("a"), F.col("first").alias("b")).filter("a <> b"))
    placed = cut(label.join(sizes, "node").withColumn("bytes", F.col("n") * 8 + MOST_BITS // 8))
    tiles = placed.groupBy("label").agg(F.ceil(F.sum("bytes") / tile_bytes).alias("tiles"))
    return cut(placed.join(tiles, "label"))


def _rarest_first(sets: DataFrame, percent: int) -> DataFrame:
    """(shingle, node) of the leading shingles of ``sets`` that others of them hold, too, the rarest first.

    The order has a zone of least hashes ahead, three times as large as the share that leads, and within it
    shingles by the number of sets that hold them: what passages in common contribute comes last and
    drops out. Only the zone is counted; a set that has too little of it goes on by hash.
    """
    bound = np.uint64(min((1 << 64) - 1, 3 * (100 - percent) * (1 << 64) // 100))

    def flat(batches):
        for batch in batches:
            for node, n, packed in zip(*(batch.column(c).to_pylist() for c in ("node", "n", "shingles")), strict=True):
                own = np.frombuffer(packed, dtype=np.uint64)
                zone, leads = int(np.searchsorted(own, bound)), n - (percent * n + 99) // 100 + 1
                own = own[: max(zone, leads)]
                yield pa.RecordBatch.from_arrays([pa.array(own.view(np.int64)), pa.array(np.full(len(own), node)), pa.array(np.full(len(own), leads - zone, np.int32)), pa.array(own >= bound)], names=["shingle", "node", "spare", "beyond"])

    rows = sets.select("node", "n", "shingles").mapInArrow(flat, "shingle bigint, node bigint, spare int, beyond boolean")
    often = rows.groupBy("shingle").agg(F.count("*").alias("often")).filter("often > 1")
    mine = Window.partitionBy("node")
    # Shingles that a node has alone come before all others, so that they only use up places.
    rank = F.row_number().over(mine.orderBy("beyond", "often", "shingle"))
    return rows.join(often, "shingle").withColumns({"rank": rank, "held": F.count("*").over(mine)}).filter("rank <= spare + held").select("shingle", "node")


def _links(sets: DataFrame, percent: int, tile_bytes: int) -> DataFrame:
    """Links (a, b) whose components are those of all linked nodes.

    Nodes that share leading shingles, directly or by way of others, are a neighbourhood. One of up to
    ``tile_bytes`` is a tile. A larger one is dealt to several tiles, and an eighth of a tile of
    its nodes goes to all of them, which connects a large group of near copies in one pass; nodes with the same
    shingle of least hash meet, too, which connects most small groups. After
    that each shingle that still holds several groups is taken by itself: nodes of its largest group
    meet all others but not each other, in pairs of tiles where they are too many for one. Sets go there only
    for nodes that by their signatures may be linked, and once for all shingles that the same nodes share.
    """
    shipped = lambda rows: rows.join(sets.drop("n"), "node")
    alone = F.lit(0).alias("half")
    live = cut(_rarest_first(sets, percent))
    placed = _neighbourhoods(live, sets.select("node", "n"), tile_bytes)
    whole = placed.filter("tiles = 1").select(F.col("label").alias("tile"), "node", "n", F.col("node").alias("group"), alone)
    links = [cut(joined_tiles(shipped(whole), percent))]
    large = placed.filter("tiles > 1")
    if large.isEmpty():
        return links[0]
    own = F.pmod(F.xxhash64("node", F.lit(5)), "tiles")
    everywhere = F.pmod(F.xxhash64("node", F.lit(6)), F.col("tiles") * 8) == 0
    dealt = large.withColumn("own", F.explode(F.when(everywhere, F.sequence(F.lit(0).cast("bigint"), F.col("tiles") - 1)).otherwise(F.array(own))))
    links.append(cut(joined_tiles(shipped(dealt.select(F.xxhash64("label", "own").alias("tile"), "node", "n", F.col("node").alias("group"), alone)), percent)))
    least = live.join(large.select("node", "n", "bytes"), "node").groupBy("node", "n", "bytes").agg(F.min(F.xxhash64("shingle", F.lit(8))).alias("tile"))
    meeting = least.groupBy("tile").agg(F.count("*").alias("nodes"), F.sum("bytes").alias("all")).filter(f"nodes > 1 AND all <= {tile_bytes}").select("tile")
    links.append(cut(joined_tiles(shipped(least.join(meeting, "tile").select("tile", "node", "n", F.col("node").alias("group"), alone)), percent)))
    group = components(links[-2].unionByName(links[-1])).select(F.col("node").alias("__n"), F.col("label").alias("__g"))
    rows = live.join(large.select("node", "n", "bytes"), "node").join(group, F.col("node") == F.col("__n"), "left")
    rows = rows.select("shingle", "node", "n", "bytes", F.coalesce("__g", "node").alias("group"))
    parts = rows.groupBy("shingle", "group").agg(F.sum("bytes").alias("bytes"))
    mixed = parts.groupBy("shingle").agg(F.max(F.struct("bytes", "group")).alias("most"), F.sum("bytes").alias("all"), F.count("*").alias("groups")).filter("groups > 1")
    inside, one = F.col("most")["bytes"], F.col("all") <= tile_bytes
    mixed = mixed.select("shingle", F.col("most")["group"].alias("main"), *(F.when(one, few).otherwise(F.ceil(size * 2 / tile_bytes)).alias(c) for c, size, few in (("ins", inside, 0), ("outs", F.col("all") - inside, 1))))
    rows = cut(rows.join(mixed, "shingle"))
    within_main = (F.col("group") == F.col("main")) & (F.col("ins") > 0)
    place = F.xxhash64("node", F.lit(7))
    number = F.when(within_main, F.col("outs") + F.pmod(place, F.greatest("ins", F.lit(1)))).otherwise(F.pmod(place, F.col("outs")))
    last = F.when(within_main, F.col("outs")).otherwise(F.col("outs") + F.col("ins")) - 1
    rows = rows.withColumn("own", number).withColumn("other", F.explode(F.sequence(F.lit(0).cast("bigint"), last)))
    tile = F.xxhash64("shingle", F.least("own", "other"), F.greatest("own", "other"))
    pairs = rows.select(tile.alias("tile"), "node", "n", "group", (F.col("own") > F.col("other")).cast("int").alias("half"))
    near = cut(_rows_of_use(pairs.join(sets.select("node", "signature"), "node"), percent))
    links.append(cut(joined_tiles(shipped(near), percent)))
    release(near)
    return reduce(DataFrame.unionByName, links)


@keeping
def similar_groups(docs: DataFrame, keep: list[str], text: str = "text", width: int = WIDTH, percent: int = PERCENT, tile_bytes: int = TILE_BYTES) -> DataFrame:
    """``keep``, n_shingles and ``group``: documents with one group are connected by links.

    Null and empty texts have no shingles, are linked with nothing and have a null group;
    a text of fewer words than ``width`` is one shingle; repeated rows share a group; an
    empty table gives no rows; very long texts count whole, alone in their slice. Ties of any kind do not matter, as links are
    exact. A kept column that has the name of a result comes back with ``_in`` added.
    """
    often = frequent_shingles(docs, text, width)
    sketched = cut(sketches(docs, keep, text, width, percent, often))
    heads = cut(_shared_heads(sketched.filter("n_shingles > 0").select("node", F.col("n_shingles").alias("n"), "prefix"), percent))
    sketched, before = cut(sketched.drop("prefix")), sketched
    release(before)
    met = heads.groupBy("shingle").agg(F.min("node").alias("x"), F.max("node").alias("y")).filter("x < y").select("shingle")
    meeting = heads.join(met, "shingle", "left_semi").select("node").distinct()
    wanted = cut(sketched.join(meeting, "node", "left_semi").groupBy("node").agg(F.min("key").alias("key")).select("key"))
    release(heads)
    sets = cut(_full_sets(docs, text, width, wanted))
    label = components(_links(sets, percent, tile_bytes)).select(F.col("node").alias("__n"), F.col("label").alias("__g"))
    release(wanted, sets)
    out = sketched.join(label, F.col("node") == F.col("__n"), "left")
    return out.select(*keep, "n_shingles", F.when(F.col("n_shingles") > 0, F.coalesce("__g", "node")).alias("group"))


def op9_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shingle counts and components of all documents."""
    found = cut(similar_groups(table(spark, sf_dir, "documents"), ["doc_id"]))
    least = found.filter(F.col("group").isNotNull()).groupBy("group").agg(F.min("doc_id").alias("component_id")).withColumnRenamed("group", "__g")
    return found.join(least, F.col("group") == F.col("__g"), "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def one_of_each_group(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", width: int = WIDTH, percent: int = PERCENT) -> DataFrame:
    """The documents without all but one of each group: the one of smallest id stays.

    Rows with that id in one group are reduced to one, too (by their text's hash, then any
    of equal rows); rows of a group without any id are reduced to one. Documents without
    shingles all stay. Only the list of what goes is joined to the documents.
    """
    key = F.xxhash64(F.coalesce(F.col(text), F.lit("")))
    found = cut(similar_groups(docs.select(F.col(doc_id).alias("__id"), key.alias("__k"), F.col(text).alias("__t")), ["__id", "__k"], "__t", width, percent).filter(F.col("group").isNotNull()).groupBy("group", "__id", "__k").agg(F.count("*").alias("rows")))
    best = found.groupBy("group").agg(F.min(F.struct(F.col("__id").isNull().alias("none"), "__id", "__k")).alias("best"), F.sum("rows").alias("all")).filter("all > 1").withColumnRenamed("group", "__g")
    judged = found.join(best, F.col("group") == F.col("__g"))
    stays = F.col("__id").eqNullSafe(F.col("best").getField("__id")) & (F.col("__k") == F.col("best").getField("__k"))
    listed = cut(judged.select(F.col("__id").alias("__i"), F.col("__k").alias("__kk"), stays.alias("__stays"), "rows").filter("NOT __stays OR rows > 1"))
    side = F.broadcast(listed) if listed.count() <= BROADCAST_NODES else listed
    marked = docs.withColumn("__k", key).join(side.drop("rows"), F.col(doc_id).eqNullSafe(F.col("__i")) & (F.col("__k") == F.col("__kk")), "left")
    single = marked.filter(F.col("__stays").isNull()).select(*docs.columns)
    if listed.filter("__stays").isEmpty():
        return single
    repeated = marked.filter("__stays").dropDuplicates(["__i", "__kk"]).select(*docs.columns)
    return single.unionByName(repeated)


OP9_SQL = r"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[i : i + 3], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 2)) AS i FROM d WHERE len(w) >= 4)
    UNION SELECT doc_id, array_to_string(w, ' ') FROM d WHERE len(w) BETWEEN 1 AND 3),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
l AS (SELECT x, y FROM p JOIN n nx ON nx.doc_id = x JOIN n ny ON ny.doc_id = y WHERE 100 * c >= 85 * (nx.n + ny.n - c)),
e AS (SELECT x, y FROM l UNION ALL SELECT y, x FROM l),
r AS (SELECT x AS node, x AS root FROM e UNION SELECT e.y, r.root FROM r JOIN e ON e.x = r.node),
m AS (SELECT node, min(root) AS root FROM r GROUP BY node)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, coalesce(m.root, d.doc_id) AS component_id FROM d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN m ON m.node = d.doc_id
"""
