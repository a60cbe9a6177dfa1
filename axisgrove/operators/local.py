"""A kd-tree over one block of points, in preorder arrays. numpy only.

Node i has its left child at i + 1 and its right child behind the left subtree, which
has ``skip`` nodes; the points of a subtree are a contiguous run. So untouched subtrees
are copied as slices when an update assembles a new tree.
"""

from __future__ import annotations

import pickle
from dataclasses import dataclass

import numpy as np

from axisgrove.model import TreeParams, is_balanced


def point_hash(ids: np.ndarray, seed: int) -> np.ndarray:
    """Order of sampling: a fixed scrambling of the ids."""
    with np.errstate(over="ignore"):
        x = ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed) * np.uint64(0xD1342543DE82EF95)
        x ^= x >> np.uint64(29)
        x *= np.uint64(0xBF58476D1CE4E5B9)
        return x ^ (x >> np.uint64(32))


#: Blocks of so many points are split level by level; smaller and larger ones node by node.
TOGETHER = 256, 1 << 16
#: Boxes are counted by bit sets in subtrees of at most so many points that so many boxes cut.
BITS, MANY_BOXES = 4096, 24
#: Queries and at most so many points below a node are compared as one block where that is so many coordinates for each node it saves.
BLOCK = 4096, 1 << 16


def choose_split(points: np.ndarray, depth: int, rule: str) -> tuple[int, float] | None:
    """Dimension and value such that some points are strictly smaller and some are not; None if all points agree.

    The value is the median of the dimension, or the next distinct one where no point is smaller.
    """
    low, high = points.min(axis=0), points.max(axis=0)
    extent = high - low
    if not extent.max() > 0:
        return None
    d = points.shape[1]
    if rule == "cycle":
        order = [(depth + j) % d for j in range(d)]
    else:
        order = [int(np.argmax(extent))]
    for dim in order:
        if extent[dim] > 0:
            column = points[:, dim]
            value = np.partition(column, len(column) // 2)[len(column) // 2]
            if value == low[dim]:
                value = column[column > value].min()
            return dim, float(value)
    return None


@dataclass
class Counters:
    """Points moved by splitting or sieving, rounds over the whole block, points in rebuilt subtrees."""

    moved: int = 0
    rounds: int = 0
    rebuilt: int = 0


class _Assembly:
    """Pieces of a tree in preorder."""

    def __init__(self, d: int):
        self.nodes: list[list] = [[], [], [], []]
        self.points, self.ids, self.d = [], [], d

    def leaf(self, points, ids) -> tuple[int, int]:
        for column, v in zip(self.nodes, (-1, 0.0, len(ids), 1), strict=True):
            column.append(v)
        self.points.append(points)
        self.ids.append(ids)
        return len(ids), 1

    def interior(self, dim: int, value: float) -> int:
        for column, v in zip(self.nodes, (dim, value, 0, 0), strict=True):
            column.append(v)
        return len(self.nodes[0]) - 1

    def copy(self, tree: LocalTree, node: int, start: int) -> tuple[int, int]:
        stop = node + int(tree.skip[node])
        for column, source in zip(self.nodes, (tree.dim, tree.val, tree.size, tree.skip), strict=True):
            column.extend(source[node:stop].tolist())
        n = int(tree.size[node])
        self.points.append(tree.points[start : start + n])
        self.ids.append(tree.ids[start : start + n])
        return n, stop - node

    def close(self, at: int, *children: tuple[int, int]) -> tuple[int, int]:
        size, skip = sum(c[0] for c in children), 1 + sum(c[1] for c in children)
        self.nodes[2][at], self.nodes[3][at] = size, skip
        return size, skip

    def done(self, params: TreeParams) -> LocalTree:
        points = np.concatenate(self.points) if self.points else np.zeros((0, self.d))
        ids = np.concatenate(self.ids) if self.ids else np.zeros(0, np.int64)
        dim, val, size, skip = self.nodes
        return LocalTree(points.reshape(-1, self.d), ids, np.array(dim, np.int16), np.array(val, float), np.array(size, np.int64), np.array(skip, np.int64), params.store_boxes)


def descend(dim: np.ndarray, val: np.ndarray, left: np.ndarray, right: np.ndarray, points: np.ndarray) -> np.ndarray:
    """Node without children that each point comes to; strictly smaller goes left."""
    at = np.zeros(len(points), dtype=np.int64)
    rows = np.arange(len(points))
    while True:
        inner = dim[at] >= 0
        if not inner.any():
            return at
        r, a = rows[inner], at[inner]
        at[inner] = np.where(points[r, dim[a]] < val[a], left[a], right[a])


def count_boxes(points: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """How many points lie in each closed box (low <= high). For every dimension there is a set of bits for
    the points below each distinct value; a box is the meet, over dimensions, of what two of these differ in."""
    n, d = points.shape
    words, at = -(-n // 64), np.arange(n)
    bit = np.uint64(1) << (at % 64).astype(np.uint64)
    tables = []
    for j in range(d):
        value, place = np.unique(points[:, j], return_inverse=True)
        below = np.zeros((len(value) + 1, words), np.uint64)
        key = (place + 1) * words + at // 64
        order = np.argsort(key, kind="stable")
        head = np.flatnonzero(np.diff(key[order], prepend=-1))
        below.ravel()[key[order][head]] = np.bitwise_or.reduceat(bit[order], head)
        np.bitwise_or.accumulate(below, axis=0, out=below)
        tables.append((below, np.searchsorted(value, low[:, j], "left"), np.searchsorted(value, high[:, j], "right")))
    counts = np.zeros(len(low), np.int64)
    one, two = np.empty((2, 128, words), np.uint64)
    for c in range(0, len(low), 128):
        held = None
        for below, a, b in tables:
            a, b = a[c : c + 128], b[c : c + 128]
            cuts = np.flatnonzero((a > 0) | (b < len(below) - 1))
            if not len(cuts):
                continue
            if held is None:
                held = np.repeat(below[-1:], len(a), axis=0)
            every = 2 * len(cuts) > len(a)
            a, b = (a, b) if every else (a[cuts], b[cuts])
            x, y = np.take(below, a, 0, one[: len(a)], "clip"), np.take(below, b, 0, two[: len(a)], "clip")
            np.bitwise_xor(x, y, x)
            if every:
                held &= x
            else:
                held[cuts] &= x
        counts[c : c + 128] = n if held is None else np.bitwise_count(held).sum(axis=1)
    return counts


def merge_nearest(best: np.ndarray, who: np.ndarray, rows: np.ndarray, dist: np.ndarray, ids: np.ndarray) -> None:
    """Takes candidates (row, distance, id) into the k best of their rows."""
    k, touched = best.shape[1], np.unique(rows)
    rows = np.concatenate([np.repeat(touched, k), rows])
    dist, ids = np.concatenate([best[touched].ravel(), dist]), np.concatenate([who[touched].ravel(), ids])
    order = np.lexsort((ids, dist, rows))
    rows = rows[order]
    place = np.arange(len(rows)) - np.searchsorted(rows, rows)
    order, rows, place = order[place < k], rows[place < k], place[place < k]
    best[rows, place], who[rows, place] = dist[order], ids[order]


class LocalTree:
    def __init__(self, points, ids, dim, val, size, skip, boxes: bool = False):
        self.points, self.ids, self.dim, self.val, self.size, self.skip = points, ids, dim, val, size, skip
        #: Whether every node has a tight box; boxes are fitted when they are first asked for.
        self.boxes, self._box_low, self._box_high = boxes, None, None

    @property
    def box_low(self) -> np.ndarray | None:
        if self.boxes and self._box_low is None:
            self.fit_boxes()
        return self._box_low

    @property
    def box_high(self) -> np.ndarray | None:
        return None if self.box_low is None else self._box_high

    # --- making -----------------------------------------------------------------

    @classmethod
    def grow(cls, points: np.ndarray, ids: np.ndarray, params: TreeParams, counters: Counters | None = None, depth: int = 0) -> LocalTree:
        points = np.ascontiguousarray(points, dtype=float)
        out = _Assembly(points.shape[1])
        if len(ids):
            _grow(out, points, np.asarray(ids, np.int64), params, counters or Counters(), depth)
        return out.done(params)

    def fit_boxes(self) -> None:
        """Tight boxes, from leaves upward, a level at a time."""
        n, d = len(self.dim), self.points.shape[1]
        self._box_low, self._box_high = np.full((n, d), np.inf), np.full((n, d), -np.inf)
        start, depth = self.starts(), self.depths()
        full = np.flatnonzero((self.dim < 0) & (self.size > 0))
        if len(full):
            self._box_low[full] = np.minimum.reduceat(self.points, start[full], axis=0)
            self._box_high[full] = np.maximum.reduceat(self.points, start[full], axis=0)
        inner = np.flatnonzero(self.dim >= 0)
        inner = inner[np.argsort(depth[inner], kind="stable")]
        edges = np.searchsorted(depth[inner], np.arange(depth[inner[-1]] + 2)) if len(inner) else []
        for a, b in reversed(list(zip(edges, edges[1:], strict=False))):
            at = inner[a:b]
            left, right = at + 1, at + 1 + self.skip[at + 1]
            self._box_low[at] = np.minimum(self._box_low[left], self._box_low[right])
            self._box_high[at] = np.maximum(self._box_high[left], self._box_high[right])

    def starts(self) -> np.ndarray:
        """First point of every node."""
        leaf = self.dim < 0
        ahead = np.concatenate([[0], np.cumsum(np.where(leaf, self.size, 0))[:-1]]) if len(leaf) else np.zeros(0, np.int64)
        return ahead

    def right(self, i: int) -> int:
        return int(i + 1 + self.skip[i + 1])

    def depths(self) -> np.ndarray:
        out = [0] * len(self.dim)
        skip = self.skip.tolist()
        for i in np.flatnonzero(self.dim >= 0).tolist():
            out[i + 1] = out[i + 1 + skip[i + 1]] = out[i] + 1
        return np.array(out, np.int64)

    def pack(self) -> bytes:
        return pickle.dumps((self.points.shape, self.points.astype(float).tobytes(), self.ids.astype(np.int64).tobytes(), self.dim.tobytes(), self.val.tobytes(), self.size.tobytes(), self.skip.tobytes(), self.boxes), protocol=5)

    @classmethod
    def unpack(cls, blob: bytes) -> LocalTree:
        shape, points, ids, dim, val, size, skip, boxes = pickle.loads(blob)
        return cls(np.frombuffer(points, float).reshape(shape), np.frombuffer(ids, np.int64), np.frombuffer(dim, np.int16), np.frombuffer(val, float), np.frombuffer(size, np.int64), np.frombuffer(skip, np.int64), boxes)

    # --- updates ----------------------------------------------------------------

    def insert(self, points: np.ndarray, ids: np.ndarray, params: TreeParams, counters: Counters | None = None) -> LocalTree:
        """The tree with more points; only the topmost nodes that would be out of balance are rebuilt."""
        counters = counters or Counters()
        if not len(ids):
            return self
        if not len(self.dim):
            counters.rebuilt += len(ids)
            return LocalTree.grow(points, ids, params, counters)
        start = self.starts()
        out = _Assembly(self.points.shape[1])

        def walk(i: int, more: np.ndarray, depth: int) -> tuple[int, int]:
            if not len(more):
                return out.copy(self, i, int(start[i]))
            n = int(self.size[i])
            smaller = None
            if self.dim[i] >= 0:
                smaller = points[more, self.dim[i]] < self.val[i]
                a, b = i + 1, self.right(i)
                sizes = int(self.size[a]) + int(smaller.sum()), int(self.size[b]) + int((~smaller).sum())
            if smaller is None or not is_balanced(*sizes, params.alpha):
                own = slice(int(start[i]), int(start[i]) + n)
                counters.rebuilt += (n + len(more)) * (smaller is not None)  # a leaf is always made anew
                return _grow(out, np.concatenate([self.points[own], points[more]]), np.concatenate([self.ids[own], ids[more]]), params, counters, depth)
            at = out.interior(int(self.dim[i]), float(self.val[i]))
            one = walk(a, more[smaller], depth + 1)
            return out.close(at, one, walk(b, more[~smaller], depth + 1))

        walk(0, np.arange(len(ids)), 0)
        return out.done(params)

    def delete(self, gone: np.ndarray, params: TreeParams, counters: Counters | None = None, rebalance: bool = True) -> LocalTree:
        """The tree without the points marked in ``gone`` (in leaf order)."""
        counters = counters or Counters()
        if not gone.any():
            return self
        start = self.starts()
        before = np.concatenate([[0], np.cumsum(gone)])
        out = _Assembly(self.points.shape[1])
        lost = lambda i: int(before[start[i] + self.size[i]] - before[start[i]])

        def walk(i: int, depth: int) -> tuple[int, int]:
            n, less = int(self.size[i]), lost(i)
            if not less:
                return out.copy(self, i, int(start[i]))
            own = np.arange(start[i], start[i] + n)
            own = own[~gone[own]]
            if self.dim[i] < 0 or len(own) <= params.leaf_capacity and rebalance:
                return out.leaf(self.points[own], self.ids[own])
            a, b = i + 1, self.right(i)
            left, right = int(self.size[a]) - lost(a), int(self.size[b]) - lost(b)
            if rebalance and not left:
                return walk(b, depth)
            if rebalance and not right:
                return walk(a, depth)
            if rebalance and not is_balanced(left, right, params.alpha):
                counters.rebuilt += len(own)
                return _grow(out, self.points[own], self.ids[own], params, counters, depth)
            at = out.interior(int(self.dim[i]), float(self.val[i]))
            one = walk(a, depth + 1)
            return out.close(at, one, walk(b, depth + 1))

        if not gone.all():
            walk(0, 0)
        return out.done(params)

    def match(self, ids: np.ndarray | None, points: np.ndarray, every_copy: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """(marks of the points that requests take, marks of the requests that find one).

        With ids a point is taken when id and coordinates agree; without, a request takes one
        copy of its coordinates, of smallest id first, or every copy.
        """
        gone, found = np.zeros(len(self.ids), bool), np.zeros(len(points), bool)
        held: dict = {}
        order = np.argsort(self.ids, kind="stable")
        if ids is not None:
            order = order[np.isin(self.ids[order], ids)]
        for j in order.tolist():
            key = self.points[j].tobytes() if ids is None else (int(self.ids[j]), self.points[j].tobytes())
            held.setdefault(key, []).append(j)
        for key in held:
            held[key].reverse()
        taken: set = set()
        for r in range(len(points)):
            key = np.ascontiguousarray(points[r], dtype=float).tobytes()
            key = key if ids is None else (int(ids[r]), key)
            left = held.get(key)
            if left:
                found[r] = True
                if every_copy:
                    gone[left] = True
                    held[key] = []
                    taken.add(key)
                else:
                    gone[left.pop()] = True
            elif key in taken:
                found[r] = True
        return gone, found

    # --- queries ----------------------------------------------------------------

    def knn(self, queries: np.ndarray, k: int, bound: np.ndarray | None = None, visits: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(squared distances, ids) of the k nearest points of each query by (distance, id); inf and -1 where there are fewer.

        ``bound``: points farther than it are of no use. Queries walk the tree together: each
        goes first to the side it lies on, and to the other while that may hold a nearer point. Where
        few are left for a subtree they are compared with all its points at once.
        """
        m, d = queries.shape
        best, who = np.full((m, k), np.inf), np.full((m, k), -1, dtype=np.int64)
        limit = np.full(m, np.inf) if bound is None else np.asarray(bound, float).copy()
        if not len(self.dim) or not m:
            return best, who
        start = self.starts()

        def leaf(i: int, q: np.ndarray) -> None:
            own = slice(int(start[i]), int(start[i] + self.size[i]))
            points, ids = self.points[own], self.ids[own]
            if len(ids) > max(k, 64) and (points == points[0]).all():  # one place: those of least id come first
                least = np.argpartition(ids, k - 1)[:k]
                points, ids = points[least], ids[least]
            for a in range(0, len(ids), 2048):
                some = points[a : a + 2048]
                for c in range(0, len(q), max(1, (1 << 20) // max(1, len(some)))):
                    part = q[c : c + max(1, (1 << 20) // max(1, len(some)))]
                    dist = np.zeros((len(part), len(some)))
                    for j in range(d):
                        gap = queries[part, j][:, None] - some[None, :, j]
                        dist += gap * gap
                    better = (dist <= limit[part][:, None]).any(axis=1)
                    if not better.all():
                        part, dist = part[better], dist[better]
                        if not len(part):
                            continue
                    dist = np.concatenate([best[part], np.where(dist <= limit[part][:, None], dist, np.inf)], axis=1)
                    names = np.concatenate([who[part], np.broadcast_to(ids[a : a + 2048], (len(part), len(some)))], axis=1)
                    names = np.where(np.isinf(dist), np.iinfo(np.int64).max, names)
                    by_name = np.argsort(names, axis=1, kind="stable")
                    dist, names = np.take_along_axis(dist, by_name, 1), np.take_along_axis(names, by_name, 1)
                    near = np.argsort(dist, axis=1, kind="stable")[:, :k]
                    best[part], who[part] = np.take_along_axis(dist, near, 1), np.take_along_axis(names, near, 1)
                    limit[part] = np.minimum(limit[part], best[part, k - 1])

        def block(i: int, q: np.ndarray) -> None:
            own = slice(int(start[i]), int(start[i] + self.size[i]))
            ids, columns = self.ids[own], [np.ascontiguousarray(self.points[own, j]) for j in range(d)]
            step = max(1, (1 << 18) // len(ids))
            for c in range(0, len(q), step):
                part = q[c : c + step]
                dist = np.zeros((len(part), len(ids)))
                for j in range(d):
                    gap = queries[part, j][:, None] - columns[j][None, :]
                    gap *= gap
                    dist += gap
                hit = dist <= limit[part][:, None]
                many = np.flatnonzero(hit.sum(axis=1) > 4 * k)
                if len(many) and len(ids) > k:
                    hit[many] &= dist[many] <= np.partition(dist[many], k - 1, axis=1)[:, k - 1 : k]
                rows, place = np.nonzero(hit)
                if len(rows):
                    near, names = best[part], who[part]
                    merge_nearest(near, names, rows, dist[rows, place], ids[place])
                    best[part], who[part] = near, names
                    limit[part] = np.minimum(limit[part], near[:, k - 1])

        def far(off: np.ndarray) -> np.ndarray:
            total = np.zeros(len(off))
            for j in range(d):
                total += off[:, j] * off[:, j]
            return total

        def gap_to_box(i: int, q: np.ndarray) -> np.ndarray:
            return np.maximum(np.maximum(self.box_low[i] - queries[q], queries[q] - self.box_high[i]), 0.0)

        stack = [(0, np.arange(m), np.zeros((m, d)))]
        while stack:
            i, q, off = stack.pop()
            if visits is None and self.dim[i] >= 0 and self.size[i] <= BLOCK[0] and len(q) * int(self.size[i]) * d <= BLOCK[1] * int(self.skip[i]):
                q = q[far(off) <= limit[q]]
                if len(q):
                    block(i, q)
                continue
            keep = far(off if self.box_low is None else gap_to_box(i, q)) <= limit[q]
            q, off = q[keep], off[keep]
            if not len(q):
                continue
            if visits is not None:
                visits[q, 0 if self.dim[i] < 0 else 1] += 1
            if self.dim[i] < 0:
                leaf(i, q)
                continue
            dim, val = int(self.dim[i]), float(self.val[i])
            x = queries[q, dim]
            lower = x < val
            for side, near, other in ((lower, i + 1, self.right(i)), (~lower, self.right(i), i + 1)):
                if side.any():
                    away = off[side].copy()
                    away[:, dim] = np.maximum(away[:, dim], np.abs(val - x[side]))
                    stack.append((other, q[side], away))
                    stack.append((near, q[side], off[side]))
        who = np.where(np.isinf(best), -1, who)
        return best, who

    def ranges(self, low: np.ndarray, high: np.ndarray, report: bool, visits: np.ndarray | None = None):
        """Counts of the points in each closed box, or (box, point number) pairs."""
        m, d = low.shape
        counts, boxes, found = np.zeros(m, np.int64), [], []
        if not len(self.dim) or not m:
            return (np.zeros(0, np.int64), np.zeros(0, np.int64)) if report else counts
        start = self.starts()

        def whole(i: int, q: np.ndarray) -> None:
            n = int(self.size[i])
            counts[q] += n
            if report and n:
                boxes.append(np.repeat(q, n))
                found.append(np.tile(np.arange(start[i], start[i] + n), len(q)))

        stack = [(0, np.arange(m)[(low <= high).all(axis=1)], np.full(d, -np.inf), np.full(d, np.inf))]
        while stack:
            i, q, a, b = stack.pop()
            if self.box_low is not None:
                a, b = self.box_low[i], self.box_high[i]
                apart = ((b < low[q]) | (a > high[q])).any(axis=1)
            else:  # the space of a left child ends before b
                apart = ((b <= low[q]) | (a > high[q])).any(axis=1) if i else np.zeros(len(q), bool)
            q = q[~apart]
            if not len(q):
                continue
            if visits is not None:
                visits[q, 0 if self.dim[i] < 0 else 1] += 1
            inside = ((low[q] <= a) & (b <= high[q])).all(axis=1)
            if inside.any():
                whole(i, q[inside])
            q = q[~inside]
            if not len(q):
                continue
            if not report and visits is None and self.size[i] <= BITS and len(q) >= MANY_BOXES:
                counts[q] += count_boxes(self.points[start[i] : start[i] + self.size[i]], low[q], high[q])
                continue
            if self.dim[i] < 0:
                points = self.points[start[i] : start[i] + self.size[i]]
                for c in range(0, len(q), 4096):
                    part = q[c : c + 4096]
                    hit = np.ones((len(part), len(points)), bool)
                    for j in range(d):
                        hit &= (points[None, :, j] >= low[part, j][:, None]) & (points[None, :, j] <= high[part, j][:, None])
                    counts[part] += hit.sum(axis=1)
                    if report:
                        one, two = np.nonzero(hit)
                        boxes.append(part[one])
                        found.append(two + start[i])
                continue
            dim, val = int(self.dim[i]), float(self.val[i])
            upper, lower = b.copy(), a.copy()
            upper[dim], lower[dim] = min(b[dim], val), max(a[dim], val)
            stack.append((self.right(i), q, lower, b))
            stack.append((i + 1, q, a, upper))
        if report:
            none = [np.zeros(0, np.int64)]
            return np.concatenate(boxes or none), np.concatenate(found or none)
        return counts

    def delete_one_by_one(self, ids: np.ndarray | None, points: np.ndarray, params: TreeParams) -> tuple[LocalTree, np.ndarray, int]:
        """Requests served one at a time by descent to the leaf, without rebalancing: the tree, marks
        of the requests that found a point, and how many nodes were passed."""
        start, gone = self.starts(), np.zeros(len(self.ids), bool)
        found, passed = np.zeros(len(points), bool), 0
        for r in range(len(points) if len(self.dim) else 0):
            i = 0
            while self.dim[i] >= 0:
                i = i + 1 if points[r, self.dim[i]] < self.val[i] else self.right(i)
                passed += 1
            own = slice(start[i], start[i] + self.size[i])
            hit = start[i] + np.flatnonzero(~gone[own] if ids is None else ~gone[own] & (self.ids[own] == ids[r]))
            hit = hit[(self.points[hit] == points[r]).all(axis=1)]
            if len(hit):
                gone[hit[np.argmin(self.ids[hit])]] = True
                found[r] = True
        return self.delete(gone, params, rebalance=False), found, passed


def _grow(out: _Assembly, points: np.ndarray, ids: np.ndarray, params: TreeParams, counters: Counters, depth: int) -> tuple[int, int]:
    """Appends the tree of some points: several levels at a time from samples while there are
    many points, then level by level at medians."""
    n = len(ids)
    if n <= params.leaf_capacity:
        return out.leaf(points, ids)
    if params.sampler == "hash" and n >= params.base_cutoff and params.levels > 0:
        picked = np.argsort(point_hash(ids, params.seed), kind="stable")[: params.base_cutoff]
        skeleton = Skeleton.from_sample(points[picked], params.levels, params.split_rule, depth)
        if skeleton is not None:
            bucket = skeleton.locate(points)
            order = np.argsort(bucket, kind="stable")
            counters.moved += n
            counters.rounds += 1
            cuts = np.searchsorted(bucket[order], np.arange(skeleton.buckets + 1))

            def attach(k: int, level: int) -> tuple[int, int]:
                if skeleton.dim[k] < 0:
                    b = int(skeleton.bucket[k])
                    own = order[cuts[b] : cuts[b + 1]]
                    if len(own) == n:
                        return _grow(out, points[own], ids[own], params.but(sampler="exact"), counters, level)
                    return _grow(out, points[own], ids[own], params, counters, level)
                one, two = int(skeleton.left[k]), int(skeleton.right[k])
                left, right = skeleton.weight(one, cuts), skeleton.weight(two, cuts)
                if not is_balanced(left, right, params.alpha) and left + right > params.leaf_capacity:
                    # The sample missed: this subtree is split at true medians.
                    own = order[np.isin(bucket[order], skeleton.below(k))]
                    return _grow(out, points[own], ids[own], params.but(sampler="exact"), counters, level)
                at = out.interior(int(skeleton.dim[k]), float(skeleton.val[k]))
                a = attach(one, level + 1)
                return out.close(at, a, attach(two, level + 1))

            return attach(0, depth)
    if TOGETHER[0] <= n <= TOGETHER[1] and (params.sampler == "exact" or n < params.base_cutoff):
        return _grow_levels(out, points, ids, params, counters, depth)
    split = choose_split(points, depth, params.split_rule)
    if split is None:
        return out.leaf(points, ids)
    counters.moved += n
    if depth == 0 or params.sampler == "exact":
        counters.rounds += depth == 0
    smaller = points[:, split[0]] < split[1]
    at = out.interior(*split)
    one = _grow(out, points[smaller], ids[smaller], params, counters, depth + 1)
    return out.close(at, one, _grow(out, points[~smaller], ids[~smaller], params, counters, depth + 1))


def _grow_levels(out: _Assembly, points: np.ndarray, ids: np.ndarray, params: TreeParams, counters: Counters, depth: int) -> tuple[int, int]:
    """The same tree of medians as node by node, all nodes of a level at once."""
    n, d = points.shape
    dims, values, lefts, runs = [-1], [0.0], [-1], [(0, n)]
    order = np.arange(n)  # points in the order of their leaves
    alive = np.array([0])
    level = depth
    while len(alive):
        alive = alive[[runs[k][1] - runs[k][0] > params.leaf_capacity for k in alive.tolist()]]
        if not len(alive):
            break
        start, stop = np.array([runs[k] for k in alive.tolist()]).T
        many = stop - start
        edge = np.concatenate([[0], np.cumsum(many)[:-1]])
        place = np.repeat(start - edge, many) + np.arange(int(many.sum()))
        own = order[place]
        here = points[own]
        low, high = np.minimum.reduceat(here, edge, axis=0), np.maximum.reduceat(here, edge, axis=0)
        extent = high - low
        if params.split_rule == "cycle":
            turn = (level + np.arange(d)) % d
            dim = turn[np.argmax(extent[:, turn] > 0, axis=1)]
        else:
            dim = np.argmax(extent, axis=1)
        nodes = np.repeat(np.arange(len(alive)), many)
        x = here[np.arange(len(here)), dim[nodes]]
        ordered = x[np.lexsort((x, nodes))]
        value = ordered[edge + many // 2]
        least = low[np.arange(len(alive)), dim]
        # Where no point is smaller than the median, the next distinct value.
        above = np.where(ordered > value[nodes], ordered, np.inf)
        value = np.where(value == least, np.minimum.reduceat(above, edge), value)
        smaller = x < value[nodes]
        order[place] = own[np.lexsort((~smaller, nodes))]
        few = np.add.reduceat(smaller.astype(np.int64), edge)
        split = extent.max(axis=1) > 0
        fresh = []
        for k, a, b, c, j, v in zip(alive[split].tolist(), start[split].tolist(), stop[split].tolist(), few[split].tolist(), dim[split].tolist(), value[split].tolist(), strict=True):
            dims[k], values[k], lefts[k] = j, v, len(dims)
            fresh += [len(dims), len(dims) + 1]
            dims += [-1, -1]
            values += [0.0, 0.0]
            lefts += [-1, -1]
            runs += [(a, a + c), (a + c, b)]
        counters.moved += int(many[split].sum())
        counters.rounds += level == 0
        alive, level = np.array(fresh, np.int64), level + 1

    points, ids = points[order], ids[order]

    def attach(k: int) -> tuple[int, int]:
        if dims[k] < 0:
            return out.leaf(points[runs[k][0] : runs[k][1]], ids[runs[k][0] : runs[k][1]])
        at = out.interior(dims[k], values[k])
        one = attach(lefts[k])
        return out.close(at, one, attach(lefts[k] + 1))

    return attach(0)


class Skeleton:
    """The first levels of a tree: splitters, and numbered buckets where it ends."""

    def __init__(self, dim, val, left, right, bucket):
        self.dim, self.val, self.left, self.right, self.bucket = (np.array(x) for x in (dim, val, left, right, bucket))
        self.buckets = int((self.dim < 0).sum())

    @classmethod
    def from_sample(cls, sample: np.ndarray, levels: int, rule: str = "widest", depth: int = 0, fits: int = 1) -> Skeleton | None:
        """Medians of the sample, level by level, of parts with more than ``fits`` points; None if the sample does not split at all."""
        columns: list[list] = [[], [], [], [], []]
        buckets = [0]

        def walk(part: np.ndarray, level: int) -> int:
            at = len(columns[0])
            for c, v in zip(columns, (-1, 0.0, -1, -1, -1), strict=True):
                c.append(v)
            split = choose_split(part, depth + level, rule) if level < levels and len(part) > fits else None
            if split is None:
                columns[4][at], buckets[0] = buckets[0], buckets[0] + 1
                return at
            columns[0][at], columns[1][at] = split
            smaller = part[:, split[0]] < split[1]
            columns[2][at] = walk(part[smaller], level + 1)
            columns[3][at] = walk(part[~smaller], level + 1)
            return at

        if not len(sample):
            return None
        walk(sample, 0)
        return cls(*columns) if len(columns[0]) > 1 else None

    @classmethod
    def from_splits(cls, splits: list[tuple[int, float]]) -> Skeleton:
        """A complete skeleton from splitters in heap order."""
        n = len(splits)
        columns: list[list] = [[], [], [], [], []]

        def walk(h: int) -> int:
            at = len(columns[0])
            for c, v in zip(columns, (-1, 0.0, -1, -1, -1), strict=True):
                c.append(v)
            if h >= n:
                columns[4][at] = sum(b >= 0 for b in columns[4])
                return at
            columns[0][at], columns[1][at] = splits[h]
            columns[2][at], columns[3][at] = walk(2 * h + 1), walk(2 * h + 2)
            return at

        walk(0)
        return cls(*columns)

    def locate(self, points: np.ndarray) -> np.ndarray:
        return self.bucket[descend(self.dim, self.val, self.left, self.right, points)]

    def below(self, k: int) -> list[int]:
        """Buckets of a node."""
        if self.dim[k] < 0:
            return [int(self.bucket[k])]
        return self.below(int(self.left[k])) + self.below(int(self.right[k]))

    def weight(self, k: int, cuts: np.ndarray) -> int:
        own = self.below(k)
        return int(cuts[own[-1] + 1] - cuts[own[0]])
