"""The upper part of a tree: nodes above the shards. A few numbers a node, held by the driver and sent to tasks."""

from __future__ import annotations

import numpy as np

from axisgrove.operators.local import Skeleton, descend


class TopTree:
    """Struct of arrays; node 0 is the root; ``left`` is -1 where a node ends in shards.

    ``shards[i]`` lists the shards of such a node: one, or several that share a point too
    common for one task. ``size`` counts points; ``parent`` is -1 at the root.
    """

    def __init__(self, d: int):
        self.d = d
        self.dim, self.val, self.left, self.right, self.parent, self.size = [-1], [0.0], [-1], [-1], [-1], [0]
        self.shards: dict[int, list[int]] = {0: []}
        self.low: dict[int, list[float]] = {}
        self.high: dict[int, list[float]] = {}
        self.shard_size: dict[int, int] = {}
        self.next_shard = 0

    def new_shards(self, n: int) -> list[int]:
        """Numbers that were never used."""
        self.next_shard += n
        return list(range(self.next_shard - n, self.next_shard))

    def copy(self) -> TopTree:
        other = TopTree(self.d)
        for name in ("dim", "val", "left", "right", "parent", "size"):
            setattr(other, name, list(getattr(self, name)))
        other.shards = {k: list(v) for k, v in self.shards.items()}
        other.low, other.high, other.shard_size, other.next_shard = dict(self.low), dict(self.high), dict(self.shard_size), self.next_shard
        return other

    def arrays(self):
        return np.array(self.dim, np.int64), np.array(self.val, float), np.array(self.left, np.int64), np.array(self.right, np.int64)

    def graft(self, at: int, skeleton: Skeleton) -> list[int]:
        """Puts a skeleton in the place of an end; returns the new ends by bucket."""
        base = len(self.dim) - 1  # node 0 of the skeleton becomes ``at``
        name = lambda k: at if k == 0 else base + k
        ends = [0] * skeleton.buckets
        self.shards.pop(at, None)
        for k in range(len(skeleton.dim)):
            if k:
                for column, v in ((self.dim, -1), (self.val, 0.0), (self.left, -1), (self.right, -1), (self.parent, -1), (self.size, 0)):
                    column.append(v)
        for k in range(len(skeleton.dim)):
            n = name(k)
            if skeleton.dim[k] >= 0:
                a, b = name(int(skeleton.left[k])), name(int(skeleton.right[k]))
                self.dim[n], self.val[n], self.left[n], self.right[n] = int(skeleton.dim[k]), float(skeleton.val[k]), a, b
                self.parent[a] = self.parent[b] = n
            else:
                self.dim[n] = -1
                self.shards[n] = []
                ends[int(skeleton.bucket[k])] = n
        return ends

    def close(self, at: int) -> list[int]:
        """Turns a node into an end without shards; returns the shards that were below."""
        below = self.ends(at)
        gone = [s for e in below for s in self.shards.pop(e, [])]
        self.dim[at] = self.left[at] = self.right[at] = -1
        self.shards[at] = []
        return gone

    def ends(self, at: int = 0) -> list[int]:
        out, stack = [], [at]
        while stack:
            k = stack.pop()
            if self.left[k] < 0:
                out.append(k)
            else:
                stack += [self.right[k], self.left[k]]
        return out

    def sum_up(self) -> None:
        """Sizes from shard sizes, children before parents."""
        order, stack = [], [0]
        while stack:
            k = stack.pop()
            order.append(k)
            if self.left[k] >= 0:
                stack += [self.left[k], self.right[k]]
        for k in reversed(order):
            self.size[k] = sum(self.shard_size.get(s, 0) for s in self.shards[k]) if self.left[k] < 0 else self.size[self.left[k]] + self.size[self.right[k]]

    def depth(self, k: int) -> int:
        n = 0
        while self.parent[k] >= 0:
            k, n = self.parent[k], n + 1
        return n

    def locate(self, points: np.ndarray) -> np.ndarray:
        """End of each point."""
        return descend(*self.arrays(), points)

    def shard_boxes(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Shards with points, and their tight boxes."""
        names = [s for s, n in self.shard_size.items() if n and s in self.low]
        return np.array(names, np.int64), np.array([self.low[s] for s in names]).reshape(-1, self.d), np.array([self.high[s] for s in names]).reshape(-1, self.d)

    def routes(self) -> Routes:
        return Routes(self)


class Routes:
    """The top tier as arrays for finding shards: a descent that follows only nodes whose box is of interest.

    Shards are listed in the order of their ends from left to right, so those below a node are a
    range. Boxes are tight: those of the shards, joined upward.
    """

    def __init__(self, top: TopTree):
        n, d = len(top.dim), top.d
        self.d, self.tree = d, top.arrays()
        self.left, self.right, self.parent, self.size = (np.array(x, np.int64) for x in (top.left, top.right, top.parent, top.size))
        low, high = np.full((n, d), np.inf), np.full((n, d), -np.inf)
        start, stop = np.zeros(n, np.int64), np.zeros(n, np.int64)
        shards: list[int] = []
        order, stack = [], [0]
        while stack:
            k = stack.pop()
            order.append(k)
            start[k] = len(shards)
            if top.left[k] >= 0:
                stack += [top.right[k], top.left[k]]
            else:
                shards += [s for s in top.shards[k] if top.shard_size.get(s)]
                stop[k] = len(shards)
        self.shards = np.array(shards, np.int64)
        self.shard_low = np.array([top.low[s] for s in shards], float).reshape(-1, d)
        self.shard_high = np.array([top.high[s] for s in shards], float).reshape(-1, d)
        self.shard_size = np.array([top.shard_size[s] for s in shards], np.int64)
        for k in reversed(order):
            if top.left[k] >= 0:
                a, b = top.left[k], top.right[k]
                low[k], high[k], stop[k] = np.minimum(low[a], low[b]), np.maximum(high[a], high[b]), stop[b]
            elif stop[k] > start[k]:
                low[k], high[k] = self.shard_low[start[k] : stop[k]].min(axis=0), self.shard_high[start[k] : stop[k]].max(axis=0)
        self.low, self.high, self.start, self.stop = low, high, start, stop

    def below(self, rows: np.ndarray, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, place of a shard) for every shard below the node of each row."""
        many = self.stop[nodes] - self.start[nodes]
        places = np.repeat(self.start[nodes] - (np.cumsum(many) - many), many) + np.arange(int(many.sum()))
        return np.repeat(rows, many), places

    def home(self, points: np.ndarray, k: int) -> np.ndarray:
        """For each point the lowest node on its path that holds k points."""
        at = descend(*self.tree, points)
        while True:
            low = np.flatnonzero((self.size[at] < k) & (self.parent[at] >= 0))
            if not len(low):
                return at
            at[low] = self.parent[at[low]]

    def near(self, points: np.ndarray, bound: np.ndarray, home: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row, place, squared distance) of the shards within each bound that are not below the home node."""

        def gaps(rows, low, high):
            total = np.zeros(len(rows))
            for j in range(self.d):
                x = points[rows, j]
                gap = np.maximum(np.maximum(low[:, j] - x, x - high[:, j]), 0.0)
                total += gap * gap
            return total

        rows, nodes, found = np.arange(len(points)), np.zeros(len(points), np.int64), []
        while len(rows):
            keep = (self.stop[nodes] > self.start[nodes]) & (nodes != home[rows])
            rows, nodes = rows[keep], nodes[keep]
            keep = gaps(rows, self.low[nodes], self.high[nodes]) <= bound[rows]
            rows, nodes = rows[keep], nodes[keep]
            ends = self.left[nodes] < 0
            r, place = self.below(rows[ends], nodes[ends])
            dist = gaps(r, self.shard_low[place], self.shard_high[place])
            near = dist <= bound[r]
            found.append((r[near], place[near], dist[near]))
            rows, nodes = np.repeat(rows[~ends], 2), np.stack([self.left[nodes[~ends]], self.right[nodes[~ends]]], axis=1).ravel()
        if not found:
            return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        return tuple(np.concatenate(x) for x in zip(*found, strict=True))

    def boxes(self, a: np.ndarray, b: np.ndarray) -> tuple[tuple[np.ndarray, np.ndarray], tuple[np.ndarray, np.ndarray]]:
        """(row, node) of the topmost nodes that lie in each closed box, and (row, place) of the shards that it cuts."""
        usable = np.flatnonzero((a <= b).all(axis=1))
        rows, nodes = usable, np.zeros(len(usable), np.int64)
        none = np.zeros(0, np.int64)
        inside, cut = [(none, none)], [(none, none)]
        while len(rows):
            keep = (self.stop[nodes] > self.start[nodes]) & (a[rows] <= self.high[nodes]).all(axis=1) & (self.low[nodes] <= b[rows]).all(axis=1)
            rows, nodes = rows[keep], nodes[keep]
            whole = (a[rows] <= self.low[nodes]).all(axis=1) & (self.high[nodes] <= b[rows]).all(axis=1)
            inside.append((rows[whole], nodes[whole]))
            rows, nodes = rows[~whole], nodes[~whole]
            ends = self.left[nodes] < 0
            r, place = self.below(rows[ends], nodes[ends])
            meets = (a[r] <= self.shard_high[place]).all(axis=1) & (self.shard_low[place] <= b[r]).all(axis=1)
            cut.append((r[meets], place[meets]))
            rows, nodes = np.repeat(rows[~ends], 2), np.stack([self.left[nodes[~ends]], self.right[nodes[~ends]]], axis=1).ravel()
        return tuple(np.concatenate(x) for x in zip(*inside, strict=True)), tuple(np.concatenate(x) for x in zip(*cut, strict=True))
