"""The tree of one block, without Spark: invariants, queries against brute force, updates."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from axisgrove.model import TreeParams, child_bounds, height_bound, is_balanced, oversample_for, plain, strict_alpha
from axisgrove.operators.local import Counters, LocalTree, Skeleton, choose_split


def cloud(n, d, seed=0, lattice=None):
    rng = np.random.default_rng(seed)
    points = rng.random((n, d)) if lattice is None else rng.integers(0, lattice, (n, d)).astype(float)
    return points, np.arange(n)


def check(tree, params, balanced=True):
    start = tree.starts()
    for i in range(len(tree.dim)):
        own = tree.points[start[i] : start[i] + tree.size[i]]
        assert len(own) == tree.size[i]
        if tree.dim[i] < 0:
            assert tree.size[i] <= params.leaf_capacity or (own == own[0]).all()
            continue
        a, b = i + 1, tree.right(i)
        assert tree.size[i] == tree.size[a] + tree.size[b]
        left, right = own[: tree.size[a]], own[tree.size[a] :]
        assert (left[:, tree.dim[i]] < tree.val[i]).all() and (right[:, tree.dim[i]] >= tree.val[i]).all()
        if balanced and tree.size[i] > params.leaf_capacity:
            assert is_balanced(int(tree.size[a]), int(tree.size[b]), params.alpha)


def brute(points, ids, q, k):
    far = np.zeros(len(points))
    for j in range(points.shape[1]):
        far += (q[j] - points[:, j]) * (q[j] - points[:, j])
    order = np.lexsort((ids, far))[:k]
    return far[order], ids[order]


@pytest.mark.parametrize("params", [TreeParams(), TreeParams(levels=3, oversample=8), plain(), TreeParams(split_rule="cycle"), TreeParams(store_boxes=True)])
@pytest.mark.parametrize("d", [1, 2, 5])
def test_growth_and_queries(params, d):
    points, ids = cloud(3000, d, d)
    tree = LocalTree.grow(points, ids, params)
    check(tree, params)
    assert sorted(tree.ids) == list(ids)
    queries = np.concatenate([points[:20], np.random.default_rng(9).random((20, d)) * 3 - 1])
    dist, who = tree.knn(queries, 7)
    for q, a, b in zip(queries, dist, who, strict=True):
        e = brute(points, ids, q, 7)
        assert (a == e[0]).all() and (b == e[1]).all()
    low, high = queries - 0.15, queries + 0.15
    inside = ((points[None] >= low[:, None]) & (points[None] <= high[:, None])).all(axis=2)
    assert (tree.ranges(low, high, False) == inside.sum(axis=1)).all()
    box, found = tree.ranges(low, high, True)
    assert sorted(zip(box.tolist(), tree.ids[found].tolist(), strict=True)) == sorted(zip(*[x.tolist() for x in np.nonzero(inside)], strict=True))


def test_duplicates_make_heavy_leaves():
    points, ids = cloud(4000, 2, 1, lattice=3)
    tree = LocalTree.grow(points, ids, TreeParams())
    check(tree, TreeParams(), balanced=False)
    assert (tree.dim < 0).sum() == 9
    one = LocalTree.grow(np.ones((500, 3)), np.arange(500), TreeParams())
    assert len(one.dim) == 1 and one.knn(np.ones((1, 3)), 3)[1].tolist() == [[0, 1, 2]]


def test_empty_and_tiny():
    empty = LocalTree.grow(np.zeros((0, 2)), np.zeros(0, int), TreeParams())
    assert len(empty.dim) == 0 and np.isinf(empty.knn(np.zeros((1, 2)), 2)[0]).all()
    assert empty.insert(np.zeros((1, 2)), np.array([5]), TreeParams()).ids.tolist() == [5]
    few = LocalTree.grow(np.array([[1.0], [2.0]]), np.array([1, 2]), TreeParams())
    assert few.knn(np.array([[1.4]]), 5)[1].tolist() == [[1, 2, -1, -1, -1]]


def test_boxes_are_visited_less():
    points, ids = cloud(5000, 3, 2)
    low = np.random.default_rng(3).random((50, 3))
    seen = []
    for stored in (False, True):
        visits = np.zeros((50, 2), int)
        LocalTree.grow(points, ids, TreeParams(store_boxes=stored)).ranges(low, low + 0.2, False, visits)
        seen.append(visits.sum(axis=1))
    assert (seen[1] <= seen[0]).all() and seen[1].sum() < seen[0].sum()


@settings(max_examples=25, deadline=None)
@given(st.integers(0, 400), st.integers(1, 600), st.integers(1, 3), st.integers(0, 10**6), st.sampled_from([0.01, 0.1, 0.3, 0.5]), st.sampled_from([None, 4]))
def test_updates_keep_the_bag_and_the_balance(n, m, d, seed, alpha, lattice):
    params = TreeParams(alpha=alpha, leaf_capacity=8, levels=3, oversample=4)
    points, ids = cloud(n + m, d, seed, lattice)
    tree = LocalTree.grow(points[:n], ids[:n], params).insert(points[n:] ** 2, ids[n:], params)
    check(tree, params, balanced=alpha >= 0.3 and lattice is None)
    assert sorted(tree.ids) == list(ids)
    gone, found = tree.match(ids[::3], np.concatenate([points[:n], points[n:] ** 2])[::3])
    assert found.all() and gone.sum() == len(ids[::3])
    after = tree.delete(gone, params)
    check(after, params, balanced=alpha >= 0.3 and lattice is None)
    assert sorted(after.ids) == sorted(set(ids) - set(ids[::3]))
    assert len(tree.delete(np.ones(len(ids), bool), params).ids) == 0


def test_only_topmost_unbalanced_nodes_are_rebuilt():
    points, ids = cloud(2000, 2, 4)
    tree = LocalTree.grow(points, ids, TreeParams())
    counters = Counters()
    tree.insert(points[:5] + 1e-9, ids[:5] + 10**6, TreeParams(), counters)
    assert counters.rebuilt == 0
    corner = np.random.default_rng(5).random((4000, 2)) * 0.05
    counters = Counters()
    assert len(tree.insert(corner, np.arange(4000) + 10**6, TreeParams(), counters).ids) == 6000
    assert 4000 <= counters.rebuilt <= 6000
    free = Counters()
    tree.insert(corner, np.arange(4000) + 10**6, TreeParams(alpha=0.5), free)
    assert free.rebuilt == 0


def test_packing_and_serial_deletion():
    points, ids = cloud(700, 2, 6)
    tree = LocalTree.unpack(LocalTree.grow(points, ids, TreeParams(store_boxes=True)).pack())
    after, found, passed = tree.delete_one_by_one(ids[:50], points[:50], TreeParams())
    assert found.all() and passed >= 50 and sorted(after.ids) == list(ids[50:])
    gone, found = LocalTree.grow(np.ones((5, 1)), np.array([9, 3, 7, 1, 5]), TreeParams()).match(None, np.ones((2, 1)))
    assert found.all() and gone.sum() == 2


def test_balance_is_exact():
    assert is_balanced(160, 40, 0.3) and not is_balanced(180, 40, 0.3)
    assert is_balanced(10**18 * 8, 2 * 10**18, 0.3) and not is_balanced(10**18 * 8 + 1, 2 * 10**18 - 1, 0.3)
    assert is_balanced(0, 100, 0.5) and is_balanced(3, 4, 0.0) and not is_balanced(3, 5, 0.0)


def test_bounds():
    assert oversample_for(2**20 - 1, 0.5) == 480 and child_bounds(100, 0.4) == (40.0, 60.0)
    assert height_bound(1 << 20, 1e-9) == 21 or height_bound(1 << 20, 1e-9) == 20
    assert strict_alpha(1023) == 0.1


def test_skeleton_and_splits():
    skeleton = Skeleton.from_splits([(0, 20.0), (0, 10.0), (0, 30.0)])
    assert skeleton.locate(np.array([[25.0], [3], [12], [31], [8], [22], [10], [20]])).tolist() == [2, 0, 1, 3, 0, 2, 1, 2]
    assert choose_split(np.ones((4, 2)), 0, "widest") is None
    assert choose_split(np.array([[1.0], [1], [1], [2]]), 0, "widest") == (0, 2.0)
