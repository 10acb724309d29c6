"""Prefix tree, rectangle tree and the merge step on hand-made and random cells."""

import numpy as np
import pytest

from cellcluster import gaptest, merge
from cellcluster.cells import radix_order
from cellcluster.functions.surface import cluster_arrays
from cellcluster.baselines import pointwise_sequential
from cellcluster.neighbours import template
from cellcluster.prefixtree import PrefixTree, RectTree

NINE = np.array([(0, 1), (1, 1), (1, 3), (2, 0), (2, 2), (3, 3), (3, 4), (3, 5), (4, 3)])


def test_nine_cells():
    tree = PrefixTree(NINE)
    assert tree.nodes() == [1, 5, 9]
    assert tree.jump_table(0, 0, 2, 5) == {0: 0, 1: 0, 2: 0, 3: 1, 4: 2, 5: 3}
    _, found, off = tree.query(NINE[5:6], 2)
    assert sorted(found) == [2, 4, 6, 7, 8]
    assert list(off) == sorted(off)
    trace = []
    tree.query(NINE[5:6], 2, trace=trace)
    assert len(trace) == 2


def test_template_sizes():
    assert [len(template(d)) for d in (1, 2, 3, 4, 5)] == [3, 21, 117, 609, 3903]


@pytest.mark.parametrize("d", [1, 2, 3, 4, 5])
def test_trees_agree_with_all_pairs(d):
    rng = np.random.default_rng(d)
    keys = np.unique(rng.integers(0, 9, (300, d)), axis=0)
    reach = int(np.ceil(np.sqrt(d)))
    gap = np.maximum(np.abs(keys[:, None] - keys[None]) - 1, 0)
    want = {(i, j) for i, j in zip(*np.nonzero((gap * gap).sum(axis=2) < d), strict=True) if i != j}
    for tree, how in ((PrefixTree(keys), {}), (PrefixTree(keys), {"mode": "scan", "fanout": 3}), (RectTree(keys, 4), {})):
        q, o, _ = tree.query(keys, reach, **how)
        assert set(zip(q.tolist(), o.tolist(), strict=True)) == want


def test_radix_passes_sort_lexicographically():
    keys = np.random.default_rng(1).integers(0, 5, (200, 3))
    assert (keys[radix_order(keys)] == np.array(sorted(map(tuple, keys)))).all()


def test_merge_orders_give_one_partition_and_few_iterations():
    rng = np.random.default_rng(3)
    points = rng.integers(0, 8000, (900, 2))
    side = 1000 / np.sqrt(2)
    keys = np.floor(points / side).astype(int)
    grid, cell = np.unique(keys, axis=0, return_inverse=True)
    cells = [points[cell.ravel() == k] for k in range(len(grid))]
    q, o, _ = PrefixTree(grid).query(grid, 2)
    near = [o[q == k] for k in range(len(grid))]
    part = lambda label: {frozenset(np.flatnonzero(np.array(label) == v)) for v in set(label)}
    a, ca = merge.merge_search(cells, near, 1000)
    b, cb = merge.merge_sparse_first(cells, near, 1000)
    c, cc = merge.merge_sparse_first(cells, near, 1000, memo_failed=False)
    truth, _ = merge.merge_search(cells, near, 1000, gaptest.brute)
    assert part(a) == part(b) == part(c) == part(truth)
    assert ca["kappa"] <= 11 and cb["checks"] <= cc["checks"]


def test_visiting_order_changes_no_core_partition():
    rng = np.random.default_rng(8)
    x = rng.integers(0, 3000, (250, 2))
    out = cluster_arrays(np.arange(250), x, 200, 5)
    want = {}
    for p, c, role in out:
        if c is not None:
            want.setdefault(c, set()).add(p)
    for order in (None, rng.permutation(250)):
        found = pointwise_sequential(x, 200, 5, order)
        assert {frozenset(f) for f in found} == {frozenset(w) for w in want.values()}
