"""Local kernels against brute force."""

from __future__ import annotations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from vecblock.functions import arrays as A
from vecblock.operators import graph, tree


@settings(max_examples=40, deadline=None)
@given(st.integers(0, 60), st.integers(1, 12), st.sampled_from(["l2", "cosine", "l1", "chebyshev"]), st.booleans(), st.integers(0, 10**6))
def test_block_topk_is_exact(m, k, metric, far, seed):
    rng = np.random.default_rng(seed)
    x, q = rng.integers(-3, 4, (m, 4)) + 0.5, rng.integers(-3, 4, (5, 4)) + 0.5  # many ties
    ids = rng.permutation(m)
    row, found, dist = A.block_topk(q, x, ids, k, metric, far)
    for i in range(5):
        d = A.distance(q[i], x, metric) if m else np.zeros(0)
        want = ids[np.lexsort((ids, -d if far else d))[:k]]
        assert found[row == i].tolist() == want.tolist()


def test_line_of_twelve_points():
    x = np.array([0, 1, 2, 3, 10, 11, 12, 13, 30, 31, 32, 33], float)[:, None]
    pieces, parts = A.split_all(x, np.arange(12), "r", 3, 2, 5, "d2", 1)
    assert max(len(p[1]) for p in pieces) <= 3
    assert sorted(np.concatenate([p[1] for p in pieces]).tolist()) == list(range(12))
    assert parts[0][:2] == ("r", 12)


def test_equal_points_are_chopped_by_id():
    pieces, _ = A.split_all(np.ones((8, 3)), np.arange(8), "r", 3, 2, 5, "d2", 1)
    assert [p[1].tolist() for p in pieces] == [[0, 1, 2], [3, 4, 5], [6, 7]]
    assert all(p[2] for p in pieces)


def test_refine_reaches_the_other_end():
    x = np.arange(6, dtype=float)[:, None]
    links = [np.array([j for j in (i - 2, i - 1, i + 1, i + 2) if 0 <= j < 6]) for i in range(6)]
    got, dist, hops, seen = A.refine(np.array([5.0]), np.array([0]), links, x, 2, "l2")
    assert got.tolist() == [5, 4] and dist.tolist() == [0, 1] and hops > 1 and seen == 6


def test_grow_keeps_balance_and_capacity():
    rng = np.random.default_rng(0)
    c = rng.normal(size=(97, 3))
    for levels in (tree.grow(c, np.ones(97), 5), tree.packed(97, 5)):
        assert sorted(k for g in levels[0] for k in g) == list(range(97))
        assert len(levels[-1]) == 1
        for below, level in zip([97, *map(len, levels)], levels):
            assert max(map(len, level)) <= 5
            assert sorted(k for g in level for k in g) == list(range(below))


def test_recommended_sizes():
    assert graph.recommended_leaf_capacity(10**6) == 270
    assert graph.recommended_link_leaves(10**6) == 2450


@pytest.mark.parametrize("metric", ["l2", "cosine"])
def test_rotated_coordinates_give_the_same_neighbours(metric):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(50, 6))
    perm = rng.permutation(6)
    a = A.block_topk(x[:5], x, np.arange(50), 7, metric)[1]
    b = A.block_topk(x[:5][:, perm], x[:, perm], np.arange(50), 7, metric)[1]
    assert a.tolist() == b.tolist()
