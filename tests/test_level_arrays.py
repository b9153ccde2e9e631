"""Quadtree algebra on level arrays against dense matrices."""

from __future__ import annotations

from collections import Counter

import numpy as np
import pytest

from pathalgebra.operators import quadtree as q


def tree_of(m: np.ndarray, levels: int) -> q.QuadTree:
    return q.encode(*np.nonzero(m), levels)


def dense(t: q.QuadTree) -> np.ndarray:
    out = np.zeros((1 << t.levels, 1 << t.levels), bool)
    r, c = q.decode(t)
    out[r, c] = True
    again = q.encode(r, c, t.levels)  # the form is the only one
    assert again.level_bits == t.level_bits and (again.bits == t.bits).all()
    return out


@pytest.mark.parametrize("levels", [1, 2, 3, 5, 8])
@pytest.mark.parametrize("density", [0, 0.02, 0.3, 1])
def test_algebra(levels, density):
    rng = np.random.default_rng(levels)
    n = 1 << levels
    a, b = rng.random((n, n)) < density, rng.random((n, n)) < 0.1
    x, y = tree_of(a, levels), tree_of(b, levels)
    r, c = (int(v) for v in rng.integers(n, size=2))
    row, col = np.zeros_like(a), np.zeros_like(a)
    row[r], col[:, c] = True, True
    for op, want in (("or", a | b), ("and", a & b), ("diff", a & ~b), ("xor", a ^ b)):
        assert (dense(q.combine(op, x, y)) == want).all()
        assert (dense(q.combine(op, x, y, row=r)) == want & row).all()
        assert (dense(q.combine(op, x, y, col=c, parallel_levels=1)) == want & col).all()
        assert (dense(q.combine(op, x, y, row=r, col=c)) == want & row & col).all()
    assert (dense(q.merge_sum(x, y)) == a | b).all() and (dense(q.merge_sum(x, y, batch_copies=False)) == a | b).all()
    product = (a.astype(int) @ b.astype(int)) > 0
    assert (dense(q.times(x, y)) == product).all()
    assert (dense(q.times(x, y, row=r)) == product & row).all() and (dense(q.times(x, y, row=r, col=c)) == product & row & col).all()
    closed = a.copy()
    for k in range(n):
        closed |= np.outer(closed[:, k], closed[k])
    assert (dense(q.closed(x)) == closed).all() and (dense(q.closed(x, leaf_levels=2)) == closed).all()
    assert (dense(q.turned(x)) == a.T).all()
    if levels > 1:
        assert (dense(q.concat(q.quadrants(x), levels)) == a).all()


def test_lone_quadrants_are_shared():
    x, counters = q.encode([0, 1], [1, 0], 4), Counter()
    part = q.quadrants(x)
    assert sum(bool(p.level_bits) for p in part) == 1
    q.concat(part, 4, counters)
    assert counters == {"trivial": 1}


def test_restrictions_leave_half_and_a_quarter_of_the_products():
    full = q.encode(*np.nonzero(np.ones((8, 8))), 3)
    made = []
    for line in ({}, {"row": 2}, {"row": 2, "col": 5}):
        counters = Counter()
        q.times(full, full, counters, **line)
        made.append(counters["products"])
    # One root, then eight, four or two pairs for each pair before.
    assert made == [1 + 8 + 64, 1 + 4 + 16, 1 + 2 + 4]


def test_copies_in_blocks_are_fewer():
    rng = np.random.default_rng(0)
    x, y = (tree_of(rng.random((256, 256)) < 0.01, 8) for _ in range(2))
    runs, single = Counter(), Counter()
    q.merge_sum(x, y, counters=runs)
    q.merge_sum(x, y, batch_copies=False, counters=single)
    assert runs["tasks"] == single["tasks"] and runs["merges"] == single["merges"] and runs["copies"] < single["copies"]
