from __future__ import annotations

from collections import Counter

import numpy as np
import pytest

from pathalgebra.operators import quadtree as qt

LEVELS = 5
SIDE = 1 << LEVELS


def tree(a):
    r, c = np.nonzero(a)
    return qt.encode(r, c, LEVELS)


def dense(t):
    out = np.zeros((SIDE, SIDE), bool)
    out[qt.decode(t)] = True
    return out


def times(a, b):
    return (a.astype(int) @ b.astype(int)) > 0


def warshall(a):
    a = a.copy()
    for k in range(len(a)):
        a |= a[:, [k]] & a[[k], :]
    return a


@pytest.fixture(params=[0.0, 0.02, 0.05, 0.1, 0.3])
def pair(request):
    rng = np.random.default_rng(int(request.param * 100))
    return rng.random((SIDE, SIDE)) < request.param, rng.random((SIDE, SIDE)) < request.param


def test_round_trip_and_order(pair):
    t = tree(pair[0])
    assert (dense(t) == pair[0]).all()
    assert (dense(qt.QuadTree.from_bytes(t.to_bytes())) == pair[0]).all()
    z = qt.codes(t)
    assert (np.diff(z.astype(np.int64)) > 0).all()
    assert t.ones == pair[0].sum()
    assert len(t.bits) <= qt.size_bound_bits(t.ones, SIDE)


def test_rank_child_and_probe(pair):
    t = tree(pair[0])
    rank = qt.RankBits(t.bits)
    before = np.concatenate([[0], np.cumsum(t.bits)])
    assert [rank.rank(i) for i in range(len(t.bits) + 1)] == before.tolist()
    assert all(qt.has(t, rank, r, c) == pair[0][r, c] for r in range(0, SIDE, 3) for c in range(SIDE))


def test_rank_over_many_blocks():
    bits = (np.random.default_rng(1).random(200_000) < 0.3).astype(np.uint8)
    rank, before = qt.RankBits(bits), np.concatenate([[0], np.cumsum(bits)])
    assert all(rank.rank(i) == before[i] for i in [0, 1, 63, 64, 65_535, 65_536, 65_537, 131_072, 199_999, 200_000])


def test_sums_and_set_operations(pair):
    a, b = pair
    assert (dense(qt.merge_sum(tree(a), tree(b))) == (a | b)).all()
    for op, want in (("or", a | b), ("and", a & b), ("diff", a & ~b), ("xor", a ^ b)):
        assert (dense(qt.flat(qt.recurse(op, qt.nest(tree(a)), qt.nest(tree(b))), LEVELS)) == want).all()


def test_batched_copies_do_less():
    a, b = np.zeros((SIDE, SIDE), bool), np.zeros((SIDE, SIDE), bool)
    a[:16, :16], b[16:, 16:] = True, True
    one, each = Counter(), Counter()
    qt.merge_sum(tree(a), tree(b), True, one)
    qt.merge_sum(tree(a), tree(b), False, each)
    assert one["copies"] < each["copies"] and one["tasks"] == each["tasks"]


def test_products_and_closure(pair):
    a, b = pair
    x, y = qt.nest(tree(a)), qt.nest(tree(b))
    assert (dense(qt.flat(qt.multiply(x, y), LEVELS)) == times(a, b)).all()
    assert (dense(qt.flat(qt.flip(x), LEVELS)) == a.T).all()
    assert (dense(qt.flat(qt.tree_closure(x), LEVELS)) == warshall(a)).all()
    want = np.zeros_like(a)
    want[7] = times(a, b)[7]
    assert (dense(qt.flat(qt.multiply(x, y, row=7, levels=LEVELS), LEVELS)) == want).all()


def test_restricted_products_of_a_full_matrix():
    """At the root of full matrices 8 products are left, 4 with one line, 2 with both."""
    full = qt.nest(qt.encode(*np.nonzero(np.ones((2, 2), bool)), 1))

    def calls(**line):
        n = Counter()
        qt.multiply(full, full, n, levels=1, **line)
        return n["products"] - 1

    assert (calls(), calls(row=0), calls(col=1), calls(row=0, col=1)) == (8, 4, 4, 2)


def test_fourteen_steps():
    """Signatures of the sum: 1 at the root, 4 below, 9 at the last level."""
    quadrants = {0: "1000", 1: "1110", 2: "1111", 3: "0001"}
    cells = [(q, k) for q, sig in quadrants.items() for k in range(4) if sig[k] == "1"]
    z = np.array([(q * 4 + k) * 4 for q, k in cells], np.uint64)
    t = qt.encode(*qt.deinterleave(z), 3)
    steps = Counter()
    qt.merge_sum(t, t, counters=steps)
    assert steps["tasks"] == 14
    assert t.signatures()[:2] == [["1111"], ["1000", "1110", "1111", "0001"]]
