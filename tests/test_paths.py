from __future__ import annotations

import pytest

from pathalgebra.plans import paths as p
from pathalgebra.plans.automaton import positions
from pathalgebra.plans.ordering import order_products, order_sums


def canonical(text):
    return p.text_of(p.normalise(p.parse_path(text)))


@pytest.mark.parametrize(
    ("text", "want"),
    [
        ("^(a/b)", "^b/^a"), ("^a+", "(^a)+"), ("(a*)*", "a*"), ("(a+)*", "a*"), ("(a*)+", "a*"), ("(a+)+", "a+"), ("(a?)+", "a*"), ("(a?)*", "a*"), ("(a?)?", "a?"),
        ("(a/b)/c", "a/b/c"), ("b|a|b", "a|b"), ("a/()/b", "a/b"), ("^(a|b)", "^a|^b"), ("!(b|a)", "!(a|b)"), ("^^a", "a"), ("<x y>/a", "<x y>/a"),
    ],
)
def test_normal_form(text, want):
    assert canonical(text) == want


@pytest.mark.parametrize("text", ["", "a/", "a||b", "(a", "a)", "+a", "a b", "!("])
def test_bad_paths(text):
    with pytest.raises(ValueError):
        p.parse_path(text)


def test_query_ends():
    q = p.parse_query("customer:7 a/b ?y")
    assert q.source == p.node("customer", 7) and q.target == "y"


def test_nullable():
    assert p.nullable(p.parse_path("a*/b?")) and not p.nullable(p.parse_path("a*/b"))


def test_positions():
    auto = positions(p.parse_path("a/(b|c)+/d?"))
    assert auto.first == {0} and auto.last == {1, 2, 3} and not auto.empty
    assert auto.follow == {(0, 1), (0, 2), (1, 1), (1, 2), (2, 1), (2, 2), (1, 3), (2, 3)}


def test_sums_smallest_first():
    assert order_sums([8, 2, 3, 4]) == [(1, 2), (3, 4), (0, 5)]


def test_products_least_pair_first():
    """Sizes 8, 2, 3, 8: the middle pair has the least total; then the left one by the tie rule."""
    assert order_products([8, 2, 3, 8], lambda i, j: 4)[:2] == [(1, 2), (0, 4)]
