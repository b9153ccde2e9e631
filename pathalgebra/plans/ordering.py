"""Orders for chains of sums and products by the sizes of their operands."""

from __future__ import annotations

import heapq
from collections.abc import Callable, Sequence


def order_sums(sizes: Sequence[int], size_after: Callable[[int, int], int] | None = None) -> list[tuple[int, int]]:
    """Pairs to add, smallest two first; results get the numbers len(sizes), len(sizes) + 1, ...

    ``size_after(i, j)`` is the true size of a sum, once it is worked out.
    """
    heap = [(s, i) for i, s in enumerate(sizes)]
    heapq.heapify(heap)
    steps: list[tuple[int, int]] = []
    while len(heap) > 1:
        (a, i), (b, j) = heapq.heappop(heap), heapq.heappop(heap)
        steps.append((i, j))
        heapq.heappush(heap, (size_after(i, j) if size_after else a + b, len(sizes) + len(steps) - 1))
    return steps


def order_products(sizes: Sequence[int], multiply: Callable[[int, int], int]) -> list[tuple[int, int]]:
    """Adjacent pairs to multiply, least total first, leftmost on ties.

    ``multiply(i, j)`` works the product out and tells its true size; results are
    numbered like those of sums.
    """
    chain = [(s, i) for i, s in enumerate(sizes)]
    steps: list[tuple[int, int]] = []
    while len(chain) > 1:
        at = min(range(len(chain) - 1), key=lambda k: (chain[k][0] + chain[k + 1][0], k))
        i, j = chain[at][1], chain[at + 1][1]
        chain[at : at + 2] = [(multiply(i, j), len(sizes) + len(steps))]
        steps.append((i, j))
    return steps
