"""Choices between physical strategies, by size."""

from __future__ import annotations

#: Up to this many leaves a descent expression beats shipping subtrees.
DESCENT_LEAVES = 100_000

#: Strata that may be broadcast to a range join; beyond it rows descend the tree instead.
BROADCAST_STRATA = 20_000

#: Points whose pairs are summed exactly for the discrepancy; beyond it boxes are sampled.
EXACT_PAIRS = 200_000

#: Dimensions up to which the exact covering radius is worked out, and its most points.
EXACT_COVER_DIMS, EXACT_COVER_POINTS = 3, 2_000


def integer_root(count: int, dims: int) -> int:
    """The largest k with k**dims <= count."""
    k = max(1, round(count ** (1 / dims)))
    while k**dims > count:
        k -= 1
    while (k + 1) ** dims <= count:
        k += 1
    return k


def strata_engine(count: int) -> str:
    return "descent" if count <= DESCENT_LEAVES else "subtree"


def stratifier(count: int, dims: int) -> str:
    """An equal grid where count is a power that fits, else two-way splits."""
    return "grid" if integer_root(count, dims) ** dims == count else "bsplit"


def discrepancy_method(count: int, dims: int) -> str:
    if dims == 1:
        return "sort"
    return "pairs" if count <= EXACT_PAIRS else "boxes"


def covering_method(count: int, dims: int) -> str:
    if dims == 1 or (dims <= EXACT_COVER_DIMS and count <= EXACT_COVER_POINTS):
        return "exact"
    return "bounds"
