"""Blocking clauses after a found itemset, over literals (+ item, - item), and their adaptive choice."""

from __future__ import annotations

from itertools import combinations

from ..functions.bits import bits

FULL, ITEMS, SUBSETS, SUBSET = "full_model", "items_only", "subsets_explicit", "subset_compact"
SUPERSETS, SUPERSET = "supersets_explicit", "superset_compact"
OPTIONS = (FULL, ITEMS, SUBSETS, SUBSET, SUPERSETS, SUPERSET)


def _exact(mask: int, n: int) -> list[int]:
    return [-(i + 1) if mask >> i & 1 else i + 1 for i in range(n)]


def blocking_clauses(mask: int, n: int, option: str) -> list[list[int]]:
    """Clauses over literals +-(item + 1). ``full_model`` is left to the caller, who knows the rows."""
    inside, outside = bits(mask), [i for i in range(n) if not mask >> i & 1]
    if option == ITEMS:
        return [_exact(mask, n)]
    if option == SUBSETS:
        return [_exact(sum(1 << i for i in c), n) for k in range(1, len(inside) + 1) for c in combinations(inside, k)]
    if option == SUBSET:
        return [[i + 1 for i in outside]]
    if option == SUPERSETS:
        return [_exact(mask | sum(1 << i for i in c), n) for k in range(len(outside) + 1) for c in combinations(outside, k)]
    if option == SUPERSET:
        return [[-(i + 1) for i in inside]]
    raise ValueError(option)


def violates(mask: int, clause: list[int]) -> bool:
    """The itemset makes every literal of the clause false."""
    return all((mask >> (abs(x) - 1) & 1) != (x > 0) for x in clause)


def adaptive(size: int, n: int, similar: int) -> str:
    """Explicit subsets while they are few and many similar itemsets repeat them; compact otherwise."""
    return SUBSETS if size <= 6 and similar > n and size < n / 3 else SUBSET


def cube(clauses: list[list[int]], n: int) -> list[tuple[int, int]]:
    """(care, value) word pairs: an itemset is blocked if it equals ``value`` on ``care``."""
    return [(sum(1 << (abs(x) - 1) for x in c), sum(1 << (abs(x) - 1) for x in c if x < 0)) for c in clauses]
