"""Searches that decide items only and evaluate rows by bitmaps: the engine for larger groups, and two baselines.

Rows are numpy vectors; the rows of an itemset are an index array, so a support check costs one gather of weights.
"""

from __future__ import annotations

import time

import numpy as np

from ..functions.bits import bits
from .blocking import SUBSET, blocking_clauses, cube
from .formula import Matrix
from .search import Run, Scope
from .solver import Budget, OutOfBudget


class Bitmap:
    """Row bitmaps of a matrix; ``extend`` gives all one-item extensions' supports at once."""

    def __init__(self, m: Matrix):
        self.n = m.n
        self.w = np.array(m.weights, dtype=np.int64)
        raw = np.zeros((len(m.masks), m.n), dtype=bool)
        for r, mask in enumerate(m.masks):
            raw[r, bits(mask)] = True
        self.has = raw

    def rows(self, itemset: int) -> np.ndarray:
        ids = bits(itemset)
        return np.flatnonzero(self.has[:, ids].all(axis=1)) if ids else np.arange(len(self.w))

    def counts(self, rows: np.ndarray) -> np.ndarray:
        """Support of the itemset behind ``rows`` together with each item."""
        return self.w[rows] @ self.has[rows] if len(rows) else np.zeros(self.n, dtype=np.int64)


def _check(budget: Budget | None, done: int) -> None:
    if budget and done % 256 == 0 and (s := budget.spent(done, done)):
        raise OutOfBudget(s)


def grow_maximal(m: Matrix, minsup: int, *, scope: Scope = Scope(), budget: Budget | None = None, must_contain: int = 0, limit: int | None = None, min_size: int | None = None) -> Run:
    """Maximal frequent itemsets of a scope by greedy growth and depth-first branching.

    A node is a set with its rows. All extensions that keep the support on every row join at once; the rest are tried
    by rising support, and a branch whose every candidate fits under a known maximal set (compact subset blocking) is
    cut. Hits are maximal over all items, those outside the scope included. ``min_size`` cuts branches that cannot reach it.
    """
    run, t = Run(), Bitmap(m)
    known: list[tuple[int, int]] = []  # blockers of found sets as cubes
    nodes = 0

    def blocked(itemset: int) -> bool:
        return any(itemset & care == value for care, value in known)

    def visit(cur: int, rows: np.ndarray, cand: list[int]) -> None:
        nonlocal nodes
        nodes += 1
        _check(budget, nodes)
        got = t.counts(rows)
        total = int(t.w[rows].sum())
        cand = [i for i in cand if got[i] >= minsup]
        same = [i for i in cand if got[i] == total]
        for i in same:
            cur |= 1 << i
        cand = sorted((i for i in cand if not cur >> i & 1), key=lambda i: (got[i], i))
        reach = cur
        for i in cand:
            reach |= 1 << i
        if min_size and reach.bit_count() < min_size or blocked(reach):
            return
        if not cand:
            others = [i for i in range(m.n) if not cur >> i & 1 and got[i] >= minsup]
            if not others and cur:
                known.extend(cube(blocking_clauses(cur, m.n, SUBSET), m.n))
                run.found[cur] = total
                if limit and len(run.found) >= limit:
                    raise StopIteration
            return
        for k, i in enumerate(cand):
            rest = cand[k + 1:]
            reach = cur | 1 << i
            for j in rest:
                reach |= 1 << j
            if min_size and reach.bit_count() < min_size or blocked(reach):
                continue
            visit(cur | 1 << i, rows[t.has[rows, i]], rest)

    start = time.perf_counter()
    first = scope.must | must_contain
    rows = t.rows(first)
    try:
        if int(t.w[rows].sum()) >= minsup:
            visit(first, rows, [i for i in range(m.n) if not (first | scope.never) >> i & 1])
    except OutOfBudget as e:
        run.status = str(e)
    except StopIteration:
        pass
    run.trace.append({"seq": 0, "kind": "bitset", "status": run.status, "mask": 0, "size": 0, "ms": (time.perf_counter() - start) * 1000, "conflicts": nodes, "blockers": len(known), "literals": 0})
    return run


def propagate_all(m: Matrix, minsup: int, *, reified: bool = True, scope: Scope = Scope(), budget: Budget | None = None, max_size: int | None = None, weights: tuple[float, ...] = (), max_weight: float | None = None) -> Run:
    """Constraint propagation baseline: every frequent itemset by depth-first search with domains.

    Fixing an item to 1 removes the rows without it (coverage); the sum of possible rows under the threshold fails the
    node. The reified form also fixes items to 0 whose own row sum cannot reach the threshold. ``max_size`` and
    ``max_weight`` (a bound on the sum of the items' ``weights``) cut the search where they are reached.
    """
    run, t = Run(), Bitmap(m)
    nodes = fails = cuts = 0
    order = sorted(range(m.n), key=lambda i: (int(t.w @ t.has[:, i]), i))
    order = [i for i in order if not (scope.must | scope.never) >> i & 1]

    def visit(cur: int, rows: np.ndarray, cand: list[int]) -> None:
        nonlocal nodes, fails, cuts
        nodes += 1
        _check(budget, nodes)
        if max_size is not None and cur.bit_count() >= max_size:
            return
        if max_weight is not None:
            left = max_weight - sum(weights[i] for i in bits(cur))
            cand = [i for i in cand if weights[i] <= left + 1e-12]
        got = t.counts(rows) if reified else None
        if reified:
            kept = [i for i in cand if got[i] >= minsup]
            cuts += len(cand) - len(kept)
            cand = kept
        for k, i in enumerate(cand):
            inside = rows[t.has[rows, i]]
            sup = int(got[i]) if reified else int(t.w[inside].sum())
            if sup < minsup:
                fails += 1
                continue
            run.found[cur | 1 << i] = sup
            visit(cur | 1 << i, inside, cand[k + 1:])

    start = time.perf_counter()
    try:
        rows = t.rows(scope.must)
        total = int(t.w[rows].sum())
        if total >= minsup:
            if scope.must and (max_size is None or scope.must.bit_count() <= max_size) and (max_weight is None or sum(weights[i] for i in bits(scope.must)) <= max_weight + 1e-12):
                run.found[scope.must] = total
            visit(scope.must, rows, order)
    except OutOfBudget as e:
        run.status = str(e)
    run.trace.append({"seq": 0, "kind": "node", "status": run.status, "mask": 0, "size": 0, "ms": (time.perf_counter() - start) * 1000, "conflicts": nodes, "blockers": fails, "literals": cuts})
    return run


class SumBound:
    """Incremental bounds of sum(w * x) over 0/1 variables: ``upper`` with open ones taken as 1, ``lower`` as 0."""

    def __init__(self, weights: list[int]):
        self.w, self.state = weights, [None] * len(weights)
        self.upper, self.lower = sum(weights), 0

    def fix(self, k: int, value: bool) -> None:
        if self.state[k] is not None:
            raise ValueError("fixed before")
        self.state[k] = value
        if value:
            self.lower += self.w[k]
        else:
            self.upper -= self.w[k]

    def at_least(self, bound: int) -> bool | None:
        """True or False once decided, None while open."""
        return True if self.lower >= bound else False if self.upper < bound else None


class ReifiedSum:
    """b implies sum >= bound: ``propagate`` gives the value that b must take, or None."""

    def __init__(self, total: SumBound, bound: int):
        self.total, self.bound = total, bound

    def propagate(self) -> bool | None:
        return False if self.total.at_least(self.bound) is False else None
