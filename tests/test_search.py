import random

import pytest

from patternspark.functions.bits import bits
from patternspark.operators import blocking as B
from patternspark.operators.bitset import ReifiedSum, SumBound, grow_maximal, propagate_all
from patternspark.operators.formula import Matrix
from patternspark.operators.search import Options, Scope, mine_matrix, minimal_hitting_sets, search_counts
from patternspark.operators.solver import PROFILES, Budget, SolverProfile


def brute(m, minsup):
    fr = {x: m.support(x) for x in range(1, 1 << m.n) if m.support(x) >= minsup}
    mx = {x for x in fr if not any(x != y and x & y == x for y in fr)}
    mi = {x for x in range(1, 1 << m.n) if x not in fr and all(x == 1 << i or x & ~(1 << i) in fr for i in bits(x))}
    return fr, mx, mi


def matrix(seed):
    r = random.Random(seed)
    n = r.randint(1, 6)
    rows = list({r.getrandbits(n) for _ in range(r.randint(1, 10))})
    m = Matrix(rows, [r.randint(1, 4) for _ in rows], n)
    return m, r.randint(1, sum(m.weights) + 1)


@pytest.mark.parametrize("seed", range(25))
def test_all_searches_agree_with_enumeration(seed):
    m, minsup = matrix(seed)
    fr, mx, mi = brute(m, minsup)
    for search in ("simple", "longest"):
        for b in (B.FULL, B.ITEMS):
            assert mine_matrix(m, minsup, Options(search, b)).found == fr
    maximal = [Options("simple", b) for b in (B.SUBSETS, B.SUBSET, "adaptive")] + [Options("longest", b) for b in (B.SUBSETS, B.SUBSET)]
    maximal += [Options("growing", restriction=r, coverage=c, frequency=f, profile=p) for r in ("free", "incremental", "fixed") for c in ("clausal", "reduced", "positive") for f in ("reified", "plain") for p in (SolverProfile(), PROFILES["native"])]
    maximal += [Options("growing", profile=PROFILES[p]) for p in ("jvm", "blackbox")] + [Options("length"), Options("length", bounds="scan"), Options("length", maximality="encoded")]
    for o in maximal:
        got = mine_matrix(m, minsup, o).found
        assert set(got) == mx and all(fr[k] == v for k, v in got.items()), o
    for b in (B.SUPERSET, B.SUPERSETS):
        assert set(mine_matrix(m, minsup, Options("dual", b)).found) == mi
    assert bool(mine_matrix(m, minsup, Options("decide")).found) == bool(fr)
    assert set(grow_maximal(m, minsup).found) == mx
    assert propagate_all(m, minsup).found == fr == propagate_all(m, minsup, reified=False).found


@pytest.mark.parametrize("seed", range(15))
@pytest.mark.parametrize("engine", ["bitset", "clausal"])
def test_prefix_groups_need_no_merge(seed, engine):
    m, minsup = matrix(seed)
    order = sorted(range(m.n), key=lambda i: (m.support(1 << i), i))
    got = {}
    for r, i in enumerate(order):
        own = [k for k, x in enumerate(m.masks) if x >> i & 1]
        if own:
            g, scope = Matrix([m.masks[k] for k in own], [m.weights[k] for k in own], m.n), Scope(1 << i, sum(1 << j for j in order[:r]))
            part = (grow_maximal(g, minsup, scope=scope) if engine == "bitset" else mine_matrix(g, minsup, Options(), scope=scope)).found
            assert not set(part) & set(got)
            got |= part
    assert set(got) == brute(m, minsup)[1]


@pytest.mark.parametrize("seed", range(10))
def test_counters(seed):
    m, minsup = matrix(seed)
    _, mx, _ = brute(m, minsup)
    cmg, lsm, ld = (search_counts(mine_matrix(m, minsup, Options(s)).trace) for s in ("growing", "longest", "length"))
    assert cmg.get("alpha", 0) == lsm.get("lsm", 0) == ld.get("ld_sat", 0) == len(mx)
    assert sum(v for k, v in cmg.items() if k.startswith("beta")) >= len(mx) - 1
    sizes = [r["size"] for r in mine_matrix(m, minsup, Options("longest")).trace if r["kind"] == "lsm"]
    assert sizes == sorted(sizes, reverse=True)
    if ld:
        assert ld["ld_unsat"] == m.n


def test_lone_maximal_set_and_edge_cases():
    m = Matrix([0b1111], [3], 4)
    assert len(mine_matrix(m, 3, Options("simple", B.ITEMS)).found) == 15
    assert mine_matrix(m, 3, Options("growing")).found == {15: 3}
    assert mine_matrix(m, 4, Options("growing")).found == {}
    assert mine_matrix(Matrix([], [], 4), 1, Options()).found == {}
    assert mine_matrix(Matrix([0], [5], 3), 1, Options()).found == {}


def test_blocking_examples():
    ac = 0b0101
    assert B.blocking_clauses(ac, 4, B.SUBSET) == [[2, 4]]
    assert B.blocking_clauses(ac, 4, B.ITEMS) == [[-1, 2, -3, 4]]
    assert len(B.blocking_clauses(ac, 4, B.SUBSETS)) == 3
    assert B.blocking_clauses(ac, 4, B.SUPERSET) == [[-1, -3]]
    assert len(B.blocking_clauses(ac, 4, B.SUPERSETS)) == 4
    for explicit, compact in ((B.SUBSETS, B.SUBSET), (B.SUPERSETS, B.SUPERSET)):
        cut = lambda o: {x for x in range(1, 16) if any(B.violates(x, c) for c in B.blocking_clauses(ac, 4, o))}
        assert cut(explicit) == cut(compact)
    care = B.cube(B.blocking_clauses(ac, 4, B.ITEMS), 4)
    assert [x for x in range(16) if any(x & c == v for c, v in care)] == [ac]


def test_hitting_sets_of_the_worked_example():
    assert minimal_hitting_sets([0b11000, 0b01010]) == [0b01000, 0b10010]


def test_budget_gives_a_status_not_a_wrong_border():
    r = random.Random(5)
    rows = list({r.getrandbits(18) for _ in range(200)})
    m = Matrix(rows, [1] * len(rows), 18)
    run = grow_maximal(m, 4, budget=Budget(seconds=0.01))
    assert run.status == "timeout" and all(m.support(x) >= 4 for x in run.found)


def test_sum_propagators():
    s = SumBound([3, 2, 1])
    s.fix(0, False)
    assert s.at_least(3) is None and ReifiedSum(s, 4).propagate() is False
    s.fix(1, True)
    assert s.at_least(2) is True and ReifiedSum(s, 3).propagate() is None
