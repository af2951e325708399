"""Search options over a clause solver: simple, longest first, growing, length decreasing, dual, decision.

All are kernels: they take a small weighted matrix and give (itemset, support) pairs and trace records. ``Scope`` says
which part of the search space is theirs when a database is split by prefixes: items that must be in, items that must
not be chosen, and whether larger sets with excluded items make a hit non-maximal.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field
from itertools import combinations

from ..functions.bits import bits
from . import blocking as B
from .formula import Formula, Matrix, build
from .solver import Budget, OutOfBudget, SolverProfile


@dataclass(frozen=True)
class Scope:
    must: int = 0
    never: int = 0


@dataclass
class Run:
    """Results, trace and status of one kernel."""

    found: dict[int, int] = field(default_factory=dict)
    trace: list[dict] = field(default_factory=list)
    status: str = "ok"


@dataclass(frozen=True)
class Options:
    """Everything a search can be told; see the modules of the single parts for the values."""

    search: str = "growing"
    blocking: str = B.SUBSET
    coverage: str = "clausal"
    frequency: str = "reified"
    restriction: str = "free"
    profile: SolverProfile = SolverProfile()
    bounds: str = "all"  # length decreasing: "all" lengths or those a scan allows ("scan")
    maximality: str = "blocking"  # length decreasing: "blocking" or "encoded"
    limit: int | None = None
    max_size: int | None = None


class _Session:
    """A formula, its solver and the trace of calls; feeds the formula anew for each call if the profile asks for it."""

    def __init__(self, m: Matrix, minsup: int, o: Options, scope: Scope, budget: Budget | None, **more):
        self.m, self.minsup, self.o, self.scope, self.run = m, minsup, o, scope, Run()
        self.make: Callable[[], Formula] = lambda: build(
            m, minsup, coverage=o.coverage, frequency=o.frequency, polarity=o.profile.polarity, params=o.profile.params, budget=budget, fixed_false=scope.never, fixed_true=scope.must, **more)
        self.f = self.make()
        self.extra: list[list[int]] = []
        self.blockers = self.literals = 0

    def add(self, lits: list[int], block: bool = True) -> None:
        if self.o.profile.restart:
            self.extra.append(lits)
        self.f.solver.add_clause(lits)
        if block:
            self.blockers += 1
            self.literals += len(lits)

    def solve(self, kind: str, assume: list[int] = (), size_of: bool = True) -> int | None:
        """The found itemset or None; writes one trace record."""
        if self.o.profile.restart:
            self.f = None  # the one before leaves first: two at a time would take twice the memory
            self.f = self.make()
            for c in self.extra:
                self.f.solver.add_clause(c)
        s = self.f.solver
        before, start = (s.conflicts, s.decisions, s.backtracks, s.restarts), time.perf_counter()
        sat = s.solve(assume)
        mask = self.f.itemset() if sat else None
        self.run.trace.append({"seq": len(self.run.trace), "kind": kind if sat else f"{kind}_unsat", "status": "sat" if sat else "unsat", "mask": mask or 0, "size": (mask or 0).bit_count(), "ms": (time.perf_counter() - start) * 1000, "conflicts": s.conflicts - before[0], "blockers": self.blockers, "literals": self.literals, "decisions": s.decisions - before[1], "backtracks": s.backtracks - before[2], "restarts": s.restarts - before[3]})
        return mask

    def solve_with(self, clause: list[int], true: list[int]) -> int | None:
        """A beta search under a temporary clause: a selector that is retired, or a formula that is fed anew."""
        if self.o.profile.restart:
            kept = len(self.extra)
            self.extra += [clause, *[[x] for x in true]]
            mask = self.solve("beta")
            del self.extra[kept:]
            return mask
        s = self.f.solver
        selector = s.new_var()
        s.add_clause([-selector, *clause])
        mask = self.solve("beta", [selector, *true])
        s.add_clause([-selector])
        return mask

    def block(self, mask: int, option: str) -> None:
        f = self.f
        if option == B.FULL:
            own = set(bits(mask))
            rows = set(f.rowset())
            self.add([-v if i in own else v for i, v in enumerate(f.item)] + [-v if t in rows else v for t, v in enumerate(f.row)])
            return
        if option == "adaptive":
            option = B.adaptive(mask.bit_count(), self.m.n, len(self.run.found))
        for c in B.blocking_clauses(mask, self.m.n, option):
            self.add([f.item[x - 1] if x > 0 else -f.item[-x - 1] for x in c])

    def outside(self, mask: int) -> list[int]:
        return [self.f.item[i] for i in bits(self.m.full & ~mask & ~self.scope.never)]

    def keep(self, mask: int) -> None:
        self.run.found[mask] = self.m.support(mask)

    def globally_maximal(self, mask: int) -> bool:
        """No item at all can be added, those of other scopes included."""
        return all(self.m.support(mask | 1 << i) < self.minsup for i in bits(self.m.full & ~mask & self.scope.never))


def _maximal_only(found: dict[int, int]) -> dict[int, int]:
    out: dict[int, int] = {}
    for x in sorted(found, key=lambda a: -a.bit_count()):
        if not any(x & y == x for y in out):
            out[x] = found[x]
    return out


def simple(s: _Session) -> None:
    """Solve, report, block, repeat. Item-only and full blocking report every frequent itemset."""
    while (mask := s.solve("simple")) is not None:
        s.keep(mask)
        s.block(mask, s.o.blocking)
        if s.o.limit and len(s.run.found) >= s.o.limit:
            return


def longest(s: _Session) -> None:
    """Each answer is a largest itemset not yet blocked: its size is raised until that is unsatisfiable."""
    if s.o.profile.restart:
        raise ValueError("longest-first search needs a solver that keeps clauses")
    f = s.f
    n = s.m.n
    size = _Totaliser(s)
    top = n if s.o.max_size is None else min(n, s.o.max_size)
    while True:
        best = s.solve("lsm_probe")
        if best is None:
            s.run.trace[-1]["kind"] = "lsm_unsat"
            return
        while best.bit_count() < top:
            more = s.solve("lsm_probe", [size.at_least(best.bit_count() + 1)])
            if more is None:
                break
            best = more
        top = best.bit_count()  # sizes never rise
        s.run.trace.append({**s.run.trace[-1], "seq": len(s.run.trace), "kind": "lsm", "status": "sat", "mask": best, "size": top, "ms": 0.0, "conflicts": 0, "decisions": 0, "backtracks": 0, "restarts": 0})
        s.f = f
        s.keep(best)
        if s.o.blocking == B.FULL:
            s.f.solver.solve([v if best >> i & 1 else -v for i, v in enumerate(f.item)])
        s.block(best, s.o.blocking)
        if s.o.limit and len(s.run.found) >= s.o.limit:
            return


class _Totaliser:
    """Unary counter over the item variables: output k is forced true only together with k true items."""

    def __init__(self, s: _Session):
        self.s = s
        self.outputs = self._node(list(s.f.item))

    def _node(self, lits: list[int]) -> list[int]:
        if len(lits) == 1:
            return lits
        half = len(lits) // 2
        a, b = self._node(lits[:half]), self._node(lits[half:])
        out = [self.s.f.solver.new_var() for _ in lits]
        for i in range(len(a) + 1):
            for j in range(len(b) + 1):
                # output i+j+1 needs more than i of a or more than j of b
                if i + j < len(out):
                    self.s.add([-out[i + j], *([a[i]] if i < len(a) else []), *([b[j]] if j < len(b) else [])], block=False)
        for k in range(len(out) - 1):
            self.s.add([-out[k + 1], out[k]], block=False)
        return out

    def at_least(self, k: int) -> int:
        return self.outputs[k - 1]


def growing(s: _Session) -> None:
    """Find any unblocked itemset (alpha), then supersets of it (beta) until none; keep the last compact blocker only."""
    o = s.o
    if o.restriction == "fixed":
        return _growing_fixed(s)
    while (mask := s.solve("alpha", list(s.f.negated))) is not None:
        while True:
            f, outside = s.f, s.outside(mask)
            if not outside:
                break
            if o.restriction == "incremental":
                # N_i false forces item i; the blocker of the current set asks for one item outside of it
                s.add(outside)
                more = s.solve("beta", [-f.negated[i] for i in bits(mask)])
            else:
                more = s.solve_with(outside, [f.item[i] for i in bits(mask)])
            if more is None:
                break
            mask = more
        s.keep(mask)
        s.block(mask, B.SUBSET)
        if o.limit and len(s.run.found) >= o.limit:
            return


def minimal_hitting_sets(sets: list[int], limit: int = 100_000) -> list[int]:
    """All minimal sets that meet each of the given masks."""
    out = [0]
    for x in sets:
        hit = [h for h in out if h & x]
        new = [h | 1 << i for h in out if not h & x for i in bits(x)]
        new = [h for h in set(new) if not any(k & h == k for k in hit)]
        out = hit + [h for h in new if not any(k != h and k & h == k for k in new)]
        if len(out) > limit:
            raise OutOfBudget("memout")
    return sorted(out, key=lambda h: (h.bit_count(), h))


def _growing_fixed(s: _Session) -> None:
    """The clause set never grows: blockers stay outside as item sets to be hit, one minimal hitting set a search."""
    f, outside = s.f, []
    never = s.scope.never
    while True:
        mask = None
        for h in minimal_hitting_sets(outside):
            if h & never:
                continue
            mask = s.solve("alpha", [f.control, *[-f.negated[i] for i in bits(h)]])
            if mask is not None:
                break
        if mask is None:
            return
        while s.outside(mask):
            more = s.solve("beta", [-f.control, *[-f.negated[i] for i in bits(mask)], *[f.negated[i] for i in bits(s.m.full & ~mask)]])
            if more is None or more == mask:
                break
            mask = more
        s.keep(mask)
        outside.append(s.m.full & ~mask)
        s.blockers += 1
        if not outside[-1] or s.o.limit and len(s.run.found) >= s.o.limit:
            return


def length_decreasing(s: _Session) -> None:
    """Sizes n, n-1, ..., 1 by assumption; what is found at a size is maximal since all larger sets are blocked."""
    f, n = s.f, s.m.n
    top, low = n, 1
    if s.o.bounds == "scan":
        top = max((k for k in range(n + 1) if sum(w for m, w in zip(s.m.masks, s.m.weights) if m.bit_count() >= k) >= s.minsup), default=0)
    for k in range(top, low - 1, -1):
        assume = f.length[:n - k] + [-x for x in f.length[n - k:]]
        while (mask := s.solve("ld", assume)) is not None:
            s.run.trace[-1]["kind"] = "ld_sat"
            s.keep(mask)
            s.block(mask, B.ITEMS if s.o.maximality == "encoded" else B.SUBSET)
            if s.o.limit and len(s.run.found) >= s.o.limit:
                return
        if s.o.bounds == "scan" and not f.solver.ok:
            return


def dual(s: _Session) -> None:
    """Minimal infrequent itemsets: an infrequent model is shrunk (what the scope asks for stays), its supersets are blocked."""
    while (mask := s.solve("dual")) is not None:
        for i in bits(mask):
            if mask != 1 << i and not s.scope.must >> i & 1 and s.m.support(mask & ~(1 << i)) < s.minsup:
                mask &= ~(1 << i)
        s.keep(mask)
        s.block(mask, s.o.blocking if s.o.blocking in (B.SUPERSETS, B.SUPERSET) else B.SUPERSET)


def decide(s: _Session) -> None:
    """One search: is there any answer?"""
    if (mask := s.solve("decide")) is not None:
        s.keep(mask)


SEARCHES = {"simple": simple, "longest": longest, "growing": growing, "length": length_decreasing, "dual": dual, "decide": decide}


def mine_matrix(m: Matrix, minsup: int, o: Options = Options(), *, scope: Scope = Scope(), budget: Budget | None = None) -> Run:
    """Run a search on a matrix. Searches that report maximal sets report globally maximal ones of their scope."""
    if o.search not in SEARCHES:
        raise ValueError(o.search)
    if m.n == 0 or not m.masks:
        return Run()
    restriction = o.restriction if o.search == "growing" else "free"
    s = _Session(m, minsup, o, scope, budget, restriction=restriction, dual=o.search == "dual", length=o.search == "length", maximality=o.search == "length" and o.maximality == "encoded")
    try:
        if s.f.solver.ok or o.profile.restart:
            SEARCHES[o.search](s)
    except OutOfBudget as e:
        s.run.status = str(e)
    run = s.run
    if o.search in ("growing", "longest", "length") or o.search == "simple" and o.blocking in (B.SUBSET, B.SUBSETS, "adaptive"):
        if o.search == "simple":
            run.found = _maximal_only(run.found)
        if scope.never:
            run.found = {k: v for k, v in run.found.items() if s.globally_maximal(k)}
    return run


def search_counts(trace: list[dict]) -> dict[str, int]:
    out: dict[str, int] = {}
    for r in trace:
        out[r["kind"]] = out.get(r["kind"], 0) + 1
    return out


def subsets(mask: int) -> list[int]:
    ids = bits(mask)
    return [sum(1 << i for i in c) for k in range(1, len(ids) + 1) for c in combinations(ids, k)]
