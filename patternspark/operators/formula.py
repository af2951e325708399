"""Formulas inside a kernel: the Boolean encodings of a small weighted matrix, given to a solver."""

from __future__ import annotations

from dataclasses import dataclass, field

from ..functions.bits import bits
from .solver import Budget, ClauseSolver, Polarity, SolverParams


@dataclass
class Matrix:
    """Distinct rows with weights over n items."""

    masks: list[int]
    weights: list[int]
    n: int

    @property
    def full(self) -> int:
        return (1 << self.n) - 1

    def support(self, itemset: int) -> int:
        return sum(w for m, w in zip(self.masks, self.weights) if m & itemset == itemset)

    def item_supports(self) -> list[int]:
        return [self.support(1 << i) for i in range(self.n)]


@dataclass
class Formula:
    """A solver with item variables ``item`` and row variables ``row``; more variables are those of a restriction."""

    solver: ClauseSolver
    item: list[int]
    row: list[int]
    negated: list[int] = field(default_factory=list)
    control: int = 0
    length: list[int] = field(default_factory=list)

    def itemset(self) -> int:
        val = self.solver.val
        return sum(1 << i for i, v in enumerate(self.item) if val[v] > 0)

    def rowset(self) -> list[int]:
        return [t for t, v in enumerate(self.row) if self.solver.val[v] > 0]


def build(m: Matrix, minsup: int, *, coverage: str = "clausal", frequency: str = "reified", dual: bool = False, restriction: str = "free", length: bool = False, maximality: bool = False, polarity: Polarity = Polarity(), params: SolverParams = SolverParams(), budget: Budget | None = None, fixed_false: int = 0, fixed_true: int = 0) -> Formula:
    """Coverage and frequency of ``m``; models are (itemset, its rows) with support at least ``minsup`` (``dual``: below).

    ``coverage`` 'clausal', 'reduced' or 'positive'; ``frequency`` 'reified' or 'plain'; ``restriction`` 'free',
    'incremental' or 'fixed'; ``length`` adds variables that fix the size by assumptions.
    """
    s = ClauseSolver(params, budget)
    supports = m.item_supports()
    half = sum(m.weights) / 2
    phase = {"pos": lambda i: True, "neg": lambda i: False, "dynamic": lambda i: supports[i] >= half}[polarity.items]
    item = [s.new_var(phase=phase(i), item=True) for i in range(m.n)]
    row = [s.new_var(phase=polarity.rows == "pos") for _ in m.masks]
    f = Formula(s, item, row)
    for i in range(m.n):  # rarer items first: they decide more
        s.activity[item[i]] = 1.0 - supports[i] / (2 * half + 1)
    for t, mask in zip(row, m.masks):
        absent = [item[i] for i in bits(m.full & ~mask)]
        s.add_clause([t, *absent])
        if coverage == "clausal":
            s.add_pairs(-t, [-x for x in absent])
        elif coverage == "positive":
            for x in absent:
                s.add_pb([1, 1], [-t, -x], 1)
        elif coverage == "reduced":
            s.add_pb([1] * len(absent) + [len(absent)], [-x for x in absent] + [-t], len(absent))
        else:
            raise ValueError(coverage)
    if dual:
        if (total := sum(m.weights)) >= minsup:
            s.add_pb(m.weights, [-t for t in row], total - minsup + 1)
    elif frequency == "reified":
        for i, x in enumerate(item):
            own = [(w, t) for w, t, mask in zip(m.weights, row, m.masks) if mask >> i & 1]
            s.add_pb([w for w, _ in own] + [minsup], [t for _, t in own] + [-x], minsup)
    else:
        s.add_pb(m.weights, row, minsup)
    s.add_clause(item)
    if maximality:
        for i, x in enumerate(item):  # an item left out cannot reach the threshold on the covered rows
            own = [(w, t) for w, t, mask in zip(m.weights, row, m.masks) if mask >> i & 1]
            total = sum(w for w, _ in own)
            if total >= minsup:
                s.add_pb([w for w, _ in own] + [total - minsup + 1], [-t for _, t in own] + [x], total - minsup + 1)
    if restriction in ("incremental", "fixed"):
        f.negated = [s.new_var(phase=True) for _ in item]
        for x, y in zip(item, f.negated):
            s.add_clause([x, y])
        if restriction == "fixed":
            f.control = s.new_var(phase=True)
            s.add_pb([1] * (2 * m.n + 1), [f.control, *item, *f.negated], m.n + 1)
    elif restriction != "free":
        raise ValueError(restriction)
    if length:
        f.length = [s.new_var() for _ in item]
        s.add_pb([1] * (2 * m.n), [*item, *f.length], m.n)
        s.add_pb([1] * (2 * m.n), [-x for x in [*item, *f.length]], m.n)
    for i in bits(fixed_false):
        s.add_clause([-item[i]])
    for i in bits(fixed_true):
        s.add_clause([item[i]])
    return f
