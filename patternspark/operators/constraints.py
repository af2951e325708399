"""Constraints on itemsets and sets of itemsets: set algebra, coverage of items and rows, rules, class measures."""

from __future__ import annotations

from collections.abc import Callable, Mapping, Sequence
from dataclasses import dataclass, field
from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import bits
from ..session import cut
from .itemdb import ItemDB
from .measure import MAX_PATTERNS, bounded, matches, patterns, support

# Set algebra on mask columns


def equal(p: Column, q: Column) -> Column:
    return p == q


def member(p: Column, item: int, n: int) -> Column:
    return bits.has(p, item, n)


def difference_is(p: Column, q: Column, r: Column, n: int) -> Column:
    return bits.difference(p, q, n) == r


def intersection_is(p: Column, q: Column, r: Column, n: int) -> Column:
    return bits.intersection(p, q, n) == r


def union_is(p: Column, q: Column, r: Column, n: int) -> Column:
    return bits.union(p, q, n) == r


#: Clauses per item over (p, q, r) = (1, 2, 3) of the same constraints.
CNF = {
    "equal": [[-1, 2], [1, -2]],
    "difference": [[-3, 1], [-3, -2], [3, -1, 2]],
    "intersection": [[-3, 1], [-3, 2], [3, -1, -2]],
    "union": [[3, -1], [3, -2], [-3, 1, 2]],
}


def set_cnf(kind: str, n: int) -> list[list[int]]:
    """Clauses for all items; variable of set j (1, 2, 3) and item i is (j - 1) * n + i + 1."""
    return [[(1 if x > 0 else -1) * ((abs(x) - 1) * n + i + 1) for x in c] for i in range(n) for c in CNF[kind]]


# Boolean expressions to CNF (equivalence, implication)

Expr = tuple | int


def to_cnf(e: Expr) -> list[list[int]]:
    """Clauses of an expression over variables 1, 2, ...: an int is a literal, else ("and" | "or" | "not" | "implies" |
    "iff", ...). Distribution keeps the variables; clauses with a literal and its negation go."""
    clauses = _cnf(_nnf(e, False))
    clean = {tuple(sorted(set(c), key=lambda x: (abs(x), x))) for c in clauses if not any(-x in c for x in c)}
    return sorted([list(c) for c in clean if not any(set(d) < set(c) for d in clean)])


def _nnf(e: Expr, neg: bool) -> Expr:
    if isinstance(e, int):
        return -e if neg else e
    op, *args = e
    if op == "not":
        return _nnf(args[0], not neg)
    if op == "implies":
        return _nnf(("or", ("not", args[0]), args[1]), neg)
    if op == "iff":
        return _nnf(("and", ("implies", args[0], args[1]), ("implies", args[1], args[0])), neg)
    if op not in ("and", "or"):
        raise ValueError(op)
    return ("or" if (op == "and") == neg else "and", *[_nnf(a, neg) for a in args])


def _cnf(e: Expr) -> list[list[int]]:
    if isinstance(e, int):
        return [[e]]
    parts = [_cnf(a) for a in e[1:]]
    return [c for p in parts for c in p] if e[0] == "and" else [[x for c in pick for x in c] for pick in product(*parts)]


# Expressions over the chosen items


@dataclass(frozen=True)
class Selected:
    """The items of a mask column as terms of an expression: disjunctions, conjunctions, numbers and sums over those
    that are chosen, and set operations with named items. Terms are columns, so +, -, * and comparisons join them."""

    names: Sequence[str]
    mask: Column = field(default_factory=lambda: F.col("mask"))

    @property
    def n(self) -> int:
        return len(self.names)

    def _of(self, which: Callable[[str], bool]) -> Column:
        return bits.literal(sum(1 << i for i, x in enumerate(self.names) if which(x)), self.n)

    def any(self, which: Callable[[str], bool]) -> Column:
        """Some chosen item is one of these."""
        return self.count(which) > 0

    def all(self, which: Callable[[str], bool]) -> Column:
        """Every chosen item is one of these."""
        return bits.contains(self._of(which), self.mask, self.n)

    def count(self, which: Callable[[str], bool] = lambda x: True) -> Column:
        return bits.size(bits.intersection(self.mask, self._of(which), self.n), self.n)

    def sum(self, values: Mapping[str, float]) -> Column:
        table = F.array(*[F.lit(float(values.get(x, 0.0))) for x in self.names])
        return F.aggregate(bits.items_of(self.mask, self.n), F.lit(0.0), lambda a, i: a + F.get(table, i))

    def union(self, other: Column) -> Selected:
        return Selected(self.names, bits.union(self.mask, other, self.n))

    def intersection(self, other: Column) -> Selected:
        return Selected(self.names, bits.intersection(self.mask, other, self.n))

    def minus(self, other: Column) -> Selected:
        return Selected(self.names, bits.difference(self.mask, other, self.n))


# Quantities


def with_area(frequent: DataFrame, db: ItemDB) -> DataFrame:
    """``itemset, size, sup, area``: support times size."""
    return patterns(frequent, db).select("itemset", "size", "sup", (F.col("sup") * F.col("size")).alias("area"))


def overlap_pairs(db: ItemDB, masks: DataFrame) -> DataFrame:
    """``p, q, overlap, coverage2`` for pairs p < q: rows under both, and that share times the items in common.

    Pairs are those of a stated set of at most MAX_PATTERNS patterns (checked); their unions are counted once each.
    """
    n = db.n
    a, b = masks.select(F.col("mask").alias("p")), bounded(masks.select(F.col("mask").alias("q")), MAX_PATTERNS, "patterns to pair")
    pairs = a.join(b, F.col("p") < F.col("q")).withColumn("mask", bits.union(F.col("p"), F.col("q"), n))
    counted = pairs.join(support(db, pairs.select("mask")), "mask")
    return counted.select("p", "q", F.col("sup").alias("overlap"), F.round(F.col("sup") / float(max(db.m, 1)) * bits.size(bits.intersection(F.col("p"), F.col("q"), n), n), 6).alias("coverage2"))


def cover_items(db: ItemDB, masks: DataFrame) -> DataFrame:
    """One row ``covered, missing``: whether every item lies in some pattern, and how many do not."""
    got = masks.select(F.explode(bits.items_of(F.col("mask"), db.n)).alias("i")).agg(F.countDistinct("i").alias("c"))
    missing = F.lit(db.n) - F.col("c")
    return got.select((missing == 0).alias("covered"), missing.cast("long").alias("missing"))


def cover_transactions(db: ItemDB, masks: DataFrame) -> DataFrame:
    """One row ``covered, missing``: whether every transaction has some whole pattern, and how many have none."""
    none = matches(db, masks.select("mask").distinct(), "left_anti")
    missing = F.coalesce(F.sum("w"), F.lit(0)).cast("long")
    return none.agg(missing.alias("missing")).select((F.col("missing") == 0).alias("covered"), "missing")


def association_rules(frequent: DataFrame, db: ItemDB, minconf: float, *, max_head: int | None = 1) -> DataFrame:
    """``body, head, sup, confidence, lift`` from all frequent itemsets; heads of up to ``max_head`` items (None: any).

    Bodies and heads are subsets of a frequent itemset, so both supports are joined from the same table.
    """
    n = db.n
    sets = frequent.where(bits.size(F.col("mask"), n) >= 2)
    if max_head == 1:
        split = sets.select("mask", "sup", F.explode(F.transform(bits.items_of(F.col("mask"), n), lambda i: bits.single(i, n))).alias("h"))
    else:
        size = bits.size(F.col("h"), n)
        split = sets.select("mask", "sup", F.explode(bits.submasks(F.col("mask"), n)).alias("h")).where((size > 0) & (size < bits.size(F.col("mask"), n)))
        split = split.where(size <= max_head) if max_head else split
    split = split.select("mask", "sup", "h", bits.difference(F.col("mask"), F.col("h"), n).alias("b"))
    known = frequent.select("mask", "sup")
    conf = F.col("sup") / F.col("bs")
    kept = split.join(known.select(F.col("mask").alias("b"), F.col("sup").alias("bs")), "b").where(F.round(conf, 9) >= minconf)
    return kept.join(known.select(F.col("mask").alias("h"), F.col("sup").alias("hs")), "h").select(
        bits.names_of(F.col("b"), db.names).alias("body"), bits.names_of(F.col("h"), db.names).alias("head"), "sup",
        F.round(conf, 6).alias("confidence"), F.round(conf * float(db.m) / F.col("hs"), 6).alias("lift"),
    )


def discriminative(db: ItemDB, frequent: DataFrame, positive: int) -> DataFrame:
    """``itemset, size, sup, sup_pos, info_gain`` of itemsets without the class item ``positive`` (its number).

    The gain is in bits between the class's entropy and that given presence of the itemset. Supports in the class are
    the supports of the itemset joined with the class item, in the same counting pass.
    """
    n = db.n
    cls = bits.literal(1 << positive, n)
    sets = frequent.where(~bits.has(F.col("mask"), positive, n))
    both = support(db, sets.select(bits.union(F.col("mask"), cls, n).alias("mask"))).select(bits.difference(F.col("mask"), cls, n).alias("mask"), F.col("sup").alias("sup_pos"))
    m, p = float(max(db.m, 1)), float(db.supports[positive])

    def entropy(a: Column, total: Column) -> Column:
        q = a / total
        return F.when((q <= 0) | (q >= 1) | q.isNull(), F.lit(0.0)).otherwise(-q * F.log2(q) - (1 - q) * F.log2(1 - q))

    base = entropy(F.lit(p), F.lit(m))
    s, sp = F.col("sup").cast("double"), F.col("sup_pos").cast("double")
    rest = F.lit(m) - s
    gain = base - s / m * entropy(sp, s) - rest / m * entropy(F.lit(p) - sp, F.when(rest > 0, rest))
    joined = sets.join(both, "mask")
    return joined.select(bits.names_of(F.col("mask"), db.names).alias("itemset"), bits.size(F.col("mask"), db.n).alias("size"), "sup", "sup_pos", F.round(gain, 6).alias("info_gain"))


def k_pattern_set(db: ItemDB, cand: DataFrame, k: int, *, max_overlap_items: int | None = 0, max_overlap_rows: int | None = None, cover_all_items: bool = False) -> DataFrame:
    """``masks, area, rows``: sets of k patterns (rising) of a candidate table ``mask, sup`` under the constraints.

    Sets grow by one pattern a round and are pruned pairwise (shared items, rows under both), so a set is never built
    from two patterns that may not meet. ``rows`` sums supports. With ``max_overlap_items`` 0 and areas summed this is
    tiling; with ``cover_all_items`` the union must hold every item. Candidates are a stated set of at most
    MAX_PATTERNS (checked).
    """
    n = db.n
    base = cut(cand.select("mask", "sup", (F.col("sup") * bits.size(F.col("mask"), n)).alias("area")), "candidates")
    pairs = base.select(F.col("mask").alias("p")).join(bounded(base.select(F.col("mask").alias("q")), MAX_PATTERNS, "candidates"), F.col("p") < F.col("q"))
    if max_overlap_items is not None:
        pairs = pairs.where(bits.size(bits.intersection(F.col("p"), F.col("q"), n), n) <= max_overlap_items)
    if max_overlap_rows is not None:
        joint = pairs.withColumn("mask", bits.union(F.col("p"), F.col("q"), n))
        pairs = joint.join(support(db, joint.select("mask")), "mask").where(F.col("sup") <= max_overlap_rows).select("p", "q")
    pairs = cut(pairs, "pattern-pairs")
    sets = base.select(F.array("mask").alias("masks"), F.col("mask").alias("last"), F.col("mask").alias("u"), "area", F.col("sup").alias("rows"))
    for size in range(2, k + 1):
        nxt = base.select(F.col("mask").alias("q"), F.col("area").alias("more"), F.col("sup").alias("own"))
        grown = sets.join(pairs, F.col("last") == F.col("p")).join(nxt, "q")
        if size > 2:  # the new pattern must be allowed beside every earlier one
            each = grown.select("masks", "q", "area", "rows", "more", "own", "u", F.explode("masks").alias("e")).join(pairs.select(F.col("p").alias("e"), "q"), ["e", "q"])
            grown = each.groupBy("masks", "q", "area", "rows", "more", "own", "u").agg(F.count(F.lit(1)).alias("c")).where(F.col("c") == size - 1)
        sets = grown.select(F.array_append("masks", F.col("q")).alias("masks"), F.col("q").alias("last"), bits.union(F.col("u"), F.col("q"), n).alias("u"), (F.col("area") + F.col("more")).alias("area"), (F.col("rows") + F.col("own")).alias("rows"))
    if cover_all_items:
        sets = sets.where(bits.size(F.col("u"), n) == n)
    return sets.select("masks", "area", "rows")


def conceptual_clustering(db: ItemDB, cand: DataFrame, k: int) -> DataFrame:
    """``masks, rows``: k patterns whose coverages part the transactions: no row under two of them, every row under one."""
    return k_pattern_set(db, cand, k, max_overlap_items=None, max_overlap_rows=0).where(F.col("rows") == db.m).select("masks", "rows")


def concept_learning(db: ItemDB, cand: DataFrame, k: int, positive: int, *, max_negative: int = 0) -> DataFrame:
    """``masks, covered``: k patterns that each cover at most ``max_negative`` rows outside of the class, by class rows covered.

    ``positive`` is the class's item; candidates ``mask, sup`` have it not. What a set of patterns covers is counted
    row by row (a row under several of them counts once).
    """
    n = db.n
    cls = bits.literal(1 << positive, n)
    own = cand.where(~bits.has(F.col("mask"), positive, n)).select("mask", "sup")
    inside = support(db, own.select(bits.union(F.col("mask"), cls, n).alias("mask"))).select(bits.difference(F.col("mask"), cls, n).alias("mask"), F.col("sup").alias("inside"))
    pure = cut(own.join(inside, "mask").where((F.col("sup") - F.col("inside") <= max_negative) & (F.col("inside") > 0)).select("mask", F.col("inside").alias("sup")), "pure")
    sets = cut(k_pattern_set(db, pure, k, max_overlap_items=None).select(F.monotonically_increasing_id().alias("id"), "masks"), "pattern-sets")
    each = sets.select("id", F.explode("masks").alias("mask"))
    rows = matches(db, pure.select("mask")).where(bits.has(F.col("row"), positive, n)).select("mask", "row", "w")
    covered = each.join(rows, "mask").select("id", "row", "w").distinct().groupBy("id").agg(F.sum("w").alias("covered"))
    return sets.join(covered, "id").select("masks", "covered")


def redescriptions(db: ItemDB, cand: DataFrame, view: int, min_jaccard: float) -> DataFrame:
    """``p, q, together, jaccard``: patterns over the items of ``view`` and over the others that cover nearly the same rows.

    Candidates of one view meet those of the other only where both cover a common row: pairs come from the supports of
    unions that reach what the Jaccard bound asks for. At most MAX_PATTERNS of each (checked).
    """
    n = db.n
    here, there = bits.literal(view, n), bits.literal(((1 << n) - 1) & ~view, n)
    a = cand.where(bits.contains(here, F.col("mask"), n)).select(F.col("mask").alias("p"), F.col("sup").alias("sp"))
    b = cand.where(bits.contains(there, F.col("mask"), n)).select(F.col("mask").alias("q"), F.col("sup").alias("sq"))
    # the Jaccard coefficient is at most the ratio of the supports
    pairs = cut(a.join(bounded(b, MAX_PATTERNS, "patterns"), (F.least("sp", "sq") >= min_jaccard * F.greatest("sp", "sq"))).withColumn("mask", bits.union(F.col("p"), F.col("q"), n)), "views")
    found = pairs.join(support(db, pairs.select("mask")), "mask")
    j = F.col("sup") / (F.col("sp") + F.col("sq") - F.col("sup"))
    return found.where(F.round(j, 9) >= min_jaccard).select("p", "q", F.col("sup").alias("together"), F.round(j, 6).alias("jaccard"))


def minimal_reducts(df: DataFrame, attributes: list[str], decision: str) -> DataFrame:
    """``reduct, size``: smallest attribute sets that tell all rows of different decision apart as well as all do.

    Distinct attribute rows (at most MAX_PATTERNS, checked) are compared pairwise once; what tells a pair apart is a
    clause, and the minimal hitting sets of the clauses (at most 2^attributes) are the answer.
    """
    from .search import minimal_hitting_sets

    rows = df.select(*attributes, decision).distinct()
    a = rows.select(*[F.col(x).alias(f"a_{x}") for x in attributes], F.col(decision).alias("da"))
    b = rows.select(*[F.col(x).alias(f"b_{x}") for x in attributes], F.col(decision).alias("db"))
    mask = sum((F.when(~F.col(f"a_{x}").eqNullSafe(F.col(f"b_{x}")), 1 << i).otherwise(0) for i, x in enumerate(attributes)), F.lit(0))
    clauses = [r[0] for r in a.join(bounded(b, MAX_PATTERNS, "distinct rows"), F.col("da") < F.col("db")).select(mask.alias("c")).distinct().where("c > 0").collect()]  # at most 2^attributes
    least = [c for c in clauses if not any(d != c and d & c == d for d in clauses)]
    found = minimal_hitting_sets(sorted(least))
    size = min((h.bit_count() for h in found), default=0)
    out = [(",".join(sorted(attributes[i] for i in bits.bits(h))), size) for h in found if h.bit_count() == size and h]
    return df.sparkSession.createDataFrame(out, "reduct string, size int")
