"""One way in: ``mine`` chooses encoding, search, engine and partitioning; ``Model`` states what is asked for."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import bits
from ..operators import blocking as B
from ..operators.baseline import mine_bruteforce, mine_levelwise, next_level
from ..operators.condense import closed, expand_maximal
from ..operators.frontier import local_length_counts, mine_growing_frontier
from ..operators.itemdb import ItemDB
from ..operators.measure import patterns, support
from ..operators.partition import GROUP_ROWS, Kernel, run_partitioned, run_whole
from ..operators.search import Options
from ..operators.solver import OutOfBudget, Polarity, SolverParams, SolverProfile
from ..session import cut


@dataclass
class MiningResult:
    """``masks`` (``mask, sup``), ``trace`` and the status of the worst group; ``patterns`` names the items."""

    db: ItemDB
    masks: DataFrame
    trace: DataFrame | None
    status: str
    again: Callable[..., "MiningResult"] | None = field(default=None, repr=False)
    settings: dict = field(default_factory=dict)

    @property
    def patterns(self) -> DataFrame:
        """The answer; a run that spent its budget has none (its part of one is in ``masks``)."""
        if self.status != "ok":
            raise OutOfBudget(self.status)
        return patterns(self.masks, self.db)

    def refine(self, condition: Column | None = None, **changes) -> MiningResult:
        """Tighten a finished run: a condition on ``itemset, size, sup, freq`` and settings are filters where that is
        exact (a higher threshold or a size bound on all frequent sets), else the run is repeated with the changes."""
        masks, output = self.masks, self.settings.get("output", "maximal")
        theta = changes.pop("theta", None)
        if (theta is not None or changes) and (output != "frequent" or changes or self.db.minsup(theta) < self.db.minsup(self.settings["theta"])):
            redone = self.again(**(self.settings | changes | ({"theta": theta} if theta is not None else {})))
            return redone.refine(condition) if condition is not None else redone
        if theta is not None:
            masks = masks.where(F.col("sup") >= self.db.minsup(theta))
        if condition is not None:
            n = self.db.n
            named = masks.select("mask", "sup", bits.names_of(F.col("mask"), self.db.names).alias("itemset"), bits.size(F.col("mask"), n).alias("size"), F.round(F.col("sup") / float(max(self.db.m, 1)), 6).alias("freq"))
            masks = named.where(condition).select("mask", "sup")
        return replace(self, masks=masks)


def _conditional(db: ItemDB, must: int) -> ItemDB:
    """Rows that have all of ``must``, and an alphabet without it: a filter before any shuffle."""
    kept = db.masks.where(bits.contains(F.col("mask"), bits.literal(must, db.n), db.n))
    counts = kept.agg(*[F.coalesce(F.sum(F.when(bits.has(F.col("mask"), i, db.n), F.col("w"))), F.lit(0)).alias(str(i)) for i in range(db.n)]).first()
    supports = [0 if must >> i & 1 else int(counts[i]) for i in range(db.n)]
    cleared = kept.select(bits.difference(F.col("mask"), bits.literal(must, db.n), db.n).alias("mask"), "w").groupBy("mask").agg(F.sum("w").alias("w"))
    return ItemDB(cleared, db.names, supports, db.m)


def _without(db: ItemDB, items: int) -> ItemDB:
    """The database without some items: rows that become equal are collapsed, the items' numbers stay."""
    masks = db.masks.select(bits.difference(F.col("mask"), bits.literal(items, db.n), db.n).alias("mask"), "w").groupBy("mask").agg(F.sum("w").alias("w"))
    return ItemDB(cut(masks, "masks"), db.names, [0 if items >> i & 1 else s for i, s in enumerate(db.supports)], db.m)


def mine(
    db: ItemDB, theta: float | int, *, search: str = "growing", blocking: str = B.SUBSET, formulation: str = "primal", coverage: str = "clausal", frequency: str = "reified",
    restriction: str = "free", engine: str = "bitset", polarity: Polarity | None = None, params: SolverParams | None = None, profile: SolverProfile | None = None, bounds: str = "all",
    maximality: str = "blocking", must_contain: list[str] | None = None, must_not: list[str] | None = None, any_of: list[list[str]] | None = None, weights: dict[str, float] | None = None,
    max_weight: float | None = None, min_weight: float | None = None, min_size: int | None = None, max_size: int | None = None, output: str = "maximal", limit: int | None = None,
    seconds: float | None = None, partitioning: str = "prefix", group_rows: int = GROUP_ROWS,
) -> MiningResult:
    """Frequent itemsets of ``db``.

    ``engine``: "bitset" (default), "clausal" (the clause solver with all its options), "propagation" and
    "propagation_plain" (baseline), "levelwise", "bruteforce". ``partitioning``: "prefix" (groups over the cluster),
    "none" (one group, faithful counters) or "frontier" (rounds of aggregations). ``output``: "maximal", "frequent",
    "closed", or "infrequent" (minimal ones; the dual formulation, clausal, one group). An empty database or a
    threshold above its size gives no pattern. ``must_contain`` filters rows first and looks for sets with these items,
    ``must_not`` takes items out of the database. ``any_of`` asks for an item of each group (a disjunction over selected
    variables); ``weights`` (of items, 0 where not named, not negative) are summed and bounded. Bounds from above on
    size and weight of all frequent sets cut the search; other bounds are on what is reported. What is reported as
    maximal is maximal without the bounds.
    """
    settings = {k: v for k, v in locals().items() if k != "db"}
    again = lambda **kw: mine(db, **kw)
    minsup = db.minsup(theta)
    if formulation == "dual" or output == "infrequent":
        search, engine, partitioning = "dual", "clausal", "none" if partitioning == "none" else "prefix"
        blocking = blocking if blocking in (B.SUPERSET, B.SUPERSETS) else B.SUPERSET
    target, must = db, 0
    if must_not:
        target = _without(target, db.mask(must_not))
    if must_contain:
        must = db.mask(must_contain)
        target = _conditional(target, must)
    loads = tuple(float((weights or {}).get(x, 0.0)) for x in db.names)
    if min(loads, default=0.0) < 0:
        raise ValueError("weights of items are not negative")
    cuts = output == "frequent" and formulation != "dual" and (max_size is not None or max_weight is not None)
    if cuts and engine == "bitset" and partitioning != "frontier":
        engine = "propagation"  # all sets up to the bounds, not the subsets of a border
    profile = profile or SolverProfile()
    if polarity or params:
        profile = replace(profile, polarity=polarity or profile.polarity, params=params or profile.params)
    options = Options(search, blocking, coverage, frequency, restriction, profile, bounds, maximality, limit)
    trace, status = None, "ok"
    full_list = engine in ("levelwise", "bruteforce") or engine.startswith("propagation") or engine == "clausal" and search in ("simple", "longest") and blocking in (B.FULL, B.ITEMS)
    if engine == "levelwise":
        masks = mine_levelwise(target, minsup, max_size=max_size - must.bit_count() if cuts and max_size is not None else None)
    elif engine == "bruteforce":
        masks = mine_bruteforce(target, minsup)
    elif partitioning == "frontier":
        masks, _ = mine_growing_frontier(target, minsup)
    else:
        kernel = Kernel(engine, options, seconds, min_size=min_size if engine == "bitset" and output == "maximal" and not must else None)
        if cuts and engine.startswith("propagation"):
            kernel = replace(kernel, max_size=None if max_size is None else max_size - must.bit_count(), weights=loads, max_weight=None if max_weight is None else max_weight - sum(loads[i] for i in bits.bits(must)))
        tagged = run_whole(target, minsup, kernel) if partitioning == "none" else run_partitioned(target, minsup, kernel, group_rows=group_rows)
        tagged = cut(tagged, "mined")
        masks = tagged.where("tag = 'pattern'").select("mask", "sup")
        trace = tagged.where("tag = 'trace'").drop("tag", "sup")
        bad = [r[0] for r in tagged.where("status in ('timeout', 'memout')").select("status").distinct().collect()]
        status = "memout" if "memout" in bad else "timeout" if bad else "ok"
    if must:
        total = target.masks.agg(F.coalesce(F.sum("w"), F.lit(0)).cast("long").alias("sup"))
        masks = masks.select(bits.union(F.col("mask"), bits.literal(must, db.n), db.n).alias("mask"), "sup")
        alone = total.where(F.col("sup") >= minsup).select(bits.literal(must, db.n).alias("mask"), "sup")
        masks = masks.union(alone) if full_list or output == "frequent" else masks.union(alone.join(masks.limit(1).select(F.lit(1).alias("x")), F.lit(True), "left_anti"))
    if output == "infrequent":
        pass
    elif formulation == "dual":
        masks = complement_of_border(db, masks.select("mask"), minsup)
        full_list = True
    if output in ("frequent", "closed") and not full_list:
        masks = expand_maximal(masks, db)
        if must:
            masks = masks.where(bits.contains(F.col("mask"), bits.literal(must, db.n), db.n))
    if output == "closed":
        masks = closed(masks, db.n)
    if output == "maximal" and full_list:
        from ..operators.condense import maximal

        masks = maximal(masks, db.n)
    if min_size:
        masks = masks.where(bits.size(F.col("mask"), db.n) >= min_size)
    if max_size:
        masks = masks.where(bits.size(F.col("mask"), db.n) <= max_size)
    for group in any_of or []:
        masks = masks.where(bits.size(bits.intersection(F.col("mask"), bits.literal(db.mask(group), db.n), db.n), db.n) > 0)
    if max_weight is not None or min_weight is not None:
        table = F.array(*[F.lit(x) for x in loads])
        load = F.aggregate(bits.items_of(F.col("mask"), db.n), F.lit(0.0), lambda a, i: a + F.get(table, i))
        masks = masks.where((load <= (max_weight if max_weight is not None else float("inf")) + 1e-12) & (load >= (min_weight if min_weight is not None else 0.0) - 1e-12))
    return MiningResult(db, masks, trace, status, again, settings)


def complement_of_border(db: ItemDB, border: DataFrame, minsup: int) -> DataFrame:
    """``mask, sup`` of all itemsets that contain no minimal infrequent one, level by level.

    A set does not if its subsets with one item less do not and it is no such set itself: equi-joins only. Each level
    is counted as it is made.
    """
    spark, n = db.spark, db.n
    border = cut(border.select("mask"), "infrequent")
    level = spark.createDataFrame([(bits.from_int(1 << i, n),) for i in range(n)], f"mask {bits.mask_type(n)}").join(border, "mask", "left_anti")
    out, k = None, 1
    while n:
        level = cut(support(db, level), "level")
        out = level if out is None else out.union(level)
        if not level.take(1):
            break
        level, k = next_level(level, n, k).join(border, "mask", "left_anti"), k + 1
    return out if out is not None else spark.createDataFrame([], f"mask {bits.mask_type(n)}, sup long")


def top_k_longest(db: ItemDB, theta: float | int, k: int, **settings) -> DataFrame:
    """``itemset, size, sup, freq`` of k longest maximal itemsets (ties by name).

    The default engine takes sizes from above: the greatest that a scan of row lengths allows, then less, each time
    cutting every branch that cannot reach the size, until k sets are found. With the clause solver every group ends
    after its k longest. The merge is a distributed top-k.
    """
    if settings.get("engine", "bitset") == "bitset" and "partitioning" not in settings:
        minsup = db.minsup(theta)
        most = local_length_counts(db).where(F.col("at_least") >= minsup).agg(F.max("size")).first()[0] or 0
        step, size = 1, most
        while size > 0:
            got = mine(db, theta, min_size=size, **settings)
            if size <= 1 or got.masks.limit(k).count() >= k:
                return got.patterns.orderBy(F.col("size").desc(), "itemset").limit(k)
            size, step = max(1, size - step), 2 * step
    if settings.get("engine") == "clausal":
        settings = {"search": "longest", "limit": k} | settings
    return mine(db, theta, **settings).patterns.orderBy(F.col("size").desc(), "itemset").limit(k)


def top_k_longest(db: ItemDB, theta: float | int, k: int, **settings) -> DataFrame:
    """``itemset, size, sup, freq`` of k longest maximal itemsets (ties by name).

    Every group gives its own; the merge is a distributed top-k. With the clause solver, ``limit`` ends each group
    after its k longest.
    """
    if settings.get("engine") == "clausal":
        settings = {"search": "longest", "limit": k} | settings
    return mine(db, theta, **settings).patterns.orderBy(F.col("size").desc(), "itemset").limit(k)


def is_satisfiable(db: ItemDB, theta: float | int, **settings) -> bool:
    """Is there any frequent itemset (with the given restrictions)? One search; stops at the first answer."""
    must = settings.pop("must_contain", None)
    target = _conditional(db, db.mask(must)) if must else db
    minsup = db.minsup(theta)
    if must:
        return int(target.masks.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]) >= minsup
    if settings:
        return bool(mine(db, theta, **({"search": "decide", "engine": "clausal", "partitioning": "none"} | settings)).masks.take(1))
    return any(s >= minsup for s in db.supports)


@dataclass
class Model:
    """What is wanted, not how: ``Model(db).require(Coverage(), Frequency(0.2), MustContain("x"), MaxSize(3)).solve()``."""

    db: ItemDB
    parts: list = field(default_factory=list)

    def require(self, *parts) -> Model:
        return Model(self.db, [*self.parts, *parts])

    def solve(self, **settings) -> MiningResult:
        kw: dict = {}
        for p in self.parts:
            kw |= p.settings()
        if "theta" not in kw:
            raise ValueError("a model needs a frequency")
        return mine(self.db, **(kw | settings))

    def formula(self, tx: DataFrame) -> DataFrame:
        """The encoding that states the same, as a relation."""
        from ..operators import encode

        kw: dict = {}
        for p in self.parts:
            kw |= p.settings()
        return encode.core(tx, self.db.names, self.db.minsup(kw["theta"]), kind=kw.get("coverage", "clausal"), freq=kw.get("frequency", "reified"))


@dataclass(frozen=True)
class Coverage:
    kind: str = "clausal"

    def settings(self) -> dict:
        return {"coverage": self.kind}


@dataclass(frozen=True)
class Frequency:
    theta: float | int
    kind: str = "reified"

    def settings(self) -> dict:
        return {"theta": self.theta, "frequency": self.kind}


@dataclass(frozen=True)
class MustContain:
    items: str

    def settings(self) -> dict:
        return {"must_contain": self.items.split(",")}


@dataclass(frozen=True)
class MustNotContain:
    items: str

    def settings(self) -> dict:
        return {"must_not": self.items.split(",")}


@dataclass(frozen=True)
class AnyOf:
    """At least one of some items, in each of the groups."""

    groups: tuple[str, ...]

    def settings(self) -> dict:
        return {"any_of": [g.split(",") for g in self.groups]}


@dataclass(frozen=True)
class MaxWeight:
    weights: tuple[tuple[str, float], ...]
    most: float

    def settings(self) -> dict:
        return {"weights": dict(self.weights), "max_weight": self.most, "output": "frequent"}


@dataclass(frozen=True)
class MaxSize:
    size: int

    def settings(self) -> dict:
        return {"max_size": self.size, "output": "frequent"}
