"""Mining split over a cluster.

Items are ranked by rising support. The group of an item holds the rows with it, full masks kept, and finds the
itemsets whose lowest-ranked item it is; since the group has every row that such a set covers, supports and the
maximality test are exact and groups need no merging. Frequent items have long groups but few items left to add. A
group whose distinct rows exceed a bound is split again by its next item, until it fits or its itemset is complete.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import bits
from ..session import cut
from .bitset import grow_maximal, propagate_all
from .formula import Matrix
from .itemdb import ItemDB
from .measure import support
from .search import Options, Run, Scope, mine_matrix
from .solver import Budget

TRACE = "group_id long, seq int, kind string, status string, mask {mask}, size int, ms double, conflicts long, blockers long, literals long, decisions long, backtracks long, restarts long"
#: Distinct rows of a group that one task takes.
GROUP_ROWS = 200_000
TAGGED = "tag string, group_id long, seq int, kind string, status string, mask {mask}, size int, sup long, ms double, conflicts long, blockers long, literals long, decisions long, backtracks long, restarts long"


@dataclass(frozen=True)
class Kernel:
    """What a group runs; picklable."""

    engine: str = "bitset"  # "bitset", "clausal", "propagation", "propagation_plain"
    options: Options = Options()
    seconds: float | None = None
    must_contain: int = 0
    min_size: int | None = None
    max_size: int | None = None
    weights: tuple[float, ...] = ()  # of the items, not negative
    max_weight: float | None = None

    def __call__(self, m: Matrix, minsup: int, scope: Scope) -> Run:
        budget = Budget(seconds=self.seconds) if self.seconds else None
        if self.engine == "bitset":
            return grow_maximal(m, minsup, scope=scope, budget=budget, must_contain=self.must_contain, limit=self.options.limit, min_size=self.min_size)
        if self.engine == "clausal":
            return mine_matrix(m, minsup, self.options, scope=scope, budget=budget)
        if self.engine in ("propagation", "propagation_plain"):
            return propagate_all(m, minsup, reified=self.engine == "propagation", scope=scope, budget=budget, max_size=self.max_size, weights=self.weights, max_weight=self.max_weight)
        raise ValueError(self.engine)


def _records(run: Run, group: int, n: int) -> pd.DataFrame:
    rows = [("trace", group, r["seq"], r["kind"], r["status"], bits.from_int(r["mask"], n), r["size"], 0, r["ms"], r["conflicts"], r["blockers"], r["literals"], *[r.get(c, 0) for c in ("decisions", "backtracks", "restarts")]) for r in run.trace]
    rows += [("pattern", group, i, "", run.status, bits.from_int(k, n), k.bit_count(), v, 0.0, 0, 0, 0, 0, 0, 0) for i, (k, v) in enumerate(sorted(run.found.items()))]
    return pd.DataFrame(rows, columns=["tag", "group_id", "seq", "kind", "status", "mask", "size", "sup", "ms", "conflicts", "blockers", "literals", "decisions", "backtracks", "restarts"])


def split_by_prefix(db: ItemDB, minsup: int, *, group_rows: int = GROUP_ROWS) -> tuple[DataFrame, list[int]]:
    """``prefix, closed, mask, w`` groups and the item ranking. ``closed``: only the prefix itself is asked for.

    Each round counts rows per prefix; those that are too long are replaced by longer prefixes until none is.
    """
    n = db.n
    order = sorted((i for i in range(n) if db.supports[i] >= minsup), key=lambda i: (db.supports[i], i))
    rank = F.array(*[F.lit(i) for i in order]) if order else F.array().cast("array<int>")
    own = F.filter(rank, lambda i: _bit(F.col("mask"), i, n))
    base = db.masks.select("mask", "w", own.alias("own"))
    # (prefix as positions in ``own``): explode position p, keep what comes after
    step = base.select("mask", "w", F.posexplode("own").alias("p", "item"), "own").select("mask", "w", F.array("item").alias("prefix"), F.slice("own", F.col("p") + 2, n + 1).alias("rest"))
    done = None
    while True:
        long_ = step.groupBy("prefix").agg(F.count(F.lit(1)).alias("rows")).where(F.col("rows") > group_rows).select("prefix")
        if not long_.take(1):
            break
        long_ = cut(long_, "long-names")  # joined as Spark sees fit: their number is the data's
        fits = step.join(long_, "prefix", "left_anti").select("prefix", F.lit(False).alias("closed"), "mask", "w")
        big = cut(step.join(long_, "prefix", "left_semi"), "long-prefixes")
        # the prefix alone: what can be added is known from counts, so its group is one row per distinct extension
        alone = big.select("prefix", F.lit(True).alias("closed"), "mask", "w")
        done = fits.union(alone) if done is None else done.union(fits).union(alone)
        step = big.select("mask", "w", "prefix", F.posexplode("rest").alias("p", "item"), "rest").select("mask", "w", F.concat("prefix", F.array("item")).alias("prefix"), F.slice("rest", F.col("p") + 2, n + 1).alias("rest"))
    last = step.select("prefix", F.lit(False).alias("closed"), "mask", "w")
    return (last if done is None else done.union(last)), order


def _bit(mask, item, n: int):
    if bits.is_wide(n):
        return F.getbit(F.element_at(mask, (F.floor(item / bits.WORD) + 1).cast("int")), (item % bits.WORD).cast("int")) == 1
    return F.getbit(mask, item) == 1


def closed_prefixes(groups: DataFrame, minsup: int, n: int) -> DataFrame:
    """``mask, sup`` of closed prefixes that are frequent and maximal, by distributed counts (never one task's rows)."""
    own = groups.where("closed")
    total = own.groupBy("prefix").agg(F.sum("w").alias("sup")).where(F.col("sup") >= minsup)
    more = own.select("prefix", "w", F.explode(F.array_except(bits.items_of(F.col("mask"), n), F.col("prefix"))).alias("item"))
    grows = more.groupBy("prefix", "item").agg(F.sum("w").alias("s")).where(F.col("s") >= minsup).select("prefix").distinct()
    left = total.join(grows, "prefix", "left_anti")
    return left.select(_mask_of(F.col("prefix"), n).alias("mask"), "sup")


def _mask_of(items, n: int):
    return bits.of_items(items, n)


def infrequent_extensions(groups: DataFrame, minsup: int, n: int, order: list[int]) -> DataFrame:
    """``mask, sup`` of closed prefixes that are infrequent, and of those with one later item that together are."""
    own = groups.where("closed")
    total = own.groupBy("prefix").agg(F.sum("w").alias("sup"))
    ranks = F.array(*[F.lit(i) for i in order])
    later = total.where(F.col("sup") >= minsup).select("prefix", F.explode(F.slice(ranks, F.array_position(ranks, F.element_at("prefix", -1)).cast("int") + 1, n)).alias("item"))
    have = own.select("prefix", "w", F.explode(bits.items_of(F.col("mask"), n)).alias("item")).groupBy("prefix", "item").agg(F.sum("w").alias("s"))
    more = later.join(have, ["prefix", "item"], "left").where(F.coalesce("s", F.lit(0)) < minsup).select(_mask_of(F.array_append("prefix", F.col("item")), n).alias("mask"), F.coalesce("s", F.lit(0)).alias("sup"))
    return more.union(total.where(F.col("sup") < minsup).select(_mask_of(F.col("prefix"), n).alias("mask"), "sup"))


def run_partitioned(db: ItemDB, minsup: int, kernel: Kernel, *, group_rows: int = GROUP_ROWS) -> DataFrame:
    """Tagged rows (patterns and trace) of every group; all frequent sets for propagation kernels, else maximal ones."""
    n = db.n
    groups, order = split_by_prefix(db, minsup, group_rows=group_rows)
    place = {i: r for r, i in enumerate(order)}
    rare = sum(1 << i for i in range(n) if i not in place)
    everything, dual = kernel.engine.startswith("propagation"), kernel.engine == "clausal" and kernel.options.search == "dual"

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        prefix = [int(i) for i in key[0]]
        if key[1] and not everything:
            return _records(Run(), 0, n)
        m = Matrix([bits.to_int(x) for x in group["mask"]], [int(x) for x in group["w"]], n)
        below = place[prefix[-1]]
        must = sum(1 << i for i in prefix)
        never = (rare | sum(1 << i for i, r in place.items() if r <= below)) & ~must
        if key[1]:  # closed: the prefix itself and nothing else
            return _records(Run({must: sum(m.weights)} if sum(m.weights) >= minsup else {}), must, n)
        return _records(kernel(m, minsup, Scope(must, never)), must & ((1 << bits.WORD) - 1), n)

    schema = TAGGED.format(mask=bits.mask_type(n))
    body = groups if everything else groups.where("not closed")
    out = body.groupBy("prefix", "closed").applyInPandas(run, schema)
    if everything:
        return out
    if dual:  # infrequent items have no group; in a group only subsets with the prefix were looked at
        singles = db.spark.createDataFrame([(bits.from_int(1 << i, n), int(db.supports[i])) for i in range(n) if i not in place], f"mask {bits.mask_type(n)}, sup long")
        found = cut(out, "dual")
        more = found.where("tag = 'pattern'").select("mask", "sup").union(infrequent_extensions(groups, minsup, n, order)).distinct()
        smaller = more.select("mask", F.explode(bits.items_of(F.col("mask"), n)).alias("i")).select("mask", bits.without_item(F.col("mask"), F.col("i"), n).alias("sub")).where(bits.size(F.col("sub"), n) > 0)
        low = support(db, smaller.select(F.col("sub").alias("mask"))).where(F.col("sup") < minsup).select(F.col("mask").alias("sub"))
        bad = smaller.join(low, "sub", "left_semi").select("mask").distinct()
        out, alone = found.where("tag <> 'pattern'"), more.join(bad, "mask", "left_anti").union(singles)
    else:
        alone = closed_prefixes(groups, minsup, n)
    alone = alone.select(F.lit("pattern").alias("tag"), F.lit(0).cast("long").alias("group_id"), F.lit(0).alias("seq"), F.lit("").alias("kind"), F.lit("ok").alias("status"), "mask", bits.size(F.col("mask"), n).alias("size"), F.col("sup").cast("long").alias("sup"), F.lit(0.0).alias("ms"), *[F.lit(0).cast("long").alias(c) for c in ("conflicts", "blockers", "literals", "decisions", "backtracks", "restarts")])
    return out.union(alone)


def run_whole(db: ItemDB, minsup: int, kernel: Callable[[Matrix, int, Scope], Run]) -> DataFrame:
    """The same from one group: faithful counters. For databases whose distinct rows fit a task."""
    n = db.n

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        group = group.assign(mask=[bits.to_int(x) for x in group["mask"]]).sort_values("mask", ignore_index=True)
        m = Matrix([int(x) for x in group["mask"]], [int(x) for x in group["w"]], n)
        return _records(kernel(m, minsup, Scope()), 0, n)

    return db.masks.select("mask", "w", F.lit(0).alias("g")).groupBy("g").applyInPandas(run, TAGGED.format(mask=bits.mask_type(n)))
