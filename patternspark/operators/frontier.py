"""Growing search as distributed rounds: all open sets grow together, supports are Spark aggregations.

For databases whose groups no task can hold. An open set has a tail of items that may join it, those after its own in
the order of rising support. A round counts, in one aggregation, every open set with each item of its tail and with the
whole tail. A tail that fits whole ends its set; items that all of a set's rows have join at once; else each frequent
item opens a set of its own with the items after it. Sets whose tail lies under a found one are dropped. Open sets, the
found ones and their check are tables: nothing but counts reaches the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import bits
from ..session import cut
from .itemdb import ItemDB
from .measure import matches
from .solver import OutOfBudget

#: Found sets are held against open ones up to this many; more open sets are counted then, and the result is the same.
MOST_COVERS = 20_000
#: Stands for the whole tail among the items of a round's counts.
_ALL = -1


def grow_round(db: ItemDB, open_: DataFrame, minsup: int) -> DataFrame:
    """``mask, tail, sup, item, s``: support of each open set with each item of its tail, and with all (item -1), if frequent."""
    n = db.n
    hit = matches(db, open_.select("mask", "tail", "sup")).withColumn("in", bits.intersection(F.col("row"), F.col("tail"), n))
    items = F.when(F.col("in") == F.col("tail"), F.array_append(bits.items_of(F.col("in"), n), F.lit(_ALL))).otherwise(bits.items_of(F.col("in"), n))
    return hit.select("mask", "tail", "sup", "w", F.explode(items).alias("item")).groupBy("mask", "tail", "sup", "item").agg(F.sum("w").alias("s")).where(F.col("s") >= minsup)


def mine_growing_frontier(db: ItemDB, minsup: int, *, max_rounds: int | None = None) -> tuple[DataFrame, dict[str, int]]:
    """Maximal frequent itemsets (``mask, sup``) and counters.

    A round adds an item to every open set, so there are at most as many as items; if ``max_rounds`` is set and they
    are spent before the last open set, OutOfBudget is raised and there is no border.
    """
    spark, n = db.spark, db.n
    kind = bits.mask_type(n)
    order = sorted((i for i in range(n) if db.supports[i] >= minsup), key=lambda i: (db.supports[i], i))
    place = [n] * max(n, 1)
    for p, i in enumerate(order):
        place[i] = p
    ranks = F.array(*[F.lit(p) for p in place])
    start = [(bits.from_int(1 << i, n), bits.from_int(sum(1 << j for j in order[p + 1:]), n), int(db.supports[i])) for p, i in enumerate(order)]
    open_ = spark.createDataFrame(start, f"mask {kind}, tail {kind}, sup long")
    found = spark.createDataFrame([], f"mask {kind}, sup long")
    stats = {"rounds": 0, "sets": len(order)}
    while open_.take(1):
        if max_rounds is not None and stats["rounds"] >= max_rounds:
            raise OutOfBudget("rounds")
        stats["rounds"] += 1
        counted = grow_round(db, open_, minsup).groupBy("mask", "tail", "sup").agg(
            F.max(F.when(F.col("item") == _ALL, F.col("s"))).alias("whole"),
            F.array_sort(F.collect_list(F.when((F.col("item") != _ALL) & (F.col("s") < F.col("sup")), F.struct(F.get(ranks, F.col("item")).alias("p"), F.col("item"), F.col("s"))))).alias("more"),
            F.collect_list(F.when((F.col("item") != _ALL) & (F.col("s") == F.col("sup")), F.col("item"))).alias("same"),
        )
        now = cut(open_.join(counted, ["mask", "tail", "sup"], "left"), "open")
        ended = now.where("whole is not null").select(bits.union(F.col("mask"), F.col("tail"), n).alias("mask"), F.col("whole").alias("sup"))
        grown = now.where("whole is null").select(bits.union(F.col("mask"), bits.of_items(F.coalesce("same", F.array().cast("array<int>")), n), n).alias("mask"), "sup", F.coalesce("more", F.array().cast("array<struct<p:int,item:int,s:bigint>>")).alias("more"))
        ended = ended.union(grown.where(F.size("more") == 0).select("mask", "sup"))
        found = cut(found.union(ended).distinct(), "found")
        kids = grown.select("mask", "more", F.posexplode("more").alias("at", "x")).select(
            bits.with_item(F.col("mask"), F.col("x.item"), n).alias("mask"), bits.of_items(F.slice("more.item", F.col("at") + 2, n + 1), n).alias("tail"), F.col("x.s").alias("sup"))
        found_now = found.select(F.col("mask").alias("cover"))
        if found_now.limit(MOST_COVERS + 1).count() <= MOST_COVERS:
            kids = kids.join(F.broadcast(found_now), bits.contains(F.col("cover"), bits.union(F.col("mask"), F.col("tail"), n), n), "left_anti")
        open_ = cut(kids, "open")
        stats["sets"] += open_.count()
    return maximal_of(db, found, minsup), stats


def maximal_of(db: ItemDB, frequent: DataFrame, minsup: int) -> DataFrame:
    """Those of some frequent itemsets ``mask, sup`` that no single item can join: one aggregation."""
    n = db.n
    hit = matches(db, frequent.select("mask")).select("mask", "w", F.explode(bits.items_of(bits.difference(F.col("row"), F.col("mask"), n), n)).alias("item"))
    grows = hit.groupBy("mask", "item").agg(F.sum("w").alias("s")).where(F.col("s") >= minsup).select("mask").distinct()
    return cut(frequent.join(grows, "mask", "left_anti"), "border")


def local_length_counts(db: ItemDB) -> DataFrame:
    """``size, rows, at_least``: rows by number of items and the reverse cumulative sum, which bounds possible lengths."""
    hist = db.masks.groupBy(bits.size(F.col("mask"), db.n).alias("size")).agg(F.sum("w").alias("rows"))
    down = Window.orderBy(F.col("size").desc()).rowsBetween(Window.unboundedPreceding, Window.currentRow)  # at most n + 1 rows
    return hist.select("size", "rows", F.sum("rows").over(down).cast("long").alias("at_least"))
