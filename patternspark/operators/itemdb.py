"""Itemset databases: a dictionary of items and weighted row masks.

Equal rows are collapsed with a weight (lossless for support), so what follows depends on distinct rows. The source is
read once: transactions collapse before they are counted and mapped to masks. Baskets whose items a table lists become
masks while they are gathered (one shuffle of numbers); others are gathered as sets of strings. The masks are written:
every later step reads them and not the source. The dictionary has a checked bound.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import bits
from ..session import cut

#: Largest dictionary; beyond, raise the threshold (infrequent items leave first) or take fewer attributes.
MAX_ITEMS = 100_000
#: Dictionaries up to this size are part of the plan as a map; longer ones are joined.
MAP_ITEMS = 2048
#: Words of masks that are gathered as numbers; baskets of more listed items are gathered as sets.
GATHER_WORDS = 16


def absolute(theta: float | int, m: int) -> int:
    """Rows a threshold asks for: an int is taken as it is, a share is rounded up."""
    if isinstance(theta, bool) or theta <= 0 or (isinstance(theta, float) and theta > 1):
        raise ValueError(f"threshold {theta}")
    return theta if isinstance(theta, int) else max(1, math.ceil(theta * m - 1e-9))


@dataclass
class ItemDB:
    """``masks(mask, w)``; ``names[k]`` and ``supports[k]`` of item k (name order); ``m`` rows, empty ones included."""

    masks: DataFrame
    names: list[str]
    supports: list[int]
    m: int
    dropped: int = 0
    cache: dict = field(default_factory=dict, repr=False)

    @property
    def n(self) -> int:
        return len(self.names)

    @property
    def spark(self) -> SparkSession:
        return self.masks.sparkSession

    def minsup(self, theta: float | int) -> int:
        return absolute(theta, self.m)

    def mask(self, items: list[str] | str) -> int:
        items = [x for x in items.split(",") if x] if isinstance(items, str) else items
        return sum(1 << self.names.index(x) for x in set(items))

    def rows(self) -> tuple[list[int], list[int]]:
        """Masks and weights on the driver, for formulas of small databases."""
        if "rows" not in self.cache:
            got = [(bits.to_int(r[0]), int(r[1])) for r in self.masks.select("mask", "w").collect()]
            got.sort()
            self.cache["rows"] = ([a for a, _ in got], [b for _, b in got])
        return self.cache["rows"]

    @property
    def dictionary(self) -> DataFrame:
        return self.spark.createDataFrame([(i, x, int(s)) for i, (x, s) in enumerate(zip(self.names, self.supports))], "item_id int, item string, sup long")


def _bounded(names: DataFrame) -> list:
    got = names.limit(MAX_ITEMS + 1).collect()
    if len(got) > MAX_ITEMS:
        raise ValueError(f"more than {MAX_ITEMS} items")
    return got


def _counts(long: DataFrame, least: int) -> list[tuple[str, int]]:
    """Items of ``item, w`` with their supports."""
    counted = long.groupBy("item").agg(F.sum("w").alias("sup")).where(F.col("sup") >= least)
    return sorted((r.item, int(r.sup)) for r in _bounded(counted))


def _gather(tx: DataFrame, names: list[str]) -> DataFrame:
    """``mask, w`` over ``names`` of the baskets of ``tid, item`` pairs: an item sets its bit, no set of strings is made."""
    n = len(names)
    ids = F.broadcast(tx.sparkSession.createDataFrame([(x, k) for k, x in enumerate(names)], "item string, id int"))
    pairs = tx.where(F.col("tid").isNotNull()).join(ids, "item", "left")
    word, bit = F.floor(F.col("id") / bits.WORD), bits.shift(F.lit(1).cast("long"), (F.col("id") % bits.WORD).cast("int"))
    bit = F.when(F.col("item").isNotNull() & F.col("id").isNull(), F.raise_error(F.lit("an item that is not listed")).cast("long")).otherwise(bit)
    words = [f"w{k}" for k in range(len(bits.words_of(0, n)))]
    by_tid = pairs.groupBy("tid").agg(*[F.coalesce(F.bit_or(bit if len(words) == 1 else F.when(F.col("id").isNull() | (word == k), bit)), F.lit(0).cast("long")).alias(x) for k, x in enumerate(words)])
    return by_tid.groupBy(*words).agg(F.count(F.lit(1)).alias("w")).select((F.array(*words) if bits.is_wide(n) else F.col("w0")).alias("mask"), "w")


def _from_listed(tx: DataFrame, names: list[str], theta: float | int | None) -> ItemDB:
    """Masks over all listed items first; those that too few baskets have leave afterwards."""
    spark, n = tx.sparkSession, len(names)
    masks = cut(_gather(tx, names), "masks")
    m = int(masks.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0])
    counted = masks.select(F.explode(bits.items_of(F.col("mask"), n)).alias("k"), "w").groupBy("k").agg(F.sum("w").alias("sup")).collect()  # at most n
    least = absolute(theta, m) if theta is not None else 1
    supports = {int(r.k): int(r.sup) for r in counted if r.sup >= least}
    keep = sorted(supports)
    if not keep:
        return ItemDB(spark.createDataFrame([(0, m)] if m else [], "mask long, w long"), [], [], m)
    if len(keep) < n:
        place = F.create_map(*[F.lit(x) for new, old in enumerate(keep) for x in (old, new)])
        ids = F.filter(F.transform(bits.items_of(F.col("mask"), n), lambda k: F.element_at(place, k)), lambda k: k.isNotNull())
        masks = cut(collapse(masks.select(bits.of_items(ids, len(keep)).alias("mask"), "w")), "masks")
    return ItemDB(masks, [names[k] for k in keep], [supports[k] for k in keep], m)


def build_item_db(tx: DataFrame, *, theta: float | int | None = None, alphabet: list[str] | None = None, collapse: bool = True, listed: DataFrame | None = None) -> ItemDB:
    """From ``tid, items`` (one row a transaction), ``items, w`` (equal ones once) or ``tid, item`` (long; transactions
    without items do not exist).

    ``theta``: items that cannot be in any pattern leave the alphabet before encoding. ``alphabet`` fixes the items
    (also such as never occur). Without ``collapse`` each row keeps its own mask with weight 1. ``listed``, for the long
    form: a table ``item`` that has every item of it, others that never occur too.
    """
    spark = tx.sparkSession
    if "items" not in tx.columns:
        if listed is not None and collapse and alphabet is None:
            names = sorted(r.item for r in _bounded(listed.where(F.col("item").isNotNull()).distinct()))
            if 0 < len(names) <= GATHER_WORDS * bits.WORD:
                return _from_listed(tx, names, theta)
        tx = cut(tx.where(F.col("tid").isNotNull()).groupBy("tid").agg(F.collect_set("item").alias("items")), "baskets")
    if collapse:
        w = F.sum("w") if "w" in tx.columns else F.count(F.lit(1))
        tx = cut(tx.groupBy("items").agg(w.alias("w")), "rows")
    else:
        tx = tx.select("items", F.lit(1).cast("long").alias("w"))
    m = int(tx.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0])
    long = tx.select(F.explode(F.array_distinct("items")).alias("item"), "w").where(F.col("item").isNotNull())
    if alphabet is None:
        counted = _counts(long, absolute(theta, m) if theta is not None else 1)
        names, supports = [a for a, _ in counted], [b for _, b in counted]
    else:
        names = sorted(alphabet)
        found = dict(_counts(long.where(F.col("item").isin(names)), 1))
        supports = [found.get(x, 0) for x in names]
    n = len(names)
    if n == 0:
        return ItemDB(spark.createDataFrame([(0, m)] if m else [], "mask long, w long"), names, supports, m)
    if n <= MAP_ITEMS:
        place = F.create_map(*[x for k, name in enumerate(names) for x in (F.lit(name), F.lit(k))])
        ids = F.filter(F.transform(F.filter("items", lambda x: x.isNotNull()), lambda x: F.element_at(place, x)), lambda k: k.isNotNull())
        masks = tx.select(bits.of_items(ids, n).alias("mask"), "w")
    else:
        table = F.broadcast(spark.createDataFrame([(name, k) for k, name in enumerate(names)], "item string, id int"))  # at most MAX_ITEMS
        numbered = tx.select(F.monotonically_increasing_id().alias("row"), "w", F.explode_outer("items").alias("item")).join(table, "item", "left")
        masks = numbered.groupBy("row").agg(F.collect_set("id").alias("ids"), F.first("w").alias("w")).select(bits.of_items(F.col("ids"), n).alias("mask"), "w")
    if collapse:
        masks = masks.groupBy("mask").agg(F.sum("w").alias("w"))
    return ItemDB(cut(masks, "masks"), names, supports, m)


def collapse(masks: DataFrame) -> DataFrame:
    return masks.groupBy("mask").agg(F.sum("w").alias("w"))


def binary_matrix(db_tx: DataFrame, names: list[str]) -> DataFrame:
    """``tid, item, present`` (0 or 1) for every transaction and item: the dense view."""
    table = F.array(*[F.lit(x) for x in sorted(names)])
    return db_tx.select("tid", "items", F.explode(table).alias("item")).select("tid", "item", F.array_contains("items", F.col("item")).cast("int").alias("present"))


def profile(db: ItemDB) -> DataFrame:
    """One row: ``m, n, distinct_masks, density, item_ratio``; density is the share of ones in the matrix."""
    n, m = db.n, db.m
    return db.masks.agg(F.count(F.lit(1)).alias("distinct_masks"), F.sum(F.col("w") * bits.size(F.col("mask"), n)).alias("ones")).select(
        F.lit(m).cast("long").alias("m"), F.lit(n).cast("long").alias("n"), "distinct_masks",
        F.round(F.coalesce(F.col("ones"), F.lit(0)) / F.lit(float(max(m * n, 1))), 6).alias("density"),
        F.round(F.lit(float(n)) / F.lit(float(max(m, 1))), 6).alias("item_ratio"),
    )
