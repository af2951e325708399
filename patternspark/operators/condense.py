"""Condensed representations: maximal, closed and minimal infrequent itemsets, expansion and bounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import bits
from .itemdb import ItemDB
from .measure import support


def _neighbours(masks: DataFrame, n: int, add: bool) -> DataFrame:
    """``mask, other``: each itemset with one item more or less."""
    own = bits.items_of(F.col("mask"), n)
    if not add:
        return masks.select("*", F.explode(own).alias("k")).withColumn("other", bits.without_item(F.col("mask"), F.col("k"), n)).drop("k")
    ids = F.array_except(F.array(*[F.lit(k) for k in range(n)]), own)
    return masks.select("*", F.explode(ids).alias("k")).withColumn("other", bits.with_item(F.col("mask"), F.col("k"), n)).drop("k")


def maximal(frequent: DataFrame, n: int) -> DataFrame:
    """Rows of ``mask, sup`` (all frequent itemsets) without a frequent superset. One anti-join on one-item neighbours."""
    up = _neighbours(frequent.select("mask"), n, False).select(F.col("other").alias("mask")).distinct()
    return frequent.join(up, "mask", "left_anti")


def closed(frequent: DataFrame, n: int) -> DataFrame:
    """Rows without a superset of equal support."""
    up = _neighbours(frequent.select("mask", "sup"), n, False).select(F.col("other").alias("mask"), "sup").distinct()
    return frequent.join(up, ["mask", "sup"], "left_anti")


def minimal_infrequent(frequent: DataFrame, db: ItemDB) -> DataFrame:
    """``mask`` of infrequent itemsets all of whose one-item-smaller subsets are frequent (the empty set counts)."""
    n, spark = db.n, db.spark
    base = frequent.select("mask").union(spark.createDataFrame([(bits.from_int(0, n),)], f"mask {bits.mask_type(n)}"))
    up = _neighbours(base, n, True).select(F.col("other").alias("mask")).distinct().join(frequent.select("mask"), "mask", "left_anti")
    down = _neighbours(up, n, False)
    bad = down.join(base.withColumnRenamed("mask", "other"), "other", "left_anti").select("mask").distinct()
    return up.join(bad, "mask", "left_anti")


#: Longest border set that is expanded: 2 to this power subsets.
MAX_EXPANDED = 30


def expand_maximal(border: DataFrame, db: ItemDB) -> DataFrame:
    """``mask, sup`` of every non-empty subset of the border's masks: all frequent itemsets, recounted.

    A set's items are halved, and the halves' subsets are combined in two steps, so no row holds more than 2^15 of
    them. Border sets over MAX_EXPANDED items are refused: report the border, or bound the size.
    """
    n = db.n
    longest = border.agg(F.max(bits.size(F.col("mask"), n))).first()[0] or 0
    if longest > MAX_EXPANDED:
        raise ValueError(f"expansion of sets of {longest} items; report the border or bound the size")
    ids = bits.items_of(F.col("mask"), n)
    half = F.ceil(F.size(ids) / 2).cast("int")
    halves = border.select(bits.of_items(F.slice(ids, F.lit(1), half), n).alias("a"), bits.of_items(F.slice(ids, half + 1, F.size(ids)), n).alias("b"))
    first = halves.select(F.explode(bits.submasks(F.col("a"), n)).alias("a"), "b").distinct()
    second = first.select("a", F.explode(bits.submasks(F.col("b"), n)).alias("b"))
    return support(db, second.select(bits.union(F.col("a"), F.col("b"), n).alias("mask")).where(bits.size(F.col("mask"), n) > 0))


def border_profile(frequent: DataFrame, db: ItemDB) -> DataFrame:
    """One row ``n_frequent, n_closed, n_maximal, n_minimal_infrequent, longest``."""
    one = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
    out = frequent.agg(F.count(F.lit(1)).alias("n_frequent"), F.coalesce(F.max(bits.size(F.col("mask"), db.n)), F.lit(0)).alias("longest"))
    for df, name in ((closed(frequent, db.n), "n_closed"), (maximal(frequent, db.n), "n_maximal"), (minimal_infrequent(frequent, db), "n_minimal_infrequent")):
        out = out.crossJoin(one(df, name))
    return out.select("n_frequent", "n_closed", "n_maximal", "n_minimal_infrequent", "longest")


def deduce_bounds(known: DataFrame, n: int, m: int) -> DataFrame:
    """Bounds on the support of each itemset of two items or more from its proper subsets, by inclusion and exclusion.

    ``known``: ``mask, sup`` closed under subsets. For J inside I the signed sum over the sets between J and I (without
    I) bounds sup(I) from above where I minus J is odd, from below where it is even. Gives ``mask, lower, upper, sup``.
    """
    base = known.select("mask", "sup").union(known.sparkSession.createDataFrame([(0, m)], "mask long, sup long"))
    sets = known.where(F.bit_count("mask") >= 2)
    subs = F.filter(bits.submasks(F.col("mask"), n), lambda s: s != F.col("mask"))
    between = sets.select("mask", "sup", F.explode(subs).alias("j")).select("mask", "sup", "j", F.explode(subs).alias("x")).where(F.col("x").bitwiseAND(F.col("j")) == F.col("j"))
    priced = between.join(base.select(F.col("mask").alias("x"), F.col("sup").alias("xs")), "x")
    sign = F.when((F.bit_count("mask") - F.bit_count("x")) % 2 == 1, 1).otherwise(-1)
    sums = priced.groupBy("mask", "sup", "j").agg(F.sum(sign * F.col("xs")).alias("s"))
    odd = (F.bit_count("mask") - F.bit_count("j")) % 2 == 1
    return sums.groupBy("mask", "sup").agg(F.greatest(F.max(F.when(~odd, F.col("s"))), F.lit(0).cast("long")).alias("lower"), F.min(F.when(odd, F.col("s"))).alias("upper")).select("mask", F.col("lower").cast("long").alias("lower"), F.col("upper").cast("long").alias("upper"), "sup")
