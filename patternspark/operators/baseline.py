"""Baselines: level-wise counting, exhaustive enumeration, and Spark's own FP-growth as an outside check."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import bits
from ..session import cut
from .itemdb import ItemDB
from .measure import support


def next_level(level: DataFrame, n: int, k: int) -> DataFrame:
    """``mask`` of sets of k + 1 items all of whose subsets of k items are in ``level``: a prefix join and a count."""
    split = level.select("mask", F.array_max(bits.items_of(F.col("mask"), n)).alias("hi")).withColumn("pre", bits.without_item(F.col("mask"), F.col("hi"), n))
    a, b = split.select("pre", F.col("hi").alias("ha")), split.select("pre", F.col("hi").alias("hb"))
    cand = a.join(b, "pre").where("ha < hb").select(bits.with_item(bits.with_item(F.col("pre"), F.col("ha"), n), F.col("hb"), n).alias("mask"))
    subs = cand.select("mask", F.explode(bits.items_of(F.col("mask"), n)).alias("i")).select("mask", bits.without_item(F.col("mask"), F.col("i"), n).alias("sub"))
    known = subs.join(level.select(F.col("mask").alias("sub")), "sub", "left_semi").groupBy("mask").agg(F.count(F.lit(1)).alias("c"))
    return known.where(F.col("c") == k + 1).select("mask")


def mine_levelwise(db: ItemDB, minsup: int, *, max_size: int | None = None) -> DataFrame:
    """``mask, sup`` of all frequent itemsets, level by level: join on the common prefix, prune by subsets, count."""
    spark, n = db.spark, db.n
    level = spark.createDataFrame([(bits.from_int(1 << i, n), s) for i, s in enumerate(db.supports) if s >= minsup], f"mask {bits.mask_type(n)}, sup long")
    out, k = level, 1
    while n and (max_size is None or k < max_size) and level.take(1):
        level = cut(support(db, next_level(level, n, k)).where(F.col("sup") >= minsup), "level")
        out, k = out.union(level), k + 1
    return out


def mine_bruteforce(db: ItemDB, minsup: int) -> DataFrame:
    """``mask, sup`` by matching all 2^n - 1 itemsets; n up to 16. The oracle of the tests."""
    if db.n > 16:
        raise ValueError("exhaustive enumeration is for at most 16 items")
    return support(db, db.spark.range(1, 1 << db.n).select(F.col("id").alias("mask"))).where(F.col("sup") >= minsup)


def mine_fpgrowth(tx: DataFrame, theta: float) -> DataFrame:
    """``itemset, size, sup`` by ``pyspark.ml.fpm`` on ``tid, items``."""
    from pyspark.ml.fpm import FPGrowth

    found = FPGrowth(itemsCol="items", minSupport=theta).fit(tx.select("items")).freqItemsets
    return found.select(F.array_join(F.array_sort("items"), ",").alias("itemset"), F.size("items").alias("size"), F.col("freq").cast("long").alias("sup"))
