"""Coverage, support and frequency, and the checks of the Boolean definitions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import bits
from .itemdb import ItemDB

#: Candidates are held against every row up to this many; beyond, rows and candidates meet through a candidate's rarest item.
BROADCAST_CANDIDATES = 1000
#: Pairs of patterns are formed for at most this many patterns.
MAX_PATTERNS = 10_000


def candidates(db: ItemDB, itemsets: list[str] | list[int]) -> DataFrame:
    """``mask`` rows of itemsets given as masks or as comma-joined names."""
    masks = [x if isinstance(x, int) else db.mask(x) for x in itemsets]
    return db.spark.createDataFrame([(bits.from_int(x, db.n),) for x in masks], f"mask {bits.mask_type(db.n)}")


def patterns(masks: DataFrame, db: ItemDB) -> DataFrame:
    """``itemset, size, sup, freq`` of ``mask, sup``."""
    return masks.select(
        bits.names_of(F.col("mask"), db.names).alias("itemset"), bits.size(F.col("mask"), db.n).alias("size"),
        F.col("sup").cast("long").alias("sup"), F.round(F.col("sup") / F.lit(float(max(db.m, 1))), 6).alias("freq"),
    )


def bounded(df: DataFrame, most: int, what: str) -> DataFrame:
    """``df`` to be broadcast, once it is known to have at most ``most`` rows."""
    if df.limit(most + 1).count() > most:
        raise ValueError(f"more than {most} {what}")
    return F.broadcast(df)


def matches(db: ItemDB, cand: DataFrame, how: str = "inner") -> DataFrame:
    """``row, w`` of the database beside the columns of ``cand`` whose ``mask`` the row contains.

    A few candidates are broadcast and held against each distinct row. More of them meet only rows that have their
    rarest item, in an equi-join on it; candidates without items meet every row.
    """
    n, rows = db.n, db.masks.select(F.col("mask").alias("row"), "w")
    inside = bits.contains(F.col("row"), F.col("mask"), n)
    if cand.limit(BROADCAST_CANDIDATES + 1).count() <= BROADCAST_CANDIDATES:
        return rows.join(F.broadcast(cand), inside, how)
    rank = F.array(*[F.lit(k) for k in sorted(range(n), key=lambda k: (db.supports[k], k))])
    place = F.array(*[F.lit(p) for p in _places([db.supports[k] for k in range(n)])])
    rarest = F.get(rank, F.array_min(F.transform(bits.items_of(F.col("mask"), n), lambda k: F.get(place, k))))
    keyed = cand.withColumn("key", F.coalesce(rarest, F.lit(-1)))
    if how == "left_anti":
        hit = rows.withColumn("key", F.explode(F.array_append(bits.items_of(F.col("row"), n), F.lit(-1)))).join(keyed.select("key", "mask"), "key").where(inside).select("row").distinct()
        return rows.join(hit, "row", "left_anti")
    return rows.withColumn("key", F.explode(F.array_append(bits.items_of(F.col("row"), n), F.lit(-1)))).join(keyed, "key").where(inside).drop("key")


def _places(supports: list[int]) -> list[int]:
    """Each item's place in the order of rising support."""
    out = [0] * len(supports)
    for p, k in enumerate(sorted(range(len(supports)), key=lambda k: (supports[k], k))):
        out[k] = p
    return out


def support(db: ItemDB, cand: DataFrame) -> DataFrame:
    """``mask, sup`` of each distinct candidate mask (0 if nothing covers it); sums are combined map side."""
    cand = cand.select("mask").distinct()
    got = matches(db, cand).groupBy("mask").agg(F.sum("w").alias("sup"))
    return cand.join(got, "mask", "left").select("mask", F.coalesce("sup", F.lit(0)).cast("long").alias("sup"))


def coverage(tx: DataFrame, itemsets: list[str]) -> DataFrame:
    """``itemset, tid`` of every transaction (``tid, items``) that has all items of an itemset: an equi-join on one of them."""
    spark = tx.sparkSession
    named = sorted({",".join(sorted(y for y in x.split(",") if y)) for x in itemsets})
    asked = spark.createDataFrame([(x, x.split(",")) for x in named if x], "itemset string, need array<string>").withColumn("item", F.element_at("need", 1))
    hit = tx.select("tid", "items", F.explode(F.array_distinct("items")).alias("item")).join(asked, "item").where(F.size(F.array_except("need", "items")) == 0).select("itemset", "tid")
    return hit.union(tx.select(F.lit("").alias("itemset"), "tid")) if "" in named else hit


def itemset_transaction_pairs(tx: DataFrame, itemsets: list[str]) -> DataFrame:
    """``itemset, tids`` (sorted): the pairs (I, T) with T the coverage of I."""
    return coverage(tx, itemsets).groupBy("itemset").agg(F.array_sort(F.collect_list("tid")).alias("tids"))


def check_coverage(tx: DataFrame, pairs: DataFrame) -> DataFrame:
    """``itemset, covered``: T holds just those transactions that have every item of I (given and true members are compared)."""
    flat = pairs.select("itemset", F.filter(F.split("itemset", ","), lambda x: x != "").alias("need"), "tids")
    rows = tx.select("tid", "items")
    true = rows.withColumn("item", F.explode(F.array_distinct("items"))).join(flat.withColumn("item", F.element_at("need", 1)), "item").where(F.size(F.array_except("need", "items")) == 0).select("itemset", "tid")
    given = flat.select("itemset", F.explode("tids").alias("tid")).distinct()
    wrong = true.withColumn("a", F.lit(1)).join(given.withColumn("b", F.lit(1)), ["itemset", "tid"], "full").where("a is null or b is null").select("itemset").distinct().withColumn("bad", F.lit(True))
    return pairs.select("itemset").join(wrong, "itemset", "left").select("itemset", F.col("bad").isNull().alias("covered"))


def check_frequency(pairs: DataFrame, minsup: int) -> DataFrame:
    """``itemset, frequent``: T has at least ``minsup`` members."""
    return pairs.select("itemset", (F.size("tids") >= minsup).alias("frequent"))


def check_reified_frequency(tx: DataFrame, pairs: DataFrame, minsup: int) -> DataFrame:
    """``itemset, frequent``: each chosen item lies in at least ``minsup`` members of T (false for the empty itemset)."""
    member = pairs.select("itemset", F.explode_outer("tids").alias("tid")).join(tx.select("tid", "items"), "tid", "left")
    need = pairs.select("itemset", F.explode(F.filter(F.split("itemset", ","), lambda x: x != "")).alias("item"))
    per = need.join(member, "itemset", "left").groupBy("itemset", "item").agg(F.sum(F.coalesce(F.array_contains("items", F.col("item")).cast("int"), F.lit(0))).alias("c"))
    least = per.groupBy("itemset").agg(F.min("c").alias("least"))
    return pairs.select("itemset").join(least, "itemset", "left").select("itemset", (F.coalesce("least", F.lit(0)) >= minsup).alias("frequent"))


def compare_sets(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row ``missing, extra``: rows of ``a`` that ``b`` lacks and the other way round, duplicates counted."""
    missing, extra = a.exceptAll(b.select(*a.columns)), b.select(*a.columns).exceptAll(a)
    return missing.agg(F.count(F.lit(1)).alias("missing")).crossJoin(extra.agg(F.count(F.lit(1)).alias("extra")))
