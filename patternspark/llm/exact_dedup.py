"""Exact deduplication by a content sort (native DataFrame operations only).

Rows are range-partitioned by bytes of the normalised text with sampled splitters, sorted externally inside each
range, so that equal texts lie side by side, and neighbours are compared in full. The sort key starts with a short
prefix of the text and a 64-bit hash of the whole of it, which bounds what the splitter sample carries; the full text
follows as the last key, so a hash collision never merges two texts.

A text with very many copies (found by counting the 64-bit hashes, which moves eight bytes a row) is dealt out by
salt over several ranges; the few local winners of these ranges are then compared in full once more.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import ascii_lower, cut, quoted

PREFIX = 24
#: A key is hot from N / HOT_SHARE rows on, so there are at most HOT_SHARE hot keys to broadcast.
HOT_SHARE, HOT_LEAST = 2048, 256


def content_groups(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest", normalise=ascii_lower, payload: list[str] | None = None, hot_rows: int | None = None, partitions: int | None = None) -> DataFrame:
    """One row per input row: ``id, keep_id, group_size, kept, sha`` (and the ``payload`` columns as struct ``row``).

    Equal means equal after ``normalise``. Null text counts as empty; empty texts equal each other. Of rows with the
    same id and text one is kept. A null id sorts as the smallest. An empty table gives an empty result. Columns of
    the input that are not named are ignored, so their names cannot clash. ``hot_rows`` overrides the share from
    which a key is salted. Texts of any length are compared whole.
    """
    if keep not in ("smallest", "largest"):
        raise ValueError(f"keep: {keep}")
    def plain(text: Column) -> Column:
        return normalise(F.coalesce(text.cast("string"), F.lit("")))

    norm = plain(quoted(text_col))
    row = F.struct(*[quoted(c) for c in payload]) if payload else F.lit(None).cast("int")
    base = docs.select(quoted(id_col).alias("id"), norm.alias("norm"), row.alias("row")).withColumn("h", F.xxhash64("norm"))
    if hot_rows is None:
        hot_rows = max(HOT_LEAST, docs.count() // HOT_SHARE)
    hot = base.groupBy("h").agg(F.count(F.lit(1)).alias("c")).where(F.col("c") > hot_rows).select("h", F.ceil(F.col("c") / hot_rows).cast("int").alias("salts"))
    salted = (
        base.join(F.broadcast(cut(hot, "hot")), "h", "left")
        .withColumn("salt", F.when(F.col("salts").isNull(), F.lit(-1)).otherwise(F.pmod(F.xxhash64(F.lit(7), "id"), F.col("salts")).cast("int")))
        .withColumn("pre", F.substring(F.col("norm").cast("binary"), 1, PREFIX))
        .drop("salts")
    )
    again = bool(payload) and text_col in payload  # a row that has the text itself need not carry it twice
    moved = salted.drop("norm") if again else salted
    spread = moved.repartitionByRange(partitions, "pre", "h", "salt") if partitions else moved.repartitionByRange("pre", "h", "salt")
    if again:
        spread = spread.withColumn("norm", plain(F.col("row")[text_col]))
    best = F.max if keep == "largest" else F.min
    # The range partitioning already clusters (pre, h, salt, norm): no second exchange, only the external sort.
    order = Window.partitionBy("pre", "h", "salt", "norm").orderBy(F.col("id").desc() if keep == "largest" else F.col("id").asc())
    whole = order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    local = spread.select(
        "id", "h", "salt", "row", "norm",
        F.first("id").over(whole).alias("best"),
        F.count(F.lit(1)).over(whole).alias("n"),
        F.row_number().over(order).alias("rank"),
    )
    local = local.select("id", "h", "salt", "row", "best", "n", "rank", F.sha2("norm", 256).alias("sha"), F.when((F.col("salt") >= 0) & (F.col("rank") == 1), F.col("norm")).alias("winner"))
    return _across_salts(local, best, bool(payload))


def _across_salts(local: DataFrame, best, payload: bool) -> DataFrame:
    """Merge what the salts of a hot text have found; at most 2 * HOT_SHARE winners and their texts take part."""
    local = cut(local, "content-sort")
    heads = local.where(F.col("winner").isNotNull()).select("h", "salt", "sha", "best", "n", "winner")
    total = heads.groupBy("winner").agg(F.first("h").alias("h"), F.first("sha").alias("sha"), best("best").alias("all_best"), F.sum("n").alias("all_n"), best(F.struct("best", "salt")).alias("top"))
    total = total.select("h", "sha", "all_best", "all_n", F.col("top.salt").alias("top_salt"))
    out = local.join(F.broadcast(total), ["h", "sha"], "left")
    hot = F.col("all_n").isNotNull() & (F.col("salt") >= 0)
    return out.select(
        "id",
        F.when(hot, F.col("all_best")).otherwise(F.col("best")).alias("keep_id"),
        F.when(hot, F.col("all_n")).otherwise(F.col("n")).cast("long").alias("group_size"),
        ((F.col("rank") == 1) & (~hot | (F.col("salt") == F.col("top_salt")))).alias("kept"),
        "sha",
        *(["row"] if payload else []),
    )


def exact_dedup(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest") -> DataFrame:
    """The rows of ``docs`` that stay, all columns unchanged."""
    rows = content_groups(docs, id_col=id_col, text_col=text_col, keep=keep, payload=docs.columns)
    return rows.where("kept").select("row.*")
