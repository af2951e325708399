"""Itemset counts over event streams."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def events(spark: SparkSession, path: str, *, schema: str = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string", stream: bool = True) -> DataFrame:
    """The event table as a file stream (or whole), with ``ts`` as an instant of the session's time zone."""
    src = spark.readStream.schema(schema).parquet(path) if stream else spark.read.schema(schema).parquet(path)
    return src.withColumn("ts", F.col("ts").cast("timestamp"))


def window_item_counts(ev: DataFrame, *, length: str = "1 day", slide: str | None = None, late: str = "1 hour", item: str = "event_type") -> DataFrame:
    """``start, item, n``: events of each item per window. State is one row per window and item, bounded by the watermark."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    if ev.isStreaming:
        ev = ev.withWatermark("ts", late)
    return ev.groupBy(w.alias("w"), F.col(item).alias("item")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "item", "n")


def session_baskets(ev: DataFrame, *, gap: str = "30 minutes", late: str = "1 hour", user: str = "user_id", item: str = "event_type") -> DataFrame:
    """``user, start, items, n``: the item set of each user session."""
    if ev.isStreaming:
        ev = ev.withWatermark("ts", late)
    got = ev.groupBy(F.session_window("ts", gap).alias("s"), F.col(user).alias("user")).agg(F.array_sort(F.collect_set(item)).alias("items"), F.count(F.lit(1)).alias("n"))
    return got.select("user", F.col("s.start").alias("start"), "items", "n")


def window_baskets(ev: DataFrame, *, length: str = "1 day", late: str = "1 hour", user: str = "user_id", item: str = "event_type") -> DataFrame:
    """``start, user, items``: the item set of each user per window."""
    if ev.isStreaming:
        ev = ev.withWatermark("ts", late)
    got = ev.groupBy(F.window("ts", length).alias("w"), F.col(user).alias("user")).agg(F.array_sort(F.collect_set(item)).alias("items"))
    return got.select(F.col("w.start").alias("start"), "user", "items")


def stream_itemsets(ev: DataFrame, theta: float, sink: Callable[[DataFrame, int], None], *, length: str = "1 day", late: str = "1 hour", trigger: dict | None = None, checkpoint: str | None = None):
    """Mine the baskets of every closed window and hand ``start, itemset, size, sup`` to ``sink``.

    Baskets come in append mode: a window's arrive together, once the watermark has passed its end, so each window is
    mined once and whole. Later rows are dropped; the last open window is held back until newer events close it.
    """
    from ..operators.itemdb import build_item_db
    from ..plans.mine import mine

    def run(batch: DataFrame, number: int) -> None:
        batch = batch.persist()
        try:
            out = None
            for r in batch.select("start").distinct().collect():  # the few windows that a batch has closed
                own = batch.where(F.col("start") == F.lit(r.start))
                tx = own.select(F.col("user").alias("tid"), "items")
                db = build_item_db(tx)
                got = mine(db, theta, output="frequent").patterns.select(F.lit(r.start).alias("start"), "itemset", "size", "sup")
                out = got if out is None else out.union(got)
            if out is not None:
                sink(out, number)
        finally:
            batch.unpersist()

    w = window_baskets(ev, length=length, late=late).writeStream.outputMode("append").foreachBatch(run).trigger(**(trigger or {"availableNow": True}))
    return (w.option("checkpointLocation", checkpoint) if checkpoint else w).start()
