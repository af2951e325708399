"""From tables to transactions.

Attribute-value rows become transactions row by row (no shuffle); market baskets come as (tid, item) pairs. Nulls give
no item. The result is always the long or the array form below (or equal rows of it once, with their number);
``operators.itemdb`` encodes either.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .bins import Bins


@dataclass(frozen=True)
class ItemRule:
    """``attr=value`` items of a column; ``bins`` for numeric ones, ``null_item`` to make an item of null."""

    attr: str
    column: str | Column
    bins: Bins | None = None
    null_item: bool = False

    def value(self) -> Column:
        c = F.col(self.column) if isinstance(self.column, str) else self.column
        value = self.bins.label(c) if self.bins else c.cast("string")
        return F.coalesce(value, F.lit("null")) if self.null_item else value

    def item(self, value: Column | None = None) -> Column:
        return F.concat(F.lit(f"{self.attr}="), self.value() if value is None else value)


def itemize_attributes(df: DataFrame, tid: Column | str, rules: list[ItemRule], *, collapse: bool = False) -> DataFrame:
    """``tid, items`` of each row; only the columns that rules name are read.

    ``collapse``: ``items, w``, for rows of equal values once and with their number; items are made of these only.
    """
    array = lambda items: F.array_sort(F.array_distinct(F.array_compact(F.array(*items)))).alias("items")
    if collapse:
        cols = [f"v{k}" for k in range(len(rules))]
        same = df.select(*[r.value().alias(c) for r, c in zip(rules, cols)]).groupBy(*cols).agg(F.count(F.lit(1)).alias("w"))
        return same.select(array([r.item(F.col(c)) for r, c in zip(rules, cols)]), "w")
    t = F.col(tid) if isinstance(tid, str) else tid
    return df.select(t.alias("tid"), array([r.item() for r in rules]))


def itemize_baskets(df: DataFrame, tid: Column | str, item: Column | str) -> DataFrame:
    """``tid, item`` pairs; repeats are harmless. Null tids or items are left out."""
    t, i = (F.col(x) if isinstance(x, str) else x for x in (tid, item))
    return df.select(t.alias("tid"), i.cast("string").alias("item")).where(F.col("tid").isNotNull() & F.col("item").isNotNull())


def itemize_words(df: DataFrame, tid: str, text: str, vocabulary: list[str] | None = None) -> DataFrame:
    """``tid, items``: which words (of a vocabulary) occur among runs of a-z of the lower-cased text."""
    found = F.array_distinct(F.regexp_extract_all(F.lower(F.coalesce(F.col(text), F.lit(""))), F.lit("[a-z]+"), F.lit(0)))
    if vocabulary is not None:
        found = F.array_intersect(F.array(*[F.lit(w) for w in vocabulary]), found)
    return df.select(F.col(tid).alias("tid"), F.array_sort(found).alias("items"))


def itemize_signs(df: DataFrame, tid: str, vector: str, dims: int) -> DataFrame:
    """``tid, items``: ``dKK+`` where component K (from 1) is above 0, else ``dKK-``."""
    signs = [F.when(F.element_at(vector, k) > 0, f"d{k:02d}+").otherwise(f"d{k:02d}-") for k in range(1, dims + 1)]
    return df.select(F.col(tid).alias("tid"), F.array(*signs).alias("items"))
