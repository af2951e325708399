"""Itemsets as bit masks.

Up to ``WORD`` items a mask is a BIGINT, bit k for item k; beyond, an ARRAY<BIGINT> of words of ``WORD`` bits. Every
function here takes either kind of column and stays inside the JVM.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = 62


def is_wide(n: int) -> bool:
    return n > WORD


def shift(value: Column, by: Column | int) -> Column:
    """``value << by`` with a column on either side."""
    return F.call_function("shiftleft", value, by if isinstance(by, Column) else F.lit(by))


def words_of(mask: int, n: int) -> list[int]:
    return [(mask >> (WORD * k)) & ((1 << WORD) - 1) for k in range(max(1, -(-n // WORD)))]


def to_int(value) -> int:
    """A Python integer of a mask value that came from Spark."""
    if isinstance(value, (int,)) or not hasattr(value, "__iter__"):
        return int(value)
    return sum(int(w) << (WORD * k) for k, w in enumerate(value))


def from_int(mask: int, n: int):
    return words_of(mask, n) if is_wide(n) else mask


def literal(mask: int, n: int) -> Column:
    return F.array(*[F.lit(w).cast("long") for w in words_of(mask, n)]) if is_wide(n) else F.lit(mask).cast("long")


def mask_type(n: int) -> str:
    return "array<bigint>" if is_wide(n) else "bigint"


def size(mask: Column, n: int) -> Column:
    if is_wide(n):
        return F.aggregate(mask, F.lit(0), lambda a, w: a + F.bit_count(w).cast("int"))
    return F.bit_count(mask).cast("int")


def contains(mask: Column, sub: Column, n: int) -> Column:
    """Every item of ``sub`` is in ``mask``."""
    if is_wide(n):
        return F.forall(F.zip_with(mask, sub, lambda a, b: a.bitwiseAND(b) == b), lambda x: x)
    return mask.bitwiseAND(sub) == sub


def union(a: Column, b: Column, n: int) -> Column:
    return F.zip_with(a, b, lambda x, y: x.bitwiseOR(y)) if is_wide(n) else a.bitwiseOR(b)


def intersection(a: Column, b: Column, n: int) -> Column:
    return F.zip_with(a, b, lambda x, y: x.bitwiseAND(y)) if is_wide(n) else a.bitwiseAND(b)


def difference(a: Column, b: Column, n: int) -> Column:
    minus = lambda x, y: x.bitwiseAND(F.bitwise_not(y))
    return F.zip_with(a, b, minus) if is_wide(n) else minus(a, b)


def has(mask: Column, item: int, n: int) -> Column:
    word = mask[item // WORD] if is_wide(n) else mask
    return F.getbit(word, F.lit(item % WORD if is_wide(n) else item)) == 1


def items_of(mask: Column, n: int) -> Column:
    """ARRAY<INT> of item ids, rising."""
    ids = F.sequence(F.lit(0), F.lit(max(n - 1, 0)))
    if is_wide(n):
        return F.filter(ids, lambda k: F.getbit(F.element_at(mask, (F.floor(k / WORD) + 1).cast("int")), (k % WORD).cast("int")) == 1)
    return F.filter(ids, lambda k: F.getbit(mask, k) == 1)


def names_of(mask: Column, names: Sequence[str]) -> Column:
    """Comma-joined item names; ids follow the order of names, so the string is name-sorted."""
    if not names:
        return F.lit("")
    table = F.array(*[F.lit(x) for x in names])
    return F.array_join(F.transform(items_of(mask, len(names)), lambda k: F.element_at(table, k + 1)), ",")


def single(item: Column, n: int) -> Column:
    """Mask of one item given by a column."""
    if is_wide(n):
        words = F.array(*[F.lit(w) for w in range(len(words_of(0, n)))])
        return F.transform(words, lambda w: F.when(F.floor(item / WORD) == w, shift(F.lit(1).cast("long"), (item % WORD).cast("int"))).otherwise(F.lit(0).cast("long")))
    return shift(F.lit(1).cast("long"), item.cast("int"))


def with_item(mask: Column, item: Column, n: int) -> Column:
    return union(mask, single(item, n), n)


def without_item(mask: Column, item: Column, n: int) -> Column:
    return difference(mask, single(item, n), n)


def of_items(ids: Column, n: int) -> Column:
    """Mask of an ARRAY<INT> of item ids."""
    one = lambda keep: F.aggregate(ids, F.lit(0).cast("long"), lambda a, i: F.when(keep(i), a.bitwiseOR(shift(F.lit(1).cast("long"), (i % WORD).cast("int")))).otherwise(a))
    if not is_wide(n):
        return F.aggregate(ids, F.lit(0).cast("long"), lambda a, i: a.bitwiseOR(shift(F.lit(1).cast("long"), i.cast("int"))))
    return F.array(*[one(lambda i, w=w: F.floor(i / WORD) == w) for w in range(len(words_of(0, n)))])


def submasks(mask: Column, n: int = WORD) -> Column:
    """ARRAY of all subsets of a mask of at most 20 items, the empty one included."""
    # the k-th subset takes the items at the places of k's bits
    ids = items_of(mask, n)
    count = shift(F.lit(1).cast("long"), F.size(ids)) - 1
    return F.transform(F.sequence(F.lit(0).cast("long"), count), lambda k: of_items(F.filter(ids, lambda item, at: F.getbit(k, at) == 1), n))


# Python-side helpers of the kernels


def bits(mask: int) -> list[int]:
    out = []
    while mask:
        low = mask & -mask
        out.append(low.bit_length() - 1)
        mask ^= low
    return out
