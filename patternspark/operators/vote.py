"""Mining fragments on their own and voting, with an exact second pass."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import bits
from ..session import cut
from .bitset import propagate_all
from .formula import Matrix
from .itemdb import ItemDB
from .measure import support


def mine_local_vote(db: ItemDB, theta: float, *, parts: int = 8, votes: int = 1, exact: bool = True) -> DataFrame:
    """``mask, sup, votes`` of itemsets that are frequent (at ``theta``) in at least ``votes`` fragments.

    An itemset that is frequent overall is frequent in some fragment, so with one vote and the recount the result is
    exact; more votes approximate. Fragments are dealt by the mask's hash, so a heavy mask stays in one, with its weight.
    """
    n = db.n

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        m = Matrix([bits.to_int(x) for x in group["mask"]], [int(x) for x in group["w"]], n)
        import math

        found = propagate_all(m, max(1, math.ceil(theta * sum(m.weights) - 1e-9))).found
        return pd.DataFrame({"mask": [bits.from_int(k, n) for k in found], "part": [int(key[0])] * len(found)})

    own = db.masks.select("mask", "w", F.pmod(F.xxhash64("mask"), F.lit(parts)).cast("int").alias("part"))
    voted = own.groupBy("part").applyInPandas(run, f"mask {bits.mask_type(n)}, part int").groupBy("mask").agg(F.count_distinct("part").alias("votes")).where(F.col("votes") >= votes)
    voted = cut(voted, "votes")
    counted = support(db, voted.select("mask"))
    if exact:
        counted = counted.where(F.col("sup") >= db.minsup(theta))
    return counted.join(voted, "mask")
