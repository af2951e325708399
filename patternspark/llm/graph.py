"""Connected components of an edge table by alternating large-star and small-star rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut


def components(edges: DataFrame, *, max_rounds: int = 60, within: str | None = None) -> DataFrame:
    """``node, label``: for each node of ``edges(a long, b long)`` the smallest node that it is linked with.

    Nothing is gathered: a round is two aggregations and two joins on the node, and a node with very many neighbours
    only meets partial minima. Rounds grow with the logarithm of a component's diameter. Nodes without an edge to
    another node are not returned; self-loops and repeated edges do no harm; no edges give an empty result. Rounds are cut
    ``within`` a folder, which must stay as long as the result is read.
    """
    now = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges", within)
    before = None
    for _ in range(max_rounds):
        mark = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if mark == before:
            break
        before = mark
        if not mark[0]:
            break
        # large star: every larger neighbour of a node moves to the least of the node and its neighbours
        both = now.union(now.select("b", "a"))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        # small star: a node and its smaller neighbours move to the least of them
        large = cut(large, "star", within)
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").select(F.explode(F.array(F.struct(F.col("b").alias("a"), F.col("m").alias("b")), F.struct("a", F.col("m").alias("b")))).alias("e")).select("e.*").where("a <> b").distinct()
        now = cut(small, "star", within)
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.groupBy("a").agg(F.min("b").alias("label")).select(F.col("a").alias("node"), "label").union(now.select(F.col("b").alias("node"), F.col("b").alias("label")).distinct())
