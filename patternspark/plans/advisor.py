"""Which method for which data: rules on a one-row profile, and a runner that follows them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.itemdb import ItemDB, profile
from .mine import MiningResult, mine

#: Fixed values of the rules of thumb.
DENSE, LOW_DENSE, LOW_OTHER, DUAL_FROM, DUAL_TO, REDUCED_FROM, POLARITY_TO = 0.45, 0.10, 0.04, 0.10, 0.25, 0.20, 0.20


@dataclass(frozen=True)
class Plan:
    method: str
    coverage: str
    polarity: str
    blocking: str

    def settings(self) -> dict:
        from ..operators.solver import Polarity

        own = {"coverage": self.coverage, "polarity": Polarity(self.polarity)}
        if self.method == "baseline":
            return {"engine": "propagation"}
        if self.method == "dual":
            return own | {"formulation": "dual"}
        if self.method == "longest":
            return own | {"engine": "clausal", "search": "longest", "blocking": self.blocking}
        if self.method == "decide":
            return own | {"engine": "clausal", "search": "decide", "partitioning": "none"}
        return own | {"engine": "clausal", "search": "growing"}


#: More items than rows: minimal infrequent sets outnumber the rows by far, so the dual is not taken.
MOST_ITEM_RATIO = 1.0


def choose_formulation(density: float, item_ratio: float, theta: float) -> str:
    """'primal' or 'dual', by density, items per row and threshold."""
    low = LOW_DENSE if density >= DENSE else LOW_OTHER
    return "dual" if theta > low and DUAL_FROM <= theta <= DUAL_TO and item_ratio <= MOST_ITEM_RATIO else "primal"


def recommend(density: float, theta: float, task: str = "all", item_ratio: float = 0.0) -> Plan:
    """``task``: 'all', 'first_k' (few of many) or 'one'."""
    low = LOW_DENSE if density >= DENSE else LOW_OTHER
    if task == "one":
        method = "decide"
    elif task == "first_k":
        method = "longest"
    elif theta <= low:
        method = "growing"
    elif choose_formulation(density, item_ratio, theta) == "dual":
        method = "dual"
    else:
        method = "baseline"
    return Plan(method, "reduced" if theta > REDUCED_FROM else "clausal", "pos" if theta <= POLARITY_TO else "neg", "subset_compact")


def recommend_column(density: Column, theta: Column, item_ratio: Column) -> Column:
    """The method for the task 'all' as a column."""
    low = F.when(density >= DENSE, LOW_DENSE).otherwise(LOW_OTHER)
    return F.when(theta <= low, "growing").when((theta >= DUAL_FROM) & (theta <= DUAL_TO) & (item_ratio <= MOST_ITEM_RATIO), "dual").otherwise("baseline")


def advise(db: ItemDB, thetas: list[float]) -> DataFrame:
    """``density, theta, method, coverage, polarity`` for each threshold."""
    t = db.spark.createDataFrame([(x,) for x in thetas], "theta double")
    p = profile(db).select("density", "item_ratio").crossJoin(F.broadcast(t))  # one row by the asked thresholds
    th = F.col("theta")
    return p.select("density", "theta", recommend_column(F.col("density"), th, F.col("item_ratio")).alias("method"), F.when(th > REDUCED_FROM, "reduced").otherwise("clausal").alias("coverage"), F.when(th <= POLARITY_TO, "pos").otherwise("neg").alias("polarity"))


def mine_auto(db: ItemDB, theta: float, *, task: str = "all", seconds: float = 30, **settings) -> MiningResult:
    """Follow the recommendation within a budget a group; where it runs out, fall back on the bitset engine."""
    p = profile(db).first()
    plan = recommend(float(p.density), theta, task, float(p.item_ratio))
    got = mine(db, theta, **({"seconds": seconds} | plan.settings() | settings))
    return got if got.status == "ok" else mine(db, theta, **settings)
