"""Generated databases of given size, density and pattern bias, by an integer hash that SQL can repeat."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed values of the hash.
P, A, B, C, D = 2147483647, 7919, 104729, 1299709, 48271


def probabilities(density: float, gamma: float, groups: int) -> tuple[float, float]:
    """Of an item inside and outside of its row's pattern; the mean stays the density unless the second is clipped."""
    inside = density + gamma * (1 - density)
    outside = max(0.0, density - gamma * (1 - density) / (groups - 1)) if groups > 1 else inside
    return inside, outside


def generate(spark: SparkSession, n: int, m: int, density: float, gamma: float = 0.0, seed: int = 1, groups: int = 4) -> DataFrame:
    """``tid, items``: m rows over items i00...; row t follows pattern t mod ``groups``, item i belongs to i mod ``groups``."""
    inside, outside = probabilities(density, gamma, groups)
    t = F.col("id")

    def there(i):
        x = (t * A + i * B + seed * C) % P
        x = (x * x) % P
        x = (x * D) % P
        limit = F.when(i % groups == t % groups, F.lit(int(inside * P))).otherwise(F.lit(int(outside * P)))
        return x < limit

    ids = F.filter(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")), there)
    return spark.range(m).select(t.alias("tid"), F.transform(ids, lambda i: F.concat(F.lit("i"), F.lpad(i.cast("string"), 2 if n <= 100 else 5, "0"))).alias("items"))


def generate_sql(n: int, m: int, density: float, gamma: float = 0.0, seed: int = 1, groups: int = 4) -> str:
    """The same (tid, item) rows as DuckDB SQL."""
    inside, outside = (int(p * P) for p in probabilities(density, gamma, groups))
    return f"""select t as tid, 'i' || lpad(i::varchar, {2 if n <= 100 else 5}, '0') as item from (
  select t, i, (((((t*{A} + i*{B} + {seed * C}) % {P}) * ((t*{A} + i*{B} + {seed * C}) % {P})) % {P}) * {D}) % {P} as x
  from range({m}) a(t), range({n}) b(i)) where x < case when i % {groups} = t % {groups} then {inside} else {outside} end"""
