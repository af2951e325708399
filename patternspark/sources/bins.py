"""Discretising numeric columns into labels."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Bins:
    """``edges`` rise; a value under edges[k] and not under an earlier one gets labels[k], others the last label."""

    edges: tuple[float, ...]
    labels: tuple[str, ...]

    def __post_init__(self):
        if len(self.labels) != len(self.edges) + 1 or list(self.edges) != sorted(self.edges):
            raise ValueError("rising edges and one label more are needed")

    def label(self, c: Column) -> Column:
        """Null for null and NaN."""
        out = None
        for e, x in zip(self.edges, self.labels):
            out = F.when(c < e, x) if out is None else out.when(c < e, x)
        last = F.lit(self.labels[-1])
        return F.when(c.isNull() | F.isnan(c.cast("double")), F.lit(None)).otherwise(last if out is None else out.otherwise(last))

    @classmethod
    def threshold(cls, edge: float, low: str, high: str) -> Bins:
        return cls((edge,), (low, high))

    @classmethod
    def width(cls, start: float, step: float, labels: Sequence[str]) -> Bins:
        return cls(tuple(start + step * (k + 1) for k in range(len(labels) - 1)), tuple(labels))

    @classmethod
    def quantile(cls, df: DataFrame, col: str, labels: Sequence[str], accuracy: int = 10_000) -> Bins:
        """Edges at equal shares of the rows, from one pass with a bounded sketch."""
        shares = [k / len(labels) for k in range(1, len(labels))]
        edges = df.agg(F.percentile_approx(col, shares, accuracy)).first()[0] or [0.0] * len(shares)
        return cls(tuple(float(x) for x in edges), tuple(labels))
