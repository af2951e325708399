"""Cost measures from search traces."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def search_counts(trace: DataFrame) -> DataFrame:
    """``kind, searches``."""
    return trace.groupBy("kind").agg(F.count(F.lit(1)).alias("searches"))


def search_times(trace: DataFrame) -> DataFrame:
    """``kind, searches, avg_ms, total_ms``."""
    return trace.groupBy("kind").agg(F.count(F.lit(1)).alias("searches"), F.avg("ms").alias("avg_ms"), F.sum("ms").alias("total_ms"))


def total_seconds(trace: DataFrame) -> DataFrame:
    return trace.agg((F.sum("ms") / 1000).alias("seconds"))


def blocking_growth(trace: DataFrame) -> DataFrame:
    """``group_id, seq, blockers, literals, added``: blocking clauses so far and what the last step added."""
    w = Window.partitionBy("group_id").orderBy("seq")
    return trace.select("group_id", "seq", "blockers", "literals", (F.col("literals") - F.lag("literals", 1, 0).over(w)).alias("added"))


def beta_alpha_ratio(trace: DataFrame) -> DataFrame:
    """Average time of a beta search over that of an alpha search."""
    mean = lambda k: F.avg(F.when(F.col("kind").startswith(k), F.col("ms")))
    return trace.agg((mean("beta") / mean("alpha")).alias("ratio"))


def overhead(a: DataFrame, b: DataFrame) -> DataFrame:
    """Per cent by which the total time of trace ``a`` exceeds that of ``b``."""
    return total_seconds(a).select(F.col("seconds").alias("x")).crossJoin(total_seconds(b).select(F.col("seconds").alias("y"))).select(((F.col("x") / F.col("y") - 1) * 100).alias("percent"))


def phase_transition(grid: DataFrame, by: str = "seconds") -> DataFrame:
    """``db, config, theta``: the threshold with the largest cost of each line of a grid."""
    w = Window.partitionBy("db", "config").orderBy(F.col(by).desc(), "theta")
    return grid.withColumn("r", F.row_number().over(w)).where("r = 1").select("db", "config", "theta", F.col(by).alias("cost"))


def conflicts(trace: DataFrame) -> DataFrame:
    """``kind, searches, conflicts, most, decisions, backtracks, restarts`` of the solver's calls."""
    total = [F.sum(c).alias(c) for c in ("decisions", "backtracks", "restarts")]
    return trace.groupBy("kind").agg(F.count(F.lit(1)).alias("searches"), F.sum("conflicts").alias("conflicts"), F.max("conflicts").alias("most"), *total)


# Costs on the Spark side

#: What is counted in a plan: name and pattern of its operators.
_OPERATORS = {"shuffles": r"(?<!Broadcast)Exchange (?:hash|range|Single|RoundRobin)", "broadcasts": "BroadcastExchange", "joins": r"(?:HashJoin|SortMergeJoin|NestedLoopJoin|CartesianProduct)", "sorts": r"\bSort \[", "scans": r"\b(?:FileScan|Scan ExistingRDD|LocalTableScan|Range )", "python": r"(?:InPandas|InArrow|EvalPython)"}


def plan_cost(df: DataFrame) -> DataFrame:
    """One row: how many shuffles, broadcasts, joins, sorts, scans and Python operators the physical plan has."""
    import re

    plan = df._jdf.queryExecution().executedPlan().toString()
    found = {k: len(re.findall(p, plan)) for k, p in _OPERATORS.items()}
    return df.sparkSession.createDataFrame([tuple(found.values())], ", ".join(f"{k} long" for k in found))


def run_cost(spark: SparkSession, make: Callable[[], DataFrame]) -> DataFrame:
    """One row ``jobs, stages, tasks, rows, seconds`` of making and reading a result."""
    import time
    import uuid

    group = uuid.uuid4().hex
    spark.sparkContext.setJobGroup(group, "run_cost")
    start = time.perf_counter()
    rows = make().count()
    took = time.perf_counter() - start
    tracker = spark.sparkContext.statusTracker()
    jobs = list(tracker.getJobIdsForGroup(group))
    stages = {i for j in map(tracker.getJobInfo, jobs) if j for i in j.stageIds}
    tasks = sum(x.numCompletedTasks for x in map(tracker.getStageInfo, stages) if x)
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    return spark.createDataFrame([(len(jobs), len(stages), tasks, rows, took)], "jobs long, stages long, tasks long, rows long, seconds double")
