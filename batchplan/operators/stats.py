"""Statistics of an execution log: run times, configuration profiles, makespans, concurrency."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def duration() -> Column:
    return F.col("finish_us") - F.col("start_us")


def avg_runtime(log: DataFrame) -> DataFrame:
    """query_id, runs, avg_us over all configurations."""
    return log.groupBy("query_id").agg(F.count("*").alias("runs"), F.avg(duration()).alias("avg_us"))


def config_profile(log: DataFrame) -> DataFrame:
    """query_id, config_id, runs, avg_us."""
    return log.groupBy("query_id", "config_id").agg(F.count("*").alias("runs"), F.avg(duration()).alias("avg_us"))


def config_rollup(log: DataFrame, cube: bool = False) -> DataFrame:
    """The profile of each (query, configuration), each query, (each configuration) and everything."""
    grouped = log.cube("query_id", "config_id") if cube else log.rollup("query_id", "config_id")
    return grouped.agg(F.grouping_id().cast("int").alias("grouping_id"), F.count("*").alias("runs"), F.avg(duration()).alias("avg_us"))


def makespan(log: DataFrame) -> DataFrame:
    """round_id, makespan_us: last finish after first start."""
    return log.groupBy("round_id").agg((F.max("finish_us") - F.min("start_us")).alias("makespan_us"))


def makespan_summary(makespans: DataFrame) -> DataFrame:
    """rounds, avg_us and the population deviation std_us."""
    return makespans.agg(F.count("*").alias("rounds"), F.avg("makespan_us").alias("avg_us"), F.stddev_pop("makespan_us").alias("std_us"))


def concurrency_profile(log: DataFrame) -> DataFrame:
    """round_id, peak (most runs at once; a finish comes before a start at the same time), avg_running."""
    marks = log.select("round_id", F.explode(F.array(F.struct(F.col("start_us").alias("t"), F.lit(1).alias("d")), F.struct(F.col("finish_us").alias("t"), F.lit(-1).alias("d")))).alias("m"))
    running = F.sum("m.d").over(Window.partitionBy("round_id").orderBy("m.t", "m.d").rowsBetween(Window.unboundedPreceding, 0))
    peak = marks.withColumn("running", running).groupBy("round_id").agg(F.max("running").alias("peak"))
    busy = log.groupBy("round_id").agg((F.sum(duration()) / (F.max("finish_us") - F.min("start_us"))).alias("avg_running"))
    return peak.join(busy, "round_id")


def degradation_flags(makespans: DataFrame, window: int = 5, tolerance: float = 0.1) -> DataFrame:
    """Rounds whose makespan exceeds the mean of the rounds before by more than tolerance.

    One row a round enters; the order over rounds is the measure itself.
    """
    before = Window.orderBy("round_id").rowsBetween(-window, -1)
    mean = F.avg("makespan_us").over(before)
    return makespans.select("round_id", "makespan_us", mean.alias("moving_avg"), F.coalesce(F.col("makespan_us") > mean * (1 + tolerance), F.lit(False)).alias("flag"))
