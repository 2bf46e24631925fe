"""Batches of independent queries out of jobs with dependencies, and distances in plan trees."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from batchplan.sources.logs import cut_lineage


def extract_batches(queries: DataFrame, edges: DataFrame) -> DataFrame:
    """query_id, level: queries of one level do not depend on one another, so each level is a batch.

    edges: query_id, depends_on. The level is one more than the deepest query that it depends on. Levels are
    walked one after another with each query once in a level, so the work is that of the edges times the
    levels, however many paths there are; a cycle raises.
    """
    on = edges.select(F.col("query_id").alias("next"), "depends_on").distinct()
    front = queries.select("query_id").join(on, F.col("query_id") == F.col("next"), "left_anti").distinct()
    found, most = front.withColumn("level", F.lit(0)), queries.count()
    for level in range(1, most + 1):
        front = cut_lineage(on.join(front, F.col("depends_on") == F.col("query_id")).select(F.col("next").alias("query_id")).distinct())
        if front.isEmpty():
            return found.groupBy("query_id").agg(F.max("level").alias("level"))
        found = found.unionByName(front.withColumn("level", F.lit(level)))
    if most:
        raise ValueError("the dependencies have a cycle")
    return found


def ancestors(nodes: DataFrame) -> DataFrame:
    """node_id, above, steps: each node of a forest (node_id, parent_id) with itself and all above it, level by level."""
    up = nodes.select(F.col("node_id").alias("at"), F.col("parent_id").alias("parent")).where("parent IS NOT NULL")
    front = nodes.select("node_id", F.col("node_id").alias("above"), F.lit(0).alias("steps"))
    found = front
    while True:
        step = front.join(up, F.col("above") == F.col("at")).select("node_id", F.col("parent").alias("above"), (F.col("steps") + 1).alias("steps"))
        front = cut_lineage(step)
        if front.isEmpty():
            return found
        found = found.unionByName(front)


def plan_distances(nodes: DataFrame) -> DataFrame:
    """node_a, node_b, dist: steps between any two nodes of a tree of the forest, by common ancestors."""
    up = ancestors(nodes)
    a, b = (up.select(F.col("node_id").alias(f"node_{s}"), "above", F.col("steps").alias(f"steps_{s}")) for s in "ab")
    return a.join(b, "above").groupBy("node_a", "node_b").agg(F.min(F.col("steps_a") + F.col("steps_b")).alias("dist"))


def plan_heights(nodes: DataFrame) -> DataFrame:
    """node_id, height: steps to the deepest leaf below."""
    return ancestors(nodes).groupBy(F.col("above").alias("node_id")).agg(F.max("steps").alias("height"))
