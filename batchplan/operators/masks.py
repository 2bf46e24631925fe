"""Adaptive masks of running parameters: which configurations are worth their resources."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Logit of what is masked.
FILL = -1e8


def config_improvement(profile: DataFrame, against: str = "next_lower") -> DataFrame:
    """query_id, config_id, avg_us, abs_gain_us, rel_gain of each configuration over a cheaper one.

    against: "next_lower", or "best_lower" (the fastest of all cheaper ones). The cheapest has nulls.
    """
    w = Window.partitionBy("query_id").orderBy("config_id")
    prior = F.lag("avg_us").over(w) if against == "next_lower" else F.min("avg_us").over(w.rowsBetween(Window.unboundedPreceding, -1))
    gain = prior - F.col("avg_us")
    return profile.select("query_id", "config_id", "avg_us", gain.alias("abs_gain_us"), (gain / prior).alias("rel_gain"))


def adaptive_mask(improvement: DataFrame, abs_share: float = 0.05, rel: float = 0.05, rule: str = "both") -> DataFrame:
    """query_id, config_id, allowed.

    A configuration is kept if its absolute gain reaches abs_share of its query's mean time and its relative
    gain reaches rel (rule "both"), or either; the cheapest is always kept.
    """
    mean = F.avg("avg_us").over(Window.partitionBy("query_id"))
    absolute, relative = F.col("abs_gain_us") >= abs_share * mean, F.col("rel_gain") >= rel
    passed = absolute & relative if rule == "both" else absolute | relative
    return improvement.select("query_id", "config_id", (F.col("abs_gain_us").isNull() | passed).alias("allowed"))


def masked_softmax(logits: DataFrame, state: list[str], allowed: str = "allowed", logit: str = "logit", fill: float = FILL) -> DataFrame:
    """logits with prob: a softmax over all (query, configuration) of a state, masked ones at ``fill``."""
    z = F.when(F.col(allowed), F.col(logit)).otherwise(F.lit(fill))
    w = Window.partitionBy(*state) if state else Window.partitionBy(F.lit(0))
    shifted = logits.withColumn("z", z).withColumn("e", F.exp(F.col("z") - F.max("z").over(w)))
    return shifted.withColumn("prob", F.col("e") / F.sum("e").over(w)).drop("z", "e")


def nearest_allowed_config(mask: DataFrame, wanted: DataFrame, ladder: DataFrame) -> DataFrame:
    """Each member's configuration: its cluster's, or the closest that its mask allows.

    wanted: query_id, cluster_id, cluster_config. ladder: config_id, steps (array of parameter levels).
    Closest by summed steps, then fewer resources, then the smaller id.
    """
    own = ladder.select("config_id", F.col("steps").alias("own"))
    goal = ladder.select(F.col("config_id").alias("cluster_config"), F.col("steps").alias("goal"))
    far = F.aggregate(F.zip_with("own", "goal", lambda a, b: F.abs(a - b)), F.lit(0), lambda s, x: s + x)
    used = F.aggregate("own", F.lit(0), lambda s, x: s + x)
    choices = wanted.join(mask.where("allowed"), "query_id").join(own, "config_id").join(goal, "cluster_config")
    best = choices.groupBy("query_id", "cluster_id", "cluster_config").agg(F.min(F.struct(far.alias("far"), used.alias("used"), "config_id")).alias("m"))
    return best.select("query_id", "cluster_id", "cluster_config", F.col("m.config_id").alias("config_id"))
