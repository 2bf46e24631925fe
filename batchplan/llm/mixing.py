"""Mixing sources to target weights by capped water-filling, in DataFrame functions only.

A level is raised until the budget is used: each source gets weight x level words, clamped at
``max_epochs`` times its size, and what a clamped source gives back is shared by the others in
proportion to their weights. The level at which nobody is above its cap has a closed form over
the sources in order of cap / weight.

A source's target is then met by whole repetitions of all its documents and a fractional one:
documents in the order of a seeded digest, up to the words that remain; the document at the
border is taken in part. A source's place of that border is found from sums over 4,096
digest buckets, so that a source with a third of all rows is never sorted in one task.

Defined results: a null text has no words; null is a source of its own, last in order;
documents without words and sources without words take nothing; an empty table gives an empty
result; rows that repeat an id share the digest and are ordered by size.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from batchplan.llm.shared import WORD, written

MAX_EPOCHS = 3
WEIGHTS = (5, 2, 1)
SEED = "mix-1"


def word_count(text_col: str = "text") -> Column:
    return F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD)), F.lit(0)).cast("long")


def water_fill(sources: DataFrame, weights: tuple[int, ...] = WEIGHTS, max_epochs: int = MAX_EPOCHS, share: float = 1.0) -> DataFrame:
    """sources (source, source_size) with target: its words in the mix.

    The table has a row for each source, so ordering it whole is bounded by their number.
    """
    ordered = Window.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(F.row_number().over(ordered) - 1, F.lit(len(weights))) + 1).cast("int"))
    base = sources.select("source", "source_size", weight.alias("weight")).withColumn("cap", F.lit(float(max_epochs)) * F.col("source_size"))
    by_level = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    every = Window.partitionBy()
    levelled = base.select(
        "*",
        (F.lit(share) * F.sum("source_size").over(every)).alias("budget"),
        F.coalesce(F.sum("cap").over(by_level.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)).alias("clamped"),
        F.sum("weight").over(by_level.rowsBetween(0, Window.unboundedFollowing)).alias("open_weight"),
        F.row_number().over(by_level).alias("place"),
    ).withColumn("level", (F.col("budget") - F.col("clamped")) / F.col("open_weight"))
    # the first source in this order that stays below its cap fixes the level for all
    fits = F.when(F.col("level") * F.col("weight") <= F.col("cap"), F.struct("place", "level"))
    target = F.least(F.col("cap"), F.coalesce(F.min(fits).over(every)["level"] * F.col("weight"), F.col("cap")))
    return levelled.select("source", "source_size", F.round(target, 6).alias("target"))


def plan_mix(docs: DataFrame, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", weights: tuple[int, ...] = WEIGHTS, max_epochs: int = MAX_EPOCHS, share: float = 1.0, seed: str = SEED) -> DataFrame:
    """docs' rows as structs ``row`` with size, source_size, target and taken (words that the mix takes)."""
    digest = F.md5(F.concat_ws(":", F.lit(seed), F.col(id_col).cast("string")).cast("binary"))
    cols = F.struct(*[F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(docs.columns)])
    sized = docs.select(F.col(source_col).alias("source"), word_count(text_col).alias("size"), digest.alias("h"), F.substring(digest, 1, 3).alias("b"), F.col(id_col).alias("id"), cols.alias("row"))
    slices = written(sized.groupBy("source", "b").agg(F.sum("size").alias("words")), "mix-slices")
    plan = water_fill(slices.groupBy("source").agg(F.sum("words").alias("source_size")), weights, max_epochs, share)
    plan = plan.withColumn("whole", F.coalesce(F.floor(F.col("target") / F.when(F.col("source_size") > 0, F.col("source_size"))), F.lit(0)))
    plan = plan.withColumn("rest", F.round(F.col("target") - F.col("whole") * F.col("source_size")).cast("long"))
    upto = F.sum("words").over(Window.partitionBy("source").orderBy("b"))
    borders = (
        slices.withColumn("upto", upto)
        .alias("s")
        .join(plan.alias("p"), F.col("s.source").eqNullSafe(F.col("p.source")))
        .where("s.upto > p.rest")
        .groupBy(F.col("p.source").alias("bsource"))
        .agg(F.min("b").alias("border"), F.min_by(F.col("s.upto") - F.col("s.words"), "b").alias("before"))
    )
    plan = written(plan.join(borders, F.col("source").eqNullSafe(F.col("bsource")), "left").drop("bsource").withColumnRenamed("source", "psource"), "mix-plan")
    joined = sized.join(F.broadcast(plan) if plan.count() <= 100_000 else plan, F.col("source").eqNullSafe(F.col("psource")))
    once = F.col("whole") * F.col("size")
    far = joined.where(F.col("border").isNull() | (F.col("b") != F.col("border"))).withColumn("taken", once + F.when(F.col("border").isNull() | (F.col("b") < F.col("border")), F.col("size")).otherwise(0))
    prior = F.sum("size").over(Window.partitionBy("source").orderBy("h", "id", "size").rowsBetween(Window.unboundedPreceding, -1))
    near = joined.where(F.col("b") == F.col("border")).withColumn("prior", F.coalesce(prior, F.lit(0)))
    near = near.withColumn("taken", once + F.greatest(F.lit(0), F.least(F.col("size"), F.col("rest") - F.col("before") - F.col("prior")))).drop("prior")
    return far.unionByName(near).select("row", "size", "source_size", "target", F.col("taken").cast("long").alias("taken"))


def mix_sizes(docs: DataFrame, id_col: str = "doc_id", **how) -> DataFrame:
    """One row for each document: id, size, source_size, target, taken."""
    k = docs.columns.index(id_col)
    return plan_mix(docs, id_col=id_col, **how).select(F.col(f"row.c{k}").alias(id_col), "size", "source_size", "target", "taken")


def mix_documents(docs: DataFrame, **how) -> DataFrame:
    """docs with each row as often as the mix repeats it; a part of at least half counts as once.

    Rows without words are repeated by no measure of words; they stay once.
    """
    times = F.when(F.col("size") == 0, 1).otherwise(F.round(F.col("taken") / F.col("size")).cast("int"))
    repeated = plan_mix(docs, **how).withColumn("times", times).where("times > 0")
    again = repeated.select("row", F.explode(F.sequence(F.lit(1), F.col("times"))).alias("copy"))
    return again.select(*[F.col(f"row.c{k}").alias(c) for k, c in enumerate(docs.columns)])
