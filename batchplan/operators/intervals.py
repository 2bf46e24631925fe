"""Interval joins by time buckets: overlapping runs, runs that hold a moment, completion samples.

Spark has no interval join; rows are put into the buckets of time that they touch, joined on (round,
bucket) as equal keys, and a pair counts only in the bucket of its later start. Completion samples come
from a sweep instead (``sweep``).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from batchplan.operators import sweep

#: Two hours.
BUCKET_US = 7_200_000_000
#: A quarter of an hour: a run meets all that touch its start's bucket.
PAIR_BUCKET_US = 900_000_000


def in_buckets(log: DataFrame, bucket_us: int) -> DataFrame:
    spread = F.explode(F.expr(f"sequence(start_us DIV {bucket_us}, (finish_us - 1) DIV {bucket_us})"))
    return log.select("round_id", "run_id", "query_id", "start_us", "finish_us", spread.alias("bucket"))


def concurrent_pairs(log: DataFrame, bucket_us: int = PAIR_BUCKET_US) -> DataFrame:
    """Runs of two queries (query_i < query_j) of a round that overlap, with their overlap ov_us.

    Each run meets, in the bucket of its start alone, those that started before it and touch that bucket.
    """
    parts = max(int(log.sparkSession.conf.get("spark.sql.shuffle.partitions")), 4 * log.sparkSession.sparkContext.defaultParallelism)
    names = {"run_id": "run", "query_id": "query", "start_us": "start", "finish_us": "finish"}
    # by number, so that few rows that make many pairs are not put together into few tasks
    side = lambda rows, s: rows.select("round_id", "bucket", *[F.col(c).alias(f"{n}_{s}") for c, n in names.items()]).repartition(parts, "round_id", "bucket")
    late, early = side(log.withColumn("bucket", F.expr(f"start_us DIV {bucket_us}")), "l"), side(in_buckets(log, bucket_us), "e")
    before = (F.col("start_e") < F.col("start_l")) | ((F.col("start_e") == F.col("start_l")) & (F.col("query_e") < F.col("query_l")))
    met = late.join(early, ["round_id", "bucket"]).where(before & (F.col("finish_e") > F.col("start_l")) & (F.col("finish_l") > F.col("start_l")) & (F.col("query_e") != F.col("query_l")))
    first = F.col("query_e") < F.col("query_l")
    pick = lambda c, d, name: [F.when(first, c).otherwise(d).alias(f"{name}_i"), F.when(first, d).otherwise(c).alias(f"{name}_j")]
    lasting = [F.col(f"finish_{s}") - F.col(f"start_{s}") for s in "el"]
    return met.select("round_id", *pick(F.col("run_e"), F.col("run_l"), "run"), *pick(F.col("query_e"), F.col("query_l"), "query"), *pick(*lasting, "dur"), (F.least("finish_e", "finish_l") - F.col("start_l")).alias("ov_us"))


def running_at(moments: DataFrame, log: DataFrame, bucket_us: int = BUCKET_US) -> DataFrame:
    """moments (round_id, state, t_us) with each run of the round that is running at t (start <= t < finish)."""
    at = moments.withColumn("bucket", F.expr(f"t_us DIV {bucket_us}"))
    return at.join(in_buckets(log, bucket_us), ["round_id", "bucket"]).where("start_us <= t_us AND t_us < finish_us").drop("bucket")


def completion_samples(log: DataFrame, states: str = "completion", bucket_us: int = BUCKET_US) -> DataFrame:
    """Which running query ends first, and when, for each state of a round.

    states: "completion" (each finish, after it) or "submission" (each start, its run included). Of equal
    finishes the smallest run counts; a state in which nothing runs gives no sample.
    """
    found = sweep.first_finishes(log, "finish_us" if states == "completion" else "start_us", bucket_us)
    return found.select("round_id", F.col("state").alias("state_run_id"), "t_us", "running_n", "next_query_id", (F.col("next_finish_us") - F.col("t_us")).alias("remaining_us"))


def running_sets(log: DataFrame, stats: DataFrame, states: str = "completion", bucket_us: int = BUCKET_US) -> DataFrame:
    """Completion samples with the running set as an array of (query_id, elapsed_us, avg_us): what a simulator learns from."""
    t = "finish_us" if states == "completion" else "start_us"
    moments = log.select("round_id", F.col("run_id").alias("state"), F.col(t).alias("t_us"))
    held = running_at(moments, log, bucket_us).join(stats.select("query_id", "avg_us"), "query_id")
    run = F.struct("query_id", (F.col("t_us") - F.col("start_us")).alias("elapsed_us"), "avg_us")
    return held.groupBy("round_id", "state", "t_us").agg(
        F.array_sort(F.collect_list(run)).alias("running"), F.min(F.struct("finish_us", "run_id", "query_id")).alias("f")
    ).select("round_id", "state", "t_us", "running", F.col("f.query_id").alias("next_query_id"), (F.col("f.finish_us") - F.col("t_us")).alias("remaining_us"))


def state_status_counts(log: DataFrame) -> DataFrame:
    """How many runs of the round are pending, running and finished at each submission.

    By ranks in the ordered starts and finishes of a round, without a join of states and runs.
    """
    from pyspark.sql import Window

    by_start = Window.partitionBy("round_id").orderBy("t").rangeBetween(Window.unboundedPreceding, 0)
    marks = log.select("round_id", F.explode(F.array(
        F.struct(F.col("start_us").alias("t"), F.col("run_id").alias("run"), F.lit(1).alias("s"), F.lit(0).alias("f")),
        F.struct(F.col("finish_us").alias("t"), F.lit(None).cast("long").alias("run"), F.lit(0).alias("s"), F.lit(1).alias("f")),
    )).alias("m")).select("round_id", "m.*")
    counted = marks.select("round_id", "run", F.sum("s").over(by_start).alias("started"), F.sum("f").over(by_start).alias("finished"), F.sum("s").over(Window.partitionBy("round_id")).alias("all_runs"))
    return counted.where("run IS NOT NULL").select(
        "round_id", F.col("run").alias("run_id"), (F.col("all_runs") - F.col("started")).alias("pending"), (F.col("started") - F.col("finished")).alias("running"), "finished"
    )


def as_of(left: DataFrame, right: DataFrame, keys: list[str], at: str, value: str) -> DataFrame:
    """left with the last value of right at or before its time, by a window over both (no join)."""
    from pyspark.sql import Window

    a = left.select(*keys, F.col(at).alias("t"), F.struct(*left.columns).alias("row"), F.lit(None).cast(right.schema[value].dataType).alias("v"), F.lit(1).alias("side"))
    b = right.select(*keys, F.col(at).alias("t"), F.lit(None).cast(a.schema["row"].dataType).alias("row"), F.col(value).alias("v"), F.lit(0).alias("side"))
    last = F.last("v", ignorenulls=True).over(Window.partitionBy(*keys).orderBy("t", "side").rowsBetween(Window.unboundedPreceding, 0))
    return a.unionByName(b).withColumn("found", last).where("side = 1").select("row.*", F.col("found").alias(f"last_{value}"))
