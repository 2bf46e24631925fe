"""Execution logs from the given tables, and the cost lists that baselines schedule.

A run is a row: round_id, run_id, query_id, config_id, conn_id, start_us, finish_us. Times are
integer microseconds; a run of no length is no run.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENT_TYPES = ("click", "error", "purchase", "signup", "view")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def log_from_events(events: DataFrame) -> DataFrame:
    """Log A: a day is a round, a user a query, an event a run whose value is its minutes."""
    start = F.unix_micros(F.col("ts").cast("timestamp"))
    dur = F.round(F.col("value") * 100).cast("long") * 600_000
    config = F.array_position(F.array(*[F.lit(x) for x in EVENT_TYPES]), F.col("event_type")) - 1
    return events.where(dur > 0).select(
        F.to_date("ts").alias("round_id"),
        F.col("event_id").alias("run_id"),
        F.col("user_id").alias("query_id"),
        config.cast("int").alias("config_id"),
        F.pmod(F.get_json_object("props", "$.k").cast("int"), F.lit(8)).alias("conn_id"),
        start.alias("start_us"),
        (start + dur).alias("finish_us"),
    )


def log_from_orders(orders: DataFrame, customer: DataFrame) -> DataFrame:
    """Log B: a nation is a query, an order a run, its priority the configuration, its price the time."""
    start = F.unix_micros(F.col("o_orderdate").cast("timestamp"))
    dur = F.round(F.col("o_totalprice") * 100).cast("long") * 10_000
    joined = orders.join(customer, orders.o_custkey == customer.c_custkey).where(dur > 0)
    return joined.select(
        F.to_date(F.date_trunc("month", "o_orderdate")).alias("round_id"),
        F.col("o_orderkey").alias("run_id"),
        F.col("c_nationkey").cast("long").alias("query_id"),
        (F.substring("o_orderpriority", 1, 1).cast("int") - 1).alias("config_id"),
        start.alias("start_us"),
        (start + dur).alias("finish_us"),
    )


def supplier_costs(lineitem: DataFrame) -> DataFrame:
    """query_id, cost: the quantity that each supplier ships."""
    return lineitem.groupBy(F.col("l_suppkey").alias("query_id")).agg(F.sum("l_quantity").cast("long").alias("cost"))


def user_costs(events: DataFrame) -> DataFrame:
    """query_id, cost: the hundredths of value of each user."""
    return events.groupBy(F.col("user_id").alias("query_id")).agg(F.sum(F.round(F.col("value") * 100).cast("long")).alias("cost"))


def first_run_per_round(log: DataFrame) -> DataFrame:
    """The earliest run of each query in each round; ties by run."""
    first = log.groupBy("round_id", "query_id").agg(F.min(F.struct("start_us", "run_id", "finish_us")).alias("r"))
    return first.select("round_id", "query_id", "r.run_id", "r.start_us", "r.finish_us")


def shared_folder(spark: SparkSession) -> str:
    """The URI of this session's folder that driver and executors share, in spark.checkpoint.dir; only a local session gets a folder of its own."""
    context = spark.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        base = spark.conf.get("spark.checkpoint.dir", None)
        if not base and not context.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir is not set: on a cluster it must name a folder that driver and executors share")
        context.setCheckpointDir(base or tempfile.mkdtemp(prefix="batchplan-"))
    folder = context._jsc.sc().getCheckpointDir().get()
    return "file:///" + folder[5:].lstrip("/") if folder.startswith("file:") else folder


def new_folder(spark: SparkSession, label: str) -> str:
    """A URI in the shared folder that nothing uses yet."""
    return f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"


def cut_lineage(df: DataFrame) -> DataFrame:
    """df checkpointed in the shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint()
