"""Logs that keep arriving: daily measures, pair sums that add up, and joined submit and finish events."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from batchplan.operators.overlaps import overlap_sums
from batchplan.sources import logs


def event_stream(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """Events under path (a folder of Parquet files of one schema) as a stream."""
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def watermarked(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Log A of a stream, with its start as event time; later rows than ``late`` are dropped by stateful steps."""
    return logs.log_from_events(events).withColumn("start_ts", F.timestamp_micros("start_us")).withWatermark("start_ts", late)


def daily_makespans(log: DataFrame) -> DataFrame:
    """round_id, makespan_us, of a stream or of a table."""
    return log.groupBy("round_id").agg((F.max("finish_us") - F.min("start_us")).alias("makespan_us"))


def user_sessions(log: DataFrame, gap: str = "2 hours") -> DataFrame:
    """Bursts of each query's runs: query_id, start, runs."""
    return log.groupBy("query_id", F.session_window("start_ts", gap).alias("w")).agg(F.count("*").alias("runs")).select("query_id", F.col("w.start").alias("session_start"), "runs")


def joined_runs(submits: DataFrame, finishes: DataFrame, longest: str = "INTERVAL 2 DAYS") -> DataFrame:
    """Runs from a stream of submissions (run_id, query_id, submit_ts) and one of finishes (run_id, finish_ts)."""
    s = submits.withWatermark("submit_ts", "1 hour").alias("s")
    f = finishes.withWatermark("finish_ts", "1 hour").alias("f")
    within = F.expr(f"s.run_id = f.run_id AND f.finish_ts >= s.submit_ts AND f.finish_ts <= s.submit_ts + {longest}")
    return s.join(f, within).select("s.run_id", "s.query_id", "s.submit_ts", "f.finish_ts")


def once_each(log: DataFrame) -> DataFrame:
    """Repeated deliveries of a run within the watermark, once."""
    return log.dropDuplicatesWithinWatermark(["run_id"])


def drain(stream: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """All that the stream has now, as a table in memory: for tests and small measures."""
    spark = stream.sparkSession
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def drain_to(stream: DataFrame, path: str) -> DataFrame:
    """All that the stream has now, as Parquet in a new folder that driver and executors share.

    The result and the state between increments (in RocksDB) may be as large as the log; neither is held on a heap.
    """
    spark, key = stream.sparkSession, "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        writer = stream.writeStream.outputMode("complete").option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True)
        q = writer.foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(f"{path}/rows")).start()
    finally:
        spark.conf.set(key, before)  # a query has its own copy of the settings from its start
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")


def each_increment(stream: DataFrame, act: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    """act(batch, number) on each micro-batch that there is: the hook of incremental updates."""
    stream.writeStream.foreachBatch(act).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def merge_pair_sums(old: DataFrame | None, log: DataFrame) -> DataFrame:
    """Pair sums with those of new whole rounds added; nothing is scanned again."""
    new = overlap_sums(log)
    if old is None:
        return new
    return old.unionByName(new).groupBy("qi", "qj").agg(*[F.sum(c).alias(c) for c in ("m_c", "s_i", "s_j", "s_ov")])
