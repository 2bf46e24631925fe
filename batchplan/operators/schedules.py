"""Orders of the heuristics, and schedules by the rule that an idle connection takes the next query."""

from __future__ import annotations

import itertools

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def order_fifo(query: str = "query_id") -> Column:
    """By submission; ids are given in that order."""
    return F.struct(F.col(query).cast("double").alias("k"), F.lit("").alias("s"), F.col(query).alias("q"))


def order_mcf(cost: str = "cost", query: str = "query_id") -> Column:
    """Longest expected time first; ties by id."""
    return F.struct((-F.col(cost)).cast("double").alias("k"), F.lit("").alias("s"), F.col(query).alias("q"))


def order_random(seed: Column, query: str = "query_id") -> Column:
    """By a digest of seed and id, the same on every engine."""
    return F.struct(F.lit(0.0).alias("k"), F.md5(F.concat_ws(":", seed.cast("string"), F.col(query).cast("string")).cast("binary")).alias("s"), F.col(query).alias("q"))


def list_schedule(jobs: DataFrame, n_conn: int, by: list[str], order: str = "ord") -> DataFrame:
    """by.., seq, query_id, conn_id, start_us, finish_us of every scenario.

    jobs: by.., ord, query_id, cost. Each scenario (a batch of queries) is one array, walked in order with
    the connections' free times; of equally free connections the lowest is taken.
    """
    walk = F.array_sort(F.collect_list(F.struct(F.col(order).alias("o"), F.col("query_id"), F.col("cost").cast("long").alias("cost"))))
    zero = f"named_struct('free', array_repeat(0L, {n_conn}), 'out', CAST(array() AS ARRAY<STRUCT<query_id: BIGINT, conn_id: INT, start_us: BIGINT, finish_us: BIGINT>>))"
    step = """aggregate(walk, {zero}, (s, j) -> named_struct(
        'free', transform(s.free, (f, k) -> if(k = array_position(s.free, array_min(s.free)) - 1, f + j.cost, f)),
        'out', concat(s.out, array(named_struct('query_id', CAST(j.query_id AS BIGINT), 'conn_id', CAST(array_position(s.free, array_min(s.free)) - 1 AS INT),
               'start_us', array_min(s.free), 'finish_us', array_min(s.free) + j.cost)))), s -> s.out)"""
    grouped = (jobs.groupBy(*by) if by else jobs.groupBy()).agg(walk.alias("walk"))
    placed = grouped.select(*by, F.posexplode(F.expr(step.format(zero=zero))).alias("seq", "x"))
    return placed.select(*by, "seq", "x.query_id", "x.conn_id", "x.start_us", "x.finish_us")


def heuristic_schedules(costs: DataFrame, n_conn: int, seeds: range = range(5)) -> DataFrame:
    """strategy, round_id, seq, ...: FIFO, MCF and one round of Random for each seed."""
    fifo = costs.select(F.lit("fifo").alias("strategy"), F.lit(0).alias("round_id"), order_fifo().alias("ord"), "query_id", "cost")
    mcf = costs.select(F.lit("mcf").alias("strategy"), F.lit(0).alias("round_id"), order_mcf().alias("ord"), "query_id", "cost")
    drawn = costs.withColumn("round_id", F.explode(F.array(*[F.lit(s) for s in seeds])))
    rand = drawn.select(F.lit("random").alias("strategy"), "round_id", order_random(F.col("round_id")).alias("ord"), "query_id", "cost")
    return list_schedule(fifo.unionByName(mcf).unionByName(rand), n_conn, ["strategy", "round_id"])


def cluster_schedule(costs: DataFrame, n_conn: int, intra: str = "fifo") -> DataFrame:
    """Clusters (cluster_id) one after another, their queries by FIFO or MCF; one scenario."""
    key = F.col("query_id").cast("double") if intra == "fifo" else (-F.col("cost")).cast("double")
    order = F.struct("cluster_id", key.alias("k"), "query_id")
    placed = list_schedule(costs.withColumn("ord", order), n_conn, [])
    return placed.join(costs.select("query_id", "cluster_id"), "query_id")


def strategy_summary(schedules: DataFrame) -> DataFrame:
    """strategy, rounds, avg, std of the makespans."""
    spans = schedules.groupBy("strategy", "round_id").agg((F.max("finish_us") - F.min("start_us")).alias("m"))
    return spans.groupBy("strategy").agg(F.count("*").alias("rounds"), F.avg("m").alias("avg"), F.stddev_pop("m").alias("std"))


def improvement(summary: DataFrame, new: str) -> DataFrame:
    """base, improvement (1 - new/base of the means), std_improvement (of the deviations; null for a base of none)."""
    mine = summary.where(F.col("strategy") == new).select(F.col("avg").alias("a"), F.col("std").alias("s"))
    base = summary.where(F.col("strategy") != new)
    return base.join(F.broadcast(mine)).select(F.col("strategy").alias("base"), (1 - F.col("a") / F.col("avg")).alias("improvement"), (1 - F.col("s") / F.when(F.col("std") > 0, F.col("std"))).alias("std_improvement"))


def best_over_worst(summary: DataFrame) -> DataFrame:
    """best, worst, ratio: what the best strategy saves of the worst."""
    return summary.agg(F.min("avg").alias("best"), F.max("avg").alias("worst")).withColumn("ratio", 1 - F.col("best") / F.col("worst"))


def lower_bound(costs: DataFrame, n_conn: int) -> DataFrame:
    """n_conn, bound: no schedule is shorter than the longest query or an even share of all."""
    return costs.agg(F.lit(n_conn).alias("n_conn"), F.greatest(F.max("cost"), F.ceil(F.sum("cost") / n_conn)).alias("bound"))


def utilisation(schedules: DataFrame, n_conn: int) -> DataFrame:
    """strategy, round_id, used_share of the connections' time, and tail_idle_us after each connection's last query."""
    last = schedules.groupBy("strategy", "round_id", "conn_id").agg(F.max("finish_us").alias("f"), F.sum(F.col("finish_us") - F.col("start_us")).alias("busy"))
    return last.groupBy("strategy", "round_id").agg((F.sum("busy") / (n_conn * F.max("f"))).alias("used_share"), (n_conn * F.max("f") - F.sum("f")).alias("tail_idle_us"))


def violations(schedules: DataFrame, costs: DataFrame, by: list[str]) -> DataFrame:
    """violations: queries missing or placed twice, and queries that overlap on their connection."""
    w = Window.partitionBy(*by, "conn_id").orderBy("start_us", "finish_us")
    clash = schedules.withColumn("prior", F.lag("finish_us").over(w)).where("prior > start_us").select(F.lit(1).alias("v"))
    scenarios = schedules.select(*by).distinct()
    wanted = scenarios.join(costs.select("query_id"))
    counted = schedules.groupBy(*by, "query_id").agg(F.count("*").alias("n"))
    wrong = wanted.join(counted, [*by, "query_id"], "left").where("n IS NULL OR n <> 1").select(F.lit(1).alias("v"))
    return clash.unionByName(wrong).agg(F.count("*").alias("violations"))


def plan_space_log10(n: int, n_conn: int, settings: tuple[int, ...] = (), mode: str = "busy", n_c: int = 0) -> Column:
    """log10 of how many plans there are.

    order_conn: n! n_conn^n; order_conn_cfg: also every configuration of every query; busy: the busy rule leaves
    orders (and configurations); cluster: orders of n_c clusters with a configuration each.
    """
    m = n_c if mode == "cluster" else n
    orders = F.aggregate(F.sequence(F.lit(1), F.lit(m)), F.lit(0.0), lambda s, k: s + F.log10(k.cast("double")))
    configs = sum((F.log10(F.lit(float(k))) for k in settings), F.lit(0.0))
    total = orders
    if mode in ("order_conn", "order_conn_cfg"):
        total = total + m * F.log10(F.lit(float(n_conn)))
    if mode in ("order_conn_cfg", "busy", "cluster"):
        total = total + m * configs
    return total


def makespan_of(order: tuple[int, ...], costs: dict[int, int], n_conn: int) -> int:
    free = [0] * n_conn
    for q in order:
        k = free.index(min(free))
        free[k] += costs[q]
    return max(free)


def exhaustive(costs: dict[int, int], n_conn: int) -> tuple[int, int, int]:
    """best, worst and number of all orders (at most eight queries)."""
    if len(costs) > 8:
        raise ValueError("at most eight queries")
    spans = [makespan_of(p, costs, n_conn) for p in itertools.permutations(sorted(costs))]
    return min(spans), max(spans), len(spans)
