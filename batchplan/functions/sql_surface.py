"""The methods from SQL: views of logs, stats and gains, SQL functions, and table functions.

``SELECT * FROM list_schedule(TABLE(SELECT query_id, cost FROM c ORDER BY cost DESC) ...)`` and the like.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from batchplan.operators import gain as gn
from batchplan.operators import intervals as iv
from batchplan.operators import stats as st
from batchplan.sources import logs


@udtf(returnType="scenario string, seq int, query_id long, conn_id int, start_us long, finish_us long")
class ListSchedule:
    """Busy-connection schedule of the rows of a partition, in the order given: (scenario, query_id, cost, n_conn)."""

    def __init__(self) -> None:
        self.free: list[int] = []
        self.seq = 0

    def eval(self, row: Row) -> Iterator[tuple]:
        self.free = self.free or [0] * row["n_conn"]
        k = self.free.index(min(self.free))
        start, self.free[k] = self.free[k], self.free[k] + row["cost"]
        yield row["scenario"], self.seq, row["query_id"], k, start, self.free[k]
        self.seq += 1


@udtf(returnType="number long, place int, item int")
class Permutations:
    """All orders of 0..n-1, for n up to 8."""

    def eval(self, n: int) -> Iterator[tuple]:
        if n > 8:
            raise ValueError("at most eight items")
        for k, order in enumerate(itertools.permutations(range(n))):
            for place, item in enumerate(order):
                yield k, place, item


def busy_makespan(costs: pd.Series, n_conn: pd.Series) -> int:
    """Makespan of a group's costs, longest first."""
    free = [0] * int(n_conn.iloc[0])
    for c in costs.sort_values(ascending=False):
        free[free.index(min(free))] += int(c)
    return max(free)


def register(spark: SparkSession, sf_dir: str) -> None:
    """Views log_a, log_b, run_stats, co_runs, gains, and the functions, for spark.sql."""
    events, orders, customer = (logs.table(spark, sf_dir, n) for n in ("events", "orders", "customer"))
    log = logs.log_from_events(events)
    log.createOrReplaceTempView("log_a")
    logs.log_from_orders(orders, customer).createOrReplaceTempView("log_b")
    st.avg_runtime(log).createOrReplaceTempView("run_stats")
    pairs = iv.concurrent_pairs(log)
    pairs.createOrReplaceTempView("co_runs")
    gn.scheduling_gain(pairs, st.avg_runtime(log)).createOrReplaceTempView("gains")
    spark.udtf.register("list_schedule", ListSchedule)
    spark.udtf.register("permutations", Permutations)
    spark.udf.register("busy_makespan", F.pandas_udf(busy_makespan, "long"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION improvement(new DOUBLE, base DOUBLE) RETURNS DOUBLE RETURN 1 - new / base")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION clipped(ratio DOUBLE, advantage DOUBLE, eps DOUBLE) RETURNS DOUBLE RETURN least(ratio * advantage, greatest(1 - eps, least(1 + eps, ratio)) * advantage)")
