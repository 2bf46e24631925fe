"""Real execution: a batch of queries on |C| connections of Spark itself, and its log.

A connection is a thread with a session of its own (so a query's running parameters are its session's
settings) and a FAIR pool. A query's rows go to a sink that discards them; what is kept is the log.
"""

from __future__ import annotations

import threading
import time
from collections.abc import Callable

import numpy as np
from pyspark import InheritableThread
from pyspark.sql import DataFrame, SparkSession

from batchplan.learn.autograd import Adam
from batchplan.learn.training import Policy, update
from batchplan.plans.workloads import Template, register_tables

#: Running parameters: settings of a session, from few resources to many.
CONFIGS = ({"spark.sql.shuffle.partitions": "2"}, {"spark.sql.shuffle.partitions": "4"}, {"spark.sql.shuffle.partitions": "8"})
RUN_LOG = "strategy string, round_id int, query_id long, config_id int, conn_id int, start_us long, finish_us long"


class SparkBackend:
    """Runs batches; choose(pending ids, running ids) gives the next (query, configuration)."""

    def __init__(self, spark: SparkSession, sf_dir: str, n_conn: int = 4) -> None:
        self.spark, self.sf_dir, self.n_conn = spark, sf_dir, n_conn

    def run(self, batch: list[Template], choose: Callable[[list[int], list[int]], tuple[int, int]], strategy: str, round_id: int = 0) -> list[tuple]:
        pending, running, log = list(range(len(batch))), [], []
        lock, errors = threading.Lock(), []
        begin = time.monotonic_ns()

        def connection(k: int) -> None:
            session = self.spark.newSession()
            register_tables(session, self.sf_dir)
            self.spark.sparkContext.setLocalProperty("spark.scheduler.pool", f"connection-{k}")
            while not errors:
                with lock:
                    if not pending:
                        return
                    q, config = choose(list(pending), list(running))
                    pending.remove(q)
                    running.append(q)
                for name, value in CONFIGS[config].items():
                    session.conf.set(name, value)
                start = (time.monotonic_ns() - begin) // 1000
                try:
                    session.sql(batch[q].sql).write.format("noop").mode("overwrite").save()
                except Exception as e:
                    errors.append(e)
                finish = (time.monotonic_ns() - begin) // 1000
                with lock:
                    running.remove(q)
                    log.append((strategy, round_id, q, config, k, start, finish))

        threads = [InheritableThread(target=connection, args=(k,)) for k in range(self.n_conn)]
        for t in threads:
            t.start()
        for t in threads:
            t.join()
        if errors:
            raise errors[0]
        return log

    def log_frame(self, rows: list[tuple]) -> DataFrame:
        return self.spark.createDataFrame(rows, RUN_LOG)


class PolicyChoice:
    """A learned policy as a backend's choice, for one round; ``steps`` are its decisions, as rollouts have them.

    unit: seconds of the backend in one unit of the policy's logged times. Decisions are greedy without a seed.
    The backend calls it under its lock, so it sees one state at a time.
    """

    def __init__(self, policy: Policy, unit: float, seed: int | None = None) -> None:
        n = policy.demands.n
        self.policy, self.unit, self.rng, self.greedy = policy, unit, np.random.default_rng(seed), seed is None
        self.status, self.config, self.started, self.t = np.zeros(n, int), np.zeros(n, int), np.zeros(n), 0.0
        self.begin, self.queue, self.steps = None, [], []

    def __call__(self, pending: list[int], running: list[int]) -> tuple[int, int]:
        now = time.monotonic()
        self.begin = self.begin or now
        self.t = (now - self.begin) / self.unit
        self.status[:] = 2
        self.status[pending], self.status[running] = 0, 1
        if not self.queue:
            x, k, step = self.policy.act(self, self.rng, self.greedy)
            self.steps.append(step)
            self.queue = self.policy.submissions(x, k)
        q, k = self.queue.pop(0)
        self.config[q], self.started[q] = k, self.t
        return q, k


def makespan_us(rows: list[tuple]) -> int:
    return max(r[6] for r in rows) - min(r[5] for r in rows)


def fine_tune(back: SparkBackend, batch: list[Template], policy: Policy, unit: float, rounds: int = 5, rate: float = 3e-3) -> list[tuple]:
    """Rounds of a sampling policy on the backend and one update from them; the log of the rounds."""
    log, rollouts = [], []
    for k in range(rounds):
        choice = PolicyChoice(policy, unit, k)
        rows = back.run(batch, choice, "explore", k)
        log += rows
        rollouts.append((makespan_us(rows) / 1e6 / unit, choice.steps, []))
    update(policy, rollouts, Adam(rate))
    return log


def fifo(pending: list[int], running: list[int]) -> tuple[int, int]:
    return pending[0], 1


def mcf(times: dict[int, float]) -> Callable[[list[int], list[int]], tuple[int, int]]:
    return lambda pending, running: (max(pending, key=lambda q: (times.get(q, 0.0), -q)), 1)


def results_of(spark: SparkSession, sf_dir: str, batch: list[Template]) -> list[int]:
    """Rows of each query run by itself, to compare with a concurrent run's."""
    register_tables(spark, sf_dir)
    return [spark.sql(t.sql).count() for t in batch]

