"""What runs at a moment, by a sweep over time instead of a join of moments and runs.

A run is dealt to the (round, bucket of time) groups that it touches; in a group, moments are walked in order with
a heap of the runs that have started, so the work is that of the runs (n log n), however many run at once. A
group is held in memory: the runs of a round that touch one bucket.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

HOUR_US = 3.6e9
LEAST = np.iinfo(np.int64).min


def dealt(log: DataFrame, columns: list[str], bucket_us: int) -> DataFrame:
    """Runs with each bucket from their start to their finish, that of the finish itself included."""
    spread = F.explode(F.expr(f"sequence(start_us DIV {bucket_us}, finish_us DIV {bucket_us})"))
    rows = log.where("round_id IS NOT NULL").select("round_id", "run_id", "start_us", "finish_us", *columns, spread.alias("bucket"))
    parts = max(int(log.sparkSession.conf.get("spark.sql.shuffle.partitions")), log.sparkSession.sparkContext.defaultParallelism)
    return rows.repartition(parts, "round_id", "bucket")


def ints(column: pa.ChunkedArray) -> np.ndarray:
    return column.fill_null(LEAST).to_numpy().astype(np.int64, copy=False)


def first_of(keys: list[tuple], starts: list[int], finishes: list[int], moments: list[int]) -> np.ndarray:
    """For each moment (ascending) the run of least key among those running then, or -1; keys end in the run's place."""
    waiting, at, heap = sorted(range(len(keys)), key=starts.__getitem__), 0, []
    out = np.full(len(moments), -1)
    for k, t in enumerate(moments):
        while at < len(waiting) and starts[waiting[at]] <= t:
            heapq.heappush(heap, keys[waiting[at]])
            at += 1
        while heap and finishes[heap[0][-1]] <= t:
            heapq.heappop(heap)
        if heap:
            out[k] = heap[0][-1]
    return out


def states_of(runs: np.ndarray, times: np.ndarray, mine: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The places of distinct (time, run) of the group's own moments by time, and how often each is there."""
    own = np.flatnonzero(mine)
    own = own[np.lexsort((runs[own], times[own]))]
    new = np.ones(len(own), bool)
    new[1:] = (times[own][1:] != times[own][:-1]) | (runs[own][1:] != runs[own][:-1])
    heads = np.flatnonzero(new)
    return own[heads], np.diff(np.append(heads, len(own)))


def running_sum(lo: np.ndarray, hi: np.ndarray, weight: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, float]:
    """Sums of the weights whose [lo, hi) holds each moment, and the sum of all weights."""
    some = hi > lo
    lo, hi, weight = lo[some], hi[some], weight[some]

    def upto(edge: np.ndarray) -> np.ndarray:
        order = np.argsort(edge, kind="stable")
        return np.append(0.0, np.cumsum(weight[order]))[np.searchsorted(edge[order], at, "right")]

    return upto(lo) - upto(hi), float(weight.sum())


def first_finishes(log: DataFrame, at: str, bucket_us: int) -> DataFrame:
    """round_id, state, t_us, running_n, next_run_id, next_query_id, next_finish_us for each run's ``at`` at which something runs."""

    def sweep(group: pa.Table) -> pa.Table:
        runs, starts, finishes = (ints(group[c]) for c in ("run_id", "start_us", "finish_us"))
        times = starts if at == "start_us" else finishes
        bucket = group["bucket"][0].as_py()
        own, often = states_of(runs, times, (np.sign(times) * (np.abs(times) // bucket_us)) == bucket)
        moments = times[own]
        f = finishes.tolist()
        first = first_of(list(zip(f, runs.tolist(), range(len(f)), strict=True)), starts.tolist(), f, moments.tolist())
        n = np.searchsorted(np.sort(starts), moments, "right") - np.searchsorted(np.sort(finishes), moments, "right")
        own, often, n, first = (x[first >= 0] for x in (own, often, n, first))
        return pa.table([
            group["round_id"].take(own), group["run_id"].take(own), pa.array(times[own]), pa.array(n * often),
            group["run_id"].take(first), group["query_id"].take(first), group["finish_us"].take(first),
        ], names=NEXT)

    rows = dealt(log, ["query_id"], bucket_us)
    kind = {f.name: f.dataType.simpleString() for f in rows.schema.fields}
    schema = f"round_id {kind['round_id']}, state {kind['run_id']}, t_us long, running_n long, next_run_id {kind['run_id']}, next_query_id {kind['query_id']}, next_finish_us long"
    return rows.groupBy("round_id", "bucket").applyInArrow(arrow(sweep), schema)


NEXT = ["round_id", "state", "t_us", "running_n", "next_run_id", "next_query_id", "next_finish_us"]


def arrow(f: Callable[[pa.Table], pa.Table]) -> Callable[[pa.Table], pa.Table]:
    """f as a function of one argument and nothing else, as Spark looks at the number of arguments."""
    return lambda group: f(group)


def guessed_finishes(log: DataFrame, means: DataFrame, bucket_us: int) -> DataFrame:
    """What least expected remaining time (mean minus elapsed) guesses at each finish, and what is true.

    state, guess, truth (runs), t_hat, t_true (hours), p_true: the softmax share of the true one by minus the
    remaining hours (0 to 50). Its sum is kept by spans of time, in which a run has over 50 hours left, some, or none.
    """

    def sweep(group: pa.Table) -> pa.Table:
        runs, starts, finishes = (ints(group[c]) for c in ("run_id", "start_us", "finish_us"))
        bucket = group["bucket"][0].as_py()
        own, _ = states_of(runs, finishes, (np.sign(finishes) * (np.abs(finishes) // bucket_us)) == bucket)
        moments = finishes[own]
        known = np.flatnonzero(group["avg_us"].is_valid().to_numpy())
        s, f, mean, run = starts[known], finishes[known], group["avg_us"].to_numpy()[known], runs[known]
        sl, fl, rl, at = s.tolist(), f.tolist(), run.tolist(), moments.tolist()
        places = range(len(known))
        truth = first_of(list(zip(fl, rl, places, strict=True)), sl, fl, at)
        # mean + start in two exact parts: at one moment the order is that of mean - (t - start)
        whole = np.floor(mean)
        guess = first_of(list(zip((s + whole.astype(np.int64)).tolist(), (mean - whole).tolist(), rl, places, strict=True)), sl, fl, at)
        own, moments, truth, guess = (x[truth >= 0] for x in (own, moments, truth, guess))

        base = bucket * bucket_us
        t, lo, hi = (moments - base).astype(float), (s - base).astype(float), (f - base).astype(float)
        end = mean + lo
        far, near_lo, near_hi = np.minimum(hi, end - 50 * HOUR_US), np.maximum(np.maximum(lo, end - 50 * HOUR_US), np.minimum(0.0, t.min(initial=0.0))), np.minimum(hi, end)
        shown = near_hi > near_lo
        near, total = running_sum(near_lo, near_hi, np.where(shown, np.exp(-np.where(shown, end, 0.0) / HOUR_US), 0.0), t)
        over, _ = running_sum(np.maximum(lo, end), hi, np.ones(len(s)), t)
        beyond, _ = running_sum(lo, far, np.ones(len(s)), t)
        sums = np.exp(t / HOUR_US) * np.maximum(near, 0.0) + np.exp(-50.0) * beyond + over

        def left(m: np.ndarray, k: np.ndarray) -> np.ndarray:
            return mean[k] - (m - s[k])

        hours = lambda x: np.minimum(np.maximum(x, 0.0) / HOUR_US, 50.0)
        for k in np.flatnonzero((near < 1e-7 * total) & (over == 0)):  # differences of sums have too few digits here
            on = np.flatnonzero((s <= moments[k]) & (moments[k] < f))
            sums[k] = np.exp(-hours(left(moments[k], on))).sum()
        return pa.table([
            group["run_id"].take(own), group["run_id"].take(known[guess]), group["run_id"].take(known[truth]), pa.array(np.maximum(left(moments, guess), 0.0) / HOUR_US),
            pa.array((f[truth] - moments) / HOUR_US), pa.array(np.exp(-hours(left(moments, truth))) / sums),
        ], names=["state", "guess", "truth", "t_hat", "t_true", "p_true"])

    rows = dealt(log.join(means.select("query_id", "avg_us"), "query_id", "left"), ["avg_us"], bucket_us)
    run = dict(log.dtypes)["run_id"]
    return rows.groupBy("round_id", "bucket").applyInArrow(arrow(sweep), f"state {run}, guess {run}, truth {run}, t_hat double, t_true double, p_true double")
