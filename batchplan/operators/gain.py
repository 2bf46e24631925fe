"""Scheduling gain of query pairs, from the overlaps of their runs, and clusters of high gain.

Of two runs that overlap, each was faster or slower than its query's mean; the part of that which the
overlap's share accounts for, weighted by the roots of the means and averaged over all co-runs, is the
pair's gain. It needs four sums for each pair, so increments of a log add up exactly for any mean.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from batchplan.operators.overlaps import gain_blocks, overlap_sums
from batchplan.sources.logs import cut_lineage


def gain_terms(pairs: DataFrame, stats: DataFrame) -> DataFrame:
    """Overlap shares o and accelerations a of both runs of each pair."""
    means = F.broadcast(stats.select("query_id", "avg_us"))  # pairs of runs are many, and stay where they are
    with_i = pairs.join(means.select(F.col("query_id").alias("query_i"), F.col("avg_us").alias("mean_i")), "query_i")
    both = with_i.join(means.select(F.col("query_id").alias("query_j"), F.col("avg_us").alias("mean_j")), "query_j")
    return both.select(
        "round_id", "run_i", "run_j", "query_i", "query_j", "mean_i", "mean_j",
        (F.col("ov_us") / F.col("dur_i")).alias("o_ij"), (1 - F.col("dur_i") / F.col("mean_i")).alias("a_ij"),
        (F.col("ov_us") / F.col("dur_j")).alias("o_ji"), (1 - F.col("dur_j") / F.col("mean_j")).alias("a_ji"),
    )


def scheduling_gain(pairs: DataFrame, stats: DataFrame) -> DataFrame:
    """qi < qj, m_c (co-runs), gain. Sums first: the means meet one row for each pair of queries, not each pair of runs."""
    return gain_from_sums(gain_sums(pairs), stats)


def gain_sums(pairs: DataFrame) -> DataFrame:
    """The additive sums of each pair; sums of two logs add up to the sums of both."""
    return pairs.groupBy(F.col("query_i").alias("qi"), F.col("query_j").alias("qj")).agg(
        F.count("*").alias("m_c"), F.sum(F.col("ov_us") / F.col("dur_i")).alias("s_i"), F.sum(F.col("ov_us") / F.col("dur_j")).alias("s_j"), F.sum("ov_us").alias("s_ov")
    )


def gain_from_sums(sums: DataFrame, stats: DataFrame) -> DataFrame:
    """qi, qj, m_c, gain from added-up sums and today's means."""
    means = F.broadcast(stats.select("query_id", "avg_us"))
    both = sums.join(means.select(F.col("query_id").alias("qi"), F.col("avg_us").alias("t_i")), "qi").join(means.select(F.col("query_id").alias("qj"), F.col("avg_us").alias("t_j")), "qj")
    w_i, w_j = F.sqrt("t_i"), F.sqrt("t_j")
    gain = ((F.col("s_i") - F.col("s_ov") / F.col("t_i")) * w_i + (F.col("s_j") - F.col("s_ov") / F.col("t_j")) * w_j) / ((w_i + w_j) * F.col("m_c"))
    return both.select("qi", "qj", "m_c", gain.alias("gain"))


def unseen_pairs(stats: DataFrame, gain: DataFrame) -> DataFrame:
    """Pairs of queries that never ran together; the queries of one batch are paired, not a log."""
    q = stats.select("query_id")
    pairs = q.select(F.col("query_id").alias("qi")).join(q.select(F.col("query_id").alias("qj")), F.col("qi") < F.col("qj"))
    return pairs.join(gain.select("qi", "qj"), ["qi", "qj"], "left_anti")


def complete_gain(gain: DataFrame, unseen: DataFrame, predicted: Column | None = None) -> DataFrame:
    """qi, qj, gain, source: the log's gain, and for unseen pairs a model's (or zero)."""
    rest = unseen.select("qi", "qj", (predicted if predicted is not None else F.lit(0.0)).alias("gain"), F.lit("zero" if predicted is None else "model").alias("source"))
    return gain.select("qi", "qj", "gain", F.lit("log").alias("source")).unionByName(rest)


def average_linkage(ids: list[int], pairs: list[tuple[int, int, float]], n_c: int) -> tuple[dict[int, int], list[tuple[int, int, float]]]:
    """Greedy merging by the largest mean gain until n_c clusters are left; a cluster is named by its least id.

    Dense in the number of queries of a batch (a few thousand). Missing pairs count as zero; ties take the
    smallest pair of names.
    """
    names = sorted(ids)
    at = {q: k for k, q in enumerate(names)}
    mean = np.zeros((len(ids), len(ids)))
    for a, b, g in pairs:
        mean[at[a], at[b]] = mean[at[b], at[a]] = g
    merges = [(names[i], names[j], g) for i, j, g in linkage(mean, n_c)]
    return owners(names, merges), merges


def linkage(mean: np.ndarray, n_c: int) -> list[tuple[int, int, float]]:
    """The merges (i < j, mean gain) of a symmetric matrix, which is used up; each row keeps its best later one."""
    n = len(mean)
    size, best, best_at, merges = np.ones(n), np.full(n, -np.inf), np.full(n, n), []

    def look(k: int) -> None:
        if k + 1 < n:
            best_at[k] = k + 1 + int(mean[k, k + 1 :].argmax())
            best[k] = mean[k, best_at[k]]

    for k in range(n):
        look(k)
    for _ in range(n - max(1, n_c)):
        i = int(best.argmax())
        j = int(best_at[i])
        merges.append((i, j, float(best[i])))
        mean[i] = mean[:, i] = (size[i] * mean[i] + size[j] * mean[j]) / (size[i] + size[j])
        size[i] += size[j]
        mean[j] = mean[:, j] = -np.inf  # merged away
        best[j] = -np.inf
        new = mean[:i, i]
        better = (new > best[:i]) | ((new == best[:i]) & (i < best_at[:i])) & (new > -np.inf)
        again = np.flatnonzero(((best_at[:j] == i) | (best_at[:j] == j)) & (best[:j] > -np.inf))
        best[:i][better], best_at[:i][better] = new[better], i
        for k in again:
            look(int(k))
        look(i)
    return merges


def owners(ids: list[int], merges: list[tuple[int, int, float]]) -> dict[int, int]:
    """The cluster of each query after merges in their order."""
    into = {b: a for a, b, _ in merges}
    owner: dict[int, int] = {}
    for q in sorted(ids):  # a cluster is named by its least id, so its owner is known
        owner[q] = owner[into[q]] if q in into else q
    return owner


#: Queries whose matrix one task holds (800 MB).
ONE_TASK = 10_000


def cluster_by_gain(gain: DataFrame, stats: DataFrame, n_c: int) -> tuple[DataFrame, DataFrame]:
    """(query_id, cluster_id) and (step, left_id, right_id, gain).

    The matrix of one batch's queries (n <= ONE_TASK, checked) is held by one task, which yields fewer merges
    than queries; the links of more queries stay distributed.
    """
    spark = gain.sparkSession
    ids = sorted(r[0] for r in stats.select("query_id").limit(ONE_TASK + 1).collect())
    if len(ids) > ONE_TASK:
        owner, merges = mutual_best_clusters(gain, stats, n_c)
        return _clusters(spark, owner, sorted(merges, key=lambda m: -m[2])[: max(0, len(owner) - n_c)])
    names = np.array(ids, np.int64)

    def pairs(batches: Iterator[pa.RecordBatch], mean: np.ndarray) -> None:
        for b in batches:
            i, j = (np.searchsorted(names, b.column(c).to_numpy()) for c in ("qi", "qj"))
            mean[i, j] = mean[j, i] = b.column("gain").to_numpy()

    merges = _merged(gain.select("qi", "qj", "gain"), names, n_c, pairs)
    return _clusters(spark, owners(ids, merges), merges)


def cluster_log(log: DataFrame, stats: DataFrame, n_c: int) -> tuple[DataFrame, DataFrame]:
    """cluster_by_gain of a log's gains; those of up to ONE_TASK queries reach the one task as blocks of its matrix, not as rows."""
    known = sorted((r[0], r[1]) for r in stats.select("query_id", "avg_us").limit(ONE_TASK + 1).collect())
    if len(known) > ONE_TASK:
        return cluster_by_gain(gain_from_sums(overlap_sums(log), stats), stats, n_c)
    names, times = np.array([q for q, _ in known], np.int64), np.array([t for _, t in known], float)

    def blocks(batches: Iterator[pa.RecordBatch], mean: np.ndarray) -> None:
        for b in batches:
            for left, right, gain in zip(*(c.to_pylist() for c in b.columns), strict=True):
                i, j = (np.searchsorted(names, np.frombuffer(x, np.int64)) for x in (left, right))
                g = np.frombuffer(gain).reshape(len(i), len(j))
                mean[np.ix_(i, j)], mean[np.ix_(j, i)] = g, g.T

    merges = _merged(gain_blocks(log, names, times), names, n_c, blocks)
    return _clusters(log.sparkSession, owners(names.tolist(), merges), merges)


def _merged(rows: DataFrame, names: np.ndarray, n_c: int, fill: Callable[[Iterator[pa.RecordBatch], np.ndarray], None]) -> list[tuple[int, int, float]]:
    """The merges of the matrix that ``fill`` makes of all rows in one task."""

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mean = np.zeros((len(names), len(names)))
        fill(batches, mean)
        merges = linkage(mean, n_c)
        if merges:
            i, j, g = (np.array(x) for x in zip(*merges, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(names[i]), pa.array(names[j]), pa.array(g)], ["a", "b", "g"])

    return [tuple(r) for r in rows.repartition(1).mapInArrow(whole, "a long, b long, g double").collect()]


def _clusters(spark: SparkSession, owner: dict[int, int], merges: list[tuple[int, int, float]]) -> tuple[DataFrame, DataFrame]:
    made = spark.createDataFrame(sorted(owner.items()), "query_id long, cluster_id long")
    return made, spark.createDataFrame([(k, *m) for k, m in enumerate(merges)], "step int, left_id long, right_id long, gain double")


def mutual_best_round(pairs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """One round of merging all pairs of clusters that are each other's best.

    pairs: a < b, total (sum of gains), n (pairs of members). Average linkage is reducible, so these merges
    are all merges of the greedy order too; returns (a, b, gain) merged, and the pairs of the new clusters.
    """
    both = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"), "total", "n"))
    order = F.struct((F.col("total") / F.col("n")).alias("g"), (-F.least("a", "b")).alias("x"), (-F.greatest("a", "b")).alias("y"))
    best = both.groupBy("a").agg(F.max_by("b", order).alias("best"))
    merged = pairs.join(best.select("a", F.col("best").alias("best_a")), "a").join(best.select(F.col("a").alias("b"), F.col("best").alias("best_b")), "b")
    merged = merged.where("best_a = b AND best_b = a").select("a", "b", (F.col("total") / F.col("n")).alias("gain"))
    name = merged.select(F.col("b").alias("old"), F.col("a").alias("new"))
    renamed = pairs.join(name.withColumnRenamed("old", "a"), "a", "left").withColumn("a2", F.coalesce("new", "a")).drop("new")
    renamed = renamed.join(name.withColumnRenamed("old", "b"), "b", "left").withColumn("b2", F.coalesce("new", "b"))
    again = renamed.where("a2 <> b2").groupBy(F.least("a2", "b2").alias("a"), F.greatest("a2", "b2").alias("b")).agg(F.sum("total").alias("total"), F.sum("n").alias("n"))
    return merged, again


def mutual_best_clusters(gain: DataFrame, stats: DataFrame, n_c: int) -> tuple[dict[int, int], list[tuple[int, int, float]]]:
    """The dendrogram by rounds of mutual best pairs, cut to n_c clusters at the highest merges.

    The links stay distributed; merges (fewer than queries) reach the driver.
    """
    q = stats.select("query_id")
    every = q.select(F.col("query_id").alias("a")).join(q.select(F.col("query_id").alias("b")), F.col("a") < F.col("b"))
    pairs = every.join(gain.select(F.col("qi").alias("a"), F.col("qj").alias("b"), F.col("gain").alias("total")), ["a", "b"], "left")
    pairs = pairs.select("a", "b", F.coalesce("total", F.lit(0.0)).alias("total"), F.lit(1).cast("long").alias("n"))
    merges: list[tuple[int, int, float]] = []
    while True:
        pairs = cut_lineage(pairs)
        merged, again = mutual_best_round(pairs)
        found = [(r.a, r.b, r.gain) for r in merged.collect()]
        if not found:
            break
        merges += found
        pairs = again
    ids = [r[0] for r in q.collect()]
    owner = {k: k for k in ids}

    def top(k: int) -> int:
        while owner[k] != k:
            k = owner[k]
        return k

    for a, b, _ in sorted(merges, key=lambda m: -m[2])[: max(0, len(ids) - n_c)]:
        x, y = sorted((top(a), top(b)))
        owner[y] = x
    return {k: top(k) for k in ids}, merges


def pool_clusters(vectors: DataFrame, assignment: DataFrame, id_col: str = "query_id", vector_col: str = "embedding") -> DataFrame:
    """cluster_id, pos, value: sums of the members' vectors, by position."""
    parts = vectors.join(assignment, id_col).select("cluster_id", F.posexplode(vector_col).alias("pos", "v"))
    return parts.groupBy("cluster_id", "pos").agg(F.sum(F.col("v").cast("double")).alias("value"))
