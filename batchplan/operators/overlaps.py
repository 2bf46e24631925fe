"""Sums of overlaps for each pair of queries, without a row for each pair of runs.

Queries are dealt to classes, and each two classes make a task: it has the runs of both, meets them round by round
in order of start, and adds up in a table of its queries. Each run is written once, in the files of its class, in
the folder that driver and executors share; tasks read the files of their two classes, so runs are shuffled once, however
many classes there are, pairs of runs never, and each pair of queries comes out of one task. A task holds one round of its
runs and the table (four numbers for each two of its queries, about ``PER_CLASS`` squared).
"""

from __future__ import annotations

import heapq
import itertools
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import pyarrow.parquet as pq
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from batchplan.sources.logs import new_folder

#: Queries of a class, about.
PER_CLASS = 700
#: Pairs of runs that are made at once, about, and that are added up at once.
STEP, HELD = 1 << 17, 1 << 21
#: Rows of a batch that goes back to Spark.
SENT = 1 << 16
#: Rows of a stripe of a matrix of gains (about 1.4 MB).
STRIPE = 256
OUT = ["qi", "qj", "m_c", "s_i", "s_j", "s_ov"]


class Table:
    """m_c, both shares and the overlap of each (later starter, earlier starter) of a task's queries."""

    def __init__(self, n: int) -> None:
        self.n, self.waiting, self.held = n, [], 0
        self.count, self.overlap = np.zeros(n * n, np.int64), np.zeros(n * n, np.int64)
        self.late, self.early = np.zeros(n * n), np.zeros(n * n)

    def add(self, cell: np.ndarray, ov: np.ndarray, late: np.ndarray, early: np.ndarray) -> None:
        self.waiting.append((cell, ov, ov / late, ov / early))
        self.held += len(cell)
        if self.held >= HELD:
            self.flush()

    def flush(self) -> None:
        if self.waiting:
            cell, ov, late, early = (np.concatenate(x) for x in zip(*self.waiting, strict=True))
            self.count += np.bincount(cell, minlength=self.n**2)
            self.late += np.bincount(cell, late, self.n**2)
            self.early += np.bincount(cell, early, self.n**2)
            np.add.at(self.overlap, cell, ov)
            self.waiting, self.held = [], 0

    def unseen(self, queries: np.ndarray, side: np.ndarray, own: bool) -> Iterator[pa.RecordBatch]:
        """The pairs that never met, each once, the smaller query first."""
        self.flush()
        count = self.count.reshape(self.n, self.n)
        i, j = np.nonzero(np.triu((count + count.T == 0) & (own | (side[:, None] != side[None])), 1))
        for k in range(0, len(i), SENT):
            yield pa.RecordBatch.from_arrays([pa.array(queries[i[k : k + SENT]]), pa.array(queries[j[k : k + SENT]])], names=OUT[:2])

    def rows(self, queries: np.ndarray) -> Iterator[pa.RecordBatch]:
        """The pairs seen, each once, the smaller query first; ``queries`` ascend."""
        self.flush()
        count, overlap, late, early = (x.reshape(self.n, self.n) for x in (self.count, self.overlap, self.late, self.early))
        i, j = np.nonzero(np.triu(count + count.T, 1))
        for k in range(0, len(i), SENT):
            x, y = i[k : k + SENT], j[k : k + SENT]
            sums = (count[x, y] + count[y, x], late[x, y] + early[y, x], early[x, y] + late[y, x], overlap[x, y] + overlap[y, x])
            yield pa.RecordBatch.from_arrays([pa.array(v) for v in (queries[x], queries[y], *sums)], names=OUT)

    def blocks(self, queries: np.ndarray, side: np.ndarray, own: bool, mean: np.ndarray) -> Iterator[pa.RecordBatch]:
        """The gains of the task's pairs as stripes of a matrix, zero where a pair never met."""
        self.flush()
        count, overlap, late, early = (x.reshape(self.n, self.n) for x in (self.count, self.overlap, self.late, self.early))
        w, met = np.sqrt(mean), count + count.T
        part = (late + early.T - (overlap + overlap.T) / mean[:, None]) * w[:, None]
        gain = np.divide(part + part.T, (w[:, None] + w[None]) * met, out=np.zeros(met.shape), where=met > 0)
        left, right = (np.arange(self.n),) * 2 if own else (np.flatnonzero(side == k) for k in (0, 1))
        for k in range(0, len(left) if len(right) else 0, STRIPE):
            some = left[k : k + STRIPE]
            yield pa.RecordBatch.from_pydict({"left": [queries[some].tobytes()], "right": [queries[right].tobytes()], "gain": [gain[np.ix_(some, right)].tobytes()]})


def meet(table: Table, q: np.ndarray, start: np.ndarray, finish: np.ndarray, side: np.ndarray, own: bool) -> None:
    """Adds the overlapping runs of one round, in order of start; of different sides only, unless the classes are one.

    Those that start after a run and before its finish are neighbours in the order of start.
    """
    length, every = finish - start, np.arange(len(q))
    for early, late in [(every, every)] if own else [(np.flatnonzero(side == k), np.flatnonzero(side != k)) for k in (0, 1)]:
        first = np.searchsorted(late, early, "right")
        ends = np.cumsum(np.searchsorted(start[late], finish[early]) - first)
        at = 0
        while at < len(early):
            done = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, done + STEP, "right")))
            many = np.diff(ends[at:to], prepend=done)
            y = np.repeat(early[at:to], many)
            x = late[np.arange(len(y)) + np.repeat(first[at:to] - (ends[at:to] - many - done), many)]
            if own:
                other = q[x] != q[y]
                x, y = x[other], y[other]
            table.add(q[x] * table.n + q[y], np.minimum(finish[x], finish[y]) - start[x], length[x], length[y])
            at = to


Rows = dict[str, np.ndarray]


def _files(uri: str, number: int) -> tuple[pafs.FileSystem, list[str]]:
    """The files of a class in order of their rounds."""
    fs, folder = pafs.FileSystem.from_uri(uri)
    found = fs.get_file_info(pafs.FileSelector(f"{folder}/class={number}", allow_not_found=True))
    return fs, sorted(f.path for f in found if f.base_name.startswith("part-"))


def _batches(uri: str, number: int, columns: list[str]) -> Iterator[Rows]:
    fs, paths = _files(uri, number)
    for path in paths:
        with fs.open_input_file(path) as source:
            for batch in pq.ParquetFile(source).iter_batches(columns=columns, use_threads=False):
                yield {c: batch.column(c).to_numpy() for c in columns}


def _queries(uri: str, number: int) -> np.ndarray:
    """The queries of a class, ascending."""
    found = np.zeros(0, np.int64)
    for rows in _batches(uri, number, ["query_id"]):
        found = np.union1d(found, rows["query_id"])
    return found


def _rounds(uri: str, number: int, side: int) -> Iterator[tuple[int, Rows]]:
    """The rounds of a class's runs, in their order, each by start."""
    at, held = None, []

    def whole() -> tuple[int, Rows]:
        rows = {c: np.concatenate([h[c] for h in held]) for c in RUN[1:]}
        return at, rows | {"side": np.full(len(rows["query_id"]), side)}

    for rows in _batches(uri, number, RUN):
        day = rows["round_no"]
        edges = [0, *(np.flatnonzero(day[1:] != day[:-1]) + 1).tolist(), len(day)]
        for lo, hi in itertools.pairwise(edges):
            if hi > lo:
                if held and day[lo] != at:
                    yield whole()
                    held = []
                at = int(day[lo])
                held.append({c: x[lo:hi] for c, x in rows.items()})
    if held:
        yield whole()


def _task(uri: str, a: int, b: int) -> tuple[Table, np.ndarray, np.ndarray]:
    """The table of two classes (or of one), its queries and their sides."""
    numbers = [a] if a == b else [a, b]
    each = [_queries(uri, k) for k in numbers]
    queries, sides = np.concatenate(each), np.repeat(np.arange(len(each)), [len(x) for x in each])
    order = np.argsort(queries)
    queries, sides, table = queries[order], sides[order], Table(len(queries))
    if all(map(len, each)):
        merged = heapq.merge(*[_rounds(uri, k, side) for side, k in enumerate(numbers)], key=lambda r: r[0])
        for _, same in itertools.groupby(merged, key=lambda r: r[0]):
            parts = [rows for _, rows in same]
            if len(parts) == len(numbers):  # runs of one side alone make no pair of two
                x = {c: np.concatenate([p[c] for p in parts]) for c in parts[0]}
                by = np.lexsort((x["query_id"], x["length"], x["start_us"]))
                q, start, length, side = (x[c][by] for c in ("query_id", "start_us", "length", "side"))
                meet(table, np.searchsorted(queries, q), start, start + length, side, a == b)
    return table, queries, sides


RUN = ["round_no", "query_id", "start_us", "length"]


def overlap_sums(log: DataFrame, per_class: int = PER_CLASS) -> DataFrame:
    """qi < qj, m_c, s_i, s_j, s_ov: what ``gain_sums`` makes of a log's pairs of runs. round_id is a date or an integer."""
    return _met(log, per_class, lambda table, queries, sides, own: table.rows(queries), "qi long, qj long, m_c long, s_i double, s_j double, s_ov long")


def gain_blocks(log: DataFrame, queries: np.ndarray, mean: np.ndarray, per_class: int = PER_CLASS) -> DataFrame:
    """left, right (queries) and gain (their matrix), as bytes: the gains of a log whose queries (ascending) have these mean times."""
    return _met(log, per_class, lambda table, some, sides, own: table.blocks(some, sides, own, mean[np.searchsorted(queries, some)]), "left binary, right binary, gain binary")


def never_met(log: DataFrame, per_class: int = PER_CLASS) -> DataFrame:
    """qi < qj: the pairs of a log's queries of which no two runs overlap."""
    return _met(log, per_class, lambda table, queries, sides, own: table.unseen(queries, sides, own), "qi long, qj long")


def _met(log: DataFrame, per_class: int, out: Callable[[Table, np.ndarray, np.ndarray, bool], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """What ``out`` makes of each task's table; the runs are written when this is called."""
    spark = log.sparkSession
    date = dict(log.dtypes)["round_id"] == "date"
    number = (F.unix_date("round_id") if date else F.col("round_id")).cast("long").alias("round_no")
    runs = log.where("round_id IS NOT NULL AND query_id IS NOT NULL AND start_us < finish_us").select(number, F.col("query_id").cast("long").alias("query_id"), "start_us", (F.col("finish_us") - F.col("start_us")).alias("length"))
    n = runs.agg(F.approx_count_distinct("query_id")).first()[0]
    classes = max(1, -(-n // per_class), min(n, int((6 * spark.sparkContext.defaultParallelism) ** 0.5)))
    uri = _dealt(runs, classes)
    tasks = classes * (classes + 1) // 2

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for task in batch.column(0).to_pylist():
                b = int(((8 * task + 1) ** 0.5 - 1) / 2)
                a = task - b * (b + 1) // 2
                yield from out(*_task(uri, a, b), a == b)

    return spark.range(0, tasks, 1, min(tasks, 4096)).mapInArrow(run, schema)


def _dealt(runs: DataFrame, classes: int) -> str:
    """A new folder with each run once, in the files of its class: those of a class hold rounds one after another."""
    spark = runs.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    placed = runs.withColumn("class", F.pmod(F.xxhash64("query_id"), F.lit(classes)).cast("int")).repartitionByRange(parts, "class", "round_no")
    uri = new_folder(spark, "runs")
    placed.sortWithinPartitions("class", *[c for c in RUN if c != "query_id"], "query_id").write.partitionBy("class").option("compression", "zstd").parquet(uri)
    return uri
