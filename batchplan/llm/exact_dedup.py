"""Exact deduplication by content sort.

Rows are ordered by (first bytes of the text, its 64-bit hash, id). Sampled splitters
cut that order into ranges, so that a text with a third of all rows is spread over many
ranges by its ids; Spark's external sort then brings equal texts next to each other and
every text is compared in full with its neighbour. A group that crosses a border of
ranges is put together again from one summary row for each of its runs.

Defined results: a null text counts as empty; a null id sorts before all others; rows
that repeat an id are rows like any other, and exactly one row of a group is kept; an
empty table gives an empty result; other columns, whatever their names, are carried along
untouched by ``drop_exact_duplicates``.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from batchplan.llm.shared import bound_arrow, tidied, written

#: Bytes of the text that lead the sort order and the splitters; ids and a hash follow them.
HEAD = 24


def _digests(texts: pa.Array) -> list[str]:
    """SHA-256 of each text as lower-case hex, without decoding the texts."""
    raw = texts.cast(pa.large_binary())
    ends, data = raw.buffers()[1], raw.buffers()[2]
    ends = memoryview(ends).cast("q")[raw.offset : raw.offset + len(raw) + 1]
    data = memoryview(data) if data is not None else memoryview(b"")
    return [hashlib.sha256(data[a:b]).hexdigest() for a, b in zip(ends[:-1], ends[1:], strict=True)]


class _Runs:
    """Runs of equal texts in one sorted range, kept only until their length is known."""

    def __init__(self, schema: pa.Schema) -> None:
        self.part = TaskContext.get().partitionId() << 40
        self.schema, self.made = schema, 0
        self.key = self.first_key = self.text = None
        self.open: list[dict] = []  # runs under the present (head, hash)

    def flush(self, last: bool) -> Iterator[pa.RecordBatch]:
        edge = last or self.key == self.first_key
        for run in self.open:
            rows = pa.concat_arrays(run["rows"])
            n = len(rows)
            ids = pc.struct_field(rows, "__id")
            yield pa.RecordBatch.from_arrays(
                [
                    rows,
                    pa.array([run["sha"]] * n),
                    pa.array([run["run"]] * n, pa.int64()),
                    pa.array([n] * n, pa.int64()),
                    pa.array([ids[n - 1].as_py()] * n, ids.type),
                    pa.array([False] * (n - 1) + [True]),
                    pa.array([edge] * n),
                ],
                schema=self.schema,
            )
        self.open = []

    def add(self, batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        texts, keys, rows = batch.column(0), batch.column(1).to_pylist(), batch.column(2)
        # a new run begins where a whole text differs from its neighbour
        starts = [0, *(pc.indices_nonzero(pc.not_equal(texts[1:], texts[:-1])).to_numpy() + 1).tolist()]
        shas = _digests(texts.take(pa.array(starts)))
        for k, (a, b) in enumerate(zip(starts, [*starts[1:], len(texts)], strict=True)):
            piece = rows.slice(a, b - a)
            if self.key != keys[a]:
                if self.key is not None:
                    yield from self.flush(False)
                else:
                    self.first_key = keys[a]
                self.key, self.text = keys[a], None
            if self.text is not None and texts[a] == self.text:
                self.open[-1]["rows"].append(piece)
                continue
            self.text = texts[a]
            self.made += 1
            self.open.append({"run": self.part + self.made, "sha": shas[k], "rows": [piece]})


def _mark(schema: pa.Schema) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        runs = _Runs(schema)
        held: list[pa.RecordBatch] = []
        for batch in batches:
            if batch.num_rows:
                for out in runs.add(batch):
                    held.append(out)
                    if sum(x.num_rows for x in held) >= 2000:
                        yield from pa.Table.from_batches(held).combine_chunks().to_batches()
                        held = []
        held += runs.flush(True) if runs.key is not None else []
        if held:
            yield from pa.Table.from_batches(held).combine_chunks().to_batches()

    return run


def _sorted_runs(docs: DataFrame, id_col: str, text: Column, keep: str, row: list[Column]) -> DataFrame:
    spark = docs.sparkSession
    bound_arrow(spark)
    order = F.col("__row.__id").asc_nulls_first() if keep == "largest" else F.col("__row.__id").desc_nulls_first()
    keyed = docs.select(
        F.coalesce(text, F.lit("")).alias("__text"), F.struct(F.col(id_col).alias("__id"), *row).alias("__row")
    ).select(
        "__text",
        F.struct(F.substring(F.encode("__text", "UTF-8"), 1, HEAD).alias("head"), F.xxhash64("__text").alias("hash")).alias("__key"),
        "__row",
    )
    ranged = keyed.repartitionByRange(F.col("__key"), order).sortWithinPartitions("__key", "__text", order)
    out = T.StructType(
        [
            ranged.schema["__row"],
            T.StructField("sha", T.StringType()),
            T.StructField("run", T.LongType()),
            T.StructField("run_size", T.LongType()),
            T.StructField("run_last", docs.schema[id_col].dataType),
            T.StructField("is_last", T.BooleanType()),
            T.StructField("edge", T.BooleanType()),
        ]
    )
    from pyspark.sql.pandas.types import to_arrow_schema

    return written(ranged.mapInArrow(tidied(_mark(to_arrow_schema(out))), out), "exact-dedup")


def _whole_groups(runs: DataFrame) -> DataFrame:
    """Runs of one text in several ranges joined to one group: keep_id, group_size, kept.

    Only runs at a border of ranges are gathered: two for each range at most (and those whose
    64-bit hash and first bytes agree with such a run), so the broadcast side is bounded by the
    number of partitions, not by the rows.
    """
    crossing = (
        runs.where("edge AND is_last")
        .groupBy("sha")
        .agg(F.sum("run_size").alias("all_size"), F.max("run").alias("top_run"), F.max_by("run_last", "run").alias("top_id"))
    )
    return runs.join(F.broadcast(crossing), "sha", "left").select(
        "__row",
        F.coalesce("top_id", "run_last").alias("keep_id"),
        F.coalesce("all_size", "run_size").alias("group_size"),
        (F.col("is_last") & (F.col("top_run").isNull() | (F.col("top_run") == F.col("run")))).alias("kept"),
        F.col("sha").alias("text_sha256"),
    )


def mark_exact_duplicates(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest", normalise: Callable[[Column], Column] | None = None
) -> DataFrame:
    """One row for each row of docs: its id, keep_id, group_size, kept, text_sha256.

    keep: "smallest" or "largest" identifier of a group stays. normalise: what is done to the
    text before it is compared and digested.
    """
    text = normalise(F.col(text_col)) if normalise else F.col(text_col)
    whole = _whole_groups(_sorted_runs(docs, id_col, text, keep, []))
    return whole.select(F.col("__row.__id").alias(id_col), "keep_id", "group_size", "kept", "text_sha256")


def drop_exact_duplicates(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest", normalise: Callable[[Column], Column] | None = None
) -> DataFrame:
    """docs with one row of each group of equal texts, all columns as they were."""
    text = normalise(F.col(text_col)) if normalise else F.col(text_col)
    row = [F.struct(*[F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(docs.columns)]).alias("__cols")]
    whole = _whole_groups(_sorted_runs(docs, id_col, text, keep, row))
    return whole.where("kept").select(*[F.col(f"__row.__cols.c{k}").alias(c) for k, c in enumerate(docs.columns)])
