"""Shuffled shards by a two-pass external shuffle, in DataFrame functions only.

First pass: a seeded hash of the id scatters whole records uniformly into buckets of a
size that fits in memory. Second pass: each bucket is put into order by its hashes and then
permuted by a seeded Fisher-Yates walk. Buckets follow one another, so a record's place in
the whole shuffle is its bucket's start plus its place in the bucket; equal slices of that
order are the shards (law ``rows``: their row counts differ by one at most).

The walk draws its numbers from a hash of (seed, bucket, step): the same input gives the same
shards on any cluster and after any lost executor.

Defined results: a null text has no bytes; rows without an id and rows that repeat one are placed by
all their columns, so the result is the same but for rows that are alike in every column, which share
a bucket; an empty table gives an empty result; other columns are carried along, but for columns
named shard and slot, which the result's own replace.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Rows and bytes of text that a bucket holds on average, at most.
BUCKET_ROWS = 512
BUCKET_BYTES = 8 << 20


def record_size(text_col: str = "text") -> Column:
    """UTF-8 bytes of the text, and 16 of framing."""
    return (F.coalesce(F.octet_length(F.col(text_col)), F.lit(0)) + 16).cast("long")


def fisher_yates(n: Column, seed: int, salt: Column) -> Column:
    """A permutation of 1..n as an array, by an inside-out Fisher-Yates walk.

    Step i puts i at a hashed place j <= i and moves what stood there to the end.
    """

    def step(done: Column, i: Column) -> Column:
        j = F.pmod(F.xxhash64(F.lit(seed), salt, i), i).cast("int") + 1
        swapped = F.concat(F.transform(done, lambda x, k: F.when(k + 1 == j, i).otherwise(x)), F.array(F.try_element_at(done, j)))
        return F.when(j == i, F.concat(done, F.array(i))).otherwise(swapped)

    return F.aggregate(F.sequence(F.lit(1), n), F.expr("CAST(array() AS ARRAY<INT>)"), step)


def _bucket_starts(counts: DataFrame) -> DataFrame:
    """bucket, start: rows in all the buckets before it; two levels, so that no task sums them all."""
    block = F.floor(F.col("bucket") / 4096)
    inner = counts.withColumn("block", block).withColumn("start", F.sum("n").over(Window.partitionBy("block").orderBy("bucket")) - F.col("n"))
    totals = counts.groupBy(block.alias("block")).agg(F.sum("n").alias("m"))
    before = totals.select("block", (F.sum("m").over(Window.orderBy("block")) - F.col("m")).alias("base"))
    return inner.join(before, "block").select("bucket", (F.col("start") + F.col("base")).alias("start"))


def shuffle_into_shards(
    docs: DataFrame, shards: int = 40, seed: int = 20240607, id_col: str = "doc_id", text_col: str = "text",
    bucket_rows: int = BUCKET_ROWS, bucket_bytes: int = BUCKET_BYTES,
) -> DataFrame:
    """docs with ``shard`` (0..shards-1) and ``slot`` (0.. without gaps in each shard)."""
    spark = docs.sparkSession
    rows, size = docs.agg(F.count("*"), F.coalesce(F.sum(record_size(text_col)), F.lit(0))).first()
    buckets = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")), -(-rows // bucket_rows), -(-size // bucket_bytes))
    docs = docs.drop(*[c for c in docs.columns if c.lower() in ("shard", "slot")])
    # all that Spark can hash, so that rows of one id (or of none) spread, and ties are rows alike
    hashed = [F.col(f"`{f.name}`") for f in docs.schema if not re.search("map<|variant", f.dataType.simpleString())]
    place = F.xxhash64(F.lit(seed), F.col(id_col), *hashed)
    bucket = F.pmod(place, F.lit(buckets)).cast("long")
    starts = _bucket_starts(docs.groupBy(bucket.alias("bucket")).agg(F.count("*").alias("n")))

    record = F.struct(F.xxhash64(F.lit(seed + 1), F.col(id_col), *hashed).alias("h"), F.col(id_col).alias("id"), F.struct(*[F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(docs.columns)]).alias("row"))
    filled = docs.select(bucket.alias("bucket"), record.alias("rec")).repartitionByRange("bucket").groupBy("bucket").agg(F.collect_list("rec").alias("recs"))
    in_order = F.array_sort(
        "recs",
        lambda a, b: F.when(a.h < b.h, -1).when(a.h > b.h, 1).when(a.id < b.id, -1).when(a.id > b.id, 1).otherwise(0),
    )
    shuffled = filled.select("bucket", in_order.alias("recs")).select("bucket", "recs", fisher_yates(F.size("recs"), seed, F.col("bucket")).alias("perm"))
    walked = shuffled.select("bucket", F.posexplode(F.transform("perm", lambda p: F.element_at("recs", p))).alias("pos", "rec"))
    placed = walked.join(starts, "bucket").withColumn("place", F.col("start") + F.col("pos"))
    shard = F.expr(f"CAST(place * {shards} DIV {max(rows, 1)} AS INT)")
    first = F.expr(f"(CAST(shard AS BIGINT) * {rows} + {shards - 1}) DIV {shards}")
    cols = [F.col(f"rec.row.c{k}").alias(c) for k, c in enumerate(docs.columns)]
    return placed.withColumn("shard", shard).select(*cols, F.col("shard").alias("shard"), (F.col("place") - first).alias("slot"))


def write_shards(shuffled: DataFrame, path: str) -> DataFrame:
    """One folder for each shard, rows in the order of their slots in each file; read again.

    A task holds a slice of the shuffled order, so it writes to few folders.
    """
    kind = shuffled.schema["shard"]
    shuffled.sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
    schema = T.StructType([*[f for f in shuffled.schema if f.name != "shard"], kind])
    return shuffled.sparkSession.read.schema(schema).parquet(path)
