"""Near-duplicate vectors by product quantisation: inverted lists, table distances, exact rerank.

Equal vectors of a label are one class. Coarse centroids and the codes of residuals (one code for
each subspace) are fitted on a bounded sample of classes; every class is indexed. On the unit
sphere a cosine of at least c is a distance of at most r = sqrt(2 - 2c), which makes both
approximate steps safe:

* Probes. A class within r of x whose nearest centroid is b lies on b's side of the plane between
  b and x's own centroid a, so x need not look into b's list when x is more than r from that
  plane: (|x-b|^2 - |x-a|^2) / (2 |a-b|) > r. All other lists are probed.
* Table distances. The distance from x to y's code is at most r plus the length of what the code
  loses of y, which is kept with y; farther codes are dropped, the others reranked exactly.

So no link is lost, whatever the quality of the centroids; they only decide the cost. Lists are
cut into tiles of about ``TILE`` classes by a hash; a task holds two tiles and returns for each of
its classes the number of vectors linked, and a spanning forest of the links, never all pairs.

Defined results: vectors that are null, empty, zero or hold null or non-finite components, and
vectors whose label is null, link with nothing; vectors of unlike lengths link with nothing; rows
that repeat an id are vectors like others; ties have no effect; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from batchplan.llm.components import connected_components
from batchplan.llm.shared import bound_arrow, release_since, tidied, written, written_mark

#: Classes that the centroids are fitted on at most; classes in a tile, on average.
SAMPLE, TILE = 8192, 384
SUBSPACES, CODES = 8, 64
#: Added to r for rounding in the approximate steps; the exact step decides.
SLACK = 1e-5


def kmeans(x: np.ndarray, k: int, rounds: int, seed: int) -> np.ndarray:
    """k centroids (fewer if there are fewer distinct rows) by Lloyd's rounds."""
    rng = np.random.default_rng(seed)
    centres = np.unique(x[rng.permutation(len(x))[:k]], axis=0)
    for _ in range(rounds):
        near = nearest(x, centres)
        sums = np.zeros_like(centres)
        np.add.at(sums, near, x)
        n = np.bincount(near, minlength=len(centres))
        centres = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], centres)
    return centres


def distances2(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.maximum(0, (x * x).sum(1)[:, None] - 2 * x @ c.T + (c * c).sum(1)[None])


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.concatenate([distances2(x[a : a + 2048], c).argmin(1) for a in range(0, len(x), 2048)])


class ProductQuantiser:
    """Coarse centroids and the residual codebooks of each subspace."""

    def __init__(self, sample: np.ndarray, lists: int, seed: int = 5) -> None:
        dims = sample.shape[1]
        self.spans = [(int(a[0]), int(a[-1]) + 1) for a in np.array_split(np.arange(dims), min(SUBSPACES, dims))]
        self.centres = kmeans(sample, lists, 8, seed)
        rest = sample - self.centres[nearest(sample, self.centres)]
        self.books = [kmeans(rest[:, a:b], CODES, 6, seed + 1) for a, b in self.spans]
        self.apart = np.sqrt(distances2(self.centres, self.centres))

    def encode(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """List, codes, and the length of what the codes lose, of each row."""
        own = nearest(x, self.centres)
        rest = x - self.centres[own]
        codes = np.stack([nearest(rest[:, a:b], book) for (a, b), book in zip(self.spans, self.books, strict=True)], 1)
        kept = np.concatenate([book[codes[:, m]] for m, book in enumerate(self.books)], 1)
        return own, codes.astype(np.uint8), np.sqrt(((rest - kept) ** 2).sum(1))

    def probes(self, x: np.ndarray, own: np.ndarray, r: float) -> np.ndarray:
        """Whether each row must look into each list besides its own."""
        d = distances2(x, self.centres)
        gap = (d - d[np.arange(len(x)), own][:, None]) / np.maximum(2 * self.apart[own], 1e-12)
        return gap <= r

    def table_distances(self, x: np.ndarray, of_list: int, codes: np.ndarray) -> np.ndarray:
        """Distance of each row of x to each code of one list, by a table for each row."""
        rest, total = x - self.centres[of_list], np.zeros((len(x), len(codes)))
        for m, ((a, b), book) in enumerate(zip(self.spans, self.books, strict=True)):
            total += distances2(rest[:, a:b], book)[:, codes[:, m]]
        return np.sqrt(total)


def _scaled(x: np.ndarray) -> np.ndarray:
    """Rows times powers of two, which is exact, so that their squares are finite and not all zero."""
    return np.ldexp(x, -np.frexp(np.abs(x).max(1))[1][:, None])


def _unit(x: np.ndarray) -> np.ndarray:
    x = _scaled(x)
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def _packed(x: np.ndarray) -> list[bytes]:
    """Rows as bytes: single precision where it holds them exactly."""
    kind = 4 if (np.abs(x) < 1e38).all() and (x.astype("<f4") == x).all() else 8
    return [bytes([kind]) + row.tobytes() for row in x.astype(f"<f{kind}")]


def _unpacked(rows: list[bytes]) -> np.ndarray:
    return np.stack([np.frombuffer(row, f"<f{row[0]}", offset=1) for row in rows]).astype(np.float64)


def _links(left: dict, right: dict | None, pq: ProductQuantiser, least: float, r: float) -> tuple[dict, list]:
    """Vectors linked to each class, and a spanning forest, of one tile or of two."""
    own, right = right is None, left if right is None else right
    counts: dict[int, int] = {}
    root, forest = {c: c for c in [*left["cls"], *right["cls"]]}, []

    def top(c: int) -> int:
        while root[c] != c:
            root[c] = c = root[root[c]]
        return c

    codes, lost = np.frombuffer(b"".join(right["codes"]), np.uint8).reshape(len(right["cls"]), -1), np.array(right["lost"])
    near = pq.table_distances(left["x"], right["list"][0], codes) <= r + SLACK + lost[None]
    i, j = np.nonzero(np.triu(near | near.T, 1) if own else near)
    cosine = np.concatenate([np.zeros(0)] + [np.einsum("ij,ij->i", left["raw"][p], right["raw"][q]) / (left["norm"][p] * right["norm"][q]) for k in range(0, len(i), 65536) for p, q in [(i[k : k + 65536], j[k : k + 65536])]])
    for a, b in zip(i[cosine >= least].tolist(), j[cosine >= least].tolist(), strict=True):
        c, d = left["cls"][a], right["cls"][b]
        counts[c] = counts.get(c, 0) + right["mult"][b]
        counts[d] = counts.get(d, 0) + left["mult"][a]
        if top(c) != top(d):
            root[top(c)] = top(d)
            forest.append((c, d))
    return counts, forest


def near_vectors(
    vectors: DataFrame, least: float = 0.98, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label", lists: int | None = None
) -> DataFrame:
    """One row for each vector: id, n_links, component_id, kept."""
    spark, mark = vectors.sparkSession, written_mark()
    bound_arrow(spark)
    r = float(np.sqrt(2 - 2 * least))
    vec = F.col("vec")
    finite = F.forall(vec, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    usable = F.col("label").isNotNull() & vec.isNotNull() & finite & F.exists(vec, lambda v: v != 0)
    every = vectors.select(F.col(id_col).alias("id"), F.col(vector_col).cast("array<double>").alias("vec"), F.col(label_col).alias("label"))
    slim = every.select("id", F.when(F.coalesce(usable, F.lit(False)), F.xxhash64("label", "vec")).alias("cls"))
    classes = every.where(F.coalesce(usable, F.lit(False))).groupBy(F.xxhash64("label", "vec").alias("cls")).agg(F.count("*").alias("mult"), F.xxhash64(F.first("label"), F.size(F.first("vec"))).alias("part"), F.first("vec").alias("vec"))
    classes = written(classes, "pq-classes")

    n = classes.count()
    widths = [row[0] for row in classes.groupBy(F.size("vec").alias("w")).agg(F.count("*").alias("n")).orderBy(F.desc("n")).limit(8).collect()]
    models: dict[int, ProductQuantiser] = {}
    for width in widths:  # vectors of one table have one length; others are compared within theirs
        drawn = classes.where(F.size("vec") == width).orderBy(F.xxhash64(F.lit(3), "cls")).limit(SAMPLE).select("vec")
        sample = np.array([row[0] for row in drawn.collect()])
        sample = _unit(sample)
        models[width] = ProductQuantiser(sample, lists or int(np.clip(np.sqrt(n / 4), 1, 1024)))
    sent = spark.sparkContext.broadcast(models)

    def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            by_width: dict[int, list[int]] = {}
            for k, v in enumerate(batch.column(3)):
                by_width.setdefault(len(v), []).append(k)
            for width, rows in by_width.items():
                pq = sent.value.get(width)
                part = batch.take(pa.array(rows))
                if pq is None:  # a rare length: one list for all of it
                    pq = ProductQuantiser(np.ones((1, width)) / np.sqrt(width), 1)
                raw = part.column(3).flatten().to_numpy(zero_copy_only=False).reshape(-1, width)
                x = _unit(raw)
                own, codes, lost = pq.encode(x)
                look = pq.probes(x, own, r + SLACK)
                # a pair is found from the list of smaller number
                look = [np.flatnonzero(row[a + 1 :]) + a + 1 for row, a in zip(look, own, strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [*part.columns[:3], pa.array(_packed(raw), pa.binary()), pa.array(own, pa.int32()), pa.array([c.tobytes() for c in codes]), pa.array(lost), pa.array([p.astype(np.int32) for p in look], pa.list_(pa.int32()))],
                    ["cls", "mult", "part", "vec", "list", "codes", "lost", "probes"],
                )

    indexed = written(classes.mapInArrow(tidied(index), "cls long, mult long, part long, vec binary, list int, codes binary, lost double, probes array<int>"), "pq-index")
    tile = lambda seed, tiles: F.pmod(F.xxhash64(F.lit(seed), "cls"), tiles).cast("int")
    entry = [F.col(c) for c in ("cls", "mult", "vec", "list", "codes", "lost")]
    residents = indexed.groupBy("part", "list").agg(F.ceil(F.count("*") / TILE).cast("int").alias("tiles"))
    visits = indexed.select("part", *entry, F.explode("probes").alias("to"))
    visitors = visits.groupBy("part", F.col("to").alias("list")).agg(F.ceil(F.count("*") / TILE).cast("int").alias("visitor_tiles"))
    lists_ = written(residents.join(visitors, ["part", "list"], "left").na.fill(0), "pq-lists")
    home = indexed.join(lists_, ["part", "list"]).withColumn("t", tile(1, F.col("tiles")))
    among = home.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1))).select(
        F.xxhash64("part", "list", F.least("t", "o"), F.greatest("t", "o")).alias("task"), (F.col("t") <= F.col("o")).alias("left"), (F.col("t") == F.col("o")).alias("own"), *entry
    )
    receive = home.where("visitor_tiles > 0").withColumn("v", F.explode(F.sequence(F.lit(0), F.col("visitor_tiles") - 1))).select(
        F.xxhash64("part", "list", "t", "v", F.lit(1)).alias("task"), F.lit(False).alias("left"), F.lit(False).alias("own"), *entry
    )
    arrive = (
        visits.join(lists_.withColumnRenamed("list", "to"), ["part", "to"])
        .withColumn("v", tile(2, F.col("visitor_tiles")))
        .withColumn("t", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
        .select(F.xxhash64("part", "to", "t", "v", F.lit(1)).alias("task"), F.lit(True).alias("left"), F.lit(False).alias("own"), *entry)
    )
    work = among.unionByName(receive).unionByName(arrive)

    def side(rows: list[tuple]) -> dict:
        found = dict(zip(("cls", "mult", "vec", "list", "codes", "lost"), zip(*rows, strict=True), strict=True))
        found["raw"] = _scaled(_unpacked(found.pop("vec")))
        found["norm"] = np.sqrt((found["raw"] ** 2).sum(1))
        found["x"] = found["raw"] / found["norm"][:, None]
        return found

    def flush(rows: list[tuple]) -> Iterator[pa.RecordBatch]:
        left, right = [x[2:] for x in rows if x[0]], [x[2:] for x in rows if not x[0]]
        if not left or not (right or rows[0][1]):
            return
        left = side(left)
        width = left["raw"].shape[1]
        pq = sent.value.get(width) or ProductQuantiser(np.ones((1, width)) / np.sqrt(width), 1)
        counts, forest = _links(left, None if rows[0][1] else side(right), pq, least, r)
        if counts:
            a = [*counts, *(x for x, _ in forest)]
            b = [None] * len(counts) + [y for _, y in forest]
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array([*counts.values(), *[0] * len(forest)], pa.int64())], ["a", "b", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, rows = None, []
        for batch in batches:
            for t, *row in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                if t != task and rows:
                    yield from flush(rows)
                    rows = []
                task = t
                rows.append(tuple(row))
        if rows:
            yield from flush(rows)

    found = written(work.repartition("task").sortWithinPartitions("task").mapInArrow(tidied(run), "a long, b long, n long"), "pq-links")
    degree = found.where("b IS NULL").groupBy(F.col("a").alias("cls")).agg(F.sum("n").alias("n"))
    joined = connected_components(found.where("b IS NOT NULL").select("a", "b"))
    named = classes.select("cls", "mult").join(degree, "cls", "left").join(joined, F.col("cls") == F.col("node"), "left")
    named = named.select(F.col("cls").alias("c"), (F.col("mult") - 1 + F.coalesce("n", F.lit(0))).alias("n_links"), F.coalesce("component", "cls").alias("root"))
    rooted = written(slim.join(named, F.col("cls") == F.col("c"), "left").select("id", "root", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links")), "pq-roots")
    release_since(spark, mark, keep=[rooted])
    smallest = rooted.where("root IS NOT NULL").groupBy(F.col("root").alias("r")).agg(F.min("id").alias("least_id"))
    whole = rooted.join(smallest, F.col("root") == F.col("r"), "left").withColumn("component_id", F.coalesce("least_id", "id"))
    return whole.select(F.col("id").alias(id_col), "n_links", "component_id", F.coalesce(F.col("id") == F.col("component_id"), F.lit(False)).alias("kept"))
