"""Jaccard self-join of documents by their word n-grams, with R-trees over count vectors.

A document's n-grams are hashed to 64 bits; equal sets form a class, and classes are compared.
Hashing the n-grams into groups gives each class a point of group counts; there are about half as
many groups as n-grams (64 to 2048, always a power of two, so finer points fold to coarser ones).
Two sets share at most the sum of the smaller of their counts in each group, so an R-tree over the
points prunes a node when the sum of minima with the node's upper corner is below the overlap that
the threshold asks for; surviving pairs are verified on the sets.

One R-tree over everything cannot prune at scale: the upper corner of a large node holds more than
any point. So an exact pigeonhole step finds which classes can meet at all. Within a band of sizes two
linked sets differ in at most d n-grams; cut the hash range into more than d pieces, and of the f
pieces that a set fills at least f - d are equal in both. Classes with an equal piece share a block.
As linked sets share f - d of them, each class leaves the f - d - 1 largest of its blocks; passages
that many documents share make large blocks, so these go first, and no link is lost. A set that fills
d pieces or fewer gets its least n-grams as further keys, enough to meet any linked set of that kind.

Links are then found without pairing whole groups. In a star round every class is compared with one
leader of its blocks; what is linked is merged, and the next round only looks at blocks that
still hold two components, with other leaders. After ``STARS`` rounds the blocks that are left go
through R-trees, in tiles of about ``TILE`` classes, which return for each two components the ``FEW`` pairs
that the bound gives most room; what is linked is merged again, and further rounds ask for ``MORE`` times
as many until no tree has left a pair out. Of the blocks that two classes share, the one of the least key
gives the pair, as far as the ``SHARED`` least keys of both tell. Each pair is compared exactly, a leader's
text once for many.

The result is exact up to collisions of 64-bit hashes.

Defined results: null and empty texts, and texts without words, have no n-grams, are a component
of their own, and link with nothing; a text with fewer words than n is one n-gram of all of them;
a row whose id is null links with nothing and its component is null; rows that repeat an id are
each reported, by their own texts; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from typing import Protocol

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from batchplan.llm.components import connected_components
from batchplan.llm.shared import bound_arrow, forget_shuffles, release_since, text_or_empty, tidied, worker_cache, written, written_mark

#: Classes in a tile of an R-tree, on average; rounds of stars before the trees.
TILE, STARS = 512, 2
#: Pairs that a tree gives for two components in its first round; times as many in each round after it.
FEW, MORE = 4, 64
#: Least keys of a class that its rows in the trees know; with more a pair may come twice, but is never lost.
SHARED, SHARED_AT_ONCE = 64, 4096
#: Groups of n-grams in a point: at least, and at most.
GROUPS = (64, 2048)
#: Classes of a block that are counted; larger blocks count as equal.
COUNTED = 1 << 16
#: Pairs of one leader that one task verifies, on average.
MEMBERS = 512
#: A bounded set of positions picks out the documents that verification needs.
POSITIONS = 1 << 19
#: Word hashes that a worker remembers; bytes of one text that are split at a time.
WORDS, STRETCH = 400_000, 4 << 20

_A, _B, _C = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def mix64(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _B
    x = (x ^ (x >> np.uint64(27))) * _C
    return x ^ (x >> np.uint64(31))


class _WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


def word_hashes(text: str) -> np.ndarray:
    """A hash for each word of the text, lower-cased in A-Z only."""
    raw, parts, at = text.encode().lower(), [], 0
    known = worker_cache(("word_hashes",), _WordHashes)
    if len(known) > WORDS:
        known.clear()
    while at < len(raw):
        end = len(raw)
        if end - at > STRETCH and (m := re.compile(rb"[\x20\x09-\x0D]").search(raw, at + STRETCH)):
            end = m.start()
        words = raw[at:end].split()
        parts.append(np.fromiter(map(known.__getitem__, words), np.uint64, len(words)))
        at = end
    return np.concatenate(parts) if parts else np.zeros(0, np.uint64)


def shingles(text: str, n: int) -> np.ndarray:
    """The sorted distinct hashes of the text's word n-grams; one of all words if there are fewer."""
    w = word_hashes(text)
    if not len(w):
        return w
    k = min(n, len(w))
    h = np.full(len(w) - k + 1, k, np.uint64)
    for j in range(k):  # word hashes are mixed already; the product tells their places apart
        h *= _A
        h += w[j : len(w) - k + 1 + j]
    return np.unique(mix64(h))


def class_of(s: np.ndarray) -> int | None:
    """A 64-bit name of a set; None for the empty one."""
    if not len(s):
        return None
    with np.errstate(over="ignore"):
        name = mix64(np.array([mix64(s + _C).sum(dtype=np.uint64) + np.uint64(len(s)) * _A]))
    return int(name.view(np.int64)[0])


class Bound(Protocol):
    def need(self, both):
        """The least sum of minima of two points of a link whose sums add up to ``both`` (a number or an array)."""


    def exactly(self, x, y):
        """The same for points whose sums are x and y."""


class Threshold:
    """Jaccard similarity of at least num / den, in integers."""

    def __init__(self, num: int, den: int) -> None:
        self.num, self.den = num, den
        self.bounds = [1]  # first size of each band; a linked set is in the same band or the next

    def band(self, size: int) -> int:
        while self.bounds[-1] <= size:
            self.bounds.append(self.bounds[-1] * self.den // self.num + 1)
        return int(np.searchsorted(self.bounds, size, "right")) - 1

    def differ(self, band: int) -> int:
        """The most n-grams in which two linked sets of this band (or it and the one before) differ."""
        while len(self.bounds) < band + 2:
            self.bounds.append(self.bounds[-1] * self.den // self.num + 1)
        both = 2 * (self.bounds[band + 1] - 1)
        return max(s - 2 * self.need(s) for s in (both - 1, both))  # it grows with s among even and among odd s

    def need(self, both):
        """The least overlap of linked sets whose sizes add up to ``both``."""
        return -(-self.num * both // (self.num + self.den))

    def exactly(self, x, y):
        return self.need(x + y)


_cuts: dict[int, np.ndarray] = {}


def _filled(s: np.ndarray, differ: int) -> tuple[np.ndarray, np.ndarray]:
    """The pieces that a set fills, of enough for two linked sets to share some, and where all pieces end."""
    pieces = differ + 3 + differ // 4
    if pieces not in _cuts:
        _cuts[pieces] = np.array([(i << 64) // pieces for i in range(1, pieces)], np.uint64)
    ends = np.concatenate([[0], np.searchsorted(s, _cuts[pieces]), [len(s)]])
    return np.flatnonzero(ends[1:] > ends[:-1]), ends


def spares(s: np.ndarray, at: Threshold) -> tuple[int, int]:
    """How many of a set's keys may go without a loss, under its own band and under the next."""
    if not len(s):
        return 0, 0
    own = at.band(len(s))
    return tuple(max(0, len(_filled(s, d)[0]) - d - 1) if (d := at.differ(b)) else 0 for b in (own, own + 1))


def piece_keys(s: np.ndarray, at: Threshold) -> np.ndarray:
    """64-bit keys of a set, under its own band and the next; the last bit is the band's."""
    own, found = at.band(len(s)), []
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix64(s ^ _B))])
    for band in (own, own + 1):
        differ = at.differ(band)
        if differ == 0:  # only equal sets are linked, and they are one class
            continue
        filled, ends = _filled(s, differ)
        tag = np.uint64(band << 32) + filled.astype(np.uint64)
        keys = [mix64((total[ends[filled + 1]] - total[ends[filled]]) ^ mix64(tag))]
        if len(filled) <= differ:
            # two such sets may share no piece, but they share one of their first n-grams
            first = s[: len(s) - -(-at.num * len(s) // at.den) + 1]
            keys.append(mix64(mix64(first ^ _A) + np.uint64((band << 32) + (1 << 31))))
        found.append(np.concatenate(keys) >> np.uint64(1) << np.uint64(1) | np.uint64(band & 1))
    return np.concatenate(found) if found else np.zeros(0, np.uint64)


def count_vector(s: np.ndarray) -> np.ndarray:
    """The number of n-grams in each group of hashes; groups are a power of two, by the size of the set."""
    bits = min(max(GROUPS[0], 1 << (len(s) // 2).bit_length()), GROUPS[1]).bit_length() - 1
    return np.bincount((s >> np.uint64(64 - bits)).astype(np.int64), minlength=1 << bits)


def packed(point: np.ndarray) -> bytes:
    kind = 1 if point.max(initial=0) < 256 else 4
    return bytes([kind]) + point.astype(f"<u{kind}").tobytes()


def unpacked(points: list[bytes]) -> np.ndarray:
    """Points as rows, all folded to the groups of the coarsest."""
    rows = [np.frombuffer(p, f"<u{p[0]}", offset=1) for p in points]
    groups = min(map(len, rows))
    out = np.empty((len(rows), groups), np.int32)
    for k, row in enumerate(rows):
        out[k] = row if len(row) == groups else row.reshape(groups, -1).sum(1, dtype=np.int32)
    return out


class CountTree:
    """R-tree over count vectors, packed by halving the widest coordinate."""

    LEAF, PROBES = 16, 64

    def __init__(self, points: np.ndarray, rows: np.ndarray | None = None) -> None:
        rows = np.arange(len(points)) if rows is None else rows
        self.upper, self.least = points[rows].max(0), int(points[rows].sum(1).min())
        self.rows, self.kids = rows, []
        if len(rows) > self.LEAF:
            widest = int(np.ptp(points[rows], axis=0).argmax())
            order = rows[np.argsort(points[rows, widest], kind="stable")]
            self.kids = [CountTree(points, half) for half in np.array_split(order, 2)]

    def pairs(self, points: np.ndarray, probes: np.ndarray, at: Threshold, which: np.ndarray | None = None) -> list[np.ndarray]:
        """Arrays of (probe, row) whose overlap may reach the threshold; a node sees all its probes at once."""
        which = np.arange(len(probes)) if which is None else which
        x = probes[which]
        size = x.sum(1)
        ok = np.minimum(x, self.upper).sum(1) >= at.need(size + self.least)
        which, x, size = which[ok], x[ok], size[ok]
        if not len(which):
            return []
        if self.kids:
            return [p for kid in self.kids for p in kid.pairs(points, probes, at, which)]
        y, found = points[self.rows], []
        for k in range(0, len(x), self.PROBES):
            part = x[k : k + self.PROBES]
            i, j = np.nonzero(np.minimum(part[:, None], y[None]).sum(2) >= at.exactly(size[k : k + self.PROBES, None], y.sum(1)[None]))
            found.append(np.stack([which[k + i], self.rows[j]], 1))
        return found


def near_pairs(points: np.ndarray, probes: np.ndarray, at: Threshold) -> list[tuple[int, int]]:
    """(probe, row) in order, from an R-tree over the points."""
    found = np.concatenate([np.zeros((0, 2), int), *CountTree(points).pairs(points, probes, at)])
    return found[np.lexsort((found[:, 1], found[:, 0]))].tolist()


def _sets(docs: DataFrame, n: int, num: int, den: int) -> DataFrame:
    """id, n_shingles, cls of each document; for the first of a class in a partition its keys, how many of them
    the class may leave (own band, next band), and the last bit of its own band."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, seen = Threshold(num, den), set()
        for batch in batches:
            sets = [shingles(t.as_py(), n) for t in batch.column(1)]
            names, keys, spare, bits = [class_of(s) for s in sets], [], [], []
            for s, c in zip(sets, names, strict=True):
                first = c is not None and c not in seen
                seen.add(c)
                keys.append(piece_keys(s, at).view(np.int64) if first else None)
                spare.append(spares(s, at) if first else (None, None))
                bits.append(at.band(len(s)) & 1 if first else None)
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array(names, pa.int64()), pa.array(keys, pa.list_(pa.int64())),
                    pa.array([x for x, _ in spare], pa.int32()), pa.array([x for _, x in spare], pa.int32()), pa.array(bits, pa.int32()),
                ],
                ["id", "n_shingles", "cls", "keys", "spare", "spare_next", "bit"],
            )

    return docs.mapInArrow(tidied(run, "word_hashes"), "id long, n_shingles long, cls long, keys array<long>, spare int, spare_next int, bit int")


def shared_blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The rows (key, class, m) of keys that at least two classes have, from sorted rows, as a stream.

    m is the number of the key's classes, and ``COUNTED`` for all of a key that has more.
    """
    key = held = np.zeros(0, np.int64)  # what has been read of the last key, and not been given out
    over = False  # whether the last key has more than COUNTED

    def rows(k: np.ndarray, c: np.ndarray, m: np.ndarray) -> Iterator[pa.RecordBatch]:
        ok = m > 1
        if ok.any():
            yield pa.RecordBatch.from_arrays([pa.array(k[ok]), pa.array(c[ok]), pa.array(m[ok], pa.int32())], ["key", "cls", "m"])

    for batch in batches:
        k, c = np.concatenate([key, batch.column(0).to_numpy()]), np.concatenate([held, batch.column(1).to_numpy()])
        if not len(k):
            continue
        fresh = np.concatenate([[True], (k[1:] != k[:-1]) | (c[1:] != c[:-1])])
        k, c = k[fresh], c[fresh]
        starts = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
        m = np.diff(np.concatenate([starts, [len(k)]]))
        last, whole = starts[-1], np.repeat(np.minimum(m, COUNTED), m)
        if over and last:  # the rest of a key that is too large to count; its first row was given out before
            whole[: m[0]] = COUNTED
            yield from rows(k[1 : m[0]], c[1 : m[0]], whole[1 : m[0]])
            k, c, whole, last = k[m[0] :], c[m[0] :], whole[m[0] :], last - m[0]
            over = False
        yield from rows(k[:last], c[:last], whole[:last])
        key, held = k[last:], c[last:]
        if over or len(held) > COUNTED:
            given = slice(1 if over else 0, len(held))
            yield from rows(key[given], held[given], np.full(len(held[given]), COUNTED))
            key, held, over = key[-1:], held[-1:], True
    if len(key) > 1 and not over:
        yield from rows(key, held, np.full(len(key), len(key)))


def _thinned(blocks: DataFrame, classes: DataFrame) -> DataFrame:
    """key, cls of the blocks that classes do not leave."""
    sized = blocks.join(classes.withColumnRenamed("cls", "c"), F.col("cls") == F.col("c"))
    band = (F.col("key").bitwiseAND(F.lit(1)) == F.col("bit")).alias("own")
    # a class has no more blocks than its text has n-grams
    place = F.row_number().over(Window.partitionBy("cls", "own").orderBy(F.desc("m"), F.desc("key")))
    stays = sized.select("key", "cls", band, "m", "spare", "spare_next").withColumn("place", place)
    return written(stays.where(F.col("place") > F.when(F.col("own"), F.col("spare")).otherwise(F.col("spare_next"))).select("key", "cls"), "blocks-left")


def unlike_blocks(blocks: DataFrame) -> DataFrame:
    """key, cls of the blocks of two classes or more, one of those that have the same classes.

    Copies share most of their keys. Blocks are told apart by their number of classes and two sums of hashes.
    """
    mark = [F.count("*").alias("m"), F.sum(F.xxhash64("cls").cast("decimal(20,0)")).alias("s"), F.bit_xor(F.xxhash64(F.lit(9), "cls")).alias("x")]
    still = blocks.groupBy("key").agg(*mark).where("m > 1").groupBy("m", "s", "x").agg(F.min("key").alias("k"))
    return written(blocks.join(still, F.col("key") == F.col("k")).select("key", "cls"), "blocks")


def _star(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(leader, member) of unlike components, from rows (key, cls, component) sorted by key, the leader first."""
    key = lead = root = np.zeros(0, np.int64)
    for batch in batches:
        k, c, comp = (batch.column(x).to_numpy() for x in range(3))
        if not len(k):
            continue
        k, c, comp = np.concatenate([key, k]), np.concatenate([lead, c]), np.concatenate([root, comp])  # the last leader leads on
        starts = np.concatenate([[True], k[1:] != k[:-1]])
        first = np.flatnonzero(starts)[np.cumsum(starts) - 1]
        key, lead, root = k[-1:], c[first[-1:]], comp[first[-1:]]
        unlike = comp != comp[first]
        pairs = np.unique(np.stack([c[first][unlike], c[unlike]], 1), axis=0)
        if len(pairs):
            yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], ["a", "b"])


def _bounded(at: Bound):
    """Pairs (a, b) whose points p, q allow a link."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ok = []
            for p, q in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                x = unpacked([p, q])
                ok.append(bool(np.minimum(x[0], x[1]).sum() >= at.exactly(int(x[0].sum()), int(x[1].sum()))))
            yield batch.select([0, 1]).filter(pa.array(ok, pa.bool_()))

    return run


def share_a_key(left: list[list[int]], right: list[list[int]]) -> np.ndarray:
    """Whether each two rows, of the left and of the right, have a key in common."""
    (lk, lr), (rk, rr) = ((np.fromiter((k for x in keys for k in x), np.int64), np.repeat(np.arange(len(keys)), list(map(len, keys)))) for keys in (left, right))
    common, found = np.intersect1d(lk, rk), np.zeros((len(left), len(right)), bool)
    for a in range(0, len(common), SHARED_AT_ONCE):
        part, sides = common[a : a + SHARED_AT_ONCE], []
        for keys, rows, n in ((lk, lr, len(left)), (rk, rr, len(right))):
            has = np.zeros((n, len(part)), np.float32)
            which = np.minimum(np.searchsorted(part, keys), len(part) - 1)
            ok = part[which] == keys
            has[rows[ok], which[ok]] = 1
            sides.append(has)
        found |= sides[0] @ sides[1].T > 0
    return found


def tree_pairs(left: tuple[list, list, list[bytes], list], right: tuple[list, list, list[bytes], list] | None, at: Threshold, most: int) -> list[tuple[int, int, bool]]:
    """(lesser, greater) class of unlike components that the R-tree's bound allows, between two tiles or within one.

    Sides are classes, components, points, and keys of other blocks, which give the pairs that share one. Of each
    two components at most the ``most`` pairs with the most room under the bound; then the last is
    marked as cut. (A link would join them, whichever pair has it.)
    """
    own, right = right is None, left if right is None else right
    points = unpacked([*left[2], *([] if own else right[2])])
    probes = points[: len(left[0])]
    rows = probes if own else points[len(left[0]) :]
    near = np.concatenate([np.zeros((0, 2), np.int64), *CountTree(rows).pairs(rows, probes, at)])
    names, roots = (np.array(left[k], np.int64) for k in (0, 1)), (np.array(right[k], np.int64) for k in (0, 1))
    (lc, lr), (rc, rr) = names, roots
    i, j = near[(lr[near[:, 0]] != rr[near[:, 1]]) & (lc[near[:, 0]] != rc[near[:, 1]]) & ((near[:, 1] > near[:, 0]) | (not own))].T
    if len(i):
        first = ~share_a_key(left[3], right[3])[i, j]
        i, j = i[first], j[first]
    if not len(i):
        return []
    room = np.concatenate([np.minimum(probes[i[k : k + 4096]], rows[j[k : k + 4096]]).sum(1) / (probes[i[k : k + 4096]].sum(1) + rows[j[k : k + 4096]].sum(1)) for k in range(0, len(i), 4096)])
    x, y = np.minimum(lr[i], rr[j]), np.maximum(lr[i], rr[j])
    a, b = np.minimum(lc[i], rc[j]), np.maximum(lc[i], rc[j])
    order = np.lexsort((b, a, -room, y, x))
    x, y, a, b = x[order], y[order], a[order], b[order]
    starts = np.flatnonzero(np.concatenate([[True], (x[1:] != x[:-1]) | (y[1:] != y[:-1])]))
    sizes = np.diff(np.concatenate([starts, [len(x)]]))
    place, many = np.arange(len(x)) - np.repeat(starts, sizes), np.repeat(sizes, sizes)
    kept = place < most
    return list(zip(a[kept].tolist(), b[kept].tolist(), ((place == most - 1) & (many > most))[kept].tolist(), strict=True))


def _trees(at: Bound, most: int):
    """Pairs of unlike components from rows (task, left, own, cls, component, point, lesser) sorted by task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, rows = None, []

        def flush() -> Iterator[pa.RecordBatch]:
            sides = [[x[2:] for x in rows if x[0] == side] for side in (True, False)]
            left, right = (tuple(map(list, zip(*x, strict=True))) if x else None for x in sides)
            if left and (right or rows[0][1]) and len(set(left[1]) | set(right[1] if right else ())) > 1:
                if found := tree_pairs(left, right, at, most):
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*found, strict=True)], ["a", "b", "cut"])

        for batch in batches:
            for t, *row in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                if t != task and rows:
                    yield from flush()
                    rows = []
                task = t
                rows.append(row)
        if rows:
            yield from flush()

    return run


def _verify(n: int, num: int, den: int):
    """Links (a, b) from rows (a, part, member, cls, text), sorted so that a's own text comes before its members'."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, leader, own = Threshold(num, den), None, None
        for batch in batches:
            a, b = [], []
            for lead, member, cls, text in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), batch.column(3).to_pylist(), batch.column(4), strict=True):
                s = shingles(text.as_py(), n)
                if class_of(s) != cls:
                    continue
                if not member:
                    leader, own = lead, s
                elif leader == lead and len(s) + len(own) - len(np.union1d(s, own)) >= at.need(len(s) + len(own)):
                    a.append(lead)
                    b.append(cls)
            if a:
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    return run


def _points(n: int):
    """c, point of each class from rows (cls, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            points = [packed(count_vector(shingles(t.as_py(), n))) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(points, pa.binary())], ["c", "point"])

    return run


def verified(pairs: DataFrame, texts: DataFrame, verify: Callable, schema: str = "a long, b long") -> DataFrame:
    """The pairs (a, b) that ``verify`` keeps of rows (a, part, member, cls, text); a's text goes to a task once for
    about ``MEMBERS`` members, and before them."""
    many = pairs.groupBy(F.col("a").alias("lead")).agg(F.ceil(F.count("*") / MEMBERS).alias("parts"))
    dealt = pairs.join(many, F.col("a") == F.col("lead")).select("a", "b", F.pmod(F.xxhash64("b"), F.col("parts")).alias("part"))
    leads = dealt.select("a", "part").distinct().join(texts, F.col("a") == F.col("cls")).select("a", "part", F.lit(False).alias("member"), "cls", "text")
    members = dealt.join(texts, F.col("b") == F.col("cls")).select("a", "part", F.lit(True).alias("member"), "cls", "text")
    rows = leads.unionByName(members).repartition("a", "part").sortWithinPartitions("a", "part", "member")
    return written(rows.mapInArrow(verify, schema), "links")


def _wanted(texts: DataFrame, slim: DataFrame, classes: DataFrame) -> DataFrame:
    """cls, text of the given classes, from the document of smallest id that has it."""
    spokesman = slim.where("cls IS NOT NULL AND id IS NOT NULL").groupBy("cls").agg(F.min("id").alias("id"))
    wanted = written(spokesman.join(classes.withColumnRenamed("cls", "c"), F.col("cls") == F.col("c"), "left_semi"), "ngram-wanted")
    position = F.pmod(F.xxhash64("id"), F.lit(POSITIONS))
    positions = wanted.select(position.alias("position")).distinct()  # at most POSITIONS rows, whatever the data
    read = texts.withColumn("position", position).join(F.broadcast(positions), "position", "left_semi").select("id", "text")
    return written(read.join(wanted, "id").select("cls", "text"), "ngram-texts")


def _held(blocks: DataFrame, roots: DataFrame | None) -> DataFrame:
    """key, cls, component of the blocks that still hold two components."""
    if roots is None:
        return blocks.withColumn("component", F.col("cls"))
    held = written(blocks.join(roots, F.col("cls") == F.col("node"), "left").select("key", "cls", F.coalesce("component", "cls").alias("component")), "ngram-held")
    mixed = held.groupBy(F.col("key").alias("k")).agg(F.min("component").alias("x"), F.max("component").alias("y")).where("x <> y")
    return held.join(mixed, F.col("key") == F.col("k"), "left_semi")


def _star_pairs(held: DataFrame, points: DataFrame, step: int, at: Bound) -> DataFrame:
    """(a, b): a leader for each class, of those that its blocks have in this round and the bound allows."""
    # first leaders that all blocks agree on, later others in each block
    order = F.xxhash64("cls") if step == 0 else F.xxhash64(F.lit(step), "key", "cls")
    stars = held.select("key", "cls", "component").repartition("key").sortWithinPartitions("key", order, "cls").mapInArrow(_star, "a long, b long").distinct()
    near = stars.join(points.toDF("c", "p"), F.col("a") == F.col("c")).drop("c").join(points.toDF("c", "q"), F.col("b") == F.col("c")).select("a", "b", "p", "q")
    return near.mapInArrow(_bounded(at), "a long, b long").groupBy("b").agg(F.min_by("a", F.xxhash64("a", F.lit(step))).alias("a")).select("a", "b")


def _tree_pairs(held: DataFrame, points: DataFrame, at: Bound, most: int) -> DataFrame:
    """(a, b, cut): pairs of unlike components by R-trees, of tiles or of two tiles of a block."""
    sizes = held.groupBy(F.col("key").alias("k")).agg(F.ceil(F.count("*") / TILE).cast("int").alias("tiles"))
    # a class has no more blocks than its text has n-grams; two unlike classes keep all blocks that they share
    known = held.groupBy(F.col("cls").alias("n")).agg(F.slice(F.sort_array(F.collect_list("key")), 1, SHARED).alias("keys"))
    placed = held.join(points, F.col("cls") == F.col("c")).join(known, F.col("cls") == F.col("n")).join(sizes, F.col("key") == F.col("k"))
    placed = placed.withColumn("t", F.pmod(F.xxhash64(F.lit(7), "cls"), F.col("tiles")).cast("int")).withColumn("lesser", F.filter("keys", lambda x: x < F.col("key")))
    spread = placed.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1))).select(
        F.xxhash64("key", F.least("t", "o"), F.greatest("t", "o")).alias("task"), (F.col("t") <= F.col("o")).alias("left"), (F.col("t") == F.col("o")).alias("own"), "cls", "component", "point", "lesser",
    )
    found = spread.repartition("task").sortWithinPartitions("task").mapInArrow(tidied(_trees(at, most)), "a long, b long, cut boolean")
    return found.groupBy("a", "b").agg(F.max("cut").alias("cut"))


def class_components(blocks: DataFrame, points: DataFrame, at: Bound, verify: Callable[[DataFrame], DataFrame], few: int = FEW) -> DataFrame:
    """(node, component) of the classes that are linked with another that shares a block.

    points: c, point of each class. at: the least sum of minima that the points of a link have.
    verify: the links of a table of pairs (a, b), written. New links are joined with the roots that are known,
    which are stars already, and not with the links before them.
    """
    roots, tried, step, most, done = None, None, 0, few, False
    while not done:
        held = _held(blocks, roots)
        if step < STARS:
            pairs = written(_star_pairs(held, points, step, at), "ngram-pairs")
        else:
            pairs = written(_tree_pairs(held, points, at, most), "ngram-pairs")
            done, most = not pairs.where("cut").count(), most * MORE
            pairs, before = pairs.select("a", "b"), tried
            tried = pairs  # it has all of those before it, but for components that are joined by now
            pairs = pairs if before is None else pairs.join(before, ["a", "b"], "left_anti")
        found, step = verify(pairs), step + 1
        if roots is None or found.count():
            roots = connected_components(found if roots is None else found.unionByName(roots.toDF("a", "b")))
        forget_shuffles(blocks.sparkSession)
    return roots


def _candidate_blocks(texts: DataFrame, n: int, num: int, den: int) -> tuple[DataFrame, DataFrame]:
    """(blocks, slim): key, cls of the blocks to search, and id, n_shingles, cls of each document."""
    mark = written_mark()
    sets = written(_sets(texts, n, num, den), "ngram-sets")
    slim = written(sets.select("id", "n_shingles", "cls"), "ngram-slim")
    classes = written(sets.where("bit IS NOT NULL").groupBy("cls").agg(*[F.min(c).alias(c) for c in ("spare", "spare_next", "bit")]), "ngram-spares")
    keyed = sets.select(F.explode("keys").alias("key"), "cls").repartition("key").sortWithinPartitions("key", "cls")
    blocks = written(keyed.mapInArrow(tidied(shared_blocks), "key long, cls long, m int"), "ngram-blocks")
    del sets, keyed  # the keys are the largest table of all; they and their shuffle go
    release_since(texts.sparkSession, mark, keep=[slim, classes, blocks])
    return unlike_blocks(_thinned(blocks, classes)), slim


def jaccard_components(docs: DataFrame, n: int = 5, num: int = 80, den: int = 100, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each document: id, n_shingles, component_id (smallest id reachable by links)."""
    spark = docs.sparkSession
    bound_arrow(spark)
    texts = docs.select(F.col(id_col).cast("long").alias("id"), text_or_empty(text_col).alias("text"))
    mark = written_mark()
    blocks, slim = _candidate_blocks(texts, n, num, den)
    near = written(blocks.select("cls").distinct(), "ngram-near")
    wanted = _wanted(texts, slim, near)
    points = written(wanted.mapInArrow(tidied(_points(n), "word_hashes"), "c long, point binary"), "ngram-points")
    verify = tidied(_verify(n, num, den), "word_hashes")
    joined = class_components(blocks, points, Threshold(num, den), lambda pairs: verified(pairs, wanted, verify))
    names = slim.where("cls IS NOT NULL").groupBy("cls").agg(F.min("id").alias("least"))
    rooted = written(names.join(joined, F.col("cls") == F.col("node"), "left").select("cls", "least", F.coalesce("component", "cls").alias("root")), "ngram-roots")
    release_since(spark, mark, keep=[rooted, slim])
    smallest = rooted.groupBy(F.col("root").alias("r")).agg(F.min("least").alias("component_id"))
    known = rooted.join(smallest, F.col("root") == F.col("r")).select(F.col("cls").alias("c"), "component_id")
    whole = slim.join(known, F.col("cls") == F.col("c"), "left")
    return whole.select(F.col("id").alias(id_col), "n_shingles", F.when(F.col("id").isNotNull(), F.coalesce("component_id", "id")).alias("component_id"))


def keep_smallest(docs: DataFrame, n: int = 5, num: int = 80, den: int = 100, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without those that a document of smaller id in the same component stands for."""
    found = jaccard_components(docs, n, num, den, id_col, text_col)
    gone = found.where(F.col(id_col) != F.col("component_id")).select(F.col(id_col).alias("__gone")).distinct()
    return docs.join(gone, F.col(id_col) == F.col("__gone"), "left_anti")
