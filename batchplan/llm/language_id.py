"""Language identification with bitmask n-gram filters.

Fitting counts character n-grams (2 to 4, over lower-cased words with a blank at either end) by
language and puts each into one bit-sliced Bloom filter: a slot is a word of one bit for each
language, so the AND of an n-gram's slots is the set of all languages that contain it. A language
contains an n-gram if its relative frequency there is at least ``SHARE`` of the largest one, so
that passages and labels that went astray don't count. A document's n-grams are looked up and
each language's hits counted; the filter's false positives, known from each bit's density, are
taken off; the largest corrected count decides.

Fitting reads a bounded sample: about ``sample_rows`` labelled rows of each language (all of them
when there are fewer). Everything else covers whole texts of all rows.

Defined results: null texts and texts without a letter are ``und`` with score 0; a text of which
no n-gram is known gets the language with most labelled rows and score 0; rows with a null
language are never learnt from; without any labelled row every text is ``und``; ties go to the
first language by code point; rows that repeat an id are each reported.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from batchplan.llm.shared import bound_arrow, text_or_empty, tidied

GRAMS = (2, 3, 4)
SAMPLE_ROWS = 3000
SHARE = 0.2
#: Least occurrences in the sample for an n-gram to count; slots for each n-gram; hash functions.
SEEN, SLOTS, HASHES = 3, 8, 3
MEMORY = 300_000
#: Languages that a filter may have.
LANGUAGES = 1024

_letters = re.compile(r"[^\W\d_]+")
_P, _Q = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)


def word_grams(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the n-grams of the words' letters, and the number of the word each comes from."""
    cores = [f" {' '.join(parts)} " if (parts := _letters.findall(w)) else "" for w in words]
    lens = np.fromiter(map(len, cores), np.int64, len(cores))
    codes = np.frombuffer("".join(cores).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    owner = np.repeat(np.arange(len(words)), lens)
    hashes, owners = [], []
    for n in GRAMS:
        if len(codes) < n:
            continue
        whole = owner[n - 1 :] == owner[: len(owner) - n + 1]
        h = np.full(len(codes) - n + 1, n, np.uint64)
        for j in range(n):
            h = (h ^ codes[j : len(codes) - n + 1 + j]) * _P
            h ^= h >> np.uint64(29)
        hashes.append(h[whole] * _Q)
        owners.append(owner[: len(whole)][whole])
    return (np.concatenate(hashes), np.concatenate(owners)) if hashes else (np.zeros(0, np.uint64), np.zeros(0, np.int64))


class GramFilter:
    """The bit-sliced Bloom filter of all languages."""

    def __init__(self, languages: list[str], prior: str, grams: np.ndarray, masks: np.ndarray) -> None:
        """masks: for each n-gram, a row of booleans, one for each language."""
        self.languages, self.prior = languages, prior
        self.bits = max(10, int(np.ceil(np.log2(max(1, len(grams)) * SLOTS))))
        planes = -(-max(1, len(languages)) // 64)
        self.slots = np.zeros((planes, 1 << self.bits), np.uint64)
        for k, _ in enumerate(languages):
            own = grams[masks[:, k]] if len(grams) else grams
            for at in self._places(own):
                np.bitwise_or.at(self.slots[k // 64], at, np.uint64(1 << (k % 64)))
        density = [np.mean((self.slots[k // 64] >> np.uint64(k % 64)) & np.uint64(1)) for k in range(len(languages))]
        self.false = np.minimum(np.array(density) ** HASHES, 0.99)

    def _places(self, grams: np.ndarray) -> list[np.ndarray]:
        step = (grams >> np.uint64(32)) | np.uint64(1)
        return [((grams + np.uint64(j) * step * _P) >> np.uint64(64 - self.bits)).astype(np.int64) for j in range(HASHES)]

    def contains(self, grams: np.ndarray) -> np.ndarray:
        """For each n-gram, the bit words of the languages that contain it."""
        places = self._places(grams)
        found = self.slots[:, places[0]]
        for at in places[1:]:
            found = found & self.slots[:, at]
        return found

    def hits(self, grams: np.ndarray, owner: np.ndarray, owners: int) -> np.ndarray:
        """For each owner: number of n-grams, and hits of each language."""
        found = self.contains(grams)
        columns = [np.bincount(owner, minlength=owners)]
        for k in range(len(self.languages)):
            bit = (found[k // 64] >> np.uint64(k % 64)) & np.uint64(1)
            columns.append(np.bincount(owner[bit.astype(bool)], minlength=owners))
        return np.stack(columns, 1)

    def decide(self, total: np.ndarray) -> tuple[str, float]:
        """Language and score from (n-grams, hits of each language)."""
        n = total[0]
        if not n or not self.languages:
            return "und", 0.0
        corrected = np.maximum(0, (total[1:] - n * self.false) / (1 - self.false))
        best = int(corrected.argmax())
        if corrected[best] <= 0:
            return self.prior, 0.0
        return self.languages[best], float(min(1.0, corrected[best] / n))


class WordHits:
    """Hits of each distinct word, so that a document's counts are a sum of rows."""

    def __init__(self, filter_: GramFilter) -> None:
        self.filter = filter_
        self.clear()

    def clear(self) -> None:
        self.index: dict[str, int] = {}
        self.rows = np.zeros((1024, 1 + len(self.filter.languages)), np.int64)

    def totals(self, texts: list[list[str]]) -> Iterator[np.ndarray]:
        if len(self.index) > MEMORY:
            self.clear()
        new = list({w for words in texts for w in words if w not in self.index})
        at = len(self.index)
        if at + len(new) > len(self.rows):
            self.rows = np.concatenate([self.rows, np.zeros((max(len(self.rows), len(new)), self.rows.shape[1]), np.int64)])
        if new:
            self.rows[at : at + len(new)] = self.filter.hits(*word_grams(new), len(new))
            self.index.update(zip(new, range(at, at + len(new)), strict=True))
        for words in texts:
            yield self.rows[np.fromiter(map(self.index.__getitem__, words), np.int64, len(words))].sum(0)


def fit(labelled: DataFrame, text_col: str = "text", lang_col: str = "lang", id_col: str = "doc_id", sample_rows: int = SAMPLE_ROWS) -> GramFilter:
    """The filter of the labelled rows; what reaches the driver is bounded by the sample."""
    bound_arrow(labelled.sparkSession)
    rows = labelled.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull())
    counts = {r[0]: r[1] for r in rows.groupBy(lang_col).agg(F.count("*")).limit(LANGUAGES + 1).collect()}
    if len(counts) > LANGUAGES:
        raise ValueError(f"more than {LANGUAGES} languages")
    if not counts:
        return GramFilter([], "und", np.zeros(0, np.uint64), np.zeros((0, 0), bool))
    languages = sorted(counts)
    draw = F.pmod(F.xxhash64(F.lit(11), F.col(id_col)), F.lit(1 << 30))
    chosen = F.lit(False)
    for name in languages:
        chosen = chosen | ((F.col(lang_col) == name) & (draw < int(min(1.0, sample_rows / counts[name]) * (1 << 30))))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, Counter] = {}
        for batch in batches:
            for lang, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                seen.setdefault(lang, Counter()).update(text.lower().split())
        for lang, words in seen.items():
            grams, owner = word_grams(list(words))
            times = np.fromiter(words.values(), np.int64, len(words))[owner]
            distinct, at = np.unique(grams, return_inverse=True)
            sums = np.bincount(at, weights=times, minlength=len(distinct)).astype(np.int64)
            yield pa.RecordBatch.from_pydict({"lang": [lang] * len(distinct), "gram": distinct.view(np.int64), "n": sums})

    found = rows.where(chosen).select(lang_col, text_col).mapInArrow(tidied(count), "lang string, gram long, n long")
    table = found.groupBy("lang", "gram").agg(F.sum("n").alias("n")).where(f"n >= {SEEN}").toPandas()
    grams, at = np.unique(table["gram"].to_numpy(np.int64), return_inverse=True)
    share = np.zeros((len(grams), len(languages)))
    share[at, np.searchsorted(languages, table["lang"].to_numpy(str))] = table["n"]
    share /= np.maximum(1, share.sum(0))
    masks = (share > 0) & (share >= SHARE * share.max(1, initial=0, keepdims=True))
    return GramFilter(languages, max(languages, key=lambda x: counts[x]), grams.view(np.uint64), masks)


def predict(docs: DataFrame, filter_: GramFilter, id_col: str = "doc_id", text_col: str = "text", carry: list[Column] | None = None) -> DataFrame:
    """One row for each document: id (or the carried columns), lang_pred, score."""
    spark = docs.sparkSession
    bound_arrow(spark)
    sent = spark.sparkContext.broadcast(filter_)
    kept = docs.select(*(carry if carry is not None else [F.col(id_col)]), text_or_empty(text_col).alias("__text"))
    out = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema[:-1]) + ", lang_pred string, score double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = WordHits(sent.value)
        for batch in batches:
            texts = batch.column(batch.num_columns - 1)
            decided = []
            for a in range(0, len(texts), 256):
                decided += [sent.value.decide(t) for t in words.totals([t.lower().split() for t in texts.slice(a, 256).to_pylist()])]
            columns = [*batch.columns[:-1], pa.array([d[0] for d in decided], pa.string()), pa.array([d[1] for d in decided], pa.float64())]
            yield pa.RecordBatch.from_arrays(columns, [*batch.schema.names[:-1], "lang_pred", "score"])

    return kept.mapInArrow(tidied(run), out)


def held_out(id_col: str = "doc_id") -> Column:
    """Whether a row is kept from learning: CRC-32 of its id as text leaves 2 on division by 4."""
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def drop_unidentified(docs: DataFrame, least: float, id_col: str = "doc_id") -> DataFrame:
    """docs without those of no language, or of which less than ``least`` of the n-grams fit any."""
    filter_ = fit(docs.where(~held_out(id_col)))
    row = F.struct(*[F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(docs.columns)]).alias("row")
    kept = predict(docs, filter_, id_col, carry=[row]).where((F.col("lang_pred") != "und") & (F.col("score") >= least))
    return kept.select(*[F.col(f"row.c{k}").alias(c) for k, c in enumerate(docs.columns)])
