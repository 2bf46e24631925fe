"""Byte-level BPE by recursive DuckDB queries, one in-memory database for each Python worker.

Texts are split by the pre-tokenizer's pattern. Each distinct word becomes rows (word, position,
token), one for each byte. The recursive query joins neighbouring tokens with the merge table
(every way to make a token from two tokens), takes each word's pair of least rank, leftmost among
equals, contracts it, and goes on with the words that changed until no pair is left. Decoding
joins token ids with the vocabulary and concatenates the pieces in order of position.

The recursion keeps every step's rows, the square of a word's length; words longer than
``LONG_WORD`` bytes are contracted by the same rule on a heap instead, whose memory is linear.

Defined results: a null text counts as empty; empty texts have no tokens; rows that repeat an id
each give a row; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import re
from collections.abc import Iterator

import duckdb
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from batchplan.llm.pieces import PieceStore, stretches
from batchplan.llm.shared import bound_arrow, text_or_empty, tidied, worker_cache

LONG_WORD = 256
#: Distinct chunks of texts (a blank and what follows) and words that a worker remembers.
CHUNKS, WORDS = 400_000, 150_000
#: Rows that one recursive query may keep (a word keeps the square of its bytes at most); tokens in one decoding query.
QUERY_ROWS, QUERY_TOKENS = 1_500_000, 200_000
#: Characters that are split into words at a time.
STRETCH = 1 << 20

#: Unicode white space, as the patterns' \s means it, inside a character class.
SPACE = "\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"

ENCODE = """
WITH RECURSIVE step(k, t, i) AS (
  SELECT k, t, 0::SMALLINT FROM letters
  UNION ALL (
    WITH pairs AS (
      SELECT k, t, i, lead(k) OVER o AS next_k, lead(t) OVER o AS next_t FROM step WINDOW o AS (ORDER BY k)),
    ranked AS (
      SELECT p.k, p.next_k, m.id FROM pairs p JOIN merges m ON m.pair = (p.t::BIGINT << 17) + p.next_t
      WHERE p.next_k >> 16 = p.k >> 16),
    least_pair AS (
      SELECT k >> 16 AS w, min(id::BIGINT << 16 | (k & 65535)) AS best, arg_min(next_k, id::BIGINT << 16 | (k & 65535)) AS gone
      FROM ranked GROUP BY 1)
    SELECT p.k, CASE WHEN p.k & 65535 = l.best & 65535 THEN (l.best >> 16)::INT ELSE p.t END, (p.i + 1)::SMALLINT
    FROM pairs p JOIN least_pair l ON l.w = p.k >> 16 WHERE p.k <> l.gone))
SELECT s.k >> 16 AS w, s.t FROM step s
JOIN (SELECT k >> 16 AS w, max(i) AS i FROM step GROUP BY 1) e ON s.k >> 16 = e.w AND s.i = e.i
ORDER BY s.k
"""

DECODE = "SELECT d, string_agg(piece, '' ORDER BY p) AS text FROM tokens JOIN vocabulary USING (id) GROUP BY d"


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


class ByteBpe:
    """Encoder and decoder of one rank file and one pre-tokenizer pattern."""

    def __init__(self, path: str, pattern: str) -> None:
        self.ranks = load_ranks(path)
        self.words = regex.compile(pattern.replace(r"[^\s", f"[^{SPACE}").replace(r"\s", f"[{SPACE}]").replace(r"\S", f"[^{SPACE}]"))
        self.irregular = re.compile(f"[{SPACE}][{SPACE}]")
        self.byte_id = np.array([self.ranks[bytes([b])] for b in range(256)], np.int32)
        self.store = PieceStore(self._encode_chunks, CHUNKS)
        self.known = PieceStore(self._encode_words, WORDS)
        self.db = duckdb.connect(config={"threads": 1, "memory_limit": "300MB", "temp_directory": ""})
        pairs = [(left, right, i) for b, i in self.ranks.items() for k in range(1, len(b)) if (left := self.ranks.get(b[:k])) is not None and (right := self.ranks.get(b[k:])) is not None]
        left, right, ids = np.array(pairs, np.int64).reshape(-1, 3).T
        self._create("merges", pair=(left << 17) + right, id=ids.astype(np.int32))
        self._create("vocabulary", id=np.fromiter(self.ranks.values(), np.int32), piece=[b.decode("latin-1") for b in self.ranks])

    def _create(self, name: str, **columns) -> None:
        self.db.register("made", pa.table(columns))
        self.db.execute(f"CREATE TABLE {name} AS SELECT * FROM made")
        self.db.unregister("made")

    def _query(self, sql: str, name: str, **columns) -> pa.Table:
        self.db.register(name, pa.table(columns))
        found = self.db.sql(sql).to_arrow_table()
        self.db.unregister(name)
        return found

    def _contract(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The words' ids one after another, and each word's number of them, by the recursive query."""
        lens = np.fromiter(map(len, words), np.int64, len(words))
        letters = self.byte_id[np.frombuffer(b"".join(words), np.uint8)]
        first = np.cumsum(lens) - lens
        k = (np.repeat(np.arange(len(words)), lens) << 16) + np.arange(len(letters)) - np.repeat(first, lens)
        done = self._query(ENCODE, "letters", k=k, t=letters)
        return done["t"].to_numpy(), np.bincount(done["w"].to_numpy(), minlength=len(words))

    def _contract_long(self, word: bytes) -> np.ndarray:
        token = [bytes([b]) for b in word]
        after, before, alive = list(range(1, len(token) + 1)), list(range(-1, len(token) - 1)), [True] * len(token)
        heap: list[tuple[int, int, bytes]] = []

        def offer(a: int) -> None:
            if a >= 0 and after[a] < len(token) and (r := self.ranks.get(token[a] + token[after[a]])) is not None:
                heapq.heappush(heap, (r, a, token[a] + token[after[a]]))

        for a in range(len(token) - 1):
            offer(a)
        while heap:
            _, a, whole = heapq.heappop(heap)
            if not alive[a] or after[a] >= len(token) or token[a] + token[after[a]] != whole:
                continue
            b = after[a]
            token[a], alive[b], after[a] = whole, False, after[b]
            if after[b] < len(token):
                before[after[b]] = a
            offer(before[a])
            offer(a)
        return np.array([self.ranks[x] for x, live in zip(token, alive, strict=True) if live], np.uint32)

    def _encode_words(self, words):
        raw = [w.encode() for w in words]
        flats, lens, todo, held = [], [], [], 0

        def contract() -> None:
            if todo:
                flat, n = self._contract(todo)
                flats.append(flat)
                lens.append(n)
                todo.clear()

        for b in raw:
            if len(b) > LONG_WORD:
                contract()
                flats.append(self._contract_long(b))
                lens.append(np.array([len(flats[-1])]))
                held = 0
                continue
            todo.append(b)
            held += len(b) * len(b)
            if held >= QUERY_ROWS or len(todo) >= 1 << 16:
                contract()
                held = 0
        contract()
        return np.concatenate(flats).astype(np.uint32), np.concatenate(lens)

    def _encode_chunks(self, chunks):
        split = [self.words.findall(c) for c in chunks]
        words = [w for found in split for w in found]
        self.known.room()
        counts = np.fromiter(map(len, split), np.int64, len(split))
        ids, lens = self.known.ids_and_lens(words)
        return ids, np.add.reduceat(lens, np.cumsum(counts) - counts)

    def chunks(self, text: str) -> list[str]:
        """The text cut where no word crosses: before a single blank between two other characters.

        Where white space stands next to white space the pattern looks further ahead, so all but
        the last character of such a run is a chunk of its own, as the pattern makes it.
        """
        if not text:
            return []
        if not self.irregular.search(text) and text[-1] not in " \t\n\r\v\f\x85\xa0" and not text[-1].isspace():
            first, *rest = text.split(" ")
            return ([first] if first else []) + [" " + r for r in rest]
        return self.words.findall(text)

    def _break(self, text: str, at: int) -> int:
        m = re.compile(r"(?<=[^\W_]) (?=[^\W_])").search(text, at)
        return m.start() if m else len(text)

    def encode_many(self, texts: list[str]) -> list[np.ndarray]:
        """Each text's ids; the new words of about ``STRETCH`` characters share a recursive query."""
        parts: list[list[np.ndarray]] = [[] for _ in texts]
        group: list[tuple[int, list[str]]] = []
        held = 0

        def learn() -> None:
            self.store.room()
            numbers = [(n, self.store.numbers(chunks)) for n, chunks in group]
            self.store.learn()
            for n, which in numbers:
                parts[n].append(self.store.taken(which)[0])
            group.clear()

        for n, text in enumerate(texts):
            for part in stretches(text, STRETCH, self._break):
                group.append((n, self.chunks(part)))
                held += len(part)
                if held >= STRETCH:
                    learn()
                    held = 0
        learn()
        return [p[0] if len(p) == 1 else np.concatenate(p) for p in parts]

    def encode(self, text: str) -> np.ndarray:
        return self.encode_many([text])[0]

    def decode(self, docs: list[np.ndarray]) -> list[bytes]:
        lens = np.fromiter(map(len, docs), np.int64, len(docs))
        texts = [b""] * len(docs)
        if lens.sum():
            ids = np.concatenate(docs).astype(np.int32)
            done = self._query(DECODE, "tokens", d=np.repeat(np.arange(len(docs), dtype=np.int32), lens), p=np.arange(len(ids), dtype=np.int32), id=ids)
            for d, text in zip(done["d"].to_pylist(), done["text"].to_pylist(), strict=True):
                texts[d] = text.encode("latin-1")
        return texts


def coder(path: str, pattern: str) -> ByteBpe:
    """One for each Python worker; the words it has contracted serve all of the worker's tasks."""
    return worker_cache(("byte_bpe", path, pattern), lambda: ByteBpe(path, pattern))


def encode_documents(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = True) -> DataFrame:
    """One row for each document: id, n_tokens, ids_sha256, decoded_sha256 (and ids, decoded)."""
    bound_arrow(docs.sparkSession)
    kind = docs.schema[id_col].dataType.simpleString()
    schema = f"{id_col} {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<long>, decoded binary" * with_ids

    def rows(bpe: ByteBpe, keys: list, coded: list[np.ndarray], key_type: pa.DataType) -> pa.RecordBatch:
        decoded = bpe.decode(coded)
        columns = {
            id_col: pa.array(keys, key_type),
            "n_tokens": pa.array([len(x) for x in coded], pa.int64()),
            "ids_sha256": [hashlib.sha256(x.astype("<u4").tobytes()).hexdigest() for x in coded],
            "decoded_sha256": [hashlib.sha256(x).hexdigest() for x in decoded],
        }
        if with_ids:
            columns |= {"ids": pa.array([x.astype(np.int64) for x in coded], pa.list_(pa.int64())), "decoded": pa.array(decoded, pa.binary())}
        return pa.RecordBatch.from_pydict(columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = coder(path, pattern)
        for batch in batches:
            keys, coded, key_type = batch.column(0).to_pylist(), bpe.encode_many(batch.column(1).to_pylist()), batch.schema.field(0).type
            a, held = 0, 0
            for b in range(len(keys)):
                held += len(coded[b])
                if held >= QUERY_TOKENS or b + 1 == len(keys):
                    yield rows(bpe, keys[a : b + 1], coded[a : b + 1], key_type)
                    a, held = b + 1, 0

    return docs.select(F.col(id_col), text_or_empty(text_col)).mapInArrow(tidied(run, "byte_bpe"), schema)
