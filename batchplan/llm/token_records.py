"""Token ids in length-delimited binary record files, with an offset index for shuffled reads.

File format. A record is: payload length (8 bytes), masked checksum of those 8 bytes (4),
payload, masked checksum of the payload (4); all integers little-endian. The payload is a
header (document id, 1 if that id is null, bytes of a token id) and the ids, 2 bytes each where
the vocabulary allows it and 4 otherwise. The checksum is CRC-32, rotated right by 15 bits plus
a constant, so that a checksum stored inside data does not check itself. Beside each record file
an index has the offset of each record (8 bytes), so that a reader may fetch records in any order.

Documents are in ascending id order over the numbered files. Each file is written under a name of
the task attempt and then renamed, so that a task that is run again replaces its own file.

Defined results: a null text encodes as empty and gets the end id alone; null ids come first;
rows that repeat an id each get a record; an empty table gives no records.
"""

from __future__ import annotations

import json
import os
import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from batchplan.llm.pieces import PieceStore, stretches
from batchplan.llm.shared import bound_arrow, filesystem, new_path, publish, text_or_empty, worker_cache

MASK_DELTA = 0xA282EAD8
HEADER = "<qBB"
#: Characters of one document that are split into words at a time.
STRETCH = 1 << 20
#: Distinct words, and distinct runs of letters and of marks, that a worker remembers.
WORDS, PARTS = 1_000_000, 600_000
#: Marks that a word may end with; the apostrophe is none, as it can begin a token of letters.
MARKS = '.,;:!?|#")]}$%&*'
#: Separators that Python's split() sees and the tokenizer does not.
ODD_SEPARATORS = re.compile("[\x1c-\x1f]")


def masked(data: bytes) -> int:
    c = zlib.crc32(data)
    return (((c >> 15) | (c << 17)) + MASK_DELTA) & 0xFFFFFFFF


def frame(payload: bytes) -> bytes:
    head = struct.pack("<Q", len(payload))
    return b"".join((head, struct.pack("<I", masked(head)), payload, struct.pack("<I", masked(payload))))


def read_frame(stream) -> bytes | None:
    """The next payload; None at the end. A damaged or cut record raises."""
    head = stream.read(12)
    if not head:
        return None
    if len(head) < 12 or struct.unpack("<I", head[8:])[0] != masked(head[:8]):
        raise ValueError("damaged record length")
    n = struct.unpack("<Q", head[:8])[0]
    payload, check = stream.read(n), stream.read(4)
    if len(payload) < n or len(check) < 4 or struct.unpack("<I", check)[0] != masked(payload):
        raise ValueError("damaged record")
    return payload


class WordTokenizer:
    """Ids of whole texts from a tokenizers file whose pre-tokenizer drops white space.

    No token spans white space, so a text's ids are those of its words in order; each distinct
    word is split once. Letters and the marks after them are always split, so words share their
    letters' ids, and each run of letters goes through the library once; many runs go in one call,
    and the tokens that end a word tell them apart. Texts with separators that only Python treats as
    white space go through the library whole.
    """

    def __init__(self, path: str) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.store, self.parts = PieceStore(self._encode, WORDS), PieceStore(self._encode_parts, PARTS)
        self.width = 2 if self.tok.get_vocab_size() <= 1 << 16 else 4
        suffix = json.loads(self.tok.to_str())["model"].get("end_of_word_suffix")
        self.ends = np.zeros(max(self.tok.get_vocab().values()) + 1, bool)
        for token, i in self.tok.get_vocab().items():
            self.ends[i] = bool(suffix) and token.endswith(suffix)

    def _each(self, pieces: list[str]) -> list[list[int]]:
        return [x.ids for x in self.tok.encode_batch_fast(pieces, add_special_tokens=False)]

    def _letters(self, runs: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of runs of letters, one run after another, and each run's number of them; many in one call."""
        flats, lens = [], []
        for a in range(0, len(runs), 256):
            some = runs[a : a + 256]
            ids = np.array(self._each([" ".join(some)])[0], np.uint32)
            cuts = np.flatnonzero(self.ends[ids]) + 1
            if len(cuts) != len(some) or cuts[-1] != len(ids):
                each = self._each(some)
                ids, cuts = np.array([i for x in each for i in x], np.uint32), np.cumsum([len(x) for x in each])
            flats.append(ids)
            lens.append(np.diff(cuts, prepend=0))
        return (np.concatenate(flats), np.concatenate(lens)) if flats else (np.zeros(0, np.uint32), np.zeros(0, np.int64))

    def _encode_parts(self, parts):
        """Ids and their numbers for parts of words: runs of letters first, then the others, put back in order."""
        alpha = np.fromiter((p.isalpha() for p in parts), bool, len(parts))
        run_ids, run_lens = self._letters([p for p in parts if p.isalpha()])
        each = self._each([p for p in parts if not p.isalpha()])
        lens = np.empty(len(parts), np.int64)
        lens[alpha], lens[~alpha] = run_lens, [len(x) for x in each]
        ids, of_run = np.empty(int(lens.sum()), np.uint32), np.repeat(alpha, lens)
        ids[of_run], ids[~of_run] = run_ids, [i for x in each for i in x]
        return ids, lens

    def _encode(self, words):
        parts, counts = [], np.ones(len(words), np.int64)
        for n, w in enumerate(words):
            run = w.rstrip(MARKS)
            if run.isalpha():
                parts.append(run.lower() if run.isascii() or max(run) <= "\xff" else run)
                if len(run) < len(w):
                    parts.append(w[len(run) :])
                    counts[n] = 2
            else:
                parts.append(w)
        self.parts.room()
        ids, lens = self.parts.ids_and_lens(parts)
        return ids, np.add.reduceat(lens, np.cumsum(counts) - counts)

    @staticmethod
    def _break(text: str, at: int) -> int:
        m = re.compile(r"\s").search(text, at)
        return m.start() if m else len(text)

    def ids_many(self, texts: list[str]) -> list[np.ndarray]:
        """Each text's ids; the new words of about ``STRETCH`` characters are learnt at once."""
        parts: list[list[np.ndarray]] = [[] for _ in texts]
        group: list[tuple[int, list[str]]] = []
        held = 0

        def learn() -> None:
            self.store.room()
            numbers = [(n, self.store.numbers(words)) for n, words in group]
            self.store.learn()
            for n, which in numbers:
                parts[n].append(self.store.taken(which)[0])
            group.clear()

        for n, text in enumerate(texts):
            if ODD_SEPARATORS.search(text):
                parts[n].append(np.array(self.tok.encode(text, add_special_tokens=False).ids, np.uint32))
                continue
            for part in stretches(text, STRETCH, self._break):
                group.append((n, part.split()))
                held += len(part)
                if held >= STRETCH:
                    learn()
                    held = 0
        learn()
        return [p[0] if len(p) == 1 else np.concatenate(p) for p in parts]

    def ids(self, text: str) -> np.ndarray:
        return self.ids_many([text])[0]


def tokenizer(path: str) -> WordTokenizer:
    """One for each Python worker; what it has learnt serves all of the worker's tasks."""
    return worker_cache(("tokenizer", path), lambda: WordTokenizer(path))


def write_token_records(docs: DataFrame, path: str, vocabulary: str, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Write docs' token ids to record files, index files and a manifest under path."""
    spark = docs.sparkSession
    bound_arrow(spark)
    filesystem(path)[0].create_dir(filesystem(path)[1], recursive=True)
    ordered = docs.select(F.col(id_col).cast("long").alias("id"), text_or_empty(text_col).alias("text")).repartitionByRange("id").sortWithinPartitions("id", "text")

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, tok, (fs, root) = TaskContext.get(), tokenizer(vocabulary), filesystem(path)
        name, attempt = f"part-{task.partitionId():06d}", f"attempt-{task.taskAttemptId()}"
        out, at, offsets, tokens = None, 0, [], 0
        for batch in batches:
            for key, found in zip(batch.column(0).to_pylist(), tok.ids_many(batch.column(1).to_pylist()), strict=True):
                ids = np.append(found, np.uint32(end_id))
                data = frame(struct.pack(HEADER, key or 0, key is None, tok.width) + ids.astype(f"<u{tok.width}").tobytes())
                out = out or fs.open_output_stream(f"{root}/.{attempt}-{name}.rec", buffer_size=1 << 20)
                out.write(data)
                offsets.append(at)
                at, tokens = at + len(data), tokens + len(ids)
        if out is None:
            return
        out.close()
        with fs.open_output_stream(f"{root}/.{attempt}-{name}.idx") as index:
            index.write(np.array(offsets, "<u8").tobytes())
        for kind in ("rec", "idx"):
            publish(fs, f"{root}/.{attempt}-{name}.{kind}", f"{root}/{name}.{kind}")
        yield pa.RecordBatch.from_pydict({"file": [name], "records": [len(offsets)], "tokens": [tokens]})

    files = sorted(ordered.mapInArrow(write, "file string, records long, tokens long").collect())
    fs, root = filesystem(path)
    with fs.open_output_stream(f"{root}/manifest.json") as out:
        out.write(json.dumps({"files": [list(f) for f in files], "end_id": end_id}).encode())


def manifest(path: str) -> list[tuple[str, int, int]]:
    """(file, records, tokens) in order: a row for each file."""
    fs, root = filesystem(path)
    with fs.open_input_stream(f"{root}/manifest.json") as f:
        return [tuple(x) for x in json.loads(f.read())["files"]]


def parse(payload: bytes) -> tuple[int | None, np.ndarray]:
    key, null, width = struct.unpack_from(HEADER, payload)
    return (None if null else key), np.frombuffer(payload, f"<u{width}", offset=struct.calcsize(HEADER)).astype(np.uint32)


def read_record(path: str, file: str, k: int) -> tuple[int | None, np.ndarray]:
    """Record k of a file by its index: two small reads."""
    fs, root = filesystem(path)
    with fs.open_input_file(f"{root}/{file}.idx") as index:
        at = struct.unpack("<Q", index.read_at(8, 8 * k))[0]
    with fs.open_input_file(f"{root}/{file}.rec") as data:
        data.seek(at)
        return parse(read_frame(data))


def read_token_records(spark: SparkSession, path: str, with_ids: bool = True) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 (and ids) of each record, checked against its checksums."""
    starts, total = [], 0
    for file, _, tokens in manifest(path):
        starts.append((file, total))
        total += tokens
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<long>" * with_ids
    if not starts:
        return spark.createDataFrame([], schema)
    files = spark.createDataFrame(starts, "file string, base long").repartition(len(starts))

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = filesystem(path)
        for batch in batches:
            for file, at in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                rows = []
                with fs.open_input_stream(f"{root}/{file}.rec", buffer_size=1 << 20) as f:
                    while (payload := read_frame(f)) is not None:
                        key, ids = parse(payload)
                        rows.append((key, at, len(ids), zlib.crc32(ids.astype("<u4").tobytes()), *([ids.tolist()] if with_ids else [])))
                        at += len(ids)
                        if len(rows) >= (200 if with_ids else 5000):
                            yield _batch(rows, with_ids)
                            rows = []
                if rows:
                    yield _batch(rows, with_ids)

    return files.mapInArrow(read, schema)


def _batch(rows: list[tuple], with_ids: bool) -> pa.RecordBatch:
    names = ["doc_id", "start", "n_tokens", "ids_crc32", *["ids"] * with_ids]
    kinds = [pa.int64()] * 4 + [pa.list_(pa.int64())] * with_ids
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)


def token_record_digests(docs: DataFrame, vocabulary: str, path: str | None = None, **how) -> DataFrame:
    """Write docs' records (under the shared folder if no path is given) and read them back."""
    path = path or new_path(docs.sparkSession, "token-records")
    write_token_records(docs, path, vocabulary, **how)
    return read_token_records(docs.sparkSession, path, with_ids=False)
