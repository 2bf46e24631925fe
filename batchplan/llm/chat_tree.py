"""Chat formatting as a prefix tree: turns that conversations share are emitted once.

A turn's node is a digest of its parent's node, its role and its text, so conversations with the
same initial turns have the same initial nodes. A node belongs to the least conversation that has it.
Going down a conversation its nodes' owners never decrease, so what a conversation owns is the end of it:
one segment, an unbroken chain. The segments hang together as a tree, and the depth-first walk that goes
to the least conversation first emits each segment in one piece, then the segments that hang from it, the
deepest first. A segment's key lists, for it and all above it, the depth it hangs from and its
conversation; the byte order of the keys is the walk, so the walk is a range partition and a sort of one row
for each segment. A key is no longer than its conversation has turns, whatever the shape of the tree.

Each segment is emitted with its place in the stream, the position of its first character in the
conversation, and the spans of the stream above it; each node with its formatted text, its place, its position
and the span of its loss. A node attends to its segment's ancestors, to its segment from the start, and
to itself: chains count as one span, so spans are linear in the turns. A token here is a character of the
formatted text. Conversations are read back from the stream by their spans.

Template: ``### role: text</turn>`` and a line feed. In roles and texts each backslash, ``#``, ``<`` and
(in roles) ``:`` gets a backslash before it, so no text can hold a control string, and removing the
backslashes gives the text back. The loss covers the texts of assistant turns, without their marks.

Defined results: null texts and roles count as empty; turns are ordered by number (null first), ties by
role and text, and repeated rows are turns like others; rows whose conversation is null form one
conversation, which is read as a stream; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from batchplan.llm.shared import bound_arrow, tidied, written

#: Bytes of a node's digest.
DIGEST = 16
#: The role whose texts are learnt.
LEARNT = "assistant"

_turn = re.compile(r"### ((?:\\.|[^\\:])*): ((?:\\.|[^\\<])*)</turn>\n", re.DOTALL)


def escape(text: str, also: str = "") -> str:
    return re.sub(rf"([\\#<{also}])", r"\\\1", text)


def unescape(text: str) -> str:
    return re.sub(r"\\(.)", r"\1", text, flags=re.DOTALL)


def format_turn(role: str, text: str) -> str:
    return f"### {escape(role, ':')}: {escape(text)}</turn>\n"


def loss_span(role: str, text: str) -> tuple[int, int]:
    """Where the learnt characters of a formatted turn begin and end."""
    start = len(f"### {escape(role, ':')}: ")
    return (start, start + len(escape(text))) if role == LEARNT else (start, start)


def parse_turns(formatted: str) -> list[tuple[str, str]]:
    """(role, text) of each turn; anything that is not the template's raises."""
    turns, at = [], 0
    while at < len(formatted):
        m = _turn.match(formatted, at)
        if not m:
            raise ValueError(f"no turn at character {at}")
        turns.append((unescape(m[1]), unescape(m[2])))
        at = m.end()
    return turns


def _chains(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each turn's depth, node, position and length, from rows sorted by conversation and turn."""
    conv, node, depth, position, first = None, b"", 0, 0, True
    for batch in batches:
        made: list[tuple] = []
        for c, role, text in zip(*[x.to_pylist() for x in batch.columns], strict=True):
            if first or c != conv:
                conv, node, depth, position, first = c, b"", 0, 0, False
            raw = role.encode()
            node = hashlib.blake2b(node + len(raw).to_bytes(8, "little") + raw + text.encode(), digest_size=DIGEST).digest()
            depth += 1
            length = len(format_turn(role, text))
            made.append((c, depth, node, position, length, role, text))
            position += length
        if made:
            kinds = (pa.int64(), pa.int32(), pa.binary(), pa.int64(), pa.int64(), pa.string(), pa.string())
            names = ["conv_id", "depth", "node", "position", "length", "role", "text"]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*made, strict=True), kinds, strict=True)], names)


def chain_turns(turns: DataFrame) -> DataFrame:
    """conv_id, depth (1..), node, position, length, role, text of each turn, written."""
    bound_arrow(turns.sparkSession)
    plain = turns.select(
        F.col("conv_id").cast("long").alias("conv_id"), F.col("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")
    )
    ordered = plain.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text").select("conv_id", "role", "text")
    return written(ordered.mapInArrow(tidied(_chains), "conv_id long, depth int, node binary, position long, length long, role string, text string"), "chat-chains")


def walk_key(above: bytes, hangs_from: int, conv: int | None) -> bytes:
    """The key of a segment: deeper hooks first, then lesser conversations, null last."""
    return above + struct.pack(">IBQ", (1 << 32) - 1 - hangs_from, conv is None, (conv or 0) + (1 << 63))


_RUN = "struct<owner: bigint, nobody: boolean, first_depth: int, last_depth: int, first: bigint, last: bigint>"


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """conv_id, key (null without a segment), and the runs of owners, from rows (conv_id, depth, owner, position, length) in order."""
    conv, key, runs, first = None, b"", [], True

    def row() -> tuple:
        own = runs[-1]["owner"] == conv
        return conv, key if own else None, runs

    def out(rows: list[tuple]) -> pa.RecordBatch:
        kind = pa.list_(pa.struct([("owner", pa.int64()), ("nobody", pa.bool_()), ("first_depth", pa.int32()), ("last_depth", pa.int32()), ("first", pa.int64()), ("last", pa.int64())]))
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.binary(), kind), strict=True)], ["conv_id", "key", "runs"])

    for batch in batches:
        rows = []
        for c, depth, owner, position, length in zip(*[x.to_pylist() for x in batch.columns], strict=True):
            if first or c != conv:
                if not first:
                    rows.append(row())
                conv, key, runs, first = c, b"", [], False
            if not runs or runs[-1]["owner"] != owner:
                key = walk_key(key, depth - 1, owner)
                runs.append({"owner": owner, "nobody": owner is None, "first_depth": depth, "last_depth": depth, "first": position, "last": position})
            runs[-1]["last_depth"], runs[-1]["last"] = depth, position + length
        if rows:
            yield out(rows)
    if not first:
        yield out([row()])


def _walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Segments (conv_id, first, length) with their place in this range of the walk."""
    part, at = TaskContext.get().partitionId(), 0
    for batch in batches:
        length = batch.column(2).to_numpy()
        ends = at + np.cumsum(length)
        if len(length):
            at = int(ends[-1])
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(length), part, np.int32)), *batch.columns, pa.array(ends - length)], ["part", "conv_id", "first", "length", "local"])


def pack_tree(chains: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(nodes, segments, spans), all written; what is named segment is the conversation that owns it.

    nodes: node, segment, depth, formatted, start and end (in the whole stream), position, loss_start, loss_end.
    segments: segment, start, end, position, ancestors (spans of the stream, outermost first).
    spans: conv_id, runs: which depths of which segments each conversation is made of.
    """
    owners = chains.groupBy("node").agg(F.min(F.struct(F.col("conv_id").isNull().alias("nobody"), F.col("conv_id").alias("owner"))).alias("by"))
    owned = chains.join(owners.withColumnRenamed("node", "n"), F.col("node") == F.col("n"))
    steps = owned.select("conv_id", "depth", F.col("by.owner").alias("owner"), "position", "length").repartition("conv_id").sortWithinPartitions("conv_id", "depth")
    spans = written(steps.mapInArrow(tidied(_runs), f"conv_id long, key binary, runs array<{_RUN}>"), "chat-spans")
    own = F.element_at("runs", -1)
    heads = spans.where("key IS NOT NULL").select("key", "conv_id", own["first"].alias("first"), (own["last"] - own["first"]).alias("length"))
    walk = heads.repartitionByRange("key").sortWithinPartitions("key").select("conv_id", "first", "length")
    walk = written(walk.mapInArrow(tidied(_walk), "part int, conv_id long, first long, length long, local long"), "chat-walk")
    # one row for each range of the walk
    bases = walk.groupBy("part").agg(F.sum("length").alias("n")).select(F.col("part").alias("p"), (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("base"))
    placed = walk.join(F.broadcast(bases), F.col("part") == F.col("p")).select(F.col("conv_id").alias("segment"), "first", "length", (F.col("local") + F.col("base")).alias("start"))
    placed = written(placed, "chat-places")
    above = spans.where("key IS NOT NULL").select(F.col("conv_id").alias("segment"), F.posexplode(F.slice("runs", 1, F.size("runs") - 1)).alias("k", "run"))
    where = placed.select(F.col("segment").alias("s"), F.col("first").alias("f"), F.col("start").alias("at"))
    held = above.join(where, F.col("run.owner").eqNullSafe(F.col("s"))).groupBy("segment").agg(
        F.array_sort(F.collect_list(F.struct("k", (F.col("at") - F.col("f") + F.col("run.first")).alias("start"), (F.col("at") - F.col("f") + F.col("run.last")).alias("end")))).alias("found")
    )
    ancestors = F.coalesce(F.transform("found", lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"))), F.expr("CAST(array() AS ARRAY<STRUCT<start: BIGINT, end: BIGINT>>)"))
    segments = placed.join(held.withColumnRenamed("segment", "s"), F.col("segment").eqNullSafe(F.col("s")), "left").select(
        "segment", "start", (F.col("start") + F.col("length")).alias("end"), F.col("first").alias("position"), ancestors.alias("ancestors")
    )
    escaped = lambda c, also="": F.regexp_replace(c, rf"([\\#<{also}])", r"\\$1")
    lead = F.concat(F.lit("### "), escaped("role", ":"), F.lit(": "))
    mine = owned.where(F.col("conv_id").eqNullSafe(F.col("by.owner"))).join(where, F.col("conv_id").eqNullSafe(F.col("s")))
    start = F.col("at") - F.col("f") + F.col("position")
    loss_from = start + F.length(lead)
    nodes = mine.select(
        "node", F.col("conv_id").alias("segment"), "depth", F.concat(lead, escaped("text"), F.lit("</turn>\n")).alias("formatted"), start.alias("start"), (start + F.col("length")).alias("end"), "position",
        loss_from.alias("loss_start"), (loss_from + F.when(F.col("role") == LEARNT, F.length(escaped("text"))).otherwise(0)).alias("loss_end"),
    )
    return written(nodes, "chat-nodes"), written(segments, "chat-segments"), spans.select("conv_id", "runs")


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """What each conversation's nodes read back to, from rows sorted by conversation and position."""
    conv, state = None, None

    def row() -> tuple:
        turns, all_, loss, chars, learnt = state
        return conv, turns, all_.hexdigest(), learnt, loss.hexdigest(), chars

    def out(rows: list[tuple]) -> pa.RecordBatch:
        kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
        names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    for batch in batches:
        rows = []
        for c, position, formatted, start, end in zip(*[x.to_pylist() for x in batch.columns], strict=True):
            if state is None or c != conv:
                if state is not None:
                    rows.append(row())
                conv, state = c, [0, hashlib.sha256(), hashlib.sha256(), 0, 0]
            if position != state[3]:
                raise ValueError(f"conversation {c}: characters {state[3]} to {position} are missing")
            for role, text in parse_turns(formatted):
                state[0] += 1
                state[1].update(f"{role}\n{text}\n".encode())
            learnt = unescape(formatted[start:end])
            state[2].update(learnt.encode())
            state[3] += len(formatted)
            state[4] += len(learnt)
        if rows:
            yield out(rows)
    if state is not None:
        yield out([row()])


def read_back(nodes: DataFrame, segments: DataFrame, spans: DataFrame) -> DataFrame:
    """conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars, from the packed stream.

    A conversation is the nodes of the depths that its spans name in each segment, in order of position;
    a gap or an overlap of positions is an error.
    """
    bound_arrow(nodes.sparkSession)
    steps = spans.select("conv_id", F.explode("runs").alias("run")).select("conv_id", F.col("run.owner").alias("s"), F.explode(F.sequence("run.first_depth", "run.last_depth")).alias("d"))
    parts = nodes.select("segment", "depth", "formatted", "position", (F.col("loss_start") - F.col("start")).alias("a"), (F.col("loss_end") - F.col("start")).alias("b"))
    joined = steps.join(parts, F.col("s").eqNullSafe(F.col("segment")) & (F.col("d") == F.col("depth")))
    ordered = joined.repartition("conv_id").sortWithinPartitions("conv_id", "position").select("conv_id", "position", "formatted", "a", "b")
    return ordered.mapInArrow(tidied(_digest), "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def format_conversations(turns: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(nodes, segments, spans) of the packed stream."""
    return pack_tree(chain_turns(turns))
