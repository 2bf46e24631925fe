"""Language ID, token records, byte-level BPE, chat, shards, mixing and the pipeline."""

import hashlib
import random
import zlib

import numpy as np
import public_tokenizers
import pytest
import tiktoken
from pyspark.sql import functions as F

from batchplan.llm import byte_bpe, chat_tree, language_id, mixing, registry, sharding, token_records
from tests.llm.test_dedup_and_joins import docs_of

SF = "/root/testdata/sf0.001"
HARD = ["", None, " ", "a  b", "\n\nx\n", "it's 's DON'T", "naïve façade é İ ΑΣ 가각", "x" * 3000, "a<|endoftext|>b", "tabs\tand 　wide spaces", "\x1cq\x1d", "1234 5,678.9", "word " * 5000, "same", "same"]


def test_language_of_held_out_texts(spark):
    found = registry.op3_language_id(spark, "/root/testdata/sf0.01").join(spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), "doc_id")
    right, all_ = found.where("held_out").agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double")), F.count("*")).first()
    assert all_ > 100 and right > 0.98


def test_language_edges(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    filter_ = language_id.fit(docs)
    rows = {r.doc_id: (r.lang_pred, r.score) for r in language_id.predict(docs_of(spark, [None, "", "12 34 !!", "the and of", "日本"]), filter_).collect()}
    assert [rows[k] for k in (0, 1, 2)] == [("und", 0.0)] * 3 and rows[3][0] == "en" and rows[4] == (filter_.prior, 0.0)
    nothing = language_id.fit(docs.where("lang IS NULL"))
    assert language_id.predict(docs_of(spark, ["words"]), nothing).first().lang_pred == "und"
    kept = language_id.drop_unidentified(docs, 0.3)
    assert kept.columns == docs.columns and kept.count() == docs.where("text IS NOT NULL").count()


def test_filter_corrects_false_positives():
    grams = np.random.default_rng(1).integers(0, 2**63, 4000).astype(np.uint64)
    masks = np.zeros((4000, 70), bool)
    masks[np.arange(4000), np.arange(4000) % 70] = True
    made = language_id.GramFilter([f"l{k:02d}" for k in range(70)], "l00", grams, masks)
    hits = made.hits(grams[::70], np.zeros(len(grams[::70]), int), 1)[0]
    assert hits[1] == len(grams[::70]) and made.decide(hits)[0] == "l00"


def test_token_records_round_trip(spark, tmp_path):
    from tokenizers import Tokenizer

    vocabulary = public_tokenizers.path("word_bpe_49k.json")
    path = f"file://{tmp_path}/records"
    ids = [k - 3 for k in range(len(HARD))]
    token_records.write_token_records(docs_of(spark, HARD, ids), path, vocabulary)
    tok, at = Tokenizer.from_file(vocabulary), 0
    rows = token_records.read_token_records(spark, path).orderBy("doc_id").collect()
    for r, text in zip(rows, HARD, strict=True):
        want = [*tok.encode(text or "", add_special_tokens=False).ids, 1]
        assert (list(r.ids), r.start, r.n_tokens, r.ids_crc32) == (want, at, len(want), zlib.crc32(np.array(want, "<u4").tobytes()))
        at += len(want)
    file, n, _ = token_records.manifest(path)[0]
    key, one = token_records.read_record(path, file, n - 1)
    assert list(one) == [*rows[key + 3].ids]


def test_damaged_records_are_found(tmp_path):
    import io

    good = token_records.frame(b"payload")
    assert token_records.read_frame(io.BytesIO(good)) == b"payload" and token_records.read_frame(io.BytesIO(b"")) is None
    for k in range(len(good)):
        with pytest.raises(ValueError):
            token_records.read_frame(io.BytesIO(good[:k] + bytes([good[k] ^ 1]) + good[k + 1 :]))


def test_token_records_of_nothing(spark, tmp_path):
    vocabulary = public_tokenizers.path("word_bpe_49k.json")
    assert token_records.token_record_digests(docs_of(spark, ["x"]).where("1 = 0"), vocabulary).count() == 0


def test_byte_bpe_is_tiktokens(spark):
    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    reference = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.load_ranks(path), special_tokens={})
    rows = {r.doc_id: r for r in byte_bpe.encode_documents(docs_of(spark, HARD), path, public_tokenizers.PATTERN).collect()}
    for k, text in enumerate(HARD):
        want = reference.encode_ordinary(text or "")
        assert list(rows[k].ids) == want and bytes(rows[k].decoded) == (text or "").encode()
        assert rows[k].ids_sha256 == hashlib.sha256(np.array(want, "<u4").tobytes()).hexdigest()
    assert byte_bpe.encode_documents(docs_of(spark, ["x"]).where("1 = 0"), path, public_tokenizers.PATTERN).count() == 0


def test_chat_escapes_and_shares(spark):
    rows = [(1, 0, "user", "hi\\ # <b> </turn>\n### x: y"), (1, 1, "assistant", "\\### Assistant: </turn> ok"), (2, 0, "user", "hi\\ # <b> </turn>\n### x: y"), (2, 1, "assistant", None), (3, 5, None, ""), (3, 5, None, ""), (4, None, "as:sis#tant", "t")]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    nodes, segments, spans = chat_tree.format_conversations(turns)
    assert nodes.count() == 6  # conversations 1 and 2 share a turn
    ordered = nodes.orderBy("start").collect()
    assert [n.start for n in ordered][1:] == [n.end for n in ordered][:-1] and ordered[0].start == 0
    got = {r.conv_id: r for r in chat_tree.read_back(nodes, segments, spans).collect()}
    for c in (1, 2, 3, 4):
        own = [(r or "", t or "") for k, _, r, t in rows if k == c]
        assert got[c].n_turns == len(own) and got[c].turns_sha256 == hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in own).encode()).hexdigest()
        learnt = "".join(t for r, t in own if r == "assistant")
        assert (got[c].loss_chars, got[c].loss_sha256) == (len(learnt), hashlib.sha256(learnt.encode()).hexdigest())
        assert chat_tree.parse_turns("".join(chat_tree.format_turn(r, t) for r, t in own)) == own


def test_chat_tree_walks_depth_first(spark):
    """Random trees: what a node attends to is the text before it in each conversation, and subtrees are unbroken."""
    rng = random.Random(5)
    convs = {k: [("assistant" if d % 2 else "user", rng.choice("ab") + "<é" * rng.randrange(2)) for d in range(rng.randint(1, 6))] for k in [*range(-9, 40), None]}
    rows = [(c, d, r, t) for c, turns in convs.items() for d, (r, t) in enumerate(turns)]
    nodes, segments, spans = chat_tree.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").repartition(5))
    where, found = {s.segment: s for s in segments.collect()}, nodes.orderBy("start").collect()
    stream = "".join(n.formatted for n in found)
    prefixes = {}
    for n in found:
        seg = where[n.segment]
        before = "".join(stream[a.start : a.end] for a in seg.ancestors) + stream[seg.start : n.start]
        assert n.position == len(before) and n.formatted == stream[n.start : n.end] and (before, n.formatted) not in prefixes
        prefixes[before, n.formatted] = n.depth
    whole = {("".join(chat_tree.format_turn(*x) for x in turns[:d]), chat_tree.format_turn(*turns[d])) for turns in convs.values() for d in range(len(turns))}
    assert set(prefixes) == whole
    stack = []
    for before, own in prefixes:
        while stack and "".join(stack) != before:
            stack.pop()
        assert "".join(stack) == before
        stack.append(own)
    got = {r.conv_id: r for r in chat_tree.read_back(nodes, segments, spans).collect()}
    assert {c: r.turns_sha256 for c, r in got.items()} == {c: hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode()).hexdigest() for c, turns in convs.items()}


def test_chat_tree_of_long_conversations_and_of_none(spark):
    schema = "conv_id long, turn long, role string, text string"
    long_ = spark.range(50_000).select(F.lit(1).alias("conv_id"), F.col("id").alias("turn"), F.lit("user").alias("role"), F.concat(F.lit("t"), "id").alias("text"))
    nameless = spark.range(100_000).select(F.lit(None).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.lit("assistant").alias("role"), F.lit("x").alias("text"))
    branch = long_.where("turn < 30000").withColumn("conv_id", F.lit(2))
    got = {r.conv_id: r for r in chat_tree.read_back(*chat_tree.format_conversations(long_.unionByName(nameless).unionByName(branch))).collect()}
    assert {c: (r.n_turns, r.loss_chars) for c, r in got.items()} == {1: (50_000, 0), 2: (30_000, 0), None: (100_000, 100_000)}
    assert chat_tree.read_back(*chat_tree.format_conversations(spark.createDataFrame([], schema))).count() == 0


def test_shards_are_even_permutations(spark):
    docs = docs_of(spark, [None, "é"] + [f"t{k}" for k in range(995)])
    rows = sharding.shuffle_into_shards(docs, shards=40, bucket_rows=64).collect()
    by = {}
    for r in rows:
        by.setdefault(r["shard"], []).append(r["slot"])
    assert sorted(r["doc_id"] for r in rows) == list(range(997)) and set(by) == set(range(40))
    assert all(sorted(v) == list(range(len(v))) for v in by.values()) and {len(v) for v in by.values()} == {24, 25}
    again = {r["doc_id"]: (r["shard"], r["slot"]) for r in sharding.shuffle_into_shards(docs.repartition(7), shards=40, bucket_rows=64).collect()}
    assert again == {r["doc_id"]: (r["shard"], r["slot"]) for r in rows}
    assert sharding.shuffle_into_shards(docs.where("1 = 0")).count() == 0


def test_shards_of_repeated_and_missing_ids(spark, tmp_path):
    """Rows of one id or of none spread over the buckets, in any partitioning alike; own shard and slot columns are replaced."""
    rows = [(7 if k % 3 else None, f"t{k}", k % 5, "x") for k in range(3000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, shard int, other string")
    first = sharding.shuffle_into_shards(docs.repartition(3), shards=7, bucket_rows=64)
    written = sharding.write_shards(first, f"file://{tmp_path}/shards")
    assert sorted(first.columns) == sorted(written.columns) == ["doc_id", "other", "shard", "slot", "text"]
    places = lambda df: {r.text: (r.doc_id, r.shard, r.slot) for r in df.collect()}
    found = places(written)
    assert found == places(first) == places(sharding.shuffle_into_shards(docs.repartition(7), shards=7, bucket_rows=64))
    assert all(found[t][0] == i for i, t, _, _ in rows)
    assert {s: sorted(v[2] for v in found.values() if v[1] == s) == list(range(sum(v[1] == s for v in found.values()))) for s in range(7)} == dict.fromkeys(range(7), True)


def test_fisher_yates_permutes(spark):
    row = spark.range(1).select(sharding.fisher_yates(F.lit(200), 5, F.lit(1)).alias("a"), sharding.fisher_yates(F.lit(200), 5, F.lit(2)).alias("b")).first()
    assert sorted(row.a) == sorted(row.b) == list(range(1, 201)) and row.a != row.b and row.a != sorted(row.a)


def test_mix_meets_targets(spark):
    rows = [(k, "w " * (k % 7), f"s{k % 4}" if k % 9 else None) for k in range(400)] + [(500, None, "s0"), (501, "a b", "zz")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    found = mixing.mix_sizes(docs).collect()
    source = {r[0]: r[2] for r in rows}
    order = sorted({s for s in source.values() if s is not None}) + [None]
    sizes = {s: sum(r["size"] for r in found if source[r["doc_id"]] == s) for s in order}
    weights = {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}
    target, open_ = {}, set(order)
    rest = float(sum(sizes.values()))
    while True:
        share = {s: rest * weights[s] / sum(weights[x] for x in open_) for s in open_}
        over = {s for s in open_ if share[s] > 3 * sizes[s]}
        if not over:
            break
        for s in over:
            target[s] = 3.0 * sizes[s]
            rest -= target[s]
        open_ -= over
    target |= share
    taken = {s: 0 for s in order}
    for r in found:
        s = source[r["doc_id"]]
        taken[s] += r["taken"]
        assert r["target"] == pytest.approx(target[s], abs=1e-5) and r["source_size"] == sizes[s] and 0 <= r["taken"] <= 3 * r["size"]
    assert all(abs(taken[s] - target[s]) <= 1 for s in order)
    mixed = mixing.mix_documents(docs)
    assert mixed.columns == docs.columns and mixing.mix_documents(docs.where("1 = 0")).count() == 0


def test_pipeline_against_its_operators(spark):
    import corpus_pipeline
    from tests.llm.test_dedup_and_joins import brute_components

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    known = corpus_pipeline.identify_language(spark, docs, SF)
    exact = {r.doc_id: r.text for r in corpus_pipeline.drop_exact(spark, known, SF).collect()}
    first = {}
    for r in sorted(known.collect(), key=lambda r: r.doc_id):
        first.setdefault(r.text or "", r.doc_id)
    assert set(exact) == set(first.values())
    ids = sorted(exact)
    groups = brute_components([exact[k] for k in ids], 5, 80, 100)
    near = {r.doc_id for r in corpus_pipeline.drop_near(spark, docs.where(F.col("doc_id").isin(ids)), SF).collect()}
    assert near == {ids[k] for k, v in groups.items() if v[1] == k}
    out = corpus_pipeline.run(spark, SF)
    assert out.columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"] and {r.doc_id for r in out.select("doc_id").distinct().collect()} <= near


def test_pieces_are_looked_up_once_and_encoded_once():
    import numpy as np

    from batchplan.llm.pieces import PieceStore

    class Piece(str):
        hashed = 0

        def __hash__(self):
            Piece.hashed += 1
            return super().__hash__()

    asked = []

    def encode(pieces):
        asked.extend(pieces)
        if "bad" in pieces:
            raise ValueError("bad")
        return np.array([ord(c) for p in pieces for c in p], np.uint32), np.array([len(p) for p in pieces])

    store = PieceStore(encode, 3)
    assert store.ids(["ab", "c", "ab"]).tolist() == [97, 98, 99, 97, 98] and store.ids([]).tolist() == []
    known = [Piece("c")] * 50
    assert store.ids(known).tolist() == [99] * 50 and Piece.hashed == 50
    assert store.ids_and_lens(["d", "ab", "", "d"])[1].tolist() == [1, 2, 0, 1] and sorted(asked) == ["", "ab", "c", "d"]
    with pytest.raises(ValueError, match="bad"):
        store.ids(["e", "bad"])
    assert store.ids(["e", "c"]).tolist() == [101, 99]
    store.ids(["f", "g"])
    store.room()
    assert not store.index and store.ids(["g"]).tolist() == [103]


def test_letters_that_words_share_go_through_the_library_once():
    tok = token_records.WordTokenizer(public_tokenizers.path("word_bpe_49k.json"))
    asked, each = [], tok._each
    tok._each = lambda pieces: asked.extend(w for p in pieces for w in p.split(" ")) or each(pieces)
    texts = ["grumel Grumel$$ ètre", "grumel%&* ÈTRE, grumel.$", "", "ΟΔΟΣ grumel's $ x1$ ètre%"]
    found = [tok.ids(t).tolist() for t in texts[:2]] + [x.tolist() for x in tok.ids_many(texts[2:])]
    assert found == [tok.tok.encode(t, add_special_tokens=False).ids for t in texts]
    assert asked.count("grumel") == 1 and asked.count("ètre") == 1 and len(asked) == len(set(asked))


def test_stages_begin_with_a_trimmed_heap(spark, monkeypatch):
    import corpus_pipeline
    from batchplan.llm import shared

    trimmed = []
    monkeypatch.setattr(corpus_pipeline, "trim_executors", lambda s: trimmed.append(s) or shared.trim_executors(s))
    docs = docs_of(spark, ["the and of", None])
    assert corpus_pipeline.encode_bytes(spark, docs, SF).count() == 2 and trimmed == [spark]
