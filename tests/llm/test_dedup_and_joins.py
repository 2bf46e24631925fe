"""Exact dedup, n-gram join, fuzzy lines and vectors against brute force, with hard rows."""

import hashlib
import random

import numpy as np
import pyarrow as pa
import pytest

from batchplan.llm import components, exact_dedup, fuzzy_lines, ngram_join, vector_links

DOCS = "doc_id long, text string, lang string, source string, n_chars long, kept boolean, cls string"


def docs_of(spark, texts, ids=None):
    ids = range(len(texts)) if ids is None else ids
    return spark.createDataFrame([(i, t, "en", "s", len(t or ""), True, "x") for i, t in zip(ids, texts, strict=True)], DOCS)


def corpus(seed, n=120):
    rng = random.Random(seed)
    words = [f"w{k}" for k in range(300)]
    base = [" ".join(rng.choices(words, k=rng.randint(1, 90))) for _ in range(n // 4)]
    out = list(base)
    while len(out) < n:
        w = rng.choice(base).split()
        for _ in range(rng.randint(0, 4)):
            w[rng.randrange(len(w))] = rng.choice(words)
        out.append(" ".join(w))
    return [*out, None, "", "  ", "One", "one", "long " * 30_000]


@pytest.mark.parametrize("keep", ["smallest", "largest"])
def test_exact_groups(spark, keep):
    texts = ["a", "b", "a", None, "", "a", "x" * 200_000, "x" * 200_000, "é"]
    rows = exact_dedup.mark_exact_duplicates(docs_of(spark, texts), keep=keep).collect()
    groups = {}
    for k, t in enumerate(texts):
        groups.setdefault(t or "", []).append(k)
    pick = min if keep == "smallest" else max
    got = {r.doc_id: (r.keep_id, r.group_size, r.kept, r.text_sha256) for r in rows}
    assert got == {k: (pick(groups[t or ""]), len(groups[t or ""]), k == pick(groups[t or ""]), hashlib.sha256((t or "").encode()).hexdigest()) for k, t in enumerate(texts)}


def test_exact_hot_group_crosses_ranges(spark):
    old = spark.conf.get("spark.sql.adaptive.coalescePartitions.enabled")
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        texts = ["same"] * 400 + [f"t{k}" for k in range(50)]
        rows = exact_dedup.mark_exact_duplicates(docs_of(spark, texts)).collect()
    finally:
        spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", old)
    hot = [r for r in rows if r.doc_id < 400]
    assert {(r.keep_id, r.group_size) for r in hot} == {(0, 400)} and sum(r.kept for r in hot) == 1 and sum(r.kept for r in rows) == 51


def test_exact_drop_keeps_columns_repeated_ids_and_nulls(spark):
    docs = docs_of(spark, ["a", "a", None, None, "b"], [1, 1, None, 2, 3])
    kept = exact_dedup.drop_exact_duplicates(docs)
    assert kept.columns == docs.columns and sorted((r.text or "") for r in kept.collect()) == ["", "a", "b"]
    assert exact_dedup.drop_exact_duplicates(docs.where("1 = 0")).count() == 0
    folded = exact_dedup.mark_exact_duplicates(docs_of(spark, ["A b", "a b"]), normalise=lambda c: __import__("pyspark.sql.functions", fromlist=["lower"]).lower(c))
    assert {r.group_size for r in folded.collect()} == {2}


def brute_components(texts, n, num, den):
    sets = []
    for t in texts:
        w = (t or "").encode().lower().split()
        sets.append({tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set()))
    root = list(range(len(texts)))

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(sets)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if both and den * both >= num * (len(sets[i]) + len(sets[j]) - both):
                a, b = top(i), top(j)
                root[max(a, b)] = min(a, b)
    return {i: (len(sets[i]), top(i)) for i in range(len(sets))}


@pytest.mark.parametrize(("n", "num", "den"), [(4, 85, 100), (5, 80, 100), (1, 50, 100)])
def test_ngram_components(spark, n, num, den):
    texts = corpus(n)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.jaccard_components(docs_of(spark, texts), n, num, den).collect()}
    assert got == brute_components(texts, n, num, den)


@pytest.mark.parametrize("stars", [0, 1, 3])
def test_ngram_large_block_and_small_tiles(spark, monkeypatch, stars):
    monkeypatch.setattr(ngram_join, "TILE", 8)
    monkeypatch.setattr(ngram_join, "STARS", stars)
    rng = random.Random(3)
    base = [f"v{k}" for k in range(60)]
    texts = []
    for _ in range(70):
        w = list(base)
        for _ in range(rng.randint(0, 3)):
            w[rng.randrange(60)] = f"z{rng.randrange(500)}"
        texts.append(" ".join(w))
    got = {r.doc_id: r.component_id for r in ngram_join.jaccard_components(docs_of(spark, texts), 2, 80, 100).collect()}
    assert got == {k: v[1] for k, v in brute_components(texts, 2, 80, 100).items()}


def test_ngram_keeps_one_of_a_group_and_null_ids(spark):
    text = " ".join(f"w{k}" for k in range(40))
    docs = docs_of(spark, [text, text + " more", "other words here", None, text], [5, 3, 9, 11, None])
    kept = ngram_join.keep_smallest(docs)
    assert kept.columns == docs.columns and sorted((r.doc_id is None, r.doc_id) for r in kept.collect()) == [(False, 3), (False, 9), (False, 11), (True, None)]
    assert ngram_join.jaccard_components(docs.where("1 = 0")).count() == 0


def test_count_tree_never_prunes_a_link():
    rng = np.random.default_rng(5)
    at = ngram_join.Threshold(80, 100)
    points = rng.integers(0, 6, (200, 16))
    found = {tuple(p) for p in ngram_join.near_pairs(points, points[:40], at)}
    assert found == {(i, j) for i, x in enumerate(points[:40]) for j, y in enumerate(points) if np.minimum(x, y).sum() >= at.need(int(x.sum() + y.sum()))}


def test_piece_keys_meet():
    rng = np.random.default_rng(6)
    at = ngram_join.Threshold(85, 100)
    for _ in range(300):
        n = int(rng.integers(6, 400))
        x = np.unique(rng.integers(0, 2**63, n).astype(np.uint64) * np.uint64(2))
        lost = int(rng.integers(0, max(1, n // 8)))
        y = np.unique(np.concatenate([x[rng.permutation(len(x))[lost:]], rng.integers(0, 2**63, int(rng.integers(0, max(1, n // 12)))).astype(np.uint64) * np.uint64(2) + np.uint64(1)]))
        both = len(np.intersect1d(x, y))
        if 100 * both >= 85 * (len(x) + len(y) - both) and ngram_join.class_of(x) != ngram_join.class_of(y):
            assert set(ngram_join.piece_keys(x, at).tolist()) & set(ngram_join.piece_keys(y, at).tolist())


@pytest.mark.parametrize(("num", "den"), [(85, 100), (80, 100)])
def test_piece_keys_meet_at_all_small_sizes(num, den):
    rng = np.random.default_rng(9)
    at = ngram_join.Threshold(num, den)
    for a in range(1, 41):
        for b in range(a, 41):
            least = min(k for k in range(a + b + 1) if den * k >= num * (a + b - k))  # by brute force
            for both in range(least, min(a, b - 1) + 1 if a == b else a + 1):
                assert a + b - 2 * both <= at.differ(at.band(b))
                for _ in range(5):
                    s = rng.integers(0, 2**63, a + b - both).astype(np.uint64) * np.uint64(2)
                    x, y = np.sort(s[:a]), np.sort(s[a - both :])
                    assert set(ngram_join.piece_keys(x, at).tolist()) & set(ngram_join.piece_keys(y, at).tolist()), (a, b, both)


@pytest.mark.parametrize(("n", "num", "den", "sizes"), [(4, 85, 100, range(9, 14)), (5, 80, 100, range(8, 11))])
def test_ngram_links_of_short_documents(spark, n, num, den, sizes):
    texts = []
    for k in sizes:
        w = [f"s{k}x{i}" for i in range(k)]
        texts += [" ".join(w), " ".join(w[1:]), " ".join([*w, f"more{k}"])]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.jaccard_components(docs_of(spark, texts), n, num, den).collect()}
    want = brute_components(texts, n, num, den)
    assert got == want and len({c for _, c in want.values()}) < len(texts)


@pytest.mark.parametrize("size", [1, 2, 5, 100])
def test_blocks_as_a_stream(monkeypatch, size):
    """Whatever the batches, each key with two classes or more comes once a class, with its count or the bound."""
    monkeypatch.setattr(ngram_join, "COUNTED", 4)
    rng = random.Random(4)
    rows = sorted((k, c) for k in range(12) for c in range(rng.choice((1, 1, 2, 4, 5, 11))) for _ in range(rng.choice((1, 1, 3))))
    batches = [pa.RecordBatch.from_arrays([pa.array([k for k, _ in part], pa.int64()), pa.array([c for _, c in part], pa.int64())], ["key", "cls"]) for part in (rows[a : a + size] for a in range(0, len(rows), size))]
    got = [tuple(r.values()) for b in ngram_join.shared_blocks(iter(batches)) for r in b.to_pylist()]
    many = {k: len({c for j, c in rows if j == k}) for k, _ in rows}
    assert got == [(k, c, min(many[k], 4)) for k, c in sorted(set(rows)) if many[k] > 1]


def test_ngram_thousands_of_short_near_copies(spark):
    """Copies of one short document with one word exchanged, among others that share a passage with them.

    Of 29 pairs of words an exchange makes two new ones (one at either end): copies exchanged at the same place
    share 27 of 31 or more, so do those at the ends with each other and with their neighbours, all others 26 of 32 or less.
    """
    rng = random.Random(12)
    base, texts, group = [f"c{k}" for k in range(30)], [], {}
    for k in range(5000):
        w, place = list(base), rng.randrange(30)
        w[place] = f"x{rng.randrange(4000)}"
        alone = k % 5 == 0
        texts.append(" ".join([f"own{k}w{i}" for i in range(20)] + base[:12]) if alone else " ".join(w))
        group.setdefault(("alone", k) if alone else 0 if place in (0, 1, 28, 29) else place, []).append(k)
    got = {r.doc_id: r.component_id for r in ngram_join.jaccard_components(docs_of(spark, texts), 2, 85, 100).collect()}
    assert len(group) == 1027 and got == {k: min(g) for g in group.values() for k in g}


@pytest.mark.parametrize(("known", "tile"), [(64, 512), (64, 8), (2, 8)])
def test_ngram_trees_give_a_pair_in_one_of_its_blocks(spark, monkeypatch, known, tile):
    """Sixty classes in up to sixty blocks each: all pairs that share a block, and each of them once."""
    monkeypatch.setattr(ngram_join, "TILE", tile)
    monkeypatch.setattr(ngram_join, "SHARED", known)
    rng, made, whole = random.Random(14), spark.sparkContext.accumulator(0), ngram_join._trees

    def counted(at, most):
        def run(batches):
            for batch in whole(at, most)(batches):
                made.add(batch.num_rows)
                yield batch

        return run

    monkeypatch.setattr(ngram_join, "_trees", counted)
    rows = sorted({(rng.randrange(-60, 60) * 2**40, c) for c in range(60) for _ in range(60 if c % 2 else 4)})
    held = spark.createDataFrame([(k, c, c) for k, c in rows], "key long, cls long, component long")
    points = spark.createDataFrame([(c, ngram_join.packed(np.full(64, 3))) for c in range(60)], "c long, point binary")
    found = [(r.a, r.b) for r in ngram_join._tree_pairs(held, points, ngram_join.Threshold(80, 100), 4).collect()]
    blocks = {}
    for k, c in rows:
        blocks.setdefault(k, set()).add(c)
    want = {(a, b) for members in blocks.values() for a in members for b in members if a < b}
    assert len(found) == len(set(found)) and set(found) == want
    assert made.value == len(want) if known == 64 else made.value >= len(want)


def test_components_of_paths_and_hubs(spark):
    links = [(k, k + 1) for k in range(40)] + [(100, 100 + k) for k in range(1, 60)] + [(7, 7), (None, 3)]
    got = {r.node: r.component for r in components.connected_components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {**{k: 0 for k in range(41)}, **{100 + k: 100 for k in range(60)}}
    assert components.connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_fuzzy_lines(spark):
    texts = ["Alpha beta gamma delta epsilon zeta eta theta iota 12\nunique line of words", "x\n\nalpha  BETA gamma delta epsilon zeta eta theta iota, 99!", None, "", "--- \n ...", "unique line of words"]
    rows = {(r.doc_id, r.line): (r.keep_id, r.keep_line, r.kept) for r in fuzzy_lines.line_groups(docs_of(spark, texts)).collect()}
    assert rows == {(0, 0): (0, 0, True), (0, 1): (0, 1, True), (1, 0): (1, 0, True), (1, 2): (0, 0, False), (5, 0): (0, 1, False)}
    out = {r.doc_id: r.text for r in fuzzy_lines.drop_repeated_lines(docs_of(spark, texts)).collect()}
    assert out == {0: texts[0], 1: "x\n", 2: None, 3: "", 4: texts[4], 5: ""}


def test_fuzzy_lines_against_brute_force(spark):
    """All pairs by edit similarity, without the operator's keys: a letter or a few changed in lines of all lengths."""
    rng = random.Random(11)
    base = [" ".join("".join(rng.choices("abcdefghijklmnopqrstuvwxyz", k=rng.randint(3, 8))) for _ in range(k)) for k in (3, 5, 8, 9, 12, 20, 31, 60) for _ in range(4)]
    lines = list(base)
    for x in base:
        for edits in (1, 1, 1 + len(x) // 50):
            y = list(x)
            for _ in range(edits):
                y[rng.randrange(len(y))] = rng.choice("abcdefghijklmnopqrstuvwxyz")
            lines.append("".join(y))
    plain = [fuzzy_lines.normalise(x) for x in lines]
    root = list(range(len(lines)))
    for i in range(len(lines)):
        for j in range(i):
            if root[i] != root[j] and fuzzy_lines.similar(plain[i], plain[j]):
                root = [min(root[i], root[j]) if r in (root[i], root[j]) else r for r in root]
    got = {r.doc_id: r.keep_id for r in fuzzy_lines.line_groups(docs_of(spark, lines)).collect()}
    assert got == dict(enumerate(root)) and len(set(root)) == len(base)


def test_fuzzy_lines_in_tiles(spark, monkeypatch):
    """Short lines of few letters, which share keys by chance: pairs in one task, by tiles, against each pair's distance."""
    rng = random.Random(5)
    lines = sorted({"".join(rng.choices("ab c", k=rng.randint(4, 14))).strip() or "a" for _ in range(150)} | {"x" * k + "y" * 90 for k in range(1, 40, 3)})
    roots = [k // 2 for k in range(len(lines))]
    for own, left in ((True, [True] * len(lines)), (False, [k % 3 == 0 for k in range(len(lines))])):
        group = list(roots)
        for i in range(len(lines)):
            for j in range(i):
                if (own or left[i] != left[j]) and group[i] != group[j] and 1 - fuzzy_lines.edit_distance(lines[i], lines[j]) / max(len(lines[i]), len(lines[j])) >= 0.8 - 1e-12:
                    group = [group[i] if g == group[j] else g for g in group]
        got = list(roots)
        for a, b in fuzzy_lines.tile_links(roots, lines, left, own, 0.8):
            assert own or left[a] != left[b]
            got = [got[a] if g == got[b] else g for g in got]
        assert len(set(got)) == len(set(group)) == len(set(zip(got, group, strict=True)))
    docs = docs_of(spark, lines)
    listed = {tuple(r) for r in fuzzy_lines.line_groups(docs).collect()}
    monkeypatch.setattr(fuzzy_lines, "TILE", 8)
    assert {tuple(r) for r in fuzzy_lines.line_groups(docs).collect()} == listed


def test_edit_distance():
    def slow(a, b):
        d = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            p, d[0] = d[0], i
            for j, y in enumerate(b, 1):
                p, d[j] = d[j], min(d[j] + 1, d[j - 1] + 1, p + (x != y))
        return d[-1]

    rng = random.Random(7)
    for _ in range(200):
        a, b = ("".join(rng.choices("abc", k=rng.randint(0, 80))) for _ in range(2))
        assert fuzzy_lines.edit_distance(a, b) == slow(a, b)


def test_vectors_against_brute_force(spark, monkeypatch):
    monkeypatch.setattr(vector_links, "TILE", 16)
    rng = np.random.default_rng(8)
    rows, base = [], rng.standard_normal((12, 8))
    for k in range(240):
        v = base[k % 12] + rng.normal(0, 0.08, 8) * rng.random()
        rows.append((k, [float(np.float32(x)) for x in v * rng.uniform(0.1, 9)], int(k % 3)))
    rows += [(300 + k, rows[0][1], rows[0][2]) for k in range(40)]
    rows += [(400, None, 1), (401, [0.0] * 8, 1), (402, [float("nan")] * 8, 1), (403, rows[0][1], None), (404, [1.0, None] * 4, 1), (405, [float("inf")] * 8, 1), (406, [], 1)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in vector_links.near_vectors(frame, lists=7).collect()}
    good = [r for r in rows if r[0] < 400]
    x = np.array([r[1] for r in good], np.float32).astype(float)
    norm = np.sqrt((x * x).sum(1))
    link = ((x @ x.T) / (norm[:, None] * norm[None]) >= 0.98) & (np.array([r[2] for r in good])[:, None] == np.array([r[2] for r in good])[None])
    np.fill_diagonal(link, False)
    ids = np.array([r[0] for r in good])
    comp = ids.copy()
    while True:
        new = np.minimum(comp, np.where(link, comp[None], 1 << 60).min(1))
        if (new == comp).all():
            break
        comp = new
    want = {int(i): (int(n), int(c), bool(i == c)) for i, n, c in zip(ids, link.sum(1), comp, strict=True)}
    want |= {k: (0, k, True) for k in range(400, 407)}
    assert link.sum() > 500 and got == want
    assert vector_links.near_vectors(frame.where("1 = 0")).count() == 0


def test_vectors_of_great_and_small_numbers_and_of_other_lengths(spark):
    rows = [(1, [1e200, 1e200], 1), (2, [1e200, 1e200 * (1 + 1e-9)], 1), (3, [1e-200, 1e-200], 1), (4, [1.0, -1.0], 1), (5, [1.0, 1.0, 1.0], 1), (6, [2.0, 2.0, 2.0], 1), (6, [2.0, 2.0, 2.0], 2), (7, [3.0], 1)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    got = sorted((r.vec_id, r.n_links, r.component_id) for r in vector_links.near_vectors(frame).collect())
    assert got == [(1, 2, 1), (2, 2, 1), (3, 2, 1), (4, 0, 4), (5, 1, 5), (6, 0, 6), (6, 1, 5), (7, 0, 7)]


def test_long_distances_are_edit_distances(monkeypatch):
    rng = np.random.default_rng(3)
    lines = ["".join(rng.choice(list("abcd é"), n)) for n in (1, 5, 63, 64, 65, 100, 127, 128, 129, 200, 300)]
    lines += [x[:k] + "z" + x[k + 2 :] + "ab" for x in lines for k in (0, len(x) // 2)]
    i, j = (x.ravel() for x in np.indices((len(lines), len(lines))))
    want = [fuzzy_lines.edit_distance(lines[a], lines[b]) for a, b in zip(i.tolist(), j.tolist(), strict=True)]
    assert fuzzy_lines.long_distances(lines, i, j).tolist() == want
    assert len(fuzzy_lines.long_distances(lines, i[:0], j[:0])) == 0
    words = ["".join(rng.choice(list("abcdefgh"), 6)) for _ in range(20)]
    shuffled = [" ".join(rng.permutation(words)) for _ in range(40)]  # alike by their pairs of characters, not by their edits
    alone: list = []
    monkeypatch.setattr(fuzzy_lines, "edit_distance", lambda a, b: alone.append(1) or 99)
    assert not fuzzy_lines.tile_links(list(range(40)), shuffled, [True] * 40, True, 0.8) and not alone
