"""The scheduling methods against worked examples, brute force and DuckDB."""

import itertools
import math
import random

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from batchplan import registry
from batchplan.functions import forward as fw
from batchplan.operators import gain as gn
from batchplan.operators import intervals as iv
from batchplan.operators import masks as mk
from batchplan.operators import schedules as sc
from batchplan.operators import stats as st

SF = "/root/testdata/sf0.001"


def log_of(spark, rows):
    return spark.createDataFrame([(r, k, q, 0, 0, a, b) for k, (r, q, a, b) in enumerate(rows)], "round_id int, run_id long, query_id long, config_id int, conn_id int, start_us long, finish_us long")


def test_gain_by_hand(spark):
    log = log_of(spark, [(1, 1, 0, 10), (1, 2, 4, 12), (2, 1, 0, 6), (2, 2, 3, 9)])
    row = gn.scheduling_gain(iv.concurrent_pairs(log, 5), st.avg_runtime(log)).first()
    assert (row.qi, row.qj, row.m_c) == (1, 2, 2)
    assert row.gain == pytest.approx(-0.01508919, abs=1e-7)


@pytest.mark.parametrize("bucket", [1, 7, 50, 10_000])
def test_bucketed_pairs_are_the_plain_join(spark, bucket):
    rng = random.Random(bucket)
    rows = [(rng.randint(1, 3), rng.randint(1, 6), a := rng.randint(0, 300), a + rng.randint(1, 120)) for _ in range(60)]
    got = {(r.run_i, r.run_j, r.ov_us) for r in iv.concurrent_pairs(log_of(spark, rows), bucket).collect()}
    want = {
        (i, j, min(x[3], y[3]) - max(x[2], y[2]))
        for (i, x), (j, y) in itertools.permutations(enumerate(rows), 2)
        if x[0] == y[0] and x[1] < y[1] and min(x[3], y[3]) > max(x[2], y[2])
    }
    assert got == want


def test_gain_sums_add_up(spark):
    log = registry.log_a(spark, SF)
    stats = st.avg_runtime(log)
    whole = {(r.qi, r.qj): r.gain for r in gn.scheduling_gain(iv.concurrent_pairs(log), stats).collect()}
    half = F.dayofmonth("round_id") <= 15
    from batchplan.streaming.arriving import merge_pair_sums

    sums = merge_pair_sums(merge_pair_sums(None, log.where(half)), log.where(~half))
    parts = {(r.qi, r.qj): r.gain for r in gn.gain_from_sums(sums, stats).collect()}
    assert parts.keys() == whole.keys() and max(abs(parts[k] - whole[k]) for k in whole) < 1e-12


def test_pinned_dendrogram_and_mutual_best(spark):
    log = registry.log_a(spark, SF)
    stats = st.avg_runtime(log)
    gain = gn.scheduling_gain(iv.concurrent_pairs(log), stats)
    made, merges = gn.cluster_by_gain(gain, stats, 5)
    clusters = {}
    for r in made.collect():
        clusters.setdefault(r.cluster_id, set()).add(r.query_id)
    assert sorted(map(sorted, clusters.values())) == [[0, 6, 13], [1, 2, 5, 14], [3, 8], [4, 9, 10, 12], [7, 11]]
    assert [(r.left_id, r.right_id) for r in merges.orderBy("step").limit(3).collect()] == [(3, 8), (2, 5), (4, 10)]
    owner, all_merges = gn.mutual_best_clusters(gain, stats, 5)
    again = {}
    for q, c in owner.items():
        again.setdefault(c, set()).add(q)
    assert sorted(map(sorted, again.values())) == sorted(map(sorted, clusters.values()))
    full = gn.cluster_by_gain(gain, stats, 1)[1].collect()
    assert sorted(round(r.gain, 9) for r in full) == sorted(round(m[2], 9) for m in all_merges)


def test_average_linkage_by_hand():
    pairs = [(0, 1, 0.9), (0, 2, 0.2), (0, 3, 0.1), (1, 2, 0.4), (1, 3, 0.3), (2, 3, 0.5)]
    _, merges = gn.average_linkage([0, 1, 2, 3], pairs, 1)
    assert [(a, b, round(g, 6)) for a, b, g in merges] == [(0, 1, 0.9), (2, 3, 0.5), (0, 2, 0.25)]


def test_list_schedule_by_hand(spark):
    costs = spark.createDataFrame([(1, 2), (2, 3), (3, 4), (4, 6), (5, 9)], "query_id long, cost long")
    made = sc.heuristic_schedules(costs, 2).where("strategy = 'fifo'").orderBy("seq").collect()
    assert [(r.query_id, r.conn_id, r.start_us, r.finish_us) for r in made] == [(1, 0, 0, 2), (2, 1, 0, 3), (3, 0, 2, 6), (4, 1, 3, 9), (5, 0, 6, 15)]
    spans = {r.strategy: r.avg for r in sc.strategy_summary(sc.heuristic_schedules(costs, 2)).collect()}
    assert (spans["fifo"], spans["mcf"]) == (15, 12)
    assert sc.exhaustive({1: 2, 2: 3, 3: 4, 4: 6, 5: 9}, 2) == (12, 16, 120)


def test_schedule_invariants(spark):
    rng = random.Random(4)
    for _ in range(3):
        costs = {q: rng.randint(1, 40) for q in range(7)}
        frame = spark.createDataFrame(list(costs.items()), "query_id long, cost long")
        made = sc.heuristic_schedules(frame, 3)
        assert sc.violations(made, frame, ["strategy", "round_id"]).first()[0] == 0
        best = sc.exhaustive(costs, 3)[0]
        bound = sc.lower_bound(frame, 3).first().bound
        for r in sc.strategy_summary(made).collect():
            assert bound <= best <= r.avg <= best * (2 - 1 / 3) + 1e-9
            if r.strategy == "mcf":
                assert r.avg <= best * (4 / 3 - 1 / 9) + 1e-9


def test_masks(spark):
    profile = spark.createDataFrame([(1, 0, 100.0), (1, 1, 50.0), (1, 2, 49.0), (2, 0, 10.0), (2, 1, 12.0)], "query_id long, config_id int, avg_us double")
    mask = {(r.query_id, r.config_id): r.allowed for r in mk.adaptive_mask(mk.config_improvement(profile)).collect()}
    assert mask == {(1, 0): True, (1, 1): True, (1, 2): False, (2, 0): True, (2, 1): False}
    logits = spark.createDataFrame([(k, x, a) for k, (x, a) in enumerate([(1.0, True), (0.5, True), (2.0, True), (9.0, False), (0.0, True), (9.0, False)])], "k int, logit double, allowed boolean")
    got = [round(r.prob, 6) for r in mk.masked_softmax(logits, []).orderBy("k").collect()]
    assert got == [0.213097, 0.12925, 0.579259, 0.0, 0.078394, 0.0]
    wanted = spark.createDataFrame([(1, 7, 2), (2, 7, 2)], "query_id long, cluster_id long, cluster_config int")
    ladder = spark.createDataFrame([(0, [0]), (1, [1]), (2, [2])], "config_id int, steps array<int>")
    masks = spark.createDataFrame([(1, 0, True), (1, 1, True), (1, 2, False), (2, 0, True), (2, 1, False)], "query_id long, config_id int, allowed boolean")
    assert {r.query_id: r.config_id for r in mk.nearest_allowed_config(masks, wanted, ladder).collect()} == {1: 1, 2: 0}


def test_losses_by_hand(spark):
    p, q = [0.5, 0.3, 0.2], [0.4, 0.4, 0.2]
    frame = spark.createDataFrame([(p, q)], "p array<double>, q array<double>")
    row = frame.select(fw.divergence(F.col("p"), F.col("q")).alias("kl"), fw.entropy(F.col("q")).alias("h")).first()
    assert row.kl == pytest.approx(0.02526715, abs=1e-8) and row.h == pytest.approx(1.05492017, abs=1e-8)
    steps = spark.createDataFrame([(math.log(0.8), 1.0), (math.log(4 / 3), -1.0), (0.0, 0.5)], "r double, adv double")
    assert steps.agg(F.avg(fw.clipped_term(F.col("r"), F.lit(0.0), F.col("adv")))).first()[0] == pytest.approx(-0.01111111, abs=1e-7)


def test_empty_log(spark):
    log = registry.log_a(spark, SF).where("1 = 0")
    assert iv.concurrent_pairs(log).count() == iv.completion_samples(log).count() == st.makespan(log).count() == 0
    assert gn.scheduling_gain(iv.concurrent_pairs(log), st.avg_runtime(log)).count() == 0


@pytest.mark.parametrize("name", ["scheduling_gain", "completion_samples", "adaptive_mask_both", "schedule_random", "strategy_summary_user", "gae", "attention_forward", "state_status_counts"])
def test_against_duckdb(spark, name):
    con = duckdb.connect()
    for t in ("events", "orders", "customer", "lineitem", "supplier", "embeddings"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    got = registry.QUERIES[name](spark, SF).toPandas()
    want = con.execute(registry.ORACLES[name]).df()[list(got.columns)]
    key = lambda d: sorted(tuple(f"{x:.5f}" if isinstance(x, float | np.floating) else str(x) for x in r) for r in d.itertuples(index=False))
    assert len(got) == len(want) and [len(r) for r in key(got)] == [len(r) for r in key(want)]
    for c in got.columns:
        if got[c].dtype.kind in "if":
            assert np.allclose(np.sort(got[c].astype(float)), np.sort(want[c].astype(float)), atol=2e-6, equal_nan=True)
