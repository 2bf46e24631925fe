"""Sums of overlaps and merges against the plain ways."""

import itertools

import numpy as np
import pytest

from batchplan import registry
from batchplan.operators import gain as gn
from batchplan.operators import intervals as iv
from batchplan.operators import overlaps as ol
from batchplan.operators import stats as st
from batchplan.operators.overlaps import gain_blocks, never_met, overlap_sums
from tests.test_scheduling import SF, log_of
from tests.test_sweep import rows_of


@pytest.mark.parametrize("per_class", [1, 3, 100])
def test_sums_and_unseen_are_the_pairs(spark, per_class):
    log = log_of(spark, [*rows_of(5, 3), (3, 77, 0, 10)])
    want = {(r.qi, r.qj): r[2:] for r in gn.gain_sums(iv.concurrent_pairs(log)).collect()}
    rows = overlap_sums(log, per_class).collect()
    got = {(r.qi, r.qj): r[2:] for r in rows}
    assert len(rows) == len(got) and got.keys() == want.keys()
    assert all(np.allclose(got[k], want[k], rtol=1e-12) for k in want)
    q = sorted(r[0] for r in log.select("query_id").distinct().collect())
    unseen = [tuple(r) for r in never_met(log, per_class).collect()]
    assert sorted(unseen) == sorted(set(itertools.combinations(q, 2)) - want.keys()) and unseen


def test_runs_are_stored_once_for_any_number_of_classes(spark, monkeypatch):
    stored, dealt = [], ol._dealt
    monkeypatch.setattr(ol, "_dealt", lambda *x: stored.append(dealt(*x)) or stored[-1])
    log = log_of(spark, rows_of(5, 3))
    for per_class in (1, 100):
        sums = overlap_sums(log, per_class)
        assert "Exchange" not in sums._jdf.queryExecution().executedPlan().toString()
        assert spark.read.parquet(stored.pop()).count() == log.where("start_us < finish_us").count()


@pytest.mark.parametrize("per_class", [1, 3, 100])
def test_blocks_are_the_matrix_of_gains(spark, per_class):
    log = log_of(spark, [*rows_of(5, 3), (3, 77, 0, 10)])
    stats = st.avg_runtime(log)
    names, times = (np.array(x) for x in zip(*sorted((r.query_id, r.avg_us) for r in stats.collect()), strict=True))
    gain = gn.gain_from_sums(overlap_sums(log, per_class), stats)
    want = {(r.qi, r.qj): r.gain for r in gain.collect()}
    got: dict = {}
    for r in gain_blocks(log, names, times, per_class).collect():
        left, right = (np.frombuffer(x, np.int64).tolist() for x in (r.left, r.right))
        for (i, j), g in zip(itertools.product(left, right), np.frombuffer(r.gain).tolist(), strict=True):
            if (i, j) not in got:
                got[i, j] = got[j, i] = g
            assert got[i, j] == g
    assert all(got[p] == got[p[::-1]] == want.get(p, 0.0) for p in itertools.combinations(names.tolist(), 2))
    for a, b in zip(gn.cluster_log(log, stats, 2), gn.cluster_by_gain(gain, stats, 2), strict=True):
        assert a.schema == b.schema and a.collect() == b.collect()


def test_clusters_get_blocks_not_rows(spark, monkeypatch):
    sent, merged = [], gn._merged
    monkeypatch.setattr(gn, "_merged", lambda rows, *how: sent.append(rows.columns) or merged(rows, *how))
    assert registry.QUERIES["cluster_merges"](spark, SF).count() and sent == [["left", "right", "gain"]]
    monkeypatch.setattr(gn, "ONE_TASK", 1)
    few = log_of(spark, rows_of(5, 3))
    assert gn.cluster_log(few, st.avg_runtime(few), 2)[0].count() == few.select("query_id").distinct().count()


def test_gains_make_no_pairs_of_runs(spark):
    for name in ("scheduling_gain", "unseen_pairs", "gain_symmetry"):
        plan = registry.QUERIES[name](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
        assert "start_i" not in plan and "start_e" not in plan


def test_pairs_do_not_move_to_their_vectors(spark):
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = registry.QUERIES["gain_symmetry"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert plan.count("BroadcastHashJoin") == 2 and "hashpartitioning(qi#" not in plan and "hashpartitioning(qj#" not in plan


@pytest.mark.parametrize("lens", [(64, 64, 64), (64, 3, 64), (2, 2, 5)])
def test_gain_model_of_any_lengths(spark, lens):
    x = spark.createDataFrame([(k, [0.01 * (k + 1) * (i % 7) for i in range(n)]) for k, n in enumerate(lens)], "vec_id long, x array<double>")
    pairs = spark.createDataFrame(list(itertools.combinations(range(3), 2)), "qi long, qj long")
    got = {(r.qi, r.qj): r.g for r in registry.with_vectors(pairs, x).select("qi", "qj", registry.halved_gain().alias("g")).collect()}
    a, b = (x.toDF(f"q{n}", f"x{n}") for n in "ij")
    want = {(r.qi, r.qj): r.g for r in pairs.join(a, "qi").join(b, "qj").select("qi", "qj", registry.pair_gain(a.xi, b.xj).alias("g")).collect()}
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-12 for k in want)


def test_terms_keep_their_pairs_in_place(spark):
    plan = registry.QUERIES["gain_terms"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("BroadcastHashJoin") >= 2 and "hashpartitioning(query_i#" not in plan


def test_linkage_is_the_greedy_order():
    rng = np.random.default_rng(4)
    for n in (2, 9, 40):
        mean = rng.integers(-3, 4, (n, n)).astype(float)  # many ties
        mean = np.triu(mean, 1) + np.triu(mean, 1).T
        plain, size, live, want = mean.copy(), np.ones(n), list(range(n)), []
        while len(live) > 1:
            i, j = min(itertools.combinations(live, 2), key=lambda p: (-plain[p], p))
            want.append((i, j, plain[i, j]))
            plain[i] = plain[:, i] = (size[i] * plain[i] + size[j] * plain[j]) / (size[i] + size[j])
            size[i] += size[j]
            live.remove(j)
        assert gn.linkage(mean, 1) == want


def test_rounding_half_away_from_zero(spark):
    x = spark.createDataFrame([(0.0078125,), (-0.0078125,), (-1e-9,), (0.1234564999,)], "x double")
    assert [r[0] for r in x.select(registry.six("x")).collect()] == [0.007813, -0.007813, 0.0, 0.123456]
