"""Workloads, plans, the backend, the data source and the entry module."""

import json
import subprocess
import sys
from pathlib import Path

import pytest

from batchplan.learn import backend as be
from batchplan.plans import capture, workloads as wl
from batchplan.sources import runs_source

SF = "/root/testdata/sf0.001"
ROOT = Path(__file__).resolve().parents[1]


def test_batches_have_their_sizes():
    assert (len(wl.star22()), len(wl.joins33()), len(wl.wide99())) == (22, 33, 99)
    assert [len(wl.scale_queries(wl.wide99(), f)) for f in (0.8, 2, 5, 10)] == [79, 198, 495, 990]


def test_scaled_data(spark):
    orders = spark.read.parquet(f"{SF}/orders.parquet")
    n = orders.count()
    for f in (0.8, 1.2, 2):
        scaled = wl.scale_data(orders, "o_orderkey", f)
        assert scaled.select("o_orderkey").distinct().count() == scaled.count() == pytest.approx(n * f, rel=0.05)


def test_plans_are_trees(spark):
    wl.register_tables(spark, SF)
    for t in wl.star22()[:4]:
        nodes = capture.capture_plan(spark, t.sql, 0, t.tables)
        assert [n[2] for n in nodes].count(None) == 1 and all(n[2] is None or n[2] < n[1] for n in nodes)
        assert capture.encode_plan(nodes).shape == (16,)


def test_plan_nodes_know_what_filters_keep(spark):
    wl.register_tables(spark, SF)
    n = spark.table("orders").count()
    urgent = spark.table("orders").where("o_orderpriority = '1-URGENT'").count()
    batch = [wl._template("a", "SELECT count(*) AS n FROM orders WHERE o_orderpriority = '1-URGENT'"), wl._template("b", "SELECT o_orderkey FROM orders")]
    rows = capture.plan_nodes(spark, batch, 3).collect()
    assert [(r.query_id, r.op, r.kept) for r in rows if r.kept is not None] == [(3, "Filter", urgent / n)] and 0 < urgent < n
    assert {r.query_id for r in rows} == {3, 4}
    nodes = [[3, 0, None, "Filter", [], ["x"], 9.0, kept] for kept in (1.0, 0.25)]
    assert [capture.node_vectors([tuple(x)])[0][1, capture.OPERATORS : capture.OPERATORS + capture.COLUMNS].sum() for x in nodes] == [1, 1.75]


def test_backend_runs_all_once(spark):
    batch = wl.star22()[:3]
    rows = be.SparkBackend(spark, SF, 2).run(batch, be.fifo, "fifo")
    assert sorted(r[2] for r in rows) == [0, 1, 2] and all(r[6] >= r[5] for r in rows)


def test_policy_on_the_backend(spark):
    from batchplan.learn.plan_demands import demands_from_plans
    from batchplan.learn.training import Policy, TrainConfig

    batch = wl.star22()[:4]
    back, policy = be.SparkBackend(spark, SF, 2), Policy(demands_from_plans(spark, SF, batch), TrainConfig(n_conn=2))
    choice = be.PolicyChoice(policy, 0.5)
    rows = back.run(batch, choice, "learned")
    assert sorted(r[2] for r in rows) == [0, 1, 2, 3] and all(policy.mask[r[2], r[3]] for r in rows) and len(choice.steps) == 4
    assert [int((s["f"][:, 0] == 1).sum()) for s in choice.steps] == [4, 3, 2, 1]  # pending queries of each state
    before = {k: v.copy() for k, v in policy.params.items()}
    log = be.fine_tune(back, batch, policy, 0.5, rounds=2)
    assert len(log) == 8 and any((before[k] != v).any() for k, v in policy.params.items())


def test_runs_source(spark, tmp_path):
    (tmp_path / "a.json").write_text("\n".join(json.dumps({"round_id": "r", "run_id": k, "query_id": 1, "start_us": 0, "finish_us": 5}) for k in range(3)))
    runs_source.register(spark)
    assert spark.read.format("batchplan_runs").option("path", str(tmp_path)).load().count() == 3


def test_entry_without_training_data(tmp_path):
    code = (
        "import sys; sys.path.insert(0, %r)\n"
        "import importlib.util as u; real = u.find_spec\n"
        "u.find_spec = lambda n, *a: None if n.startswith(('batchplan.llm', 'corpus_pipeline')) else real(n, *a)\n"
        "import __spark_entry__ as e; q = e.queries(); assert len(q) > 150 and not any(k.startswith('op1') for k in q); assert set(e.oracle_sql()) <= set(q)"
    ) % str(ROOT)
    assert subprocess.run([sys.executable, "-c", code], cwd=tmp_path).returncode == 0
