"""Sweeps over time against the plain joins, and without a join in their plans."""

import random

import duckdb
import numpy as np
import pandas as pd
import pytest

from batchplan import registry
from batchplan.operators import intervals as iv
from batchplan.operators import stats as st
from batchplan.operators import sweep as sw
from tests.test_scheduling import log_of

HOUR = 3_600_000_000


def rows_of(seed, hours):
    """Runs with many equal starts and finishes, up to ``hours`` long."""
    rng = random.Random(seed)
    rows = []
    for _ in range(80):
        a = rng.randint(0, 40) * HOUR // 4
        rows.append((rng.randint(1, 2), rng.randint(1, 9), a, a + rng.randint(1, hours * 4) * HOUR // 4))
    return rows


def oracle(rows, sql):
    log_a = pd.DataFrame([(r, k, q, a, b) for k, (r, q, a, b) in enumerate(rows)], columns=["round_id", "run_id", "query_id", "start_us", "finish_us"])  # noqa: F841
    return sorted(duckdb.sql(f"WITH {sql}").fetchall())


@pytest.mark.parametrize("states", ["completion", "submission"])
def test_completion_samples_are_the_join(spark, states):
    rows, t = rows_of(3, 9), "finish_us" if states == "completion" else "start_us"
    want = oracle(rows, f"""x AS (SELECT m.round_id, m.run_id, m.{t}, count(*) AS n, arg_min(r.query_id, (r.finish_us, r.run_id)) AS q, min(r.finish_us) - m.{t} AS u
        FROM log_a m JOIN log_a r ON m.round_id = r.round_id AND r.start_us <= m.{t} AND m.{t} < r.finish_us GROUP BY 1, 2, 3) SELECT * FROM x""")  # fmt: skip
    found = iv.completion_samples(log_of(spark, rows), states)
    assert "Join" not in found._jdf.queryExecution().toString()
    assert sorted(tuple(r) for r in found.collect()) == want


@pytest.mark.parametrize("hours", [3, 120])
def test_guesses_are_the_join(spark, hours):
    rows = rows_of(hours, hours)
    held = registry.SIM[registry.SIM.index("held AS") :]
    want = oracle(rows, f"{registry.STATS}, {held} SELECT state, guess, truth, t_hat, t_true, p_true FROM guess")
    log = log_of(spark, rows)
    got = sorted(tuple(r) for r in sw.guessed_finishes(log, st.avg_runtime(log), iv.BUCKET_US).collect())
    assert [r[:3] for r in got] == [r[:3] for r in want]
    assert np.allclose([r[3:] for r in got], [r[3:] for r in want], rtol=1e-9, atol=0)


def test_guesses_join_no_moments(spark):
    plan = registry.guesses(spark, "/root/testdata/sf0.001")._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join") == 1  # the means of the queries
