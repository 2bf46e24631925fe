"""Forests and batches over a given table, and means rounded as the SQL's engine rounds them."""

import duckdb
import pytest

from batchplan import registry, workload_registry  # noqa: F401
from batchplan.plans import batches
from tests.test_scheduling import SF


def test_two_trees_by_hand(spark):
    nodes = spark.createDataFrame([(1, None), (2, 1), (3, 1), (4, 2), (9, None), (8, 9)], "node_id long, parent_id long")
    assert {tuple(r) for r in batches.plan_heights(nodes).collect()} == {(1, 2), (2, 1), (3, 0), (4, 0), (9, 1), (8, 0)}
    dist = {(r.node_a, r.node_b): r.dist for r in batches.plan_distances(nodes).collect()}
    assert len(dist) == 16 + 4 and (dist[4, 3], dist[3, 4], dist[1, 4], dist[8, 8], dist[9, 8]) == (3, 3, 2, 0, 1)


@pytest.mark.parametrize("name", ["extract_batches", "plan_heights", "plan_distances"])
def test_forests_come_from_orders(spark, name):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW orders AS SELECT * FROM '{SF}/orders.parquet'")
    found = registry.QUERIES[name](spark, SF)
    want = con.execute(registry.ORACLES[name]).fetchall()
    assert sorted(tuple(r) for r in found.collect()) == sorted(want) and len(want) >= con.execute("SELECT count(*) FROM orders").fetchall()[0][0]


def test_mean_half_way_between_two_results(spark):
    """40 values of sf0.01 have a mean of 62.28625, that is 62.286249999999995 as a double."""
    d = "/root/testdata/sf0.01"
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{d}/events.parquet'")
    pick = lambda rows: sorted((e, str(day)[:10], n, v) for e, day, n, v in rows)
    assert pick(map(tuple, registry.QUERIES["wide99_h11_4"](spark, d).collect())) == pick(con.execute(registry.ORACLES["wide99_h11_4"]).fetchall())
