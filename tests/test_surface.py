"""SQL functions and views, and the stateful stream."""

from batchplan.functions import sql_surface
from batchplan.streaming import arriving, running_set

SF = "/root/testdata/sf0.001"


def test_sql_functions(spark):
    sql_surface.register(spark, SF)
    assert spark.sql("SELECT count(*) FROM gains").first()[0] == 105
    spark.createDataFrame([("a", k, c) for k, c in ((1, 2), (2, 3), (3, 4), (4, 6), (5, 9))], "scenario string, query_id long, cost long").createOrReplaceTempView("jobs")
    made = spark.sql("SELECT * FROM list_schedule(TABLE(SELECT *, 2 AS n_conn FROM jobs) PARTITION BY scenario ORDER BY query_id)").orderBy("seq").collect()
    assert [(r.query_id, r.conn_id, r.finish_us) for r in made] == [(1, 0, 2), (2, 1, 3), (3, 0, 6), (4, 1, 9), (5, 0, 15)]
    assert spark.sql("SELECT busy_makespan(cost, 2) FROM jobs").first()[0] == 12
    assert spark.sql("SELECT count(*) FROM permutations(4)").first()[0] == 96
    assert spark.sql("SELECT improvement(8D, 10D), clipped(1.5D, 1D, 0.2D)").first()[:] == (0.19999999999999996, 1.2)


def test_sessions_are_no_table_in_memory(spark):
    from __spark_entry__ import queries

    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    got = queries()["stream_sessions"](spark, SF)
    assert got.inputFiles() and got.agg({"runs": "sum"}).first()[0] == spark.read.parquet(f"{SF}/events.parquet").where("round(value * 100) > 0").count()
    assert spark.conf.get(key) == before


def test_running_set_stream(spark, tmp_path):
    rows = [("e", 1, 10, "submit", 0), ("e", 2, 20, "submit", 1), ("e", 2, 20, "finish", 5), ("e", 3, 30, "submit", 5), ("e", 1, 10, "finish", 9), ("e", 3, 30, "finish", 12)]
    frame = spark.createDataFrame(rows, "env string, run_id long, query_id long, kind string, t_us long")
    frame.coalesce(1).write.parquet(f"{tmp_path}/events")
    stream = arriving.event_stream(spark, f"{tmp_path}/events")
    got = arriving.drain(running_set.completion_stream(stream), "running_set", "append").orderBy("t_us").collect()
    assert [(r.running_n, r.next_query_id, r.since_us) for r in got] == [(2, 20, 5), (2, 10, 4), (1, 30, 3)]
