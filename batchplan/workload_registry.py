"""Registered queries: the workloads, their scalings, and the surrounding relational toolkit."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from batchplan.plans import capture, workloads as wl
from batchplan.registry import A, LOG_A, entry, log_a, r6, supplier
from batchplan.operators import intervals as iv
from batchplan.operators import stats as st
from batchplan.sources.logs import table

for _t in wl.star22():
    entry(f"star22_{_t.name}", _t.sql)(lambda s, d, t=_t: wl.run(s, d, t))
for _t in wl.joins33():
    entry(f"joins33_{_t.name}", _t.sql)(lambda s, d, t=_t: wl.run(s, d, t))
for _t in wl.wide99():
    entry(f"wide99_{_t.name}", _t.sql)(lambda s, d, t=_t: wl.run(s, d, t))


def both(name: str, sql: str, duck: str | None = None) -> None:
    """A toolkit entry whose SQL both engines run (or with DuckDB's own form)."""
    entry(name, duck or sql)(lambda s, d, t=wl._template(name, sql): wl.run(s, d, t))


@entry("rewrite_slow_equal", "SELECT CAST(0 AS BIGINT) AS differing")
def rewrite_slow_equal(s: SparkSession, d: str) -> DataFrame:
    wl.register_tables(s, d, ("lineitem",))
    a, b = s.sql(wl.SLOW), s.sql(wl.FAST)
    return a.exceptAll(b).unionByName(b.exceptAll(a)).agg(F.count("*").alias("differing"))


for _f in (0.8, 0.9, 1.1, 1.2):
    _n = f"{round(_f * 10):02d}"
    _where = f"WHERE {{k}} % 10 < {round(_f * 10)}" if _f < 1 else f"UNION ALL SELECT * FROM {{t}} WHERE {{k}} % 10 < {round(_f * 10) - 10}"
    entry(f"scale_data_{_n}", f"SELECT count(*) AS n, CAST(sum(o_custkey) AS BIGINT) AS total FROM (SELECT * FROM orders {_where.format(k='o_orderkey', t='orders')})")(
        lambda s, d, f=_f: wl.scale_data(table(s, d, "orders"), "o_orderkey", f).agg(F.count("*").alias("n"), F.sum("o_custkey").alias("total"))
    )
    entry(f"scale_queries_{_n}", f"WITH c AS (SELECT l_suppkey AS q, CAST(sum(l_quantity) AS BIGINT) AS cost FROM lineitem GROUP BY 1) SELECT count(*) AS n, CAST(sum(cost) AS BIGINT) AS total FROM (SELECT * FROM c {_where.format(k='q', t='c')})")(
        lambda s, d, f=_f: wl.scale_data(supplier(s, d), "query_id", f).agg(F.count("*").alias("n"), F.sum("cost").alias("total"))
    )

# --- plans --------------------------------------------------------------------------------------


@entry("plan_nodes")
def plan_nodes(s: SparkSession, d: str) -> DataFrame:
    wl.register_tables(s, d)
    return capture.plan_nodes(s, wl.star22())


entry("plan_embeddings")(lambda s, d: r6(capture.encode_plans(plan_nodes(s, d)).select("query_id", F.posexplode("embedding").alias("pos", "value"))))
entry(
    "column_histograms",
    """WITH e AS (SELECT min(o_totalprice) AS lo, (max(o_totalprice) - min(o_totalprice)) / 8 AS w FROM orders),
    b AS (SELECT least(7, CAST(floor((o_totalprice - lo) / w) AS INTEGER)) AS bin, lo, w FROM orders, e)
    SELECT 'o_totalprice' AS col, bin, round(any_value(lo) + bin * any_value(w), 4) AS lo, round(any_value(lo) + (bin + 1) * any_value(w), 4) AS hi, count(*) AS rows FROM b GROUP BY bin""",
)(lambda s, d: capture.column_histograms(table(s, d, "orders"), ["o_totalprice"]))

# --- toolkit ------------------------------------------------------------------------------------

entry("tk_asof", f"""{A} SELECT e.event_id, max(r.start_us) AS last_start_us FROM (SELECT event_id, user_id, epoch_us(ts) AS t FROM events) e LEFT JOIN log_a r ON r.query_id = e.user_id AND r.start_us <= e.t GROUP BY 1""")(
    lambda s, d: iv.as_of(
        table(s, d, "events").select("event_id", F.col("user_id").alias("query_id"), F.unix_micros(F.col("ts").cast("timestamp")).alias("start_us")),
        log_a(s, d).select("query_id", "start_us"), ["query_id"], "start_us", "start_us",
    ).select("event_id", "last_start_us")
)
both("tk_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')")
both("tk_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')")
both("tk_full", "SELECT coalesce(a.k, -1) AS ak, coalesce(b.k, -1) AS bk, coalesce(an, -1) AS an, coalesce(bn, -1) AS bn FROM (SELECT user_id AS k, count(*) AS an FROM events GROUP BY user_id) a FULL OUTER JOIN (SELECT s_suppkey AS k, count(*) AS bn FROM supplier GROUP BY s_suppkey) b ON a.k = b.k")
both("tk_cross", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a CROSS JOIN nation b WHERE a.n_nationkey < b.n_nationkey")
both("tk_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier UNION ALL SELECT n_nationkey FROM nation")
both("tk_intersect", "SELECT o_custkey AS k FROM orders INTERSECT SELECT user_id FROM events")
both("tk_except", "SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders")
both("tk_topk_per_group", "SELECT user_id, event_id, r FROM (SELECT user_id, event_id, rank() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS r FROM events) x WHERE r <= 3")
both("tk_frames_rows", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS moving FROM events")
both("tk_frames_range", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS near FROM orders")
both("tk_ntile", "SELECT o_orderkey, ntile(10) OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey) AS bucket FROM orders")
both("tk_lead_lag", "SELECT event_id, coalesce(lag(event_id) OVER w, -1) AS before, coalesce(lead(event_id) OVER w, -1) AS after, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
both("tk_distinct", "SELECT user_id, count(DISTINCT event_type) AS kinds, count(DISTINCT CAST(ts AS DATE)) AS days FROM events GROUP BY user_id")
both("tk_percentile_exact", "SELECT event_type, round(percentile_cont(0.5) WITHIN GROUP (ORDER BY value), 6) AS median FROM events GROUP BY event_type")
both("tk_grouping_sets", "SELECT coalesce(event_type, '') AS event_type, coalesce(user_id % 10, -1) AS u, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type, user_id % 10), (event_type), ())")
both("tk_corr", "SELECT event_type, round(corr(value, CAST(user_id AS DOUBLE)), 6) AS r FROM events GROUP BY event_type")
both("tk_string", "SELECT doc_id, CAST(length(text) AS BIGINT) AS n, lower(substr(text, 1, 5)) AS head, md5(coalesce(source, '')) AS h, CAST(length(regexp_replace(text, '[aeiou]', '')) AS BIGINT) AS rest FROM documents", "SELECT doc_id, CAST(length(text) AS BIGINT) AS n, lower(substr(text, 1, 5)) AS head, md5(coalesce(source, '')) AS h, length(regexp_replace(text, '[aeiou]', '', 'g')) AS rest FROM documents")
both("tk_datetime", "SELECT event_id, year(ts) AS y, month(ts) AS m, hour(ts) AS h, CAST(date_trunc('week', ts) AS DATE) AS week FROM events")
both("tk_json", "SELECT CAST(get_json_object(props, '$.k') AS INT) AS k, count(*) AS n FROM events GROUP BY 1", "SELECT CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")
both(
    "tk_array_hof",
    "SELECT vec_id, round(aggregate(transform(embedding, x -> CAST(x AS DOUBLE) * x), 0D, (s, x) -> s + x), 4) AS square, size(filter(embedding, x -> x > 0)) AS positive FROM embeddings",
    "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS square, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive FROM embeddings",
)
both("tk_map", "SELECT user_id, map_from_entries(array_sort(collect_set(struct(event_type, 1))))['click'] AS click FROM events GROUP BY user_id", "SELECT user_id, max(CASE WHEN event_type = 'click' THEN 1 END) AS click FROM events GROUP BY user_id")
entry("tk_pivot", "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY user_id")(
    lambda s, d: table(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).na.fill(0)
)
both("tk_tumbling", "SELECT window(CAST(ts AS TIMESTAMP), '1 day').start AS t, count(*) AS n FROM events GROUP BY window(CAST(ts AS TIMESTAMP), '1 day')", "SELECT date_trunc('day', ts) AS t, count(*) AS n FROM events GROUP BY 1")
