"""The registered queries of the scheduling methods, each with the SQL that DuckDB checks it by."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from batchplan.functions import forward as fw
from batchplan.operators import gain as gn
from batchplan.operators import intervals as iv
from batchplan.operators import masks as mk
from batchplan.operators import schedules as sc
from batchplan.operators import stats as st
from batchplan.operators import sweep as sw
from batchplan.operators.overlaps import never_met, overlap_sums
from batchplan.plans import batches
from batchplan.sources import logs
from batchplan.sources.logs import table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
N_CONN = 4


def entry(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def r6(df: DataFrame) -> DataFrame:
    """df with doubles rounded to six digits, as the oracles have them."""
    return df.select(*[F.round(F.col(c), 6).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def six(c: str) -> Column:
    """Column c rounded to six digits, half away from zero, without the decimals that ``round`` goes through for each value."""
    scaled = F.abs(c) * 1e6
    whole = F.floor(scaled)
    near = (whole + F.when(scaled - whole >= 0.5, 1).otherwise(0)) / 1e6
    return F.when(F.col(c) < 0, 0.0 - near).otherwise(near).alias(c)


def cents(df: DataFrame) -> DataFrame:
    """df with mean times rounded to hundredths of a microsecond: a double has no more digits."""
    return df.withColumn("avg_us", F.round("avg_us", 2))


def log_a(spark: SparkSession, d: str) -> DataFrame:
    return logs.log_from_events(table(spark, d, "events"))


def log_b(spark: SparkSession, d: str) -> DataFrame:
    return logs.log_from_orders(table(spark, d, "orders"), table(spark, d, "customer"))


LOG_A = """log_a AS (
  SELECT CAST(ts AS DATE) AS round_id, event_id AS run_id, user_id AS query_id,
         CAST(list_position(['click', 'error', 'purchase', 'signup', 'view'], event_type) - 1 AS INTEGER) AS config_id,
         CAST(CAST(json_extract_string(props, '$.k') AS INTEGER) % 8 AS INTEGER) AS conn_id, epoch_us(ts) AS start_us,
         epoch_us(ts) + CAST(round(value * 100) AS BIGINT) * 600000 AS finish_us
  FROM events WHERE CAST(round(value * 100) AS BIGINT) > 0)"""
LOG_B = """log_b AS (
  SELECT CAST(date_trunc('month', o_orderdate) AS DATE) AS round_id, o_orderkey AS run_id, CAST(c_nationkey AS BIGINT) AS query_id,
         CAST(substr(o_orderpriority, 1, 1) AS INTEGER) - 1 AS config_id, epoch_us(o_orderdate) AS start_us,
         epoch_us(o_orderdate) + CAST(round(o_totalprice * 100) AS BIGINT) * 10000 AS finish_us
  FROM orders JOIN customer ON o_custkey = c_custkey WHERE CAST(round(o_totalprice * 100) AS BIGINT) > 0)"""
STATS = "stats AS (SELECT query_id, count(*) AS runs, avg(finish_us - start_us) AS avg_us FROM log_a GROUP BY query_id)"
PAIRS = """pairs AS (
  SELECT i.round_id, i.run_id AS run_i, j.run_id AS run_j, i.query_id AS query_i, j.query_id AS query_j,
         i.finish_us - i.start_us AS dur_i, j.finish_us - j.start_us AS dur_j,
         least(i.finish_us, j.finish_us) - greatest(i.start_us, j.start_us) AS ov_us
  FROM log_a i JOIN log_a j ON i.round_id = j.round_id AND i.query_id < j.query_id AND i.start_us < j.finish_us AND j.start_us < i.finish_us)"""
TERMS = """terms AS (
  SELECT p.*, s.avg_us AS mean_i, t.avg_us AS mean_j, ov_us / dur_i AS o_ij, 1 - dur_i / s.avg_us AS a_ij, ov_us / dur_j AS o_ji, 1 - dur_j / t.avg_us AS a_ji
  FROM pairs p JOIN stats s ON s.query_id = query_i JOIN stats t ON t.query_id = query_j)"""
GAIN = """gain AS (
  SELECT query_i AS qi, query_j AS qj, count(*) AS m_c,
         avg((sqrt(mean_i) * o_ij * a_ij + sqrt(mean_j) * o_ji * a_ji) / (sqrt(mean_i) + sqrt(mean_j))) AS gain
  FROM terms GROUP BY 1, 2)"""
PROFILE = "profile AS (SELECT query_id, config_id, count(*) AS runs, avg(finish_us - start_us) AS avg_us FROM log_b GROUP BY 1, 2)"
A = f"WITH {LOG_A}"
G = f"WITH {LOG_A}, {STATS}, {PAIRS}, {TERMS}, {GAIN}"

# --- logs and statistics ---------------------------------------------------------------------

entry("log_a_runs", f"{A} SELECT * FROM log_a")(log_a)
entry("log_b_runs", f"WITH {LOG_B} SELECT * FROM log_b")(log_b)
entry("avg_runtime", f"{A}, {STATS} SELECT query_id, runs, round(avg_us, 2) AS avg_us FROM stats")(lambda s, d: cents(st.avg_runtime(log_a(s, d))))
entry("config_profile", f"WITH {LOG_B}, {PROFILE} SELECT query_id, config_id, runs, round(avg_us, 2) AS avg_us FROM profile")(lambda s, d: cents(st.config_profile(log_b(s, d))))
for _kind in ("rollup", "cube"):
    entry(
        f"config_{_kind}",
        f"WITH {LOG_B} SELECT coalesce(query_id, -1) AS query_id, coalesce(config_id, -1) AS config_id, CAST(grouping(query_id) * 2 + grouping(config_id) AS INTEGER) AS grouping_id, count(*) AS runs, round(avg(finish_us - start_us), 2) AS avg_us FROM log_b GROUP BY {_kind}(query_id, config_id)",
    )(lambda s, d, cube=_kind == "cube": cents(st.config_rollup(log_b(s, d), cube)).na.fill(-1))
entry("first_run_per_round", f"{A} SELECT round_id, query_id, run_id, start_us, finish_us FROM log_a QUALIFY row_number() OVER (PARTITION BY round_id, query_id ORDER BY start_us, run_id) = 1")(lambda s, d: logs.first_run_per_round(log_a(s, d)))
entry("round_makespan", f"{A} SELECT round_id, max(finish_us) - min(start_us) AS makespan_us FROM log_a GROUP BY 1")(lambda s, d: st.makespan(log_a(s, d)))
MAKESPANS = "spans AS (SELECT round_id, max(finish_us) - min(start_us) AS makespan_us FROM log_a GROUP BY 1)"
entry("makespan_summary", f"{A}, {MAKESPANS} SELECT count(*) AS rounds, round(avg(makespan_us), 4) AS avg_us, round(stddev_pop(makespan_us), 2) AS std_us FROM spans")(
    lambda s, d: st.makespan_summary(st.makespan(log_a(s, d))).select("rounds", F.round("avg_us", 4).alias("avg_us"), F.round("std_us", 2).alias("std_us"))
)
entry(
    "concurrency_profile",
    f"""{A}, marks AS (SELECT round_id, start_us AS t, 1 AS d FROM log_a UNION ALL SELECT round_id, finish_us, -1 FROM log_a),
    run AS (SELECT round_id, sum(d) OVER (PARTITION BY round_id ORDER BY t, d ROWS UNBOUNDED PRECEDING) AS n FROM marks)
    SELECT round_id, CAST(max(n) AS BIGINT) AS peak, any_value(b) AS avg_running FROM run
    JOIN (SELECT round_id AS r, round(sum(finish_us - start_us) / (max(finish_us) - min(start_us)), 6) AS b FROM log_a GROUP BY 1) ON r = round_id GROUP BY round_id""",
)(lambda s, d: r6(st.concurrency_profile(log_a(s, d))))
entry(
    "degradation_flags",
    f"""{A}, {MAKESPANS}, m AS (SELECT *, avg(makespan_us) OVER (ORDER BY round_id ROWS BETWEEN 5 PRECEDING AND 1 PRECEDING) AS moving_avg FROM spans)
    SELECT round_id, makespan_us, round(moving_avg, 4) AS moving_avg, coalesce(makespan_us > moving_avg * 1.1::DOUBLE, false) AS flag FROM m""",
)(lambda s, d: st.degradation_flags(st.makespan(log_a(s, d))).withColumn("moving_avg", F.round("moving_avg", 4)))

# --- intervals, samples and state ------------------------------------------------------------

entry("concurrent_pairs", f"{A}, {PAIRS} SELECT * FROM pairs")(lambda s, d: iv.concurrent_pairs(log_a(s, d)))
for _name, _t in (("completion_samples", "finish_us"), ("completion_samples_submission", "start_us")):
    entry(
        _name,
        f"""{A} SELECT m.round_id, m.run_id AS state_run_id, m.{_t} AS t_us, count(*) AS running_n, arg_min(r.query_id, (r.finish_us, r.run_id)) AS next_query_id,
        min(r.finish_us) - m.{_t} AS remaining_us FROM log_a m JOIN log_a r ON m.round_id = r.round_id AND r.start_us <= m.{_t} AND m.{_t} < r.finish_us GROUP BY 1, 2, 3""",
    )(lambda s, d, states="completion" if _t == "finish_us" else "submission": iv.completion_samples(log_a(s, d), states))
entry(
    "aux_targets_absolute",
    f"""{A} SELECT m.run_id, min(r.finish_us) AS next_finish_us FROM log_a m JOIN log_a r ON m.round_id = r.round_id AND r.start_us <= m.start_us AND m.start_us < r.finish_us GROUP BY 1""",
)(lambda s, d: iv.completion_samples(log_a(s, d), "submission").select(F.col("state_run_id").alias("run_id"), (F.col("t_us") + F.col("remaining_us")).alias("next_finish_us")))
entry(
    "state_status_counts",
    f"""{A} SELECT m.round_id, m.run_id, count(*) FILTER (r.start_us > m.start_us) AS pending, count(*) FILTER (r.start_us <= m.start_us AND r.finish_us > m.start_us) AS running,
    count(*) FILTER (r.finish_us <= m.start_us) AS finished FROM log_a m JOIN log_a r ON m.round_id = r.round_id GROUP BY 1, 2""",
)(lambda s, d: iv.state_status_counts(log_a(s, d)))


@entry(
    "running_features",
    f"""{A}, {STATS}, moment AS (SELECT round_id, (min(start_us) + max(start_us)) // 2 AS t FROM log_a GROUP BY 1),
    f AS (SELECT run_id, CASE WHEN start_us > t THEN 0 WHEN finish_us > t THEN 1 ELSE 2 END AS status, config_id, CASE WHEN start_us <= t AND finish_us > t THEN t - start_us ELSE 0 END AS elapsed, avg_us,
          (SELECT max(avg_us) FROM stats) AS t_max FROM log_a JOIN stats USING (query_id) JOIN moment USING (round_id)),
    v AS (SELECT run_id, unnest([CAST(status = 0 AS DOUBLE), CAST(status = 1 AS DOUBLE), CAST(status = 2 AS DOUBLE)]
          || list_transform([0, 1, 2, 3, 4], lambda k: CASE WHEN status > 0 AND k = config_id THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) || [elapsed / t_max, avg_us / t_max]) AS value,
          generate_subscripts([1, 2, 3, 4, 5, 6, 7, 8, 9, 10], 1) - 1 AS pos FROM f)
    SELECT run_id, CAST(pos AS INTEGER) AS pos, round(value, 6) AS value FROM v""",
)
def running_features(s: SparkSession, d: str) -> DataFrame:
    """The features of every round's runs at the middle of its starts."""
    log = log_a(s, d)
    stats = st.avg_runtime(log)
    at = log.groupBy("round_id").agg(F.expr("(min(start_us) + max(start_us)) DIV 2").alias("t"))
    t_max = stats.agg(F.max("avg_us").alias("t_max"))  # one row
    rows = log.join(stats, "query_id").join(at, "round_id").join(F.broadcast(t_max))
    status = F.when(F.col("start_us") > F.col("t"), 0).when(F.col("finish_us") > F.col("t"), 1).otherwise(2)
    elapsed = F.when(status == 1, F.col("t") - F.col("start_us")).otherwise(0)
    v = fw.running_features(status, F.col("config_id"), 5, elapsed, F.col("avg_us"), F.col("t_max"))
    return r6(rows.select("run_id", F.posexplode(v).alias("pos", "value")))


# --- gains and clusters ----------------------------------------------------------------------

def gains(s: SparkSession, d: str) -> DataFrame:
    log = log_a(s, d)
    return gn.gain_from_sums(overlap_sums(log), st.avg_runtime(log))


entry("gain_terms", f"{G} SELECT run_i, run_j, round(o_ij, 6) AS o_ij, round(a_ij, 6) AS a_ij, round(o_ji, 6) AS o_ji, round(a_ji, 6) AS a_ji FROM terms")(
    lambda s, d: gn.gain_terms(iv.concurrent_pairs(log_a(s, d)), st.avg_runtime(log_a(s, d))).select("run_i", "run_j", *[six(c) for c in ("o_ij", "a_ij", "o_ji", "a_ji")])
)
entry("scheduling_gain", f"{G} SELECT qi, qj, m_c, round(gain, 6) AS gain FROM gain")(lambda s, d: r6(gains(s, d)))
entry("top_gain_pairs", f"{G} SELECT qi, qj, m_c, round(gain, 6) AS gain FROM gain ORDER BY round(gain, 6) DESC, qi, qj LIMIT 20")(lambda s, d: r6(gains(s, d)).orderBy(F.desc("gain"), "qi", "qj").limit(20))
entry("gain_from_sums", f"{G} SELECT qi, qj, m_c, round(gain, 6) AS gain FROM gain")(lambda s, d: r6(gn.gain_from_sums(overlap_sums(log_a(s, d)), st.avg_runtime(log_a(s, d)))))
UNSEEN = "unseen AS (SELECT a.query_id AS qi, b.query_id AS qj FROM stats a JOIN stats b ON a.query_id < b.query_id WHERE NOT EXISTS (SELECT 1 FROM gain g WHERE g.qi = a.query_id AND g.qj = b.query_id))"
entry("unseen_pairs", f"{G}, {UNSEEN} SELECT qi, qj FROM unseen")(lambda s, d: never_met(log_a(s, d)))
W = lambda i, j: f"((({i}) * 7919 + ({j}) * 104729) % 2001 - 1000) / 1000.0::DOUBLE"


def sql_dense(vec: str, n: int, shift: int, act: bool) -> str:
    """DuckDB's form of a pinned layer."""
    total = f"list_sum(list_transform({vec}, lambda x, i: x * {W(f'i - 1 + {shift}', 'j')}))"
    return f"list_transform(range({n}), lambda j: {'tanh(' + total + ')' if act else total})"


EMB = "emb AS (SELECT vec_id, label, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS x FROM embeddings)"
GMODEL = f"({sql_dense(sql_dense('a.x || b.x', 4, 300, True), 1, 400, False)})[1] + ({sql_dense(sql_dense('b.x || a.x', 4, 300, True), 1, 400, False)})[1]"


WIDTH = 64  # of a vector of ``embeddings``


def emb(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "embeddings").select("vec_id", "label", F.transform("embedding", lambda x: x.cast("double")).alias("x"))


def pair_gain(a: Column, b: Column) -> Column:
    """The symmetric gain model with pinned weights."""
    one = lambda x, y: F.element_at(fw.dense(fw.dense(F.concat(x, y), 4, 300), 1, 400, None), 1)
    return one(a, b) + one(b, a)


def halves(x: DataFrame) -> DataFrame:
    """x with what each vector of WIDTH gives to the first layer, as first and as second of two: once for each vector, not each pair."""
    whole = F.size("x") == WIDTH
    return x.withColumn("p", F.when(whole, fw.dense(F.col("x"), 4, 300, None))).withColumn("q", F.when(whole, fw.dense(F.col("x"), 4, 300 + WIDTH, None)))


def halved_gain() -> Column:
    """pair_gain of xi and xj by their halves; pair_gain itself for vectors of other lengths."""
    one = lambda p, q: F.element_at(fw.dense(F.zip_with(p, q, lambda u, v: F.tanh(u + v)), 1, 400, None), 1)
    fast = one(F.col("pi"), F.col("qj_")) + one(F.col("pj"), F.col("qi_"))
    return F.when(F.col("pi").isNotNull() & F.col("pj").isNotNull(), fast).otherwise(pair_gain(F.col("xi"), F.col("xj")))


def paired(s: SparkSession, d: str) -> DataFrame:
    """The vectors of all pairs of queries that the log has seen together."""
    log, x = log_a(s, d), emb(s, d).select("vec_id", "x")
    return with_vectors(overlap_sums(with_vector(log, x)).select("qi", "qj"), of_queries(x, log))


def with_vector(log: DataFrame, x: DataFrame) -> DataFrame:
    """The runs of queries that have a vector: a pair needs two."""
    ids = of_queries(x, log).select(F.col("vec_id").alias("query_id")).distinct()
    return log.join(F.broadcast(ids), "query_id", "left_semi")  # no more than queries, and runs stay where they are


def of_queries(x: DataFrame, log: DataFrame) -> DataFrame:
    """The vectors of the log's queries."""
    return x.join(log.select(F.col("query_id").alias("vec_id")).distinct(), "vec_id", "left_semi")


def with_vectors(pairs: DataFrame, x: DataFrame) -> DataFrame:
    """Pairs with what ``halved_gain`` needs of the vectors x of a log's queries; whole vectors only if any is not of WIDTH.

    The halves (two times four numbers for each query) are broadcast: pairs are many, and stay where they are.
    """
    whole = x.where(F.coalesce(F.size("x"), F.lit(-1)) == WIDTH).count() == x.count()
    kept = halves(x).withColumn("x", F.lit(None).cast("array<double>")) if whole else halves(x)
    side = lambda n: kept.select(F.col("vec_id").alias(f"q{n}"), F.col("x").alias(f"x{n}"), F.col("p").alias(f"p{n}"), F.col("q").alias(f"q{n}_"))
    i, j = (F.broadcast(side(n)) if whole else side(n) for n in "ij")
    return pairs.join(i, "qi").join(j, "qj")


entry("gain_model_forward", f"{G}, {EMB} SELECT qi, qj, round({GMODEL}, 6) AS gain_hat FROM gain JOIN emb a ON a.vec_id = qi JOIN emb b ON b.vec_id = qj")(
    lambda s, d: r6(paired(s, d).select("qi", "qj", halved_gain().alias("gain_hat")))
)
entry("gain_symmetry", f"{G}, {EMB} SELECT qi, qj, round({GMODEL.replace('a.x', 'c.x').replace('b.x', 'a.x').replace('c.x', 'b.x')}, 6) AS turned FROM gain JOIN emb a ON a.vec_id = qi JOIN emb b ON b.vec_id = qj")(
    lambda s, d: r6(paired(s, d).select("qi", "qj", halved_gain().alias("turned")))
)


@entry(
    "complete_gain",
    f"""{G}, {UNSEEN}, {EMB} SELECT qi, qj, round(gain, 6) AS gain, 'log' AS source FROM gain
    UNION ALL SELECT qi, qj, round({GMODEL}, 6), 'model' FROM unseen JOIN emb a ON a.vec_id = qi JOIN emb b ON b.vec_id = qj""",
)
def complete_gain(s: SparkSession, d: str) -> DataFrame:
    log, x = log_a(s, d), emb(s, d).select("vec_id", "x")
    unseen = with_vectors(never_met(with_vector(log, x)), of_queries(x, log))
    return r6(gn.complete_gain(gains(s, d), unseen, halved_gain()))


entry("cluster_by_gain")(lambda s, d: gn.cluster_log(log_a(s, d), st.avg_runtime(log_a(s, d)), 5)[0])
entry("cluster_merges")(lambda s, d: r6(gn.cluster_log(log_a(s, d), st.avg_runtime(log_a(s, d)), 5)[1]))
entry("cluster_pool", "SELECT label AS cluster_id, CAST(pos AS INTEGER) AS pos, round(sum(v), 5) AS value FROM (SELECT label, unnest(embedding)::DOUBLE AS v, generate_subscripts(embedding, 1) - 1 AS pos FROM embeddings) GROUP BY 1, 2")(
    lambda s, d: gn.pool_clusters(table(s, d, "embeddings"), table(s, d, "embeddings").select("vec_id", F.col("label").alias("cluster_id")), "vec_id").withColumn("value", F.round("value", 5))
)

# --- masks -----------------------------------------------------------------------------------

B = f"WITH {LOG_B}, {PROFILE}"
IMPROVED = "improved AS (SELECT query_id, config_id, avg_us, prior - avg_us AS abs_gain_us, (prior - avg_us) / prior AS rel_gain FROM (SELECT *, lag(avg_us) OVER (PARTITION BY query_id ORDER BY config_id) AS prior FROM profile))"
BEST = IMPROVED.replace("lag(avg_us) OVER (PARTITION BY query_id ORDER BY config_id)", "min(avg_us) OVER (PARTITION BY query_id ORDER BY config_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)")
MASK = "mask AS (SELECT query_id, config_id, abs_gain_us IS NULL OR (abs_gain_us >= 0.05::DOUBLE * avg(avg_us) OVER (PARTITION BY query_id) {op} rel_gain >= 0.05) AS allowed FROM improved)"


def improved(s: SparkSession, d: str, against: str = "next_lower") -> DataFrame:
    return mk.config_improvement(st.config_profile(log_b(s, d)), against)


for _name, _sql, _against in (("config_improvement", IMPROVED, "next_lower"), ("config_improvement_best_lower", BEST, "best_lower")):
    entry(_name, f"{B}, {_sql} SELECT query_id, config_id, round(avg_us, 2) AS avg_us, round(abs_gain_us, 2) AS abs_gain_us, round(rel_gain, 6) AS rel_gain FROM improved")(
        lambda s, d, a=_against: improved(s, d, a).select("query_id", "config_id", F.round("avg_us", 2).alias("avg_us"), F.round("abs_gain_us", 2).alias("abs_gain_us"), F.round("rel_gain", 6).alias("rel_gain"))
    )
for _rule, _op in (("both", "AND"), ("either", "OR")):
    entry(f"adaptive_mask_{_rule}", f"{B}, {IMPROVED}, {MASK.format(op=_op)} SELECT * FROM mask")(lambda s, d, r=_rule: mk.adaptive_mask(improved(s, d), rule=r))


@entry(
    "masked_softmax",
    f"""{B}, {IMPROVED}, {MASK.format(op="AND")}, z AS (SELECT query_id, config_id, -avg_us / avg(avg_us) OVER () AS logit, allowed FROM profile JOIN mask USING (query_id, config_id)),
    e AS (SELECT *, CASE WHEN allowed THEN logit ELSE -1e8 END AS zz FROM z), f AS (SELECT *, exp(zz - max(zz) OVER ()) AS ee FROM e)
    SELECT query_id, config_id, round(logit, 6) AS logit, round(ee / sum(ee) OVER (), 6) AS prob FROM f""",
)
def masked_softmax(s: SparkSession, d: str) -> DataFrame:
    profile = st.config_profile(log_b(s, d))
    mean = profile.agg(F.avg("avg_us").alias("m"))
    logits = profile.join(mk.adaptive_mask(improved(s, d)), ["query_id", "config_id"]).join(F.broadcast(mean)).select("query_id", "config_id", "allowed", (-F.col("avg_us") / F.col("m")).alias("logit"))
    return r6(mk.masked_softmax(logits, []).select("query_id", "config_id", "logit", "prob"))


@entry(
    "nearest_allowed_config",
    f"""{B}, {IMPROVED}, {MASK.format(op="AND")}, w AS (SELECT DISTINCT query_id, query_id % 5 AS cluster_id, CAST(query_id % 5 AS INTEGER) AS cluster_config FROM mask)
    SELECT query_id, cluster_id, cluster_config, arg_min(config_id, (abs(config_id // 2 - cluster_config // 2) + abs(config_id % 2 - cluster_config % 2), config_id // 2 + config_id % 2, config_id)) AS config_id
    FROM w JOIN mask USING (query_id) WHERE allowed GROUP BY 1, 2, 3""",
)
def nearest_allowed_config(s: SparkSession, d: str) -> DataFrame:
    mask = mk.adaptive_mask(improved(s, d))
    wanted = mask.select("query_id", F.pmod("query_id", F.lit(5)).alias("cluster_id"), F.pmod("query_id", F.lit(5)).cast("int").alias("cluster_config")).distinct()
    ladder = s.range(5).select(F.col("id").cast("int").alias("config_id"), F.array(F.expr("CAST(id DIV 2 AS INT)"), F.expr("CAST(id % 2 AS INT)")).alias("steps"))
    return mk.nearest_allowed_config(mask, wanted, ladder)


# --- schedules and measures ------------------------------------------------------------------

SUPPLIER = "costs AS (SELECT l_suppkey AS query_id, CAST(sum(l_quantity) AS BIGINT) AS cost FROM lineitem GROUP BY 1)"
USERS = "costs AS (SELECT user_id AS query_id, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cost FROM events GROUP BY 1)"
ORDERED = """jobs AS (
  SELECT 'fifo' AS strategy, 0 AS round_id, query_id, cost, row_number() OVER (ORDER BY query_id) AS seq FROM costs
  UNION ALL SELECT 'mcf', 0, query_id, cost, row_number() OVER (ORDER BY cost DESC, query_id) FROM costs
  UNION ALL SELECT 'random', r, query_id, cost, row_number() OVER (PARTITION BY r ORDER BY md5(r || ':' || query_id), query_id) FROM costs, range(5) t(r))"""


def sql_walk(conn: int = N_CONN) -> str:
    return f"""walk(strategy, round_id, seq, query_id, conn, start_us, finish_us, free) AS (
  SELECT DISTINCT strategy, CAST(round_id AS INTEGER), 0::BIGINT, 0::BIGINT, 0::BIGINT, 0::BIGINT, 0::BIGINT, list_transform(range({conn}), lambda x: 0::BIGINT) FROM jobs
  UNION ALL
  SELECT w.strategy, w.round_id, j.seq, j.query_id, list_position(w.free, list_min(w.free)) - 1, list_min(w.free), list_min(w.free) + j.cost,
         list_transform(w.free, lambda f, k: CASE WHEN k = list_position(w.free, list_min(w.free)) THEN f + j.cost ELSE f END)
  FROM walk w JOIN jobs j ON j.strategy = w.strategy AND j.round_id = w.round_id AND j.seq = w.seq + 1)"""


def sql_schedule(costs: str, tail: str) -> str:
    return f"WITH RECURSIVE {costs}, {ORDERED}, {sql_walk()}, placed AS (SELECT strategy, round_id, CAST(seq - 1 AS INTEGER) AS seq, query_id, CAST(conn AS INTEGER) AS conn_id, start_us, finish_us FROM walk WHERE seq > 0) {tail}"


SUMMARY = "summary AS (SELECT strategy, count(*) AS rounds, avg(m) AS avg, stddev_pop(m) AS std FROM (SELECT strategy, round_id, max(finish_us) - min(start_us) AS m FROM placed GROUP BY 1, 2) GROUP BY 1)"


def supplier(s: SparkSession, d: str) -> DataFrame:
    return logs.supplier_costs(table(s, d, "lineitem"))


def users(s: SparkSession, d: str) -> DataFrame:
    return logs.user_costs(table(s, d, "events"))


def scheduled(s: SparkSession, d: str, costs: Query = supplier) -> DataFrame:
    return sc.heuristic_schedules(costs(s, d), N_CONN)


for _s in ("fifo", "mcf", "random"):
    entry(f"schedule_{_s}", sql_schedule(SUPPLIER, f"SELECT * FROM placed WHERE strategy = '{_s}'"))(lambda s, d, k=_s: scheduled(s, d).where(F.col("strategy") == k))
for _kind, _sql, _costs in (("supplier", SUPPLIER, supplier), ("user", USERS, users)):
    entry(f"strategy_summary_{_kind}", sql_schedule(_sql, f", {SUMMARY} SELECT strategy, rounds, round(avg, 4) AS avg, round(std, 4) AS std FROM summary"))(
        lambda s, d, c=_costs: sc.strategy_summary(scheduled(s, d, c)).select("strategy", "rounds", F.round("avg", 4).alias("avg"), F.round("std", 4).alias("std"))
    )
    entry(
        f"improvement_table_{_kind}",
        sql_schedule(_sql, f", {SUMMARY} SELECT b.strategy AS base, round(1 - m.avg / b.avg, 6) AS improvement, round(1 - m.std / CASE WHEN b.std > 0 THEN b.std END, 6) AS std_improvement FROM summary b, summary m WHERE m.strategy = 'mcf' AND b.strategy <> 'mcf'"),
    )(lambda s, d, c=_costs: r6(sc.improvement(sc.strategy_summary(scheduled(s, d, c)), "mcf")))
    entry(f"best_over_worst_{_kind}", sql_schedule(_sql, f", {SUMMARY} SELECT round(min(avg), 4) AS best, round(max(avg), 4) AS worst, round(1 - min(avg) / max(avg), 6) AS ratio FROM summary"))(
        lambda s, d, c=_costs: sc.best_over_worst(sc.strategy_summary(scheduled(s, d, c))).select(F.round("best", 4).alias("best"), F.round("worst", 4).alias("worst"), F.round("ratio", 6).alias("ratio"))
    )
    entry(f"lower_bound_{_kind}", f"WITH {_sql} SELECT CAST({N_CONN} AS INTEGER) AS n_conn, greatest(max(cost), CAST(ceil(sum(cost) / {N_CONN}) AS BIGINT)) AS bound FROM costs")(lambda s, d, c=_costs: sc.lower_bound(c(s, d), N_CONN))
entry(
    "utilisation",
    sql_schedule(SUPPLIER, f", l AS (SELECT strategy, round_id, conn_id, max(finish_us) AS f, sum(finish_us - start_us) AS busy FROM placed GROUP BY 1, 2, 3) SELECT strategy, round_id, round(sum(busy) / ({N_CONN} * max(f)), 6) AS used_share, CAST({N_CONN} * max(f) - sum(f) AS BIGINT) AS tail_idle_us FROM l GROUP BY 1, 2"),
)(lambda s, d: r6(sc.utilisation(scheduled(s, d), N_CONN)))
entry("schedule_valid", "SELECT CAST(0 AS BIGINT) AS violations")(lambda s, d: sc.violations(scheduled(s, d), supplier(s, d), ["strategy", "round_id"]))


@entry(
    "plan_space",
    """WITH n AS (SELECT count(*) AS n FROM supplier), o AS (SELECT n, (SELECT sum(log10(k::DOUBLE)) FROM range(1, n + 1) t(k)) AS orders FROM n)
    SELECT CAST(n AS INTEGER) AS n, mode, round(CASE mode WHEN 'busy' THEN orders WHEN 'order_conn' THEN orders + n * log10(4.0::DOUBLE) WHEN 'order_conn_cfg' THEN orders + n * (log10(4.0::DOUBLE) + log10(5.0::DOUBLE)) ELSE log10(120.0::DOUBLE) END, 6) AS log10_plans
    FROM o, (SELECT unnest(['busy', 'order_conn', 'order_conn_cfg', 'cluster']) AS mode)""",
)
def plan_space(s: SparkSession, d: str) -> DataFrame:
    n = table(s, d, "supplier").count()
    parts = {"busy": (), "order_conn": (), "order_conn_cfg": (5,), "cluster": ()}
    rows = [F.struct(F.lit(n).alias("n"), F.lit(m).alias("mode"), F.round(sc.plan_space_log10(n, N_CONN, k, m, 5), 6).alias("log10_plans")) for m, k in parts.items()]
    return s.range(1).select(F.explode(F.array(*rows)).alias("r")).select("r.*")


@entry(
    "exhaustive_best",
    """WITH RECURSIVE costs AS (SELECT l_suppkey AS query_id, CAST(sum(l_quantity) AS BIGINT) AS cost FROM lineitem WHERE l_suppkey IN (SELECT s_suppkey FROM supplier ORDER BY s_suppkey LIMIT 6) GROUP BY 1),
    p(used, a, b) AS (SELECT []::BIGINT[], 0::BIGINT, 0::BIGINT UNION ALL
      SELECT list_append(used, query_id), CASE WHEN a <= b THEN a + cost ELSE a END, CASE WHEN a <= b THEN b ELSE b + cost END FROM p, costs WHERE NOT list_contains(used, query_id))
    SELECT min(greatest(a, b)) AS best, max(greatest(a, b)) AS worst, count(*) AS orders FROM p WHERE len(used) = 6""",
)
def exhaustive_best(s: SparkSession, d: str) -> DataFrame:
    six = table(s, d, "supplier").select(F.col("s_suppkey").alias("query_id")).orderBy("query_id").limit(6)
    costs = {r.query_id: r.cost for r in supplier(s, d).join(F.broadcast(six), "query_id").collect()}
    return s.createDataFrame([sc.exhaustive(costs, 2)], "best long, worst long, orders long")


for _intra in ("fifo", "mcf"):
    _key = "query_id" if _intra == "fifo" else "cost DESC, query_id"
    entry(
        f"cluster_schedule_{_intra}",
        f"""WITH RECURSIVE {SUPPLIER}, jobs AS (SELECT 'c' AS strategy, 0 AS round_id, query_id, cost, row_number() OVER (ORDER BY query_id % 5, {_key}) AS seq FROM costs), {sql_walk()}
        SELECT query_id % 5 AS cluster_id, CAST(seq - 1 AS INTEGER) AS seq, query_id, CAST(conn AS INTEGER) AS conn_id, start_us, finish_us FROM walk WHERE seq > 0""",
    )(lambda s, d, i=_intra: sc.cluster_schedule(supplier(s, d).withColumn("cluster_id", F.pmod("query_id", F.lit(5))), N_CONN, i))

# --- batches, plans and forward passes -------------------------------------------------------

# a customer's orders by key stand for the operators of a plan: the k-th hangs below the (k DIV 2)-th, and waits for that and the (k DIV 3)-th
RANKS = "r AS (SELECT o_orderkey AS id, o_custkey AS c, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS k FROM orders)"


def below(s: SparkSession, d: str, by: int) -> DataFrame:
    """node_id, parent_id: each order, and its customer's order of a rank ``by`` times smaller."""
    ranks = table(s, d, "orders").select(F.col("o_orderkey").alias("node_id"), F.col("o_custkey").alias("c"), F.row_number().over(Window.partitionBy("o_custkey").orderBy("o_orderkey")).alias("k"))
    above = ranks.select("c", F.col("k").alias("above"), F.col("node_id").alias("parent_id"))
    return ranks.withColumn("above", F.floor(F.col("k") / by).cast("int")).join(above, ["c", "above"], "left").select("node_id", "parent_id")


@entry(
    "extract_batches",
    f"""WITH RECURSIVE {RANKS}, e AS (SELECT a.id AS q, b.id AS dep FROM r a JOIN r b ON b.c = a.c AND (b.k = a.k // 2 OR b.k = a.k // 3)),
    w AS (SELECT id AS q, 0 AS level FROM r WHERE k = 1 UNION SELECT e.q, level + 1 FROM w JOIN e ON e.dep = w.q)
    SELECT q AS query_id, max(level) AS level FROM w GROUP BY q""",
)
def extract_batches(s: SparkSession, d: str) -> DataFrame:
    edges = below(s, d, 2).unionByName(below(s, d, 3)).where("parent_id IS NOT NULL").select(F.col("node_id").alias("query_id"), F.col("parent_id").alias("depends_on"))
    return batches.extract_batches(table(s, d, "orders").select(F.col("o_orderkey").alias("query_id")), edges)


UP = f"{RANKS}, t AS (SELECT a.id AS node_id, b.id AS parent_id FROM r a LEFT JOIN r b ON b.c = a.c AND b.k = a.k // 2), up AS (SELECT node_id, node_id AS above, 0 AS steps FROM t UNION ALL SELECT u.node_id, t.parent_id, steps + 1 FROM up u JOIN t ON t.node_id = u.above WHERE t.parent_id IS NOT NULL)"
entry("plan_heights", f"WITH RECURSIVE {UP} SELECT above AS node_id, max(steps) AS height FROM up GROUP BY 1")(lambda s, d: batches.plan_heights(below(s, d, 2)))
entry("plan_distances", f"WITH RECURSIVE {UP} SELECT a.node_id AS node_a, b.node_id AS node_b, min(a.steps + b.steps) AS dist FROM up a JOIN up b ON a.above = b.above GROUP BY 1, 2")(lambda s, d: batches.plan_distances(below(s, d, 2)))


def exploded(df: DataFrame, value: Column, name: str = "value") -> DataFrame:
    return r6(df.select("vec_id", F.posexplode(value).alias("pos", name)))


def sql_exploded(value: str, src: str = "emb") -> str:
    return f"SELECT vec_id, CAST(pos AS INTEGER) AS pos, round(value, 6) AS value FROM (SELECT vec_id, unnest(v) AS value, generate_subscripts(v, 1) - 1 AS pos FROM (SELECT vec_id, {value} AS v FROM {src}))"


entry("query_repr_forward", f"WITH {EMB} {sql_exploded(sql_dense(sql_dense('x', 8, 0, True), 4, 50, False))}")(lambda s, d: exploded(emb(s, d), fw.dense(fw.dense(F.col("x"), 8), 4, 50, None)))
SOFT = "list_transform({v}, lambda a: exp(a - list_max({v})) / list_sum(list_transform({v}, lambda b: exp(b - list_max({v})))))"
entry("policy_softmax", f"WITH {EMB}, p AS (SELECT vec_id, {sql_dense('x', 5, 20, False)} AS z FROM emb) {sql_exploded(SOFT.format(v='z'), 'p')}")(lambda s, d: exploded(emb(s, d), fw.softmax(fw.dense(F.col("x"), 5, 20, None))))
entry("value_head", f"WITH {EMB} SELECT vec_id, round(({sql_dense(sql_dense('x', 4, 30, True), 1, 40, False)})[1], 6) AS value FROM emb")(lambda s, d: r6(emb(s, d).select("vec_id", F.element_at(fw.dense(fw.dense(F.col("x"), 4, 30), 1, 40, None), 1).alias("value"))))
entry("finish_time_head", f"WITH {EMB} SELECT vec_id, round(({sql_dense(sql_dense('x', 4, 60, True), 1, 70, False)})[1], 6) AS pred FROM emb")(lambda s, d: r6(emb(s, d).select("vec_id", F.element_at(fw.dense(fw.dense(F.col("x"), 4, 60), 1, 70, None), 1).alias("pred"))))


@entry(
    "attention_forward",
    f"""WITH {EMB}, own AS (SELECT label, vec_id // 16 AS part, vec_id, x FROM emb),
    r AS (SELECT * FROM own UNION ALL SELECT DISTINCT label, part, -1, list_transform(range(64), lambda k: 0.1::DOUBLE) FROM own),
    s AS (SELECT a.label, a.part, a.vec_id, a.x, b.x AS v, list_dot_product({sql_dense('a.x', 4, 100, False)}, {sql_dense('b.x', 4, 200, False)}) / 2 AS s FROM r a JOIN r b ON a.label = b.label AND a.part = b.part),
    p AS (SELECT *, exp(s - max(s) OVER w) / sum(exp(s - max_s)) OVER w AS p FROM (SELECT *, max(s) OVER (PARTITION BY label, part, vec_id) AS max_s FROM s) WINDOW w AS (PARTITION BY label, part, vec_id)),
    u AS (SELECT label, part, vec_id, unnest(x) AS xi, p * unnest(v) AS pv, generate_subscripts(x, 1) - 1 AS pos FROM p)
    SELECT label, CAST(part AS BIGINT) AS part, vec_id, CAST(pos AS INTEGER) AS pos, round(any_value(xi) + sum(pv), 6) AS value FROM u GROUP BY 1, 2, 3, 4""",
)
def attention_forward(s: SparkSession, d: str) -> DataFrame:
    """All vectors, in states of a label's vectors of sixteen neighbouring ids and a super query."""
    own = emb(s, d).select("label", F.expr("vec_id DIV 16").alias("part"), "vec_id", "x")
    above = own.select("label", "part").distinct().select("label", "part", F.lit(-1).cast("long").alias("vec_id"), F.array_repeat(F.lit(0.1), 64).alias("x"))
    return r6(fw.attention(own.unionByName(above), ["label", "part"], "vec_id", "x"))


# --- losses: events' value and props.k stand in for logged numbers --------------------------------

LOSS = """n AS (SELECT event_id, user_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, value FROM events),
x AS (SELECT *, -(k + 1) / 50.0::DOUBLE AS logp, -(k + 3) / 52.0::DOUBLE AS logp_old, (value - 50) / 50 AS adv, value / 100 AS v, k / 100.0::DOUBLE AS target FROM n)"""


def loss_rows(s: SparkSession, d: str) -> DataFrame:
    k = F.get_json_object("props", "$.k").cast("int")
    return table(s, d, "events").select("event_id", "user_id", k.alias("k"), "value").select(
        "*", (-(F.col("k") + 1) / 50.0).alias("logp"), (-(F.col("k") + 3) / 52.0).alias("logp_old"), ((F.col("value") - 50) / 50).alias("adv"), (F.col("value") / 100).alias("v"), (F.col("k") / 100.0).alias("target")
    )


CLIP = "avg(least(exp(logp - logp_old) * adv, greatest(0.8, least(1.2, exp(logp - logp_old))) * adv))"
VALUE = "avg(0.5::DOUBLE * (v - target) * (v - target))"
ENT = "-avg(p * ln(p) + (1 - p) * ln(1 - p))"


def clip_loss() -> Column:
    return F.avg(fw.clipped_term(F.col("logp"), F.col("logp_old"), F.col("adv")))


def value_loss() -> Column:
    return F.avg(fw.squared(F.col("v"), F.col("target")))


def two_way(shift: int, total: float) -> Column:
    p = (F.col("k") + shift) / total
    return F.array(p, 1 - p)


def entropy_bonus() -> Column:
    return F.avg(fw.entropy(two_way(1, 102.0)))


def clone_kl() -> Column:
    return F.avg(fw.divergence(two_way(1, 102.0), two_way(2, 104.0)))


for _name, _sql, _col in (
    ("clipped_surrogate", CLIP, clip_loss),
    ("value_loss", VALUE, value_loss),
    ("entropy_bonus", ENT, entropy_bonus),
    ("joint_loss", f"-({CLIP}) + 0.5::DOUBLE * ({VALUE}) - 0.01::DOUBLE * ({ENT})", lambda: -clip_loss() + fw.BETA_VALUE * value_loss() - fw.BETA_ENTROPY * entropy_bonus()),
    ("clone_kl", "avg(p * ln(p / q) + (1 - p) * ln((1 - p) / (1 - q)))", clone_kl),
    ("aux_loss", VALUE, value_loss),
    ("aux_joint_loss", f"{VALUE} + avg(p * ln(p / q) + (1 - p) * ln((1 - p) / (1 - q)))", lambda: value_loss() + fw.BETA_CLONE * clone_kl()),
):
    entry(_name, f"WITH {LOSS}, y AS (SELECT *, (k + 1) / 102.0::DOUBLE AS p, (k + 2) / 104.0::DOUBLE AS q FROM x) SELECT round({_sql}, 6) AS value FROM y")(lambda s, d, c=_col: r6(loss_rows(s, d).agg(c().alias("value"))))


@entry(
    "gae",
    f"""WITH RECURSIVE {LOSS}, o AS (SELECT event_id, user_id, v, target AS reward, row_number() OVER (PARTITION BY user_id ORDER BY event_id DESC) AS back FROM x),
    g AS (SELECT user_id, back, event_id, v, reward - v AS adv FROM o WHERE back = 1
          UNION ALL SELECT o.user_id, o.back, o.event_id, o.v, o.reward + g.v - o.v + 0.95::DOUBLE * g.adv FROM g JOIN o ON o.user_id = g.user_id AND o.back = g.back + 1)
    SELECT user_id, event_id, round(adv, 10) AS advantage, round(adv + v, 10) AS target FROM g""",
)
def gae(s: SparkSession, d: str) -> DataFrame:
    steps = loss_rows(s, d).select("user_id", "event_id", F.col("target").alias("reward"), F.col("v").alias("value"))
    found = fw.gae(steps, ["user_id"], "event_id")
    return found.select("user_id", "event_id", F.round("advantage", 10).alias("advantage"), F.round("target", 10).alias("target"))


entry("reward_terminal", f"{A} SELECT round_id, -(max(finish_us) - min(start_us)) AS return_us FROM log_a GROUP BY 1")(lambda s, d: st.makespan(log_a(s, d)).select("round_id", (-F.col("makespan_us")).alias("return_us")))


@entry("reward_elapsed", f"{A} SELECT round_id, -(max(finish_us) - min(start_us)) AS return_us FROM log_a GROUP BY 1")
def reward_elapsed(s: SparkSession, d: str) -> DataFrame:
    """Rewards of minus the time between one mark (start or finish) and the next add up to minus the makespan."""
    from pyspark.sql import Window

    marks = log_a(s, d).select("round_id", F.explode(F.array("start_us", "finish_us")).alias("t"))
    step = F.lead("t").over(Window.partitionBy("round_id").orderBy("t")) - F.col("t")
    return marks.withColumn("step", step).groupBy("round_id").agg((-F.sum("step")).alias("return_us"))


# a heuristic predictor of the earliest finisher: least expected remaining time (mean minus elapsed)
SIM = f"""{A}, {STATS}, held AS (SELECT m.round_id, m.run_id AS state, m.finish_us AS t, r.query_id, r.run_id, r.finish_us, s.avg_us - (m.finish_us - r.start_us) AS remain
  FROM log_a m JOIN log_a r ON m.round_id = r.round_id AND r.start_us <= m.finish_us AND m.finish_us < r.finish_us JOIN stats s ON s.query_id = r.query_id),
guess AS (SELECT state, arg_min(run_id, (remain, run_id)) AS guess, arg_min(run_id, (finish_us, run_id)) AS truth, (greatest(min(remain), 0) / 3.6e9::DOUBLE) AS t_hat, (min(finish_us) - any_value(t)) / 3.6e9::DOUBLE AS t_true,
  exp(-least(greatest(arg_min(remain, (finish_us, run_id)), 0) / 3.6e9::DOUBLE, 50)) / sum(exp(-least(greatest(remain, 0) / 3.6e9::DOUBLE, 50))) AS p_true FROM held GROUP BY state)"""


def guesses(s: SparkSession, d: str) -> DataFrame:
    log = log_a(s, d)
    return sw.guessed_finishes(log, st.avg_runtime(log), iv.BUCKET_US)


for _name, _sql, _col in (
    ("sim_accuracy", "avg(CAST(guess = truth AS DOUBLE))", lambda: F.avg((F.col("guess") == F.col("truth")).cast("double"))),
    ("sim_mse", "avg((t_hat - t_true) * (t_hat - t_true))", lambda: F.avg((F.col("t_hat") - F.col("t_true")) ** 2)),
    ("sim_loss", "avg(-ln(p_true)) + 0.1::DOUBLE * avg((t_hat - t_true) * (t_hat - t_true))", lambda: F.avg(-F.ln("p_true")) + 0.1 * F.avg((F.col("t_hat") - F.col("t_true")) ** 2)),
):
    entry(_name, f"{SIM} SELECT round({_sql}, 5) AS value FROM guess")(lambda s, d, c=_col: guesses(s, d).agg(F.round(c(), 5).alias("value")))
