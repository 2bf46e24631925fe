"""Registered queries that train, roll out or execute: rows of (setting, strategy, metric, value)."""

from __future__ import annotations

import functools
import os
import tempfile
import time
import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from batchplan.learn import backend as be
from batchplan.learn import training as tr
from batchplan.learn.executor import PROFILES, Demands, Executor
from batchplan.learn.gain_model import GainModel, completed
from batchplan.learn.plan_demands import demands_from_plans
from batchplan.learn.simulator import Simulator
from batchplan.operators import gain as gn
from batchplan.plans.workloads import Template, joins33, star22, wide99
from batchplan.registry import A, entry, log_a
from batchplan.sources.logs import table
from batchplan.streaming import arriving

ROWS = "setting string, strategy string, metric string, value double"
FAST = tr.TrainConfig()


def demands(s: SparkSession, d: str, n: int = 12) -> Demands:
    """A batch of star22's first queries (then wide99's), by their plans on the tables of d."""
    return demands_from_plans(s, d, batch(n))


def batch(n: int) -> list[Template]:
    return [*star22(), *wide99()][:n]


def table_of(s: SparkSession, rows: list[tuple]) -> DataFrame:
    return s.createDataFrame([(a, b, c, round(float(v), 6)) for a, b, c, v in rows], ROWS)


def measured(setting: str, strategy: str, pair: tuple[float, float]) -> list[tuple]:
    return [(setting, strategy, "makespan", pair[0]), (setting, strategy, "deviation", pair[1])]


def learn(s: SparkSession, dem: Demands, **how) -> tuple[tr.Policy, list[dict]]:
    return tr.train(s, dem, tr.variant(FAST, **how))


@entry("train_learned")
def train_learned(s: SparkSession, d: str) -> DataFrame:
    """The learned scheduler beside the heuristics, for each contention profile, with its learning curve."""
    dem, rows = demands(s, d), []
    for profile in ("cpu", "io", "shared"):
        policy, log = learn(s, dem, profile=profile)
        rows += measured(profile, "learned", tr.evaluate(s, policy))
        rows += [(profile, "learned", f"curve_{x['rounds']}", x["evaluated"]) for x in log if "evaluated" in x]
        for name, pair in tr.heuristics(dem, policy.cfg).items():
            rows += measured(profile, name, pair)
        for name, pair in tr.best_fixed(dem, policy.cfg).items():
            rows += measured(profile, f"{name}_best_fixed", pair)
    return table_of(s, rows)


def efficiency_rows(s: SparkSession, d: str, n: int, iterations: int, rounds: int = 5) -> list[tuple]:
    """Makespan and deviation of five strategies on three workloads and three engines, and the learned one's improvement."""
    rows = []
    for name, templates in (("wide99", wide99()[:: max(1, 99 // n)][:n]), ("star22", star22()[:n]), ("joins33", joins33()[:: max(1, 33 // n)][:n])):
        dem = demands_from_plans(s, d, templates)
        for engine in PROFILES:
            cell = {**tr.heuristics(dem, tr.variant(FAST, profile=engine), rounds)}
            for strategy, how in (("oplevel", {"learner": "plain", "aux": "none", "masked": False}), ("learned", {})):
                cell[strategy] = tr.evaluate(s, learn(s, dem, profile=engine, iterations=iterations, **how)[0], rounds)
            setting = f"{name}/{engine}"
            rows += [r for strategy, pair in cell.items() for r in measured(setting, strategy, pair)]
            rows += [(setting, strategy, "improvement", 1 - cell["learned"][0] / pair[0]) for strategy, pair in cell.items() if strategy != "learned"]
    return rows


@entry("efficiency_table")
def efficiency_table(s: SparkSession, d: str) -> DataFrame:
    """The reduced form: batches of ten queries, ten iterations of training; ``efficiency_rows`` takes whole workloads."""
    return table_of(s, efficiency_rows(s, d, 10, 10))


@entry("training_cost")
def training_cost(s: SparkSession, d: str) -> DataFrame:
    """Wall time and counted rounds of training from scratch, of the competitor, and of pre-training and fine-tuning."""
    dem, rows = demands(s, d), []

    def timed(name: str, run) -> object:
        begin = time.monotonic()
        out = run()
        rows.append(("shared", name, "seconds", time.monotonic() - begin))
        return out

    for name, how in (("learned", {}), ("oplevel", {"learner": "plain", "aux": "none", "masked": False})):
        rows.append(("shared", name, "real_rounds", timed(name, lambda how=how: learn(s, dem, iterations=8, **how))[1][-1]["rounds"]))
    samples = timed("simulator_samples", lambda: logged_states(s, dem))
    sim = timed("simulator_fit", lambda: Simulator(dem.features()).fit(samples, epochs=8))
    policy, _ = timed("pretrain", lambda: tr.train(s, dem, tr.variant(FAST, iterations=8), env="sim", extra=sim))
    _, log = timed("finetune", lambda: tr.train(s, dem, tr.variant(FAST, iterations=2, seed=9), policy))
    rows.append(("shared", "finetune", "real_rounds", LOGGED + log[-1]["rounds"]))
    return table_of(s, rows)


@entry("safe_policy")
def safe_policy(s: SparkSession, d: str) -> DataFrame:
    """Rounds of an untrained policy behind the safety switch: which of them the fallback order played."""
    dem = demands(s, d)
    safe = tr.SafePolicy(tr.Policy(dem, FAST), tr.heuristics(dem, FAST)["mcf"][0], tolerance=-0.5)
    played = [safe.play(Executor(dem, FAST.n_conn, FAST.profile, FAST.noise, k), k) for k in range(8)]
    fresh = safe.refresh(lambda policy: tr.train(s, dem, tr.variant(FAST, iterations=4), policy)[0])
    played += [safe.play(Executor(dem, FAST.n_conn, FAST.profile, FAST.noise, k), k) for k in range(8, 11)]
    return table_of(s, [("shared", who, f"round_{k}", span) for k, (who, span) in enumerate(played)] + [("shared", "trigger", "retrained", fresh)])


@entry("train_oplevel")
def train_oplevel(s: SparkSession, d: str) -> DataFrame:
    """The operator-level competitor: a plain policy gradient, no mask and no auxiliary phase."""
    dem = demands(s, d)
    policy, _ = learn(s, dem, learner="plain", aux="none", masked=False)
    return table_of(s, measured("shared", "oplevel", tr.evaluate(s, policy)))


def compared(s: SparkSession, d: str, variants: dict[str, dict]) -> DataFrame:
    dem, rows = demands(s, d), []
    for name, how in variants.items():
        policy, log = learn(s, dem, **how)
        rows += measured("shared", name, tr.evaluate(s, policy))
        rows.append(("shared", name, "rounds", log[-1]["rounds"]))
    return table_of(s, rows)


entry("ablation_rl")(lambda s, d: compared(s, d, {"full": {}, "backbone": {"aux": "none"}, "value_aux": {"aux": "value"}, "joined": {"state": "joined"}, "no_attention": {"state": "concat"}}))
entry("ablation_mask")(lambda s, d: compared(s, d, {"masked": {}, "unmasked": {"masked": False}}))


def cluster_rows(s: SparkSession, d: str, n: int, counts: tuple[int, ...], iterations: int = 5) -> list[tuple]:
    """Numbers of clusters of a batch: logged gains, completed by the fitted model, clustered and scheduled by cluster."""
    dem, rows = demands(s, d, n), []
    gains = completed(dem.features(), executor_gains(dem, FAST, 8))
    for n_c in (*counts, dem.n):
        owner, _ = gn.average_linkage(list(range(dem.n)), gains, n_c)
        policy, log = learn(s, dem, clusters=None if n_c == dem.n else tuple(owner[q] for q in range(dem.n)), iterations=iterations)
        rows += [*measured(f"n_c={n_c}", "learned", tr.evaluate(s, policy)), (f"n_c={n_c}", "learned", "rounds", log[-1]["rounds"])]
    for name, pair in tr.heuristics(dem, FAST).items():
        rows += measured("all", name, pair)
    return rows


@entry("nc_sweep")
def nc_sweep(s: SparkSession, d: str) -> DataFrame:
    """The reduced form: 4 and 8 clusters of 24 queries; ``cluster_rows`` takes batches of 5x and 10x."""
    return table_of(s, cluster_rows(s, d, 24, (4, 8)))


@entry("gain_model_fit")
def gain_model_fit(s: SparkSession, d: str) -> DataFrame:
    """The gain model fitted on four of five logged pairs: squared errors on the rest, and those of their mean."""
    dem = demands(s, d, 24)
    gains = executor_gains(dem, FAST, 160)
    held = gains[::5]
    known = [g for k, g in enumerate(gains) if k % 5]
    truth, guess = np.array([g for _, _, g in held]), np.mean([g for _, _, g in known])
    error = GainModel(dem.features()).fit(known).predict([(i, j) for i, j, _ in held]) - truth
    rows = [("shared", "model", "mse", np.mean(error**2)), ("shared", "mean", "mse", np.mean((guess - truth) ** 2))]
    rows += [("shared", "log", "pairs", len(gains)), ("shared", "model", "unseen_pairs", len(completed(dem.features(), gains)) - len(gains))]
    return s.createDataFrame([(a, b, c, float(v)) for a, b, c, v in rows], ROWS)


def executor_gains(dem: Demands, cfg: tr.TrainConfig, rounds: int = 20) -> list[tuple[int, int, float]]:
    """Scheduling gains of random rounds on the reference executor."""
    runs = []
    for r in range(rounds):
        env = Executor(dem, cfg.n_conn, cfg.profile, cfg.noise, r)
        todo = np.random.default_rng(r).permutation(dem.n).tolist()
        while not env.done():
            while todo and env.idle():
                env.submit(todo.pop(0), 0)
            env.advance()
        runs.append([(q, a, b) for q, _, _, a, b in env.log])
    mean = {q: np.mean([b - a for one in runs for p, a, b in one if p == q]) for q in range(dem.n)}
    terms: dict[tuple[int, int], list[float]] = {}
    for one in runs:
        for i, a, b in one:
            for j, c, e in one:
                ov = min(b, e) - max(a, c)
                if i < j and ov > 0:
                    wi, wj = mean[i] ** 0.5, mean[j] ** 0.5
                    terms.setdefault((i, j), []).append((wi * ov * (1 / (b - a) - 1 / mean[i]) + wj * ov * (1 / (e - c) - 1 / mean[j])) / (wi + wj))
    return [(i, j, float(np.mean(v))) for (i, j), v in terms.items()]


#: Rounds that are logged for the simulator's first samples.
LOGGED = 24


def logged_states(s: SparkSession, dem: Demands, rounds: int = LOGGED) -> list[tuple]:
    """Completion samples of rounds of an untrained policy."""
    return [x for _, _, fin in tr.collect(s, tr.Policy(dem, FAST), list(range(rounds))) for x in fin]


@entry("simulator_table")
def simulator_table(s: SparkSession, d: str) -> DataFrame:
    """Accuracy and error of the simulator's variants and of gamma, on states it has not seen."""
    dem = demands(s, d)
    samples = logged_states(s, dem, 32)
    cut, rows = len(samples) * 3 // 4, []
    for name, how in {"no_attention": {"attention": False}, "no_multitask": {"multitask": False}, "gamma=0.01": {"gamma": 0.01}, "gamma=0.1": {}, "gamma=1": {"gamma": 1.0}}.items():
        accuracy, mse = Simulator(dem.features(), **how).fit(samples[:cut], epochs=12).score(samples[cut:])
        rows += [("shared", name, "accuracy", accuracy), ("shared", name, "mse", mse)]
    return table_of(s, rows)


@entry("pretrain_finetune")
def pretrain_finetune(s: SparkSession, d: str) -> DataFrame:
    """Rounds on the real executor: from scratch, and after pre-training on the simulator with checkpoint choice."""
    dem = demands(s, d)
    samples = logged_states(s, dem)
    sim = Simulator(dem.features()).fit(samples, epochs=15)
    scratch, log = learn(s, dem)
    rows = measured("shared", "scratch", tr.evaluate(s, scratch)) + [("shared", "scratch", "real_rounds", log[-1]["rounds"])]
    cfg, policy, found, real = FAST, tr.Policy(dem, FAST), [], LOGGED
    for part in range(3):  # checkpoints on the way
        policy, _ = tr.train(s, dem, tr.variant(cfg, iterations=6, seed=part), policy, env="sim", extra=sim)
        found.append((tr.evaluate(s, policy, 3)[0], {k: v.copy() for k, v in policy.params.items()}))
        real += 3
    policy.params = min(found, key=lambda x: x[0])[1]
    rows += measured("shared", "pretrained", tr.evaluate(s, policy)) + [("shared", "pretrained", "real_rounds", real)]
    policy, log = tr.train(s, dem, tr.variant(cfg, iterations=6, seed=9, rate=3e-3), policy)
    more = [x for _, _, fin in tr.collect(s, policy, list(range(50, 58))) for x in fin]
    sim.fit(more, epochs=3)  # incremental
    rows += measured("shared", "finetuned", tr.evaluate(s, policy)) + [("shared", "finetuned", "real_rounds", real + log[-1]["rounds"] + 8)]
    return table_of(s, rows)


def compared_on(s: SparkSession, setting: str, dem: Demands, policies: dict[str, tr.Policy]) -> list[tuple]:
    """Trained policies, unchanged, and the heuristics on a batch."""
    rows = [r for name, p in policies.items() for r in measured(setting, name, tr.evaluate(s, tr.policy_of(dem, p.cfg, p.params)))]
    return rows + [r for k, v in tr.heuristics(dem, FAST).items() for r in measured(setting, k, v)]


def both_learners(s: SparkSession, dem: Demands, iterations: int) -> dict[str, tr.Policy]:
    return {"learned": learn(s, dem, iterations=iterations)[0], "oplevel": learn(s, dem, iterations=iterations, learner="plain", aux="none", masked=False)[0]}


@entry("transfer_eval")
def transfer_eval(s: SparkSession, d: str) -> DataFrame:
    """Policies trained on 1x, unchanged on tables of 0.8x to 1.2x and on fewer or more queries.

    Larger tables fill the executor's memory sooner, so a batch does not just take a factor longer.
    """
    policies, rows = both_learners(s, demands(s, d), 12), []
    for factor in (0.8, 0.9, 1.1, 1.2):
        rows += compared_on(s, f"data_{factor}", demands_from_plans(s, d, batch(12), factor), policies)
        rows += compared_on(s, f"query_{factor}", demands(s, d, round(12 * factor)), policies)
    return table_of(s, rows)


@entry("scaling_eval")
def scaling_eval(s: SparkSession, d: str) -> DataFrame:
    """Tables of the neighbouring scale folders (where there are any) and of 2x and 5x, and batches of 12 and 24 queries."""
    base, rows = os.path.dirname(d.rstrip("/")), []
    settings = {f"data_{f:g}": (d, f, 12) for f in (1, 2, 5)} | {"query_2": (d, 1, 24)}
    for folder in ("sf0.001", "sf0.01", "sf0.1"):
        if os.path.basename(d.rstrip("/")).startswith("sf") and os.path.isdir(f"{base}/{folder}"):
            settings[f"tables_{folder}"] = (f"{base}/{folder}", 1, 12)
    for name, (folder, factor, n) in settings.items():
        dem = demands_from_plans(s, folder, batch(n), factor)
        rows += compared_on(s, name, dem, both_learners(s, dem, 6))
    return table_of(s, rows)


@entry("gantt_case")
def gantt_case(s: SparkSession, d: str) -> DataFrame:
    """One round of a trained policy as schedule rows, with the rank of each query's cost."""
    dem = demands(s, d)
    policy, _ = learn(s, dem)
    env, rng = Executor(dem, FAST.n_conn, FAST.profile, 0.0, 1), np.random.default_rng(1)
    while not env.done():
        while env.idle() and (env.status == 0).any():
            env.submit(*policy.act(env, rng, True)[:2])
        env.advance()
    rank = np.argsort(np.argsort(-policy.solo[:, 0])) + 1
    rows = [(seq, q, k, c, round(a, 6), round(b, 6), int(rank[q])) for seq, (q, k, c, a, b) in enumerate(sorted(env.log, key=lambda x: x[3]))]
    return s.createDataFrame(rows, "seq int, query_id int, config_id int, conn_id int, start double, finish double, cost_rank int")


@entry("spark_backend_run")
def spark_backend_run(s: SparkSession, d: str) -> DataFrame:
    """star22's first queries on Spark itself: makespans of measured runs of FIFO, MCF and a learned policy.

    The policy is trained on the executor, fine-tuned on five measured rounds, and then runs one greedy round.
    """
    batch = star22()[:8]
    back = be.SparkBackend(s, d, 4)
    back.run(batch, be.fifo, "warm", 0)
    rows = back.run(batch, be.fifo, "fifo", 1)
    times = {q: (f - a) for _, _, q, _, _, a, f in rows}
    rows += back.run(batch, be.mcf(times), "mcf", 1)
    policy, _ = learn(s, demands_from_plans(s, d, batch), iterations=6, n_conn=4)
    unit = sum(times.values()) / 1e6 / float(policy.solo[:, 1].sum())
    rows += be.fine_tune(back, batch, policy, unit)
    rows += back.run(batch, be.PolicyChoice(policy, unit), "learned", 1)
    log = back.log_frame(rows)
    return log.groupBy("strategy", "round_id").agg(F.count("*").alias("queries"), (F.max("finish_us") - F.min("start_us")).alias("makespan_us"))


# --- streams, equal to their batch twins ----------------------------------------------------------


@functools.cache
def _chunks(d: str, base: str) -> str:
    """events cut into ten files by id, in the shared folder."""
    from pyspark.sql import SparkSession as Session

    s = Session.getActiveSession()
    path = f"{base.rstrip('/')}/batchplan-events-{os.getpid()}-{abs(hash(d))}"
    events = table(s, d, "events")
    events.repartitionByRange(10, "event_id").write.mode("overwrite").parquet(path)
    return path


def _shared(s: SparkSession) -> str:
    base = s.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not s.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir is not set: on a cluster it must name a folder that driver and executors share")
        base = tempfile.gettempdir() + "/batchplan-streams"
    return base.rstrip("/")


def stream_of(s: SparkSession, d: str) -> DataFrame:
    return arriving.watermarked(arriving.event_stream(s, _chunks(d, _shared(s)), 3), "3650 days")


entry("stream_makespan", f"{A} SELECT round_id, max(finish_us) - min(start_us) AS makespan_us FROM log_a GROUP BY 1")(lambda s, d: arriving.drain(arriving.daily_makespans(stream_of(s, d)), "stream_makespan"))
entry(
    "stream_sessions",
    f"""{A}, m AS (SELECT query_id, start_us, CASE WHEN start_us - lag(start_us) OVER w < 7200000000 THEN 0 ELSE 1 END AS fresh FROM log_a WINDOW w AS (PARTITION BY query_id ORDER BY start_us)),
    g AS (SELECT *, sum(fresh) OVER (PARTITION BY query_id ORDER BY start_us ROWS UNBOUNDED PRECEDING) AS g FROM m)
    SELECT query_id, min(start_us) AS session_us, count(*) AS runs FROM g GROUP BY query_id, g""",
)(lambda s, d: arriving.drain_to(arriving.user_sessions(stream_of(s, d)), f"{_shared(s)}/stream-sessions-{uuid.uuid4().hex}").select("query_id", F.unix_micros("session_start").alias("session_us"), "runs"))


@entry(
    "stream_pairs",
    f"""{A} SELECT i.query_id AS qi, j.query_id AS qj, count(*) AS m_c, CAST(sum(least(i.finish_us, j.finish_us) - greatest(i.start_us, j.start_us)) AS BIGINT) AS s_ov
    FROM log_a i JOIN log_a j ON i.round_id = j.round_id AND i.query_id < j.query_id AND i.start_us < j.finish_us AND j.start_us < i.finish_us GROUP BY 1, 2""",
)
def stream_pairs(s: SparkSession, d: str) -> DataFrame:
    """Pair sums of two increments of whole rounds, added up."""
    log = log_a(s, d)
    half = F.dayofmonth("round_id") <= 15
    return arriving.merge_pair_sums(arriving.merge_pair_sums(None, log.where(half)), log.where(~half)).select("qi", "qj", "m_c", "s_ov")
