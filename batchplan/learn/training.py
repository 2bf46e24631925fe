"""Learned scheduling policies: rollouts in Spark tasks, updates on the driver.

Variants of one trainer: aux="finish" (an auxiliary phase predicts who finishes next and when, and keeps the
policy near itself by a cloning term), "value" (it predicts state values), "none" (the clipped surrogate
alone); state "attention", "joined" or "concat"; a mask of configurations or none; clusters of queries instead of
queries; learner "plain" is the operator-level competitor: policy gradient against the mean return.

Parameters travel as a broadcast of at most some MB; a rollout is a task's row, so a lost executor repeats
its seeds and gets the same rollouts.
"""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession

from batchplan.learn.autograd import Adam, Tensor, gradients
from batchplan.learn.executor import WORKERS, Demands, Executor, features, run_order
from batchplan.learn.networks import StateEncoder
from batchplan.learn.plan_demands import logged_solo


@dataclass(frozen=True)
class TrainConfig:
    iterations: int = 24
    rollouts: int = 25
    n_ppo: int = 10
    evaluate_every: int = 2
    evaluations: int = 5
    epochs: int = 4
    aux: str = "finish"
    learner: str = "clipped"
    state: str = "attention"
    masked: bool = True
    eps: float = 0.2
    beta_v: float = 0.5
    beta_s: float = 0.01
    beta_clone: float = 1.0
    rate: float = 1e-2
    seed: int = 0
    n_conn: int = 3
    profile: str = "shared"
    noise: float = 0.05
    clusters: tuple[int, ...] | None = None


def mask_of(demands: Demands, profile: str, least: float = 0.05) -> np.ndarray:
    """Configurations whose workers save at least a share of the logged time of the next cheaper one [n, K]."""
    solo = logged_solo(demands, profile)
    gain = (solo[:, :-1] - solo[:, 1:]) / solo[:, :-1]
    return np.concatenate([np.ones((demands.n, 1), bool), gain >= least], 1)


class Policy:
    """Chooses (query, configuration) in states of an environment."""

    def __init__(self, demands: Demands, cfg: TrainConfig, params: dict | None = None) -> None:
        self.demands, self.cfg = demands, cfg
        self.solo = logged_solo(demands, cfg.profile)
        self.scale = float(self.solo.mean()) * 2
        self.mask = mask_of(demands, cfg.profile) if cfg.masked else np.ones(self.solo.shape, bool)
        self.e = self.embeddings()
        self.net = StateEncoder(self.e.shape[1], 3 + len(WORKERS) + 2, len(self.e), kind=cfg.state, slots=cfg.n_conn)
        self.calibrated = params is not None
        self.params = params if params is not None else self.net.init(cfg.seed, {"q_policy": len(WORKERS), "s_value": 1, "q_finish": 1})

    def embeddings(self) -> np.ndarray:
        return self.demands.features()

    def seen(self, env) -> tuple[np.ndarray, np.ndarray]:
        """Running features of what is chosen from, and which of it is running."""
        return features(env, self.solo, self.scale), env.status == 1

    def choices(self, env) -> np.ndarray:
        return self.mask & (env.status == 0)[:, None]

    def submissions(self, q: int, config: int) -> list[tuple[int, int]]:
        """The queries and configurations that a choice stands for, in order."""
        return [(q, config)]

    def item(self, q: int) -> int:
        return q

    def act(self, env, rng, greedy: bool = False) -> tuple[int, int, dict]:
        (f, running), open_ = self.seen(env), self.choices(env)
        x2, xs = self.net.forward(self.params, self.e[None], f[None], running[None])
        logp = self.net.logits(self.params, x2, open_[None]).data[0]
        p = np.exp(logp)
        a = int(p.argmax()) if greedy else int(rng.choice(len(p), p=p / p.sum()))
        step = {"f": f, "open": open_, "running": running, "a": a, "logp": logp[a], "v": float(self.net.mlp(self.params, "s_value", xs).data[0, 0]), "t": env.t}
        return *divmod(a, len(WORKERS)), step

    def rollout(self, env, seed: int, greedy: bool = False) -> tuple[float, list[dict], list[tuple]]:
        """Makespan, decisions, and what is known of finishes: (state, query, time to it)."""
        rng, steps, finishes, queue = np.random.default_rng(seed), [], [], []
        while not env.done():
            while env.idle() and (env.status == 0).any():
                if not queue:
                    x, k, step = self.act(env, rng, greedy)
                    steps.append(step)
                    queue = self.submissions(x, k)
                env.submit(*queue.pop(0))
            f, running = self.seen(env)
            q, passed = env.advance()
            finishes.append((f, running, self.item(q), passed / self.scale))
        return env.t, steps, finishes


class ClusterPolicy(Policy):
    """Chooses (cluster, configuration); the cluster's queries are then submitted one by one, longest first.

    A cluster's embedding is the sum of its queries', its running features are their mean, and it is running while
    one of them is. A query takes the cluster's configuration, or the nearest one that its own mask allows (the
    cheaper of two); a cluster may choose what at least one of its queries allows.
    """

    def embeddings(self) -> np.ndarray:
        self.owner = np.unique(self.cfg.clusters, return_inverse=True)[1]
        cost = self.solo.mean(1)
        self.members = [sorted(np.flatnonzero(self.owner == c).tolist(), key=lambda q: -cost[q]) for c in range(self.owner.max() + 1)]
        e = self.demands.features()
        return np.stack([e[m].sum(0) for m in self.members])

    def seen(self, env) -> tuple[np.ndarray, np.ndarray]:
        f, running = super().seen(env)
        return np.stack([f[m].mean(0) for m in self.members]), np.array([running[m].any() for m in self.members])

    def choices(self, env) -> np.ndarray:
        open_ = super().choices(env)
        return np.stack([open_[m].any(0) for m in self.members])

    def submissions(self, q: int, config: int) -> list[tuple[int, int]]:
        return [(m, min(np.flatnonzero(self.mask[m]).tolist(), key=lambda k: (abs(k - config), k))) for m in self.members[q]]

    def item(self, q: int) -> int:
        return int(self.owner[q])


def policy_of(demands: Demands, cfg: TrainConfig, params: dict | None = None) -> Policy:
    return (Policy if cfg.clusters is None else ClusterPolicy)(demands, cfg, params)


def collect(spark: SparkSession, policy: Policy, seeds: list[int], greedy: bool = False, env: str = "executor", extra=None) -> list[tuple[float, list, list]]:
    """Rollouts of all seeds, a few in each task."""
    sent = spark.sparkContext.broadcast(pickle.dumps((policy.demands, policy.cfg, policy.params, extra)))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        demands, cfg, params, sim = pickle.loads(sent.value)
        own = policy_of(demands, cfg, params)
        for frame in frames:
            out = []
            for seed in frame["id"].tolist():
                world = Executor(demands, cfg.n_conn, cfg.profile, cfg.noise, seed) if env == "executor" else sim.world(demands, cfg.n_conn, cfg.profile)
                out.append(pickle.dumps(own.rollout(world, seed, greedy)))
            yield pd.DataFrame({"id": frame["id"], "r": out})

    rows = spark.range(len(seeds), numPartitions=min(8, len(seeds))).withColumn("id", _at(seeds)).mapInPandas(run, "id long, r binary").collect()
    sent.unpersist()
    return [pickle.loads(bytes(r.r)) for r in sorted(rows, key=lambda r: r.id)]


def _at(seeds: list[int]):
    from pyspark.sql import functions as F

    return F.element_at(F.array(*[F.lit(s).cast("long") for s in seeds]), (F.col("id") + 1).cast("int"))


def advantages(steps: list[dict], end: float, scale: float, lam: float = 0.95) -> tuple[np.ndarray, np.ndarray]:
    """Generalised advantages of rewards that are minus the time until the next decision."""
    t = np.array([s["t"] for s in steps] + [end]) / scale
    r, v = -(t[1:] - t[:-1]), np.array([s["v"] for s in steps] + [0.0])
    adv, last = np.zeros(len(r)), 0.0
    for k in range(len(r) - 1, -1, -1):
        last = r[k] + v[k + 1] - v[k] + lam * last
        adv[k] = last
    return adv, adv + v[:-1]


def update(policy: Policy, batch: list[tuple[float, list, list]], opt: Adam) -> float:
    """Several epochs of the clipped surrogate (or one plain step) over one batch of rollouts."""
    cfg, net = policy.cfg, policy.net
    steps = [s for _, one, _ in batch for s in one]
    f, open_, running = (np.stack([s[k] for s in steps]) for k in ("f", "open", "running"))
    e = np.broadcast_to(policy.e, (len(f), *policy.e.shape))
    act, old = np.array([s["a"] for s in steps]), np.array([s["logp"] for s in steps])
    if cfg.learner == "plain":
        spans = np.array([m for m, _, _ in batch])
        adv = np.concatenate([np.full(len(one), (spans.mean() - m) / policy.scale) for m, one, _ in batch])
        target = np.zeros(len(adv))
    else:
        both = [advantages(one, m, policy.scale) for m, one, _ in batch]
        adv, target = np.concatenate([a for a, _ in both]), np.concatenate([t for _, t in both])
    adv = (adv - adv.mean()) / (adv.std() + 1e-8)

    def loss(p: dict[str, Tensor]) -> Tensor:
        x2, xs = net.forward(p, e, f, running)
        logp = net.logits(p, x2, open_)
        own = logp.pick((np.arange(len(act)), act))
        if cfg.learner == "plain":
            return -(own * adv).mean()
        ratio = (own - old).exp()
        surrogate = (ratio * adv).minimum(ratio.clip(1 - cfg.eps, 1 + cfg.eps) * adv).mean()
        value = net.mlp(p, "s_value", xs).reshape(-1)
        bonus = -(logp.exp() * (logp * (logp.data > -1e7))).sum(-1).mean()
        return -surrogate + ((value - target) ** 2).mean() * (0.5 * cfg.beta_v) - bonus * cfg.beta_s

    for _ in range(1 if cfg.learner == "plain" else cfg.epochs):
        last = _step(policy, loss, opt)
    return last


def calibrate(policy: Policy, batch: list[tuple[float, list, list]], keep: float = 0.0) -> None:
    """Set the normalisation statistics from the states of rollouts, before a policy's first update.

    Updates then run with the same statistics as rollouts did, so ratios to the old policy start at one.
    """
    steps = [s for _, one, _ in batch for s in one]
    f, running = np.stack([s["f"] for s in steps]), np.stack([s["running"] for s in steps])
    policy.calibrated = True
    for _ in range(2 * policy.net.layers):  # a layer's statistics depend on those before it
        stats: dict = {}
        policy.net.forward({k: Tensor(v) for k, v in policy.params.items()}, np.broadcast_to(policy.e, (len(f), *policy.e.shape)), f, running, stats=stats)
        for k, v in stats.items():
            policy.params[k] = keep * policy.params[k] + (1 - keep) * v


def auxiliary(policy: Policy, batch: list[tuple[float, list, list]], opt: Adam) -> float:
    """Predict the earliest finisher's time (or the states' values) without moving the policy."""
    cfg, net = policy.cfg, policy.net
    steps = [s for _, one, _ in batch for s in one]
    f, open_, running = (np.stack([s[k] for s in steps]) for k in ("f", "open", "running"))
    e = np.broadcast_to(policy.e, (len(f), *policy.e.shape))
    ends = [x for _, _, fin in batch for x in fin]
    ef, er, eq, et = np.stack([x[0] for x in ends]), np.stack([x[1] for x in ends]), np.array([x[2] for x in ends]), np.array([x[3] for x in ends])
    ee = np.broadcast_to(policy.e, (len(ef), *policy.e.shape))
    target = np.concatenate([advantages(one, m, policy.scale)[1] for m, one, _ in batch])
    frozen = net.logits(policy.params, net.forward(policy.params, e, f, running)[0], open_).data
    old = np.exp(frozen)

    def loss(p: dict[str, Tensor]) -> Tensor:
        x2, xs = net.forward(p, e, f, running)
        clone = ((frozen - net.logits(p, x2, open_)) * (old * (frozen > -1e7))).sum(-1).mean()
        if cfg.aux == "value":
            error = net.mlp(p, "s_value", xs).reshape(-1) - target
        else:
            y2, _ = net.forward(p, ee, ef, er)
            error = net.mlp(p, "q_finish", y2).reshape(len(ef), -1).pick((np.arange(len(eq)), eq)) - et
        return (error**2).mean() * 0.5 + clone * cfg.beta_clone

    for _ in range(cfg.epochs):
        last = _step(policy, loss, opt)
    return last


def _step(policy: Policy, loss, opt: Adam) -> float:
    value, grads = gradients(policy.params, loss)
    opt.step(policy.params, {k: g for k, g in grads.items() if not k.startswith("run_")})
    return value


def train(spark: SparkSession, demands: Demands, cfg: TrainConfig, policy: Policy | None = None, env: str = "executor", extra=None) -> tuple[Policy, list[dict]]:
    """Backbone iterations, an auxiliary phase after every n_ppo of them; keeps the policy that evaluates best.

    Every ``evaluate_every`` iterations (and at the end) the greedy policy plays evaluation rounds on the
    training environment; their mean decides what is kept, and log rows have it as ``evaluated``.
    """
    policy = policy or policy_of(demands, cfg)
    opt, log, held, best, rounds = Adam(cfg.rate), [], [], (np.inf, policy.params), 0
    for i in range(cfg.iterations):
        batch = collect(spark, policy, [cfg.seed * 100_003 + i * cfg.rollouts + k for k in range(cfg.rollouts)], env=env, extra=extra)
        rounds += len(batch)
        log.append({"iteration": i, "rounds": rounds, "makespan": float(np.mean([m for m, _, _ in batch])), "loss": 0.0})
        if not policy.calibrated:
            calibrate(policy, batch)
            continue
        held += batch
        log[-1]["loss"] = update(policy, batch, opt)
        if cfg.aux != "none" and cfg.learner == "clipped" and (i + 1) % cfg.n_ppo == 0:
            log[-1]["aux"] = auxiliary(policy, held, opt)
            held = []
        if (i + 1) % cfg.evaluate_every == 0 or i + 1 == cfg.iterations:
            seen = [m for m, _, _ in collect(spark, policy, list(range(800_000, 800_000 + cfg.evaluations)), True, env, extra)]
            rounds += len(seen)
            log[-1] |= {"evaluated": float(np.mean(seen)), "rounds": rounds}
            if log[-1]["evaluated"] < best[0]:
                best = (log[-1]["evaluated"], {k: v.copy() for k, v in policy.params.items()})
    policy.params = best[1]
    return policy, log


def evaluate(spark: SparkSession, policy: Policy, rounds: int = 5, greedy: bool = True) -> tuple[float, float]:
    """Mean and population deviation of the makespan over rounds."""
    spans = [m for m, _, _ in collect(spark, policy, list(range(900_000, 900_000 + rounds)), greedy)]
    return float(np.mean(spans)), float(np.std(spans))


def heuristics(demands: Demands, cfg: TrainConfig, rounds: int = 5, config: int = 1) -> dict[str, tuple[float, float]]:
    """FIFO, MCF (by logged times) and Random, with one configuration for all queries."""
    n, solo = demands.n, logged_solo(demands, cfg.profile)
    world = lambda s: Executor(demands, cfg.n_conn, cfg.profile, cfg.noise, 900_000 + s)
    orders = {"fifo": lambda s: list(range(n)), "mcf": lambda s: np.argsort(-solo[:, config], kind="stable").tolist(), "random": lambda s: np.random.default_rng(s).permutation(n).tolist()}
    out = {}
    for name, order in orders.items():
        spans = [run_order(world(s), order(s), config) for s in range(rounds)]
        out[name] = (float(np.mean(spans)), float(np.std(spans)))
    return out


def best_fixed(demands: Demands, cfg: TrainConfig, rounds: int = 5) -> dict[str, tuple[float, float]]:
    """The heuristics, each with the configuration that suits it best: the strongest form of the baselines."""
    every = [heuristics(demands, cfg, rounds, k) for k in range(len(WORKERS))]
    return {name: min(one[name] for one in every) for name in every[0]}


class SafePolicy:
    """A policy that gives way to the longest-first order when its recent rounds are worse than that order's."""

    def __init__(self, policy: Policy, fallback_span: float, window: int = 5, tolerance: float = 0.05, config: int = 1) -> None:
        self.policy, self.fallback_span, self.window, self.tolerance, self.config, self.spans = policy, fallback_span, window, tolerance, config, []

    def record(self, span: float) -> None:
        self.spans.append(span)

    def degraded(self) -> bool:
        recent = self.spans[-self.window :]
        return len(recent) == self.window and float(np.mean(recent)) > self.fallback_span * (1 + self.tolerance)

    def refresh(self, fine_tune: Callable[[Policy], Policy]) -> bool:
        """Where recent rounds are worse: the policy that fine_tune makes of this one, with an empty record."""
        if not self.degraded():
            return False
        self.policy, self.spans = fine_tune(self.policy), []
        return True

    def play(self, env, seed: int = 0) -> tuple[str, float]:
        """One round: by the policy, or by the fallback order (which is not recorded: fresh parameters start a new one)."""
        if self.degraded():
            return "fallback", run_order(env, np.argsort(-self.policy.solo[:, self.config], kind="stable").tolist(), self.config)
        span = self.policy.rollout(env, seed, True)[0]
        self.record(span)
        return "policy", span


def variant(cfg: TrainConfig, **how) -> TrainConfig:
    return replace(cfg, **how)
