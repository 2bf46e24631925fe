"""Networks by finite differences, the executor's invariants, and that training and simulation learn."""

import numpy as np
import pytest

from batchplan.learn.autograd import Tensor, gradients
from batchplan.learn.executor import Demands, Executor, run_order
from batchplan.learn.gain_model import GainModel, completed
from batchplan.learn.networks import StateEncoder
from batchplan.learn.simulator import Simulator
from batchplan.learn.training import ClusterPolicy, Policy, SafePolicy, TrainConfig, advantages, evaluate, heuristics, policy_of, train, variant


@pytest.fixture
def demands():
    rng = np.random.default_rng(0)
    return Demands(0.5 + 5 * rng.random(8) ** 2, 3 * rng.random((8, 4)), rng.random(8))


def test_gradients_by_finite_differences():
    rng = np.random.default_rng(1)
    net = StateEncoder(3, 4, 5, d=8)
    p = net.init(0, {"q_policy": 3, "s_value": 1})
    e, f, running = rng.random((2, 5, 3)), rng.random((2, 5, 4)), rng.random((2, 5)) > 0.5
    allowed = np.ones((2, 5, 3), bool)

    def loss(h):
        x2, xs = net.forward(h, e, f, running, stats={})
        return -net.logits(h, x2, allowed).pick((np.arange(2), np.array([1, 7]))).mean() + (net.mlp(h, "s_value", xs) ** 2).mean()

    _, grads = gradients(p, loss)
    for name in ("in_w0", "super", "l0_q", "l0_v", "l0_n1_g", "l0_ff_w1", "glob_w0", "fin_w1", "q_policy_w1", "s_value_b1"):
        at = tuple(rng.integers(0, n) for n in p[name].shape)
        ends = []
        for h in (1e-6, -1e-6):
            moved = {k: v.copy() for k, v in p.items()}
            moved[name][at] += h
            ends.append(float(loss({k: Tensor(v) for k, v in moved.items()}).data))
        assert grads[name][at] == pytest.approx((ends[0] - ends[1]) / 2e-6, rel=1e-4, abs=1e-7)


def test_joined_state_sees_every_slot():
    rng = np.random.default_rng(4)
    net = StateEncoder(3, 4, 5, d=8, kind="joined", slots=3)
    p = net.init(0, {"q_policy": 2})
    e, f, running = rng.random((1, 5, 3)), rng.random((1, 5, 4)), np.array([[True, False, True, False, False]])
    whole, state = net.forward(p, e, f, running)
    assert p["glob_w0"].shape[0] == 8 + 5 * 4 and p["fin_w0"].shape[0] == 2 * 8 + 3 * 4
    # two runs that trade half a feature have the same mean, but not the same slots
    turned = f.copy()
    turned[0, 0, 0], turned[0, 2, 0] = f[0, 0, 0] + 0.5, f[0, 2, 0] - 0.5
    assert not np.allclose(whole.data, net.forward(p, e, turned, running)[0].data) and state.shape == (1, 8)


def test_permutation_equivariance():
    rng = np.random.default_rng(2)
    net = StateEncoder(3, 4, 6, d=8)
    p = net.init(0, {"q_policy": 2})
    e, f, running = rng.random((1, 6, 3)), rng.random((1, 6, 4)), rng.random((1, 6)) > 0.5
    x2, xs = net.forward(p, e, f, running)
    perm = rng.permutation(6)
    y2, ys = net.forward(p, e[:, perm], f[:, perm], running[:, perm])
    assert np.allclose(x2.data[:, perm], y2.data) and np.allclose(xs.data, ys.data)


def test_executor_runs_each_query_once(demands):
    env = Executor(demands, 3)
    span = run_order(env, list(range(8)), 1)
    assert sorted(q for q, *_ in env.log) == list(range(8)) and span == max(x[4] for x in env.log)
    by_conn = {}
    for _, _, c, a, b in sorted(env.log, key=lambda x: x[3]):
        assert a >= by_conn.get(c, 0) - 1e-9
        by_conn[c] = b


def test_advantages_telescope():
    steps = [{"t": t, "v": 0.0} for t in (0.0, 1.0, 4.0)]
    adv, _ = advantages(steps, 10.0, 1.0, lam=1.0)
    assert np.allclose(adv, [-10, -9, -6])


def test_training_beats_fifo(spark, demands):
    """The evaluated policy against the heuristics' rounds, not its own noise."""
    cfg = TrainConfig(iterations=14, profile="io")
    policy, log = train(spark, demands, cfg)
    others = heuristics(demands, cfg)
    assert set(others) == {"fifo", "mcf", "random"} and evaluate(spark, policy)[0] < others["fifo"][0]
    assert [x["iteration"] for x in log if "evaluated" in x] == [1, 3, 5, 7, 9, 11, 13] and log[-1]["rounds"] == 14 * 25 + 7 * 5


def test_policies_see_logs_and_plans_only(spark):
    from batchplan.learn.plan_demands import demands_from_plans, logged_solo
    from batchplan.plans.workloads import star22

    # of the tables' sizes a policy only sees the optimiser's estimate, as one feature of the plan
    small, large = (demands_from_plans(spark, f"/root/testdata/sf{x}", star22()[:6]) for x in ("0.001", "0.01"))
    assert (small.cpu < large.cpu).all() and (small.volume.sum(1) < large.volume.sum(1)).all()
    assert np.abs(small.features() - large.features()).max() < 0.02 and len({tuple(x) for x in small.features()}) == 6
    assert np.abs(logged_solo(large, "shared") / large.solo("shared") - 1).max() < 0.6
    policy = Policy(large, TrainConfig())
    assert not np.allclose(policy.solo, large.solo("shared")) and policy.mask[:, 0].all()


def test_larger_tables_are_not_a_factor(spark):
    from batchplan.learn.plan_demands import demands_from_plans
    from batchplan.plans.workloads import star22

    spans = [run_order(Executor(demands_from_plans(spark, "/root/testdata/sf0.01", star22()[:8], f), 3, "io"), list(range(8)), 1) for f in (1, 4)]
    assert spans[1] > 4.2 * spans[0]


def test_cluster_policy(spark, demands):
    cfg = TrainConfig(clusters=(0, 0, 2, 2, 2, 5, 5, 7), iterations=4, rollouts=6)
    policy = policy_of(demands, cfg)
    policy.mask[3] = [True, False, True]
    env = Executor(demands, 3)
    _, steps, finishes = policy.rollout(env, 1)
    assert isinstance(policy, ClusterPolicy) and policy.e.shape[0] == 4 and np.allclose(policy.e[1], demands.features()[2:5].sum(0))
    assert len(steps) == 4 and all(s["open"].shape == (4, 3) for s in steps) and sorted(q for q, *_ in env.log) == list(range(8))
    assert len(finishes) == 8 and {x[2] for x in finishes} == {0, 1, 2, 3}
    order = [policy.item(q) for q, *_ in sorted(env.log, key=lambda x: x[3])]
    assert len([k for k in range(1, 8) if order[k] != order[k - 1]]) == 3  # a cluster is drained before the next
    assert dict(policy.submissions(1, 1))[3] == 0 and dict(policy.submissions(1, 2))[3] == 2  # repaired to the nearest, cheaper first
    assert all(policy.mask[q, k] for q, k, *_ in env.log)
    trained, log = train(spark, demands, cfg)
    assert len(trained.e) == 4 and np.isfinite(evaluate(spark, trained, 2)[0]) and log[-1]["rounds"] == 4 * 6 + 2 * 5


def test_gain_model_learns_and_has_no_direction():
    rng = np.random.default_rng(3)
    e = rng.random((24, 4))
    every = [(i, j, float(e[i] @ e[j] + 0.05 * rng.standard_normal())) for i in range(24) for j in range(i + 1, 24)]
    known, held = [x for k, x in enumerate(every) if k % 4], every[::4]
    model = GainModel(e).fit(known)
    pairs, truth = [x[:2] for x in held], np.array([x[2] for x in held])
    guess = np.mean([x[2] for x in known])
    assert ((model.predict(pairs) - truth) ** 2).mean() < 0.5 * ((guess - truth) ** 2).mean()
    assert np.allclose(model.predict(pairs), model.predict([(j, i) for i, j in pairs]))
    whole = completed(e, known)
    assert whole[: len(known)] == known and sorted(x[:2] for x in whole) == [x[:2] for x in every] and completed(e, every) == every


def test_degraded_policy_is_trained_again(demands):
    safe = SafePolicy(Policy(demands, TrainConfig()), fallback_span=1e-3, window=2)
    fresh = Policy(demands, variant(TrainConfig(), seed=5))
    assert not safe.refresh(lambda p: fresh)
    for k in range(2):
        safe.play(Executor(demands, 3, seed=k), k)
    assert safe.refresh(lambda p: fresh) and safe.policy is fresh and safe.play(Executor(demands, 3), 0)[0] == "policy"


def test_safe_policy_gives_way(demands):
    policy = Policy(demands, TrainConfig())
    safe = SafePolicy(policy, fallback_span=1e-3, window=3)
    played = [safe.play(Executor(demands, 3, noise=0.05, seed=k), k)[0] for k in range(5)]
    assert played == ["policy"] * 3 + ["fallback"] * 2


def test_simulator_beats_guessing(demands):
    cfg = TrainConfig()
    policy = Policy(demands, cfg)
    samples = [x for s in range(24) for x in policy.rollout(Executor(demands, 3, noise=0.05, seed=s), s)[2]]
    cut = len(samples) * 3 // 4
    accuracy, _ = Simulator(policy.e).fit(samples[:cut], epochs=20).score(samples[cut:])
    longest = np.mean([x[0][:, -2].argmax() == x[2] for x in samples[cut:]])
    assert accuracy > longest
    world = Simulator(policy.e).world(demands, 3, cfg.profile)
    assert np.allclose(world.solo, policy.solo) and world.scale == policy.scale  # of the log, as the policy's
    assert len(policy.rollout(world, 0)[1]) == demands.n and world.done()
