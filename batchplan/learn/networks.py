"""State encoder with attention, and the policy, value, finish-time and simulator heads.

A state is a set of queries: plan embeddings e [B, n, d_e], running features f [B, n, d_f] and which queries
are running [B, n]. An artificial super query stands for the whole; attention mixes all; n may vary.
Parameters are a flat dict of arrays; names that begin with ``run_`` are statistics, not learnt.
"""

from __future__ import annotations

import numpy as np

from batchplan.learn.autograd import Tensor, concat, log_softmax

FILL = -1e8


class StateEncoder:
    """kind "attention", "joined" or "concat".

    "attention" sees the mean of all queries' running features beside the super query, and of the running ones'
    beside each query, so n may vary. "joined" sees them side by side instead: all n for the state, and ``slots``
    of running queries (in their order, empty ones zero) for a query. "concat" has no attention, for a fixed n.
    """

    def __init__(self, d_e: int, d_f: int, n: int, d: int = 16, heads: int = 2, layers: int = 1, kind: str = "attention", slots: int = 1) -> None:
        self.d_e, self.d_f, self.n, self.d, self.heads, self.layers, self.kind, self.slots = d_e, d_f, n, d, heads, layers, kind, slots

    def _mlp(self, p: dict, rng, name: str, sizes: tuple[int, ...]) -> None:
        for k, (a, b) in enumerate(zip(sizes[:-1], sizes[1:], strict=True)):
            p[f"{name}_w{k}"] = rng.normal(0, (1.0 / a) ** 0.5, (a, b))
            p[f"{name}_b{k}"] = np.zeros(b)

    def init(self, seed: int, heads: dict[str, int]) -> dict[str, np.ndarray]:
        """Parameters of the trunk and of heads {name: outputs}; heads named q_.. read a query, s_.. the state."""
        rng, d, p = np.random.default_rng(seed), self.d, {}
        self._mlp(p, rng, "in", (self.d_e + self.d_f, d, d))
        p["super"] = rng.normal(0, 0.1, d)
        for k in range(self.layers):
            for w in ("q", "k", "v", "o"):
                p[f"l{k}_{w}"] = rng.normal(0, d**-0.5, (d, d))
            self._mlp(p, rng, f"l{k}_ff", (d, 2 * d, d))
            for bn in ("n1", "n2"):
                p[f"l{k}_{bn}_g"], p[f"l{k}_{bn}_b"] = np.ones(d), np.zeros(d)
                p[f"run_l{k}_{bn}_m"], p[f"run_l{k}_{bn}_v"] = np.zeros(d), np.ones(d)
        wide = {"concat": self.n * self.d_f, "joined": d + self.n * self.d_f, "attention": d + self.d_f}[self.kind]
        self._mlp(p, rng, "glob", (wide, d, d))
        self._mlp(p, rng, "fin", (2 * d + self.d_f * (self.slots if self.kind == "joined" else 1), d, d))
        for name, out in heads.items():
            self._mlp(p, rng, name, (d, d, out))
            p[f"{name}_w1"] *= 0.1
        return p

    @staticmethod
    def mlp(p: dict, name: str, x: Tensor) -> Tensor:
        """A hidden tanh layer and a linear one."""
        return (x @ p[f"{name}_w0"] + p[f"{name}_b0"]).tanh() @ p[f"{name}_w1"] + p[f"{name}_b1"]

    def _norm(self, p: dict, name: str, x: Tensor, valid: np.ndarray, stats: dict | None) -> Tensor:
        """Batch normalisation over valid queries of all states; running statistics outside training."""
        if stats is None:
            mean, var = Tensor.of(p[f"run_{name}_m"]), Tensor.of(p[f"run_{name}_v"])
        else:
            w = valid[..., None] / valid.sum()
            mean = (x * w).sum((0, 1))
            var = ((x - mean) ** 2 * w).sum((0, 1))
            for k, v in (("m", mean), ("v", var)):
                stats[f"run_{name}_{k}"] = v.data
        return (x - mean) * ((var + 1e-5) ** -0.5) * p[f"{name}_g"] + p[f"{name}_b"]

    def forward(self, p: dict, e: np.ndarray, f: np.ndarray, running: np.ndarray, valid: np.ndarray | None = None, stats: dict | None = None) -> tuple[Tensor, Tensor]:
        """x'' of each query [B, n, d] and x''_s of the state [B, d]; stats collects batch statistics in training."""
        b, n, d = len(f), f.shape[1], self.d
        valid = np.ones((b, n), bool) if valid is None else valid
        x = self.mlp(p, "in", Tensor(np.concatenate([e, f], -1)))
        if self.kind == "concat":
            glob = self.mlp(p, "glob", Tensor(f.reshape(b, -1)))
            mixed, whole = x, glob
        else:
            top = Tensor(np.zeros((b, 1, d))) + Tensor.of(p["super"])
            x = concat([x, top], 1)
            ok = np.concatenate([valid, np.ones((b, 1), bool)], 1)
            block = np.where(ok, 0.0, FILL)[:, None, None, :]
            h, dh = self.heads, d // self.heads
            for k in range(self.layers):
                q, key, v = ((x @ p[f"l{k}_{w}"]).reshape(b, n + 1, h, dh).swap(1, 2) for w in ("q", "k", "v"))
                a = log_softmax((q @ key.swap(2, 3)) * dh**-0.5 + block).exp() @ v
                x = self._norm(p, f"l{k}_n1", x + a.swap(1, 2).reshape(b, n + 1, d) @ p[f"l{k}_o"], ok, stats)
                x = self._norm(p, f"l{k}_n2", x + self.mlp(p, f"l{k}_ff", x), ok, stats)
            mixed, whole = x.pick((slice(None), slice(0, n))), x.pick((slice(None), n))
            all_f = (f * valid[..., None]).reshape(b, -1) if self.kind == "joined" else (f * valid[..., None]).sum(1) / np.maximum(valid.sum(1), 1)[:, None]
            glob = self.mlp(p, "glob", concat([whole, Tensor(all_f)]))
        if self.kind == "joined":
            first = np.argsort(~running, axis=1, kind="stable")[:, : self.slots]
            run_f = np.zeros((b, self.slots, self.d_f))
            run_f[:, : first.shape[1]] = np.take_along_axis(f * running[..., None], first[..., None], 1)
            run_f = run_f.reshape(b, -1)
        else:
            run_f = (f * running[..., None]).sum(1) / np.maximum(running.sum(1), 1)[:, None]
        spread = concat([whole, Tensor(run_f)]).reshape(b, 1, -1) + np.zeros((b, n, 1))
        return self.mlp(p, "fin", concat([mixed, spread])), glob

    def logits(self, p: dict, x2: Tensor, allowed: np.ndarray) -> Tensor:
        """log pi over all (query, configuration) of a state, flattened; allowed [B, n, K]."""
        z = self.mlp(p, "q_policy", x2)
        z = z * allowed + np.where(allowed, 0.0, FILL)
        return log_softmax(z.reshape(len(allowed), -1))
