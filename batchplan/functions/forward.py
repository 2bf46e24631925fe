"""Forward passes and losses as column expressions, for pinned weights and for measured columns.

The networks that learn are in ``batchplan.learn``; these forms score tables without Python.
Pinned weights: w(i, j) = ((7919 i + 104729 j) mod 2001 - 1000) / 1000.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

EPS, BETA_VALUE, BETA_ENTROPY, BETA_CLONE = 0.2, 0.5, 0.01, 1.0


def pinned(i: Column, j: Column) -> Column:
    return (F.pmod(i * 7919 + j * 104729, F.lit(2001)) - 1000) / 1000.0


def dense(vector: Column, outputs: int, shift: int = 0, activate: str | None = "tanh") -> Column:
    """A layer of pinned weights over an array; ``shift`` tells layers apart."""

    def unit(j: Column) -> Column:
        total = F.aggregate(F.transform(vector, lambda x, i: x * pinned(i + shift, j)), F.lit(0.0), lambda s, t: s + t)
        return F.tanh(total) if activate == "tanh" else total

    return F.transform(F.sequence(F.lit(0), F.lit(outputs - 1)), unit)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, t: s + t)


def l2(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (l2(a) * l2(b))


def one_hot(value: Column, n: int) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda k: F.when(k == value, 1.0).otherwise(0.0))


def softmax(values: Column) -> Column:
    shifted = F.transform(values, lambda x: F.exp(x - F.array_max(values)))
    return F.transform(shifted, lambda x: x / F.aggregate(shifted, F.lit(0.0), lambda s, t: s + t))


def running_features(status: Column, config: Column, configs: int, elapsed: Column, avg: Column, t_max: Column) -> Column:
    """One-hot status (pending, running, finished), one-hot configuration, elapsed and mean time over t_max."""
    return F.concat(one_hot(status, 3), F.when(status == 0, F.array_repeat(F.lit(0.0), configs)).otherwise(one_hot(config, configs)), F.array(elapsed / t_max, avg / t_max))


def attention(rows: DataFrame, state: list[str], id_col: str, x: str) -> DataFrame:
    """Single-head self-attention with a skip, within each state; a state is a batch of queries."""
    q = rows.select(*state, F.col(id_col), F.col(x).alias("x"), dense(F.col(x), 4, 100, None).alias("q"))
    kv = rows.select(*state, F.col(id_col).alias("other"), dense(F.col(x), 4, 200, None).alias("k"), F.col(x).alias("v"))
    pairs = (q.join(kv, state) if state else q.join(kv)).withColumn("s", dot(F.col("q"), F.col("k")) / 2.0)
    w = Window.partitionBy(*state, id_col)
    weighed = pairs.withColumn("e", F.exp(F.col("s") - F.max("s").over(w))).withColumn("p", F.col("e") / F.sum("e").over(w))
    parts = weighed.select(*state, id_col, "x", "p", F.posexplode("v").alias("pos", "value"))
    return parts.groupBy(*state, id_col, "pos").agg((F.first(F.element_at("x", F.col("pos") + 1)) + F.sum(F.col("p") * F.col("value"))).alias("value"))


def clipped_term(logp: Column, logp_old: Column, advantage: Column, eps: float = EPS) -> Column:
    ratio = F.exp(logp - logp_old)
    return F.least(ratio * advantage, F.greatest(F.lit(1 - eps), F.least(F.lit(1 + eps), ratio)) * advantage)


def squared(a: Column, b: Column) -> Column:
    return 0.5 * (a - b) * (a - b)


def entropy(p: Column) -> Column:
    return -F.aggregate(F.transform(p, lambda x: F.when(x > 0, x * F.ln(x)).otherwise(0.0)), F.lit(0.0), lambda s, t: s + t)


def divergence(old: Column, new: Column) -> Column:
    """KL(old || new); entries where old is zero count for nothing."""
    return F.aggregate(F.zip_with(old, new, lambda a, b: F.when(a > 0, a * F.ln(a / b)).otherwise(0.0)), F.lit(0.0), lambda s, t: s + t)


def gae(steps: DataFrame, by: list[str], order: str, gamma: float = 1.0, lam: float = 0.95) -> DataFrame:
    """by.., order, advantage, target: generalised advantages, from the last step back; a rollout is one array."""
    walk = F.array_sort(F.collect_list(F.struct(F.col(order).alias("o"), F.col("reward").alias("r"), F.col("value").alias("v"))))
    fold = f"""reverse(aggregate(reverse(walk), named_struct('next_v', 0.0D, 'adv', 0.0D, 'out', CAST(array() AS ARRAY<STRUCT<o: BIGINT, advantage: DOUBLE, target: DOUBLE>>)),
      (s, x) -> named_struct('next_v', x.v, 'adv', x.r + {gamma}D * s.next_v - x.v + {gamma * lam}D * s.adv,
        'out', concat(s.out, array(named_struct('o', x.o, 'advantage', x.r + {gamma}D * s.next_v - x.v + {gamma * lam}D * s.adv,
                                               'target', x.r + {gamma}D * s.next_v + {gamma * lam}D * s.adv)))), s -> s.out))"""
    return steps.groupBy(*by).agg(walk.alias("walk")).select(*by, F.explode(F.expr(fold)).alias("x")).select(*by, F.col("x.o").alias(order), "x.advantage", "x.target")
