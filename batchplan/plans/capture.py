"""Plans of queries as trees of nodes, without running them, and features of the nodes."""

from __future__ import annotations

import json
import re

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Buckets that operator names and predicate columns are hashed into.
OPERATORS, COLUMNS = 24, 16
FEATURES = OPERATORS + COLUMNS + 3


def capture_plan(spark: SparkSession, sql: str, query_id: int, tables: tuple[str, ...] = (), columns: dict[str, set[str]] | None = None) -> list[tuple]:
    """(query_id, node_id, parent_id, op, tables, predicates, bytes) of the optimised plan, root first.

    Only the analyser and the optimiser run; the tree comes in preorder with numbers of children.
    """
    plan = spark.sql(sql)._jdf.queryExecution().optimizedPlan()
    size = float(str(plan.stats().sizeInBytes()))
    columns = columns or {t: set(spark.table(t).columns) for t in tables}
    nodes, open_ = [], []
    for k, n in enumerate(json.loads(plan.toJSON())):
        while open_ and open_[-1][1] == 0:
            open_.pop()
        parent = open_[-1][0] if open_ else None
        if open_:
            open_[-1][1] -= 1
        open_.append([k, n.get("num-children", 0)])
        op = n["class"].rsplit(".", 1)[-1]
        names = sorted(set(re.findall(r'"name":"(\w+)"', json.dumps(n.get("condition", n.get("output", [])), separators=(",", ":")))))
        predicates = names if "condition" in n else []
        # a scan reads the table that has most of its columns
        read = sorted((t for t in tables if op == "LogicalRelation" and columns[t] & set(names)), key=lambda t: (-len(columns[t] & set(names)), t))[:1]
        nodes.append((query_id, k, parent, op, read, predicates, size if k == 0 else None))
    return nodes


def scan_filters(spark: SparkSession, sql: str) -> list[tuple]:
    """(node_id, filter, relation) of the optimised plan's filters of whole tables, as Java plans; ids as in ``capture_plan``."""
    found, number = [], [0]

    def walk(node) -> None:
        at, kids = number[0], node.children()
        number[0] += 1
        kids = [kids.apply(k) for k in range(kids.length())]
        if node.nodeName() == "Filter" and kids[0].getClass().getSimpleName() == "LogicalRelation":
            found.append((at, node, kids[0]))
        for kid in kids:
            walk(kid)

    walk(spark.sql(sql)._jdf.queryExecution().optimizedPlan())
    return found


def kept_shares(spark: SparkSession, templates, start: int = 0) -> DataFrame:
    """query_id, node_id, kept: the share of its table's rows that each filter of a table keeps, counted in whole tables.

    A table is scanned once for each different filter; no rows at all give no share.
    """
    made, places, out = {}, [], None

    def numbered(plan) -> int:
        return made.setdefault(plan.canonicalized().toString(), (len(made), plan))[0]

    for k, t in enumerate(templates):
        places += [(start + k, at, numbered(part), numbered(whole)) for at, part, whole in scan_filters(spark, t.sql)]
    for number, plan in made.values():
        rows = DataFrame(spark._jvm.org.apache.spark.sql.classic.Dataset.ofRows(spark._jsparkSession, plan), spark)
        one = rows.agg(F.count("*").alias("n")).select(F.lit(number).alias("number"), "n")
        out = one if out is None else out.unionByName(one)
    counts = dict(out.collect()) if out is not None else {}  # a row for each different filter of the batch
    return spark.createDataFrame([(q, at, counts[a] / counts[b] if counts[b] else None) for q, at, a, b in places], "query_id long, node_id int, kept double")


SCHEMA = "query_id long, node_id int, parent_id int, op string, tables array<string>, predicates array<string>, est_bytes double"


def plan_nodes(spark: SparkSession, templates, start: int = 0) -> DataFrame:
    """The nodes of a batch's plans, with what filters of tables keep; the templates' tables must be registered."""
    rows = [n for k, t in enumerate(templates) for n in capture_plan(spark, t.sql, start + k, t.tables)]
    return spark.createDataFrame(rows, SCHEMA).join(F.broadcast(kept_shares(spark, templates, start)), ["query_id", "node_id"], "left")


def node_vectors(nodes: list[tuple]) -> tuple[np.ndarray, np.ndarray]:
    """Features of each node of one plan, and the tree distances between nodes, with a super node at 0.

    Features: hashed operator, hashed predicate columns, height, size and joins; the super node is linked to all.
    Where it is known (an eighth field) which share of a table a filter keeps, its columns count more the less it keeps.
    """
    n = len(nodes)
    x, up = np.zeros((n + 1, FEATURES)), np.full(n, -1)
    height = np.zeros(n, int)
    at = {node[1]: k for k, node in enumerate(nodes)}
    for k, (_, _, parent, op, tables, predicates, size, *kept) in enumerate(nodes):
        x[k + 1, _bucket(op, OPERATORS)] = 1
        for c in predicates:
            x[k + 1, OPERATORS + _bucket(c, COLUMNS)] += 2 - kept[0] if kept and kept[0] is not None else 1
        x[k + 1, -2] = np.log1p(size or 0) / 30
        x[k + 1, -1] = float(op == "Join") + 0.1 * len(tables)
        up[k] = at[parent] if parent is not None else -1
    for k in range(n - 1, -1, -1):
        if up[k] >= 0:
            height[up[k]] = max(height[up[k]], height[k] + 1)
    x[1:, -3] = height / 10
    ancestors = [[k] for k in range(n)]
    for k in range(n):
        while up[ancestors[k][-1]] >= 0:
            ancestors[k].append(up[ancestors[k][-1]])
    dist = np.ones((n + 1, n + 1), int)
    for a in range(n):
        place = {v: s for s, v in enumerate(ancestors[a])}
        for b in range(n):
            dist[a + 1, b + 1] = min((place[v] + s for s, v in enumerate(ancestors[b]) if v in place), default=9)
    dist[0, 0] = 0
    return x, dist


def _bucket(name: str, n: int) -> int:
    h = 0
    for ch in name:
        h = (h * 131 + ord(ch)) % 1_000_003
    return h % n


def encode_plan(nodes: list[tuple], dim: int = 16, seed: int = 1) -> np.ndarray:
    """A plan's embedding: the super node's output of one attention layer biased by tree distance."""
    x, dist = node_vectors(nodes)
    rng = np.random.default_rng(seed)
    w = [rng.normal(0, FEATURES**-0.5, (FEATURES, dim)) for _ in range(3)]
    bias = -0.3 * np.arange(64)
    s = (x @ w[0]) @ (x @ w[1]).T / np.sqrt(dim) + bias[np.minimum(dist, 63)]
    p = np.exp(s - s.max(1, keepdims=True))
    p /= p.sum(1, keepdims=True)
    return np.tanh(p @ (x @ w[2]) + x @ w[2])[0]


def encode_plans(nodes: DataFrame, dim: int = 16, seed: int = 1) -> DataFrame:
    """query_id, embedding of each plan; a plan is one group of at most some hundred nodes."""
    import pandas as pd

    def one(group: pd.DataFrame) -> pd.DataFrame:
        rows = [(r.query_id, r.node_id, None if pd.isna(r.parent_id) else int(r.parent_id), r.op, list(r.tables), list(r.predicates), None if pd.isna(r.est_bytes) else r.est_bytes, None if pd.isna(r.kept) else r.kept) for r in group.sort_values("node_id").itertuples()]
        return pd.DataFrame({"query_id": [rows[0][0]], "embedding": [encode_plan(rows, dim, seed).tolist()]})

    return nodes.groupBy("query_id").applyInPandas(one, "query_id long, embedding array<double>")


def column_histograms(df: DataFrame, cols: list[str], bins: int = 8) -> DataFrame:
    """col, bin, lo, hi, rows: equi-width bins of numeric columns, in two scans."""
    ends = df.agg(*[f(F.col(c).cast("double")).alias(f"{c}_{k}") for c in cols for k, f in (("lo", F.min), ("hi", F.max))]).first()
    out = None
    for c in cols:
        lo, width = ends[f"{c}_lo"], (ends[f"{c}_hi"] - ends[f"{c}_lo"]) / bins
        bin_ = F.least(F.lit(bins - 1), F.floor((F.col(c).cast("double") - lo) / width)).cast("int")
        part = df.where(F.col(c).isNotNull()).groupBy(bin_.alias("bin")).agg(F.count("*").alias("rows"))
        part = part.select(F.lit(c).alias("col"), "bin", F.round(lo + F.col("bin") * width, 4).alias("lo"), F.round(lo + (F.col("bin") + 1) * width, 4).alias("hi"), "rows")
        out = part if out is None else out.unionByName(part)
    return out


def predicate_selectivity(histogram: DataFrame, col: str, upto: float) -> DataFrame:
    """The share of rows below a value, by linear interpolation within bins."""
    part = F.greatest(F.lit(0.0), F.least(F.lit(1.0), (F.lit(upto) - F.col("lo")) / (F.col("hi") - F.col("lo"))))
    return histogram.where(F.col("col") == col).agg((F.sum(part * F.col("rows")) / F.sum("rows")).alias("selectivity"))
