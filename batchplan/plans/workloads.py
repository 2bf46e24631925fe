"""The batches of queries that are scheduled: star22, joins33 and wide99, as SQL that Spark and DuckDB both run.

Each query is a Template: its name, the tables it reads (plans of one batch share scans) and its SQL.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@dataclass(frozen=True)
class Template:
    name: str
    tables: tuple[str, ...]
    sql: str


def _template(name: str, sql: str) -> Template:
    words = set(sql.replace("(", " ").replace(")", " ").replace(",", " ").split())
    return Template(name, tuple(t for t in TABLES if t in words), sql)


def register_tables(spark: SparkSession, sf_dir: str, names: list[str] | tuple[str, ...] = TABLES) -> None:
    """Temporary views of the tables, so that templates run as they are."""
    for n in names:
        spark.read.parquet(f"{sf_dir}/{n}.parquet").createOrReplaceTempView(n)


def rounded_as_doubles(sql: str) -> str:
    """sql for Spark with rounded means scaled, rounded half away from zero and scaled back, all in doubles.

    A mean of hundredths often lies half way between two results; Spark's ``round`` looks at its exact binary value, the
    SQL's engine at the scaled one.
    """

    def scaled(m: re.Match[str]) -> str:
        x, unit = m[1], f"1e{m[2]}D"
        near = f"(floor(abs({x}) * {unit}) + CASE WHEN abs({x}) * {unit} - floor(abs({x}) * {unit}) >= 0.5D THEN 1 ELSE 0 END) / {unit}"
        return f"CASE WHEN isnan({x}) OR abs({x}) * {unit} > 9e15D THEN {x} WHEN {x} < 0 THEN 0D - {near} ELSE {near} END"

    return re.sub(r"\bround\((avg\(\w+\)), (\d+)\)(?! OVER)", scaled, sql)


def run(spark: SparkSession, sf_dir: str, template: Template) -> DataFrame:
    register_tables(spark, sf_dir, template.tables)
    return spark.sql(rounded_as_doubles(template.sql))


REV = "l_extendedprice * (1 - l_discount)"
MONEY = "round(sum({x}), 2)".format

STAR22 = {
    "s01": f"SELECT l_returnflag, l_linestatus, CAST(sum(l_quantity) AS BIGINT) AS quantity, {MONEY(x=REV)} AS revenue, round(avg(l_discount), 6) AS avg_discount, count(*) AS n FROM lineitem WHERE l_shipdate <= DATE '2000-09-01' GROUP BY l_returnflag, l_linestatus",
    "s02": """SELECT l_partkey, l_suppkey, unit FROM (SELECT l_partkey, l_suppkey, round(min(l_extendedprice / l_quantity), 4) AS unit,
        row_number() OVER (PARTITION BY l_partkey ORDER BY round(min(l_extendedprice / l_quantity), 4), l_suppkey) AS r
        FROM lineitem JOIN part ON p_partkey = l_partkey JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey
        WHERE p_size <= 10 AND r_name = 'EUROPE' GROUP BY l_partkey, l_suppkey) x WHERE r = 1""",
    "s03": f"""SELECT o_orderkey, {MONEY(x=REV)} AS revenue FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON l_orderkey = o_orderkey
        WHERE c_mktsegment = 'BUILDING' GROUP BY o_orderkey ORDER BY revenue DESC, o_orderkey LIMIT 10""",
    "s04": """SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_orderdate >= DATE '1996-01-01' AND o_orderdate < DATE '1996-04-01'
        AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'R') GROUP BY o_orderpriority""",
    "s05": f"""SELECT n_name, {MONEY(x=REV)} AS revenue FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey AND s_nationkey = c_nationkey
        JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey WHERE r_name = 'ASIA' AND o_orderdate >= DATE '1997-01-01' AND o_orderdate < DATE '1999-01-01' GROUP BY n_name""",
    "s06": "SELECT round(sum(l_extendedprice * l_discount), 2) AS gain, count(*) AS n FROM lineitem WHERE l_discount BETWEEN 0.03 AND 0.07 AND l_quantity < 24",
    "s07": f"""SELECT a.n_name AS from_nation, b.n_name AS to_nation, year(l_shipdate) AS y, {MONEY(x=REV)} AS volume FROM lineitem JOIN supplier ON s_suppkey = l_suppkey JOIN orders ON o_orderkey = l_orderkey
        JOIN customer ON c_custkey = o_custkey JOIN nation a ON a.n_nationkey = s_nationkey JOIN nation b ON b.n_nationkey = c_nationkey
        WHERE (a.n_name = 'NATION_1' AND b.n_name = 'NATION_2') OR (a.n_name = 'NATION_2' AND b.n_name = 'NATION_1') GROUP BY a.n_name, b.n_name, year(l_shipdate)""",
    "s08": f"""SELECT year(o_orderdate) AS y, round(sum(CASE WHEN n2.n_name = 'NATION_3' THEN {REV} ELSE 0 END) / sum({REV}), 6) AS share FROM lineitem JOIN part ON p_partkey = l_partkey JOIN supplier ON s_suppkey = l_suppkey
        JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN nation n1 ON n1.n_nationkey = c_nationkey JOIN region ON r_regionkey = n1.n_regionkey JOIN nation n2 ON n2.n_nationkey = s_nationkey
        WHERE r_name = 'AMERICA' AND p_type = 'PROMO' GROUP BY year(o_orderdate)""",
    "s09": f"""SELECT n_name, year(o_orderdate) AS y, round(sum({REV} - 0.5 * p_retailprice * l_quantity), 2) AS margin FROM lineitem JOIN part ON p_partkey = l_partkey JOIN supplier ON s_suppkey = l_suppkey
        JOIN orders ON o_orderkey = l_orderkey JOIN nation ON n_nationkey = s_nationkey WHERE p_name LIKE '%blue%' GROUP BY n_name, year(o_orderdate)""",
    "s10": f"""SELECT c_custkey, {MONEY(x=REV)} AS revenue FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' GROUP BY c_custkey ORDER BY revenue DESC, c_custkey LIMIT 20""",
    "s11": """SELECT l_partkey, round(sum(l_extendedprice), 2) AS supplied FROM lineitem JOIN supplier ON s_suppkey = l_suppkey WHERE s_nationkey < 5 GROUP BY l_partkey
        HAVING sum(l_extendedprice) > (SELECT sum(l_extendedprice) * 0.002 FROM lineitem JOIN supplier ON s_suppkey = l_suppkey WHERE s_nationkey < 5)""",
    "s12": """SELECT l_linestatus, year(l_shipdate) AS y, count(CASE WHEN o_orderpriority IN ('1-URGENT', '2-HIGH') THEN 1 END) AS urgent, count(CASE WHEN o_orderpriority NOT IN ('1-URGENT', '2-HIGH') THEN 1 END) AS other
        FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY l_linestatus, year(l_shipdate)""",
    "s13": "SELECT n, count(*) AS customers FROM (SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey AND o_orderstatus <> 'P' GROUP BY c_custkey) x GROUP BY n",
    "s14": f"SELECT year(l_shipdate) AS y, month(l_shipdate) AS m, round(100.0 * sum(CASE WHEN p_type = 'PROMO' THEN {REV} ELSE 0 END) / sum({REV}), 4) AS promo FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY year(l_shipdate), month(l_shipdate)",
    "s15": f"""WITH q AS (SELECT l_suppkey, {MONEY(x=REV)} AS revenue FROM lineitem WHERE l_shipdate >= DATE '1996-01-01' AND l_shipdate < DATE '1996-04-01' GROUP BY l_suppkey)
        SELECT s_suppkey, s_name, revenue FROM supplier JOIN q ON s_suppkey = l_suppkey WHERE revenue = (SELECT max(revenue) FROM q)""",
    "s16": """SELECT p_brand, p_type, p_size, count(DISTINCT l_suppkey) AS suppliers FROM lineitem JOIN part ON p_partkey = l_partkey WHERE p_brand <> 'Brand#5' AND p_size < 9
        AND l_suppkey NOT IN (SELECT s_suppkey FROM supplier WHERE s_acctbal < 0) GROUP BY p_brand, p_type, p_size""",
    "s17": """SELECT round(sum(l_extendedprice) / 7.0, 2) AS yearly FROM lineitem JOIN part ON p_partkey = l_partkey JOIN (SELECT l_partkey AS k, 0.2 * avg(l_quantity) AS least FROM lineitem GROUP BY l_partkey) a ON k = l_partkey
        WHERE p_brand IN ('Brand#3', 'Brand#7') AND l_quantity < least""",
    "s18": """SELECT c_custkey, o_orderkey, CAST(sum(l_quantity) AS BIGINT) AS quantity FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON l_orderkey = o_orderkey
        WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem GROUP BY l_orderkey HAVING sum(l_quantity) > 200) GROUP BY c_custkey, o_orderkey ORDER BY quantity DESC, o_orderkey LIMIT 100""",
    "s19": f"""SELECT {MONEY(x=REV)} AS revenue FROM lineitem JOIN part ON p_partkey = l_partkey WHERE (p_brand = 'Brand#1' AND p_size <= 15 AND l_quantity BETWEEN 1 AND 20)
        OR (p_brand = 'Brand#2' AND p_size <= 25 AND l_quantity BETWEEN 10 AND 30) OR (p_brand = 'Brand#4' AND p_size <= 35 AND l_quantity BETWEEN 20 AND 40)""",
    "s20": """SELECT s_suppkey, s_name FROM supplier WHERE s_suppkey IN (SELECT l_suppkey FROM lineitem JOIN part ON p_partkey = l_partkey WHERE p_name LIKE 'red%' AND l_shipdate >= DATE '1997-01-01' AND l_shipdate < DATE '1998-01-01'
        GROUP BY l_suppkey, l_partkey HAVING sum(l_quantity) > 30)""",
    "s21": """SELECT l_suppkey, count(DISTINCT l_orderkey) AS n FROM lineitem l1 WHERE l_returnflag = 'R' AND EXISTS (SELECT 1 FROM lineitem l2 WHERE l2.l_orderkey = l1.l_orderkey AND l2.l_suppkey <> l1.l_suppkey)
        AND NOT EXISTS (SELECT 1 FROM lineitem l3 WHERE l3.l_orderkey = l1.l_orderkey AND l3.l_suppkey <> l1.l_suppkey AND l3.l_returnflag = 'R') GROUP BY l_suppkey""",
    "s22": """SELECT c_nationkey % 5 AS code, count(*) AS n, round(sum(c_acctbal), 2) AS total FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer WHERE c_acctbal > 0)
        AND NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderdate >= DATE '1999-01-01') GROUP BY c_nationkey % 5""",
}


def star22() -> list[Template]:
    return [_template(k, v) for k, v in STAR22.items()]


#: Join graphs with three filters each, from wide to narrow, and what is asked of the rows.
_G1 = "lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey"
GRAPHS = {
    "g1": (_G1, "min(o_orderdate) AS a, min(c_name) AS b", ("l_quantity > 5", "l_quantity > 25", "l_quantity > 48")),
    "g2": (f"{_G1} JOIN nation ON n_nationkey = c_nationkey", "min(n_name) AS a, min(o_orderkey) AS b", ("c_acctbal > 0", "n_nationkey < 10", "n_nationkey = 7")),
    "g3": (f"{_G1} JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey", "min(c_name) AS a, min(l_shipdate) AS b", ("r_name <> 'ASIA'", "r_name IN ('ASIA', 'EUROPE')", "r_name = 'AFRICA' AND c_mktsegment = 'MACHINERY'")),
    "g4": ("lineitem JOIN part ON p_partkey = l_partkey JOIN supplier ON s_suppkey = l_suppkey", "min(p_name) AS a, min(s_name) AS b", ("p_size > 5", "p_type = 'STANDARD'", "p_brand = 'Brand#9' AND s_acctbal > 0")),
    "g5": ("lineitem JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey", "min(s_name) AS a, min(l_orderkey) AS b", ("l_discount > 0.01", "r_name = 'EUROPE'", "r_name = 'EUROPE' AND l_returnflag = 'A'")),
    "g6": ("lineitem JOIN orders ON o_orderkey = l_orderkey JOIN part ON p_partkey = l_partkey", "min(p_name) AS a, min(o_totalprice) AS b", ("o_orderstatus <> 'P'", "o_orderpriority = '1-URGENT'", "o_orderpriority = '1-URGENT' AND p_size < 5")),
    "g7": (f"{_G1} JOIN part ON p_partkey = l_partkey JOIN supplier ON s_suppkey = l_suppkey JOIN nation cn ON cn.n_nationkey = c_nationkey JOIN nation sn ON sn.n_nationkey = s_nationkey JOIN region ON r_regionkey = sn.n_regionkey", "min(cn.n_name) AS a, min(sn.n_name) AS b", ("p_size > 3", "r_name = 'ASIA'", "r_name = 'ASIA' AND p_type = 'SMALL'")),
    "g8": ("events JOIN customer ON c_custkey = user_id JOIN orders ON o_custkey = c_custkey", "min(event_id) AS a, min(o_orderkey) AS b", ("value > 1", "event_type = 'purchase'", "event_type = 'purchase' AND o_orderstatus = 'F'")),
    "g9": ("events JOIN customer ON c_custkey = user_id JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey", "min(n_name) AS a, min(event_id) AS b", ("value > 10", "event_type = 'click'", "event_type = 'click' AND r_name = 'AMERICA'")),
    "g10": ("supplier JOIN nation ON n_nationkey = s_nationkey JOIN customer ON c_nationkey = n_nationkey", "min(s_name) AS a, min(c_name) AS b", ("s_acctbal > 0", "c_mktsegment = 'HOUSEHOLD'", "c_mktsegment = 'HOUSEHOLD' AND n_nationkey = 3")),
    "g11": ("documents a JOIN labels l ON l.doc_id = a.doc_id JOIN documents b ON b.source = a.source AND b.lang <> a.lang", "min(a.doc_id) AS a, min(b.doc_id) AS b", ("l.quality = 1", "l.toxic = 1", "l.toxic = 1 AND a.lang = 'de'")),
}


def joins33() -> list[Template]:
    return [_template(f"{g}{'abc'[k]}", f"SELECT {what}, count(*) AS n FROM {graph} WHERE {where}") for g, (graph, what, filters) in GRAPHS.items() for k, where in enumerate(filters)]


def _shapes(k: int) -> dict[str, str]:
    """The eleven shapes of wide99 with parameter k in 1..9."""
    year, nation, seg = 1994 + min(k, 6), k * 2, ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")[k % 5]
    return {
        "h1": f"SELECT l_returnflag, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS q FROM lineitem WHERE l_quantity > {3 * k} GROUP BY l_returnflag",
        "h2": f"SELECT p_brand, count(*) AS n, round(sum(l_extendedprice), 2) AS v FROM lineitem JOIN part ON p_partkey = l_partkey WHERE p_size > {5 * k} GROUP BY p_brand",
        "h3": f"SELECT r_name, count(*) AS n, round(sum(o_totalprice), 2) AS v FROM orders JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey WHERE n_nationkey >= {nation} GROUP BY r_name",
        "h4": f"SELECT o_custkey, o_orderkey, r FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) x WHERE r <= {k}",
        "h5": f"SELECT day, n, CAST(sum(n) OVER (ORDER BY day ROWS BETWEEN {k} PRECEDING AND CURRENT ROW) AS BIGINT) AS moving FROM (SELECT CAST(ts AS DATE) AS day, count(*) AS n FROM events GROUP BY CAST(ts AS DATE)) x",
        "h6": f"SELECT c_mktsegment, o_orderstatus, count(*) AS n FROM orders JOIN customer ON c_custkey = o_custkey WHERE c_nationkey > {k} GROUP BY ROLLUP (c_mktsegment, o_orderstatus)",
        "h7": f"SELECT count(*) AS n FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > {5 * k}) AND NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'N' AND l_quantity < {k})",
        "h8": f"SELECT o_custkey FROM orders WHERE year(o_orderdate) = {year} INTERSECT SELECT o_custkey FROM orders WHERE year(o_orderdate) = {year + 1} EXCEPT SELECT c_custkey FROM customer WHERE c_mktsegment = '{seg}'",
        "h9": f"SELECT count(*) AS n, round(sum(l_extendedprice), 2) AS v FROM lineitem l JOIN (SELECT l_partkey AS k, avg(l_quantity) AS m FROM lineitem GROUP BY l_partkey) a ON a.k = l.l_partkey WHERE l_quantity < 0.{k} * m",
        "h10": f"SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars, count(DISTINCT text) AS texts FROM documents WHERE n_chars > {100 * k} GROUP BY lang, source",
        "h11": f"SELECT event_type, CAST(ts AS DATE) AS day, count(*) AS n, round(avg(value), 4) AS v FROM events WHERE value > {5 * k} GROUP BY event_type, CAST(ts AS DATE)",
    }


def wide99() -> list[Template]:
    return [_template(f"{h}_{k}", sql) for k in range(1, 10) for h, sql in _shapes(k).items()]


def scale_queries(templates: list[Template], factor: float) -> list[Template]:
    """factor times as many queries: copies under other names, or the first of them."""
    n = round(len(templates) * factor)
    return [Template(f"{t.name}_x{k // len(templates)}" if k >= len(templates) else t.name, t.tables, t.sql) for k, t in ((k, templates[k % len(templates)]) for k in range(n))]


def scale_data(df: DataFrame, key: str, factor: float, offset: int = 1 << 40) -> DataFrame:
    """0.8x or 0.9x: rows whose key leaves less than 8 or 9 on division by 10; 1.1x, 1.2x, 2x ...: with copies of a slice under other keys."""
    from pyspark.sql import functions as F

    whole, tenths = divmod(round(factor * 10), 10)
    parts = [df.withColumn(key, F.col(key) + k * offset) if k else df for k in range(whole)]
    if tenths:
        slice_ = df.where(F.pmod(F.col(key), F.lit(10)) < tenths)
        parts.append(slice_.withColumn(key, F.col(key) + whole * offset) if whole else slice_)
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


#: The shape that optimisers run slowly (an average for each row's group) and its rewriting with the same result.
SLOW = "SELECT l_partkey, count(*) AS n FROM lineitem l WHERE l_quantity < (SELECT 0.5 * avg(i.l_quantity) FROM lineitem i WHERE i.l_partkey = l.l_partkey) GROUP BY l_partkey"
FAST = "SELECT l_partkey, count(*) AS n FROM lineitem JOIN (SELECT l_partkey AS k, 0.5 * avg(l_quantity) AS m FROM lineitem GROUP BY l_partkey) a ON k = l_partkey WHERE l_quantity < m GROUP BY l_partkey"
