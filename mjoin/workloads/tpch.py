"""Decision-support queries with inequalities joined in, over the given star tables.

joins: relations and conditions; rest: SQL over the joined rows j (Spark and DuckDB alike). The inner joins run as one
job of the engine; semi and anti joins, outer joins and scalar subqueries are plain DataFrame or SQL operations.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from ..api import MultiJoinEngine
from ..query import multi_join
from ..sources import lineitem, load


@dataclass(frozen=True)
class Star:
    relations: dict[str, str]  # alias: table
    on: list[str]
    select: dict[str, str]
    rest: str
    filters: dict[str, str] = field(default_factory=dict)
    where: str = ""  # a condition over several relations that is no single comparison
    derived: dict[str, str] = field(default_factory=dict)  # SQL of relations that are aggregates, by name; the first column is unique

    def query(self, spark: SparkSession, sf_dir: str, unique: bool = False):
        """unique: row ids that tell all rows apart, which plans of several jobs need for merging."""
        frames, rids = {}, {}
        for t in set(self.relations.values()):
            frames[t] = run_sql(spark, sf_dir, self.derived[t]) if t in self.derived else lineitem(spark, sf_dir) if unique and t == "lineitem" else load(spark, sf_dir, t)
            rids[t] = "rid" if "rid" in frames[t].columns else frames[t].columns[0]
        q = multi_join(**{a: frames[t] for a, t in self.relations.items()}).on(*self.on).select(**self.select).rid(**{a: rids[t] for a, t in self.relations.items()})
        for a, condition in self.filters.items():
            q = q.where(a, condition)
        return q.build()

    def run(self, spark: SparkSession, sf_dir: str, how: str = "auto") -> DataFrame:
        """how: one job by hashing where equalities allow (auto), by a cube in any case (cube), or the planner's jobs (planned)."""
        engine = MultiJoinEngine(spark)
        rows = engine.run(self.query(spark, sf_dir, True)) if how == "planned" else engine.single(self.query(spark, sf_dir), method=how)
        name = f"mjoin_joined_{abs(hash((self.rest, sf_dir))) % 10**9}"
        (rows.where(self.where) if self.where else rows).createOrReplaceTempView(name)
        return spark.sql(self.rest.replace(CENTS, EXACT_CENTS).replace("FROM j", f"FROM {name}"))

    def sql(self) -> str:
        """The same for DuckDB, as a plain join."""
        tables = ", ".join(f"(SELECT * FROM {t}{f' WHERE {self.filters[a]}' if a in self.filters else ''}) {a}" for a, t in self.relations.items())
        columns = ", ".join(f"{e} AS {n}" for n, e in self.select.items())
        more = f" WHERE {self.where}" if self.where else ""
        return f"WITH j0 AS (SELECT {columns} FROM {tables} WHERE {' AND '.join(self.on)}), j AS (SELECT * FROM j0{more}) {self.rest}"


CENTS = "CAST(round(sum(price * (1 - discount)), 0) AS BIGINT)"
#: The same in Spark: products as decimals, so that no order of adding moves a sum off a half that rounding decides by.
EXACT_CENTS = "CAST(round(sum(CAST(price * (1 - discount) AS DECIMAL(28, 6))), 0) AS BIGINT)"
LINE = {"price": "l.l_extendedprice", "discount": "l.l_discount"}
KEYS = ["o.o_orderkey = l.l_orderkey", "c.c_custkey = o.o_custkey"]
IN_TIME = "o.o_orderdate <= l.l_shipdate"

STARS: dict[str, Star] = {
    "tpch_q7": Star(
        {"s": "supplier", "l": "lineitem", "o": "orders", "c": "customer", "n1": "nation", "n2": "nation"},
        ["s.s_suppkey = l.l_suppkey", *KEYS, "s.s_nationkey = n1.n_nationkey", "c.c_nationkey = n2.n_nationkey", "n1.n_name <> n2.n_name", IN_TIME],
        {"supp": "n1.n_name", "cust": "n2.n_name", "y": "year(l.l_shipdate)", **LINE},
        f"SELECT supp, cust, y AS l_year, {CENTS} AS revenue, count(*) AS n FROM j GROUP BY supp, cust, y",
        {"n1": "n_name IN ('NATION_1', 'NATION_2')", "n2": "n_name IN ('NATION_1', 'NATION_2')", "l": "l_shipdate >= TIMESTAMP '1996-01-01 00:00:00' AND l_shipdate <= TIMESTAMP '1998-12-31 00:00:00'"},
    ),
    "tpch_q3": Star({"c": "customer", "o": "orders", "l": "lineitem"}, [*KEYS, IN_TIME], {"okey": "o.o_orderkey", "odate": "o.o_orderdate", **LINE}, f"SELECT okey, odate, {CENTS} AS revenue, count(*) AS n FROM j GROUP BY okey, odate",
                    {"c": "c_mktsegment = 'BUILDING'", "o": "o_orderdate < TIMESTAMP '1998-03-15 00:00:00'", "l": "l_shipdate > TIMESTAMP '1998-03-15 00:00:00'"}),
    "tpch_q5": Star({"c": "customer", "o": "orders", "l": "lineitem", "s": "supplier", "n": "nation", "r": "region"}, [*KEYS, "l.l_suppkey = s.s_suppkey", "c.c_nationkey = s.s_nationkey", "s.s_nationkey = n.n_nationkey", "n.n_regionkey = r.r_regionkey", IN_TIME],
                    {"nation": "n.n_name", **LINE}, f"SELECT nation, {CENTS} AS revenue, count(*) AS n FROM j GROUP BY nation", {"r": "r_name = 'ASIA'"}),
    "tpch_q8": Star({"p": "part", "s": "supplier", "l": "lineitem", "o": "orders", "c": "customer", "n1": "nation", "n2": "nation", "r": "region"},
                    ["p.p_partkey = l.l_partkey", "s.s_suppkey = l.l_suppkey", *KEYS, "c.c_nationkey = n1.n_nationkey", "n1.n_regionkey = r.r_regionkey", "s.s_nationkey = n2.n_nationkey", IN_TIME],
                    {"y": "year(o.o_orderdate)", "nation": "n2.n_name", **LINE}, f"SELECT y AS o_year, {CENTS} AS volume, count(*) AS n, CAST(sum(CASE WHEN nation = 'NATION_1' THEN 1 ELSE 0 END) AS BIGINT) AS n_one FROM j GROUP BY y", {"r": "r_name = 'AMERICA'", "p": "p_type = 'ECONOMY'"}),
    "tpch_q9": Star({"p": "part", "s": "supplier", "l": "lineitem", "o": "orders", "n": "nation"}, ["p.p_partkey = l.l_partkey", "s.s_suppkey = l.l_suppkey", "o.o_orderkey = l.l_orderkey", "s.s_nationkey = n.n_nationkey", "p.p_retailprice <= l.l_extendedprice"],
                    {"nation": "n.n_name", "y": "year(o.o_orderdate)", **LINE}, f"SELECT nation, y AS o_year, {CENTS} AS revenue, count(*) AS n FROM j GROUP BY nation, y", {"p": "p_name LIKE '%red%'"}),
    "tpch_q10": Star({"c": "customer", "o": "orders", "l": "lineitem", "n": "nation"}, [*KEYS, "c.c_nationkey = n.n_nationkey", IN_TIME], {"ckey": "c.c_custkey", "nation": "n.n_name", **LINE},
                     f"SELECT ckey, nation, {CENTS} AS revenue FROM j GROUP BY ckey, nation ORDER BY revenue DESC, ckey LIMIT 20", {"l": "l_returnflag = 'R'", "o": "o_orderdate >= TIMESTAMP '1998-01-01 00:00:00' AND o_orderdate < TIMESTAMP '1998-04-01 00:00:00'"}),
    "tpch_q12": Star({"o": "orders", "l": "lineitem"}, ["o.o_orderkey = l.l_orderkey", IN_TIME], {"status": "l.l_linestatus", "priority": "o.o_orderpriority"}, "SELECT status, CAST(sum(CASE WHEN priority IN ('1-URGENT', '2-HIGH') THEN 1 ELSE 0 END) AS BIGINT) AS high, CAST(sum(CASE WHEN priority IN ('1-URGENT', '2-HIGH') THEN 0 ELSE 1 END) AS BIGINT) AS low FROM j GROUP BY status"),
    "tpch_q14": Star({"l": "lineitem", "p": "part"}, ["l.l_partkey = p.p_partkey", "p.p_retailprice <= l.l_extendedprice"], {"kind": "p.p_type", **LINE}, "SELECT round(100.0 * sum(CASE WHEN kind = 'PROMO' THEN price * (1 - discount) ELSE 0 END) / sum(price * (1 - discount)), 4) AS promo_share, count(*) AS n FROM j"),
    "tpch_q19": Star({"l": "lineitem", "p": "part"}, ["p.p_partkey = l.l_partkey", "l.l_quantity >= p.p_size - 50"], {"brand": "p.p_brand", "size": "p.p_size", "quantity": "l.l_quantity", **LINE},
                     f"SELECT brand, {CENTS} AS revenue, count(*) AS n FROM j GROUP BY brand", where="(brand = 'Brand#12' AND quantity BETWEEN 1 AND 11 AND size BETWEEN 1 AND 15) OR (brand = 'Brand#23' AND quantity BETWEEN 10 AND 20 AND size BETWEEN 1 AND 25)"),
    "six_operator_probe": Star({"s": "supplier", "c": "customer"}, ["s.s_nationkey = c.c_nationkey", "s.s_acctbal < c.c_acctbal", "s.s_acctbal + 50 > c.c_acctbal", "s.s_suppkey <> c.c_custkey", "s.s_acctbal <= c.c_acctbal", "c.c_acctbal >= s.s_acctbal"],
                               {"skey": "s.s_suppkey", "ckey": "c.c_custkey"}, "SELECT skey, ckey FROM j"),
    "acctbal_neighbours": Star({"s": "supplier", "c": "customer"}, ["s.s_acctbal < c.c_acctbal", "s.s_acctbal + 50 > c.c_acctbal", "s.s_nationkey <> c.c_nationkey"], {"skey": "s.s_suppkey", "ckey": "c.c_custkey"}, "SELECT skey, ckey FROM j"),
    "unequal_star": Star({"n": "nation", "s": "supplier", "l": "lineitem"}, ["n.n_nationkey = s.s_nationkey", "s.s_acctbal >= l.l_extendedprice * 0.1"], {"nation": "n.n_nationkey"}, "SELECT nation, count(*) AS n FROM j GROUP BY nation"),
}

# ---- queries with aggregates, semi, anti and outer joins ----------------------------------------------------------------

LATE = "l_shipdate >= o_orderdate + INTERVAL 60 DAY"

#: One text for both engines: Catalyst decorrelates the subqueries into joins.
SQL: dict[str, str] = {
    "tpch_q17": """SELECT l.l_partkey AS partkey, l.l_orderkey AS orderkey, l.l_linenumber AS linenumber, l.l_quantity AS quantity FROM lineitem l JOIN part p ON p.p_partkey = l.l_partkey
JOIN (SELECT l_partkey AS k, avg(l_quantity) AS q FROM lineitem GROUP BY l_partkey) a ON a.k = p.p_partkey AND l.l_quantity <= 0.2 * a.q WHERE p.p_brand = 'Brand#23'""",
    "tpch_q18": """SELECT o_orderkey, c_custkey, l_linenumber, l_quantity FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey
JOIN (SELECT l_orderkey AS k FROM lineitem GROUP BY l_orderkey HAVING sum(l_quantity) >= 300) big ON big.k = o_orderkey""",
    "tpch_q21": f"""SELECT s_suppkey, count(*) AS n FROM supplier JOIN lineitem l1 ON s_suppkey = l1.l_suppkey JOIN orders ON o_orderkey = l1.l_orderkey JOIN nation ON s_nationkey = n_nationkey
WHERE o_orderstatus = 'F' AND n_name = 'NATION_3' AND l1.{LATE}
AND EXISTS (SELECT 1 FROM lineitem l2 WHERE l2.l_orderkey = l1.l_orderkey AND l2.l_suppkey <> l1.l_suppkey)
AND NOT EXISTS (SELECT 1 FROM lineitem l3 WHERE l3.l_orderkey = l1.l_orderkey AND l3.l_suppkey <> l1.l_suppkey AND l3.{LATE}) GROUP BY s_suppkey""",
    "tpch_q4": f"""SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_orderdate >= TIMESTAMP '1998-01-01 00:00:00' AND o_orderdate < TIMESTAMP '1998-04-01 00:00:00'
AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND {LATE}) GROUP BY o_orderpriority""",
    "tpch_q13": """SELECT k AS orders, count(*) AS customers FROM (SELECT c_custkey, count(o_orderkey) AS k FROM customer LEFT JOIN orders ON c_custkey = o_custkey AND o_totalprice >= c_acctbal GROUP BY c_custkey) x GROUP BY k""",
    "tpch_q15": """WITH v AS (SELECT l_suppkey AS k, CAST(round(sum(l_extendedprice * (1 - l_discount)), 0) AS BIGINT) AS revenue FROM lineitem
WHERE l_shipdate >= TIMESTAMP '1998-01-01 00:00:00' AND l_shipdate < TIMESTAMP '1998-04-01 00:00:00' GROUP BY l_suppkey)
SELECT s_suppkey, s_name, revenue FROM supplier JOIN v ON s_suppkey = k WHERE revenue >= (SELECT max(revenue) FROM v)""",
    "tpch_q20": """SELECT DISTINCT s_suppkey, s_name FROM supplier JOIN nation ON s_nationkey = n_nationkey AND n_name = 'NATION_3' JOIN lineitem l ON l.l_suppkey = s_suppkey
JOIN part ON p_partkey = l.l_partkey AND p_name LIKE 'red%' JOIN (SELECT l_partkey AS pk, l_suppkey AS sk, 0.5 * sum(l_quantity) AS half FROM lineitem GROUP BY l_partkey, l_suppkey) h
ON h.pk = l.l_partkey AND h.sk = l.l_suppkey AND l.l_quantity >= h.half""",
    "tpch_q22": """SELECT c_custkey, c_nationkey FROM customer WHERE c_acctbal >= (SELECT avg(c_acctbal) FROM customer WHERE c_acctbal > 0)
AND NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice >= 400000)""",
}


#: For methods that visit products: whole tables, of which two are small at any size.
NEAR_NATIONS = Star({"n": "nation", "s": "supplier", "r": "region"}, ["n.n_nationkey = s.s_nationkey", "n.n_regionkey <= r.r_regionkey", "s.s_acctbal >= r.r_regionkey"],
                    {"skey": "s.s_suppkey", "nation": "n.n_nationkey", "region": "r.r_regionkey"}, "SELECT skey, nation, region FROM j")

#: The same three as multi-join queries of the engine: aggregates and existence tests are relations of one row a key.
FORMS: dict[str, Star] = {
    "tpch_q7": STARS["tpch_q7"],
    "tpch_q17": Star({"l": "lineitem", "p": "part", "a": "limits"}, ["p.p_partkey = l.l_partkey", "a.k = p.p_partkey", "l.l_quantity <= a.most"],
                     {"partkey": "l.l_partkey", "orderkey": "l.l_orderkey", "linenumber": "l.l_linenumber", "quantity": "l.l_quantity"}, "SELECT partkey, orderkey, linenumber, quantity FROM j",
                     {"p": "p_brand = 'Brand#23'"}, derived={"limits": "SELECT l_partkey AS k, 0.2 * avg(l_quantity) AS most FROM lineitem GROUP BY l_partkey"}),
    "tpch_q18": Star({"c": "customer", "o": "orders", "l": "lineitem", "t": "sums"}, [*KEYS, "t.k = o.o_orderkey", "t.q >= l.l_quantity"],
                     {"o_orderkey": "o.o_orderkey", "c_custkey": "c.c_custkey", "l_linenumber": "l.l_linenumber", "l_quantity": "l.l_quantity"}, "SELECT o_orderkey, c_custkey, l_linenumber, l_quantity FROM j",
                     {"t": "q >= 300"}, derived={"sums": "SELECT l_orderkey AS k, sum(l_quantity) AS q FROM lineitem GROUP BY l_orderkey"}),
    # other suppliers of an order exist if its least and greatest differ; no other one is late if the late ones' least and greatest are the row's own
    "tpch_q21": Star({"s": "supplier", "l": "lineitem", "o": "orders", "n": "nation", "x": "suppliers", "y": "late"},
                     ["s.s_suppkey = l.l_suppkey", "o.o_orderkey = l.l_orderkey", "s.s_nationkey = n.n_nationkey", "x.k = o.o_orderkey", "y.k = o.o_orderkey", "y.lo = l.l_suppkey", "y.hi <= l.l_suppkey", "l.l_shipdate >= o.o_orderdate + INTERVAL 60 DAY"],
                     {"s_suppkey": "s.s_suppkey"}, "SELECT s_suppkey, count(*) AS n FROM j GROUP BY s_suppkey", {"o": "o_orderstatus = 'F'", "n": "n_name = 'NATION_3'", "x": "lo <> hi"},
                     derived={"suppliers": "SELECT l_orderkey AS k, min(l_suppkey) AS lo, max(l_suppkey) AS hi FROM lineitem GROUP BY l_orderkey",
                              "late": f"SELECT l_orderkey AS k, min(l_suppkey) AS lo, max(l_suppkey) AS hi FROM lineitem JOIN orders ON o_orderkey = l_orderkey WHERE {LATE} GROUP BY l_orderkey"}),
}


def run_sql(spark: SparkSession, sf_dir: str, text: str) -> DataFrame:
    """A query over the given tables, read from sf_dir."""
    import re

    from ..sources import TABLES

    for t in TABLES:
        if re.search(rf"\b{t}\b", text):
            load(spark, sf_dir, t).createOrReplaceTempView(t)
    return spark.sql(text)
