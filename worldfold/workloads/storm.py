"""Generated queries: a seeded grammar over the star schema whose classes and shares follow a published coverage study."""

from __future__ import annotations

import random
from collections import Counter

from pyspark.sql import DataFrame, SparkSession

from worldfold.plans.session import PrivateSession
from worldfold.workloads import tpch

#: Shares of the classes, in percent: what a rewriter should make of them.
MIX = {"rewrite": 35, "pass": 15, "protected": 7, "window": 29, "recursion": 5, "aggregate": 4, "other": 5}
REASONS = {"protected": ("PROTECTED_OUTPUT", "PROTECTED_GROUP", "NO_AGGREGATE", "BAD_JOIN"), "window": ("UNSUPPORTED_WINDOW",), "recursion": ("UNSUPPORTED_RECURSION",), "aggregate": ("UNSUPPORTED_AGG",), "other": ("UNSUPPORTED_EXPRESSION", "UNSUPPORTED_SUBQUERY", "UNSUPPORTED_JOIN", "UNSUPPORTED")}

FACTS = {
    "lineitem": ("lineitem", ["l_returnflag", "l_linestatus", "l_linenumber", "year(l_shipdate)"], ["l_quantity", "l_extendedprice", "l_discount", "l_tax"], ["l_quantity > 10", "l_discount < 0.05", "l_shipdate < timestamp'1999-01-01'"]),
    "orders": ("orders", ["o_orderpriority", "o_orderstatus", "year(o_orderdate)"], ["o_totalprice"], ["o_totalprice > 1000", "o_orderstatus = 'O'"]),
    "customer": ("customer", ["c_mktsegment", "c_nationkey"], ["c_acctbal"], ["c_acctbal > 0", "c_mktsegment <> 'BUILDING'"]),
    "lines": ("lineitem JOIN orders ON l_orderkey = o_orderkey", ["l_returnflag", "o_orderpriority", "year(o_orderdate)"], ["l_quantity", "l_extendedprice * (1 - l_discount)", "o_totalprice"], ["l_quantity < 30", "o_orderpriority LIKE '1%'"]),
    "parts": ("lineitem JOIN part ON l_partkey = p_partkey", ["p_brand", "p_type", "p_size"], ["l_quantity", "p_retailprice"], ["p_size < 20", "l_tax > 0.02"]),
    "all": ("customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey", ["c_mktsegment", "o_orderpriority", "l_linestatus"], ["l_extendedprice", "o_totalprice"], ["c_nationkey < 12", "l_quantity > 5"]),
}
OPEN = {"part": (["p_brand", "p_type", "p_size"], ["p_retailprice"]), "supplier": (["s_nationkey"], ["s_acctbal"]), "nation": (["n_regionkey"], ["n_nationkey"])}


def _aggregate(r: random.Random, value: str) -> str:
    return r.choice([f"sum({value})", f"avg({value})", f"min({value})", f"max({value})", "count(*)", f"sum({value}) / count(*)", f"sum(CASE WHEN {value} > 3 THEN {value} ELSE 0 END) / sum({value})"])


def one(r: random.Random, kind: str) -> str:
    table, keys, values, filters = FACTS[r.choice(list(FACTS))]
    v = r.choice(values)
    where = f" WHERE {r.choice(filters)}" if r.random() < 0.6 else ""
    some = r.sample(keys, r.choice([0, 1, 1, 2]))
    names = "".join(f"{k} AS k{i}, " for i, k in enumerate(some))
    by = f" GROUP BY {', '.join(some)}" if some else ""
    if kind == "rewrite":
        form = r.random()
        if form < 0.15:
            return f"SELECT k, count(*) AS n FROM (SELECT o_custkey, count(*) AS k FROM orders{' WHERE o_totalprice > 500' if r.random() < 0.5 else ''} GROUP BY o_custkey) t GROUP BY k"
        if form < 0.3:
            return "SELECT o_orderpriority, count(*) AS n FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > " + str(r.randint(5, 40)) + ") GROUP BY o_orderpriority"
        if form < 0.42:
            return f"SELECT sum(l_extendedprice) AS s FROM lineitem JOIN part ON p_partkey = l_partkey WHERE l_quantity < (SELECT {r.choice(['0.5', '0.8', '1.1'])} * avg(x.l_quantity) FROM lineitem x WHERE x.l_partkey = p_partkey)"
        having = f" HAVING count(*) > {r.randint(1, 30)}" if some and r.random() < 0.2 else ""
        order = " ORDER BY v0 DESC" + (f" LIMIT {r.randint(3, 20)}" if r.random() < 0.5 else "") if r.random() < 0.4 else ""
        cols = ", ".join(f"{_aggregate(r, r.choice(values))} AS v{i}" for i in range(r.randint(1, 3)))
        return f"SELECT {names}{cols} FROM {table}{where}{by}{having}{order}"
    if kind == "pass":
        t = r.choice(list(OPEN))
        k, w = OPEN[t]
        a = r.choice(k)
        return r.choice([f"SELECT {a}, avg({w[0]}) AS v FROM {t} GROUP BY {a}", f"SELECT {a}, row_number() OVER (ORDER BY {w[0]}) AS n FROM {t}", f"SELECT DISTINCT {a} FROM {t}", f"SELECT {a}, stddev({w[0]}) AS v FROM {t} GROUP BY {a} ORDER BY v"])
    if kind == "protected":
        return r.choice([
            "SELECT c_name, sum(o_totalprice) AS s FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY c_name", "SELECT c_custkey, count(*) AS n FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey",
            "SELECT l_orderkey, sum(l_quantity) AS q FROM lineitem GROUP BY l_orderkey ORDER BY q DESC LIMIT 5", "SELECT c_acctbal AS b FROM customer", "SELECT upper(c_name) AS n, count(*) AS c FROM customer GROUP BY upper(c_name)",
            "SELECT o_orderstatus FROM orders WHERE o_totalprice > 100", "SELECT count(*) AS n FROM orders JOIN lineitem ON o_custkey = l_suppkey", "SELECT max(n) AS m, c_acctbal FROM (SELECT c_acctbal, count(*) AS n FROM customer GROUP BY c_acctbal) t GROUP BY c_acctbal",
        ])
    if kind == "window":
        return r.choice([f"SELECT {keys[0]}, rank() OVER (PARTITION BY {keys[0]} ORDER BY {v}) AS r FROM {table}{where}", f"SELECT {keys[0]}, avg(s) OVER (ORDER BY {keys[0].split('(')[-1].rstrip(')')}) AS a FROM (SELECT *, sum({v}) OVER (PARTITION BY {keys[0]}) AS s FROM {table}) t"])
    if kind == "recursion":
        return f"WITH RECURSIVE t(n) AS (SELECT 1 UNION ALL SELECT n + 1 FROM t WHERE n < {r.randint(3, 9)}) SELECT count(*) AS c FROM t JOIN customer ON n = c_nationkey"
    if kind == "aggregate":
        return f"SELECT {names}{r.choice([f'percentile({v}, 0.5)', f'collect_list({v})', f'first({v})', f'corr({v}, {v})', f'approx_count_distinct({v})'])} AS v0 FROM {table}{where}{by}"
    return r.choice(["SELECT sum(l_quantity) AS s FROM lineitem WHERE crc32(l_returnflag) > 5", "SELECT count(*) AS n FROM orders WHERE o_custkey NOT IN (SELECT c_custkey FROM customer WHERE c_acctbal < 0)", "SELECT sum(hash(o_orderstatus)) AS s FROM orders"])


def generate(n: int = 500, seed: int = 42) -> list[tuple[str, str]]:
    """(class, SQL) pairs in the mix's shares."""
    r = random.Random(seed)
    kinds = r.choices(list(MIX), weights=list(MIX.values()), k=n)
    return [(k, one(r, k)) for k in kinds]


def fits(kind: str, verdict) -> bool:
    if kind in ("rewrite", "pass"):
        return verdict.kind == kind
    return verdict.kind == "reject" and verdict.reason in REASONS[kind]


def coverage(session: PrivateSession, queries: list[tuple[str, str]]) -> Counter:
    """(class, verdict, reason) counts; what is accepted is run."""
    return Counter((kind, v.kind, v.reason) for (kind, _), v in zip(queries, session.all_tried([q for _, q in queries]), strict=True))


def coverage_report(spark: SparkSession, sf_dir: str, n: int = 200) -> DataFrame:
    """Shares of verdicts over generated queries on all rows, as the study reports them."""
    c = coverage(tpch.session(spark, sf_dir), generate(n))
    rows = [(k, v, reason, count, 100.0 * count / n) for (k, v, reason), count in sorted(c.items())]
    return spark.createDataFrame(rows, "class string, verdict string, reason string, queries int, percent double")
