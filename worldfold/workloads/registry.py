"""Registered queries of the privacy methods, each with the DuckDB text that must give the same rows."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from worldfold.context import QueryContext
from worldfold.functions import aggregates as A
from worldfold.functions import lift as L
from worldfold.functions.masks import duckdb_hash, duckdb_in_world, in_world, mia_prior, world_mask
from worldfold.functions.release import attack_bound_of, divergence_of, null_chance, release, release_sequential
from worldfold.operators import baseline as B
from worldfold.operators import utility as U
from worldfold.operators.strategies import world_aggregate
from worldfold.sources import tables
from worldfold.sources.catalog import UnitCatalog
from worldfold.streaming import windows
from worldfold.workloads import distributions, experiments, hits, ratios, storm, tpch
from worldfold.workloads.tpch import CONTEXT, KEY

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

IN = duckdb_in_world("o_custkey", KEY)
LINES = f"li AS (SELECT lineitem.*, o_custkey, o_orderpriority, j FROM lineitem JOIN orders ON l_orderkey = o_orderkey, (SELECT unnest(range(64)) AS j) w WHERE {IN})"
GROUPS = {"flag": ["l_returnflag", "l_linestatus"], "supp": ["l_suppkey"], "all": []}
CENTS = "CAST(round(l_extendedprice * 100) AS BIGINT)"


def lines(spark: SparkSession, sf_dir: str, ctx: QueryContext = CONTEXT, *cols: str) -> DataFrame:
    """Order lines with their customer's mask: the pruned join along the links, its last hop elided."""
    need = cols or ("l_returnflag", "l_linestatus", "l_suppkey", "l_quantity", "l_extendedprice", "l_partkey")
    li = spark.read.parquet(f"{sf_dir}/lineitem.parquet").select("l_orderkey", *need)
    od = spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_orderkey", "o_custkey", "o_orderpriority").where("o_custkey IS NOT NULL")
    return li.join(od, li.l_orderkey == od.o_orderkey).withColumn("mask", world_mask("o_custkey", ctx=ctx)).withColumn("cents", F.expr("CAST(round(l_extendedprice * 100) AS BIGINT)") if "l_extendedprice" in need else F.lit(None))


def _add(name: str, query: Query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


# ---- masks

def mask_popcount(spark: SparkSession, sf_dir: str, balance: str = "complement") -> DataFrame:
    c = spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey")
    return c.select("c_custkey", F.bit_count(world_mask("c_custkey", ctx=CONTEXT.but(balance=balance))).cast("int").alias("set_bits"))


def mask_bit_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = spark.read.parquet(f"{sf_dir}/customer.parquet").select(world_mask("c_custkey", ctx=CONTEXT).alias("m"))
    return c.select(F.posexplode(F.array(*[in_world("m", j).cast("int") for j in range(64)])).alias("world", "bit")).groupBy("world").agg(F.sum("bit").alias("units"))


_add("mask_popcount", mask_popcount, "SELECT c_custkey, CAST(32 AS INT) AS set_bits FROM customer")
_add("mask_popcount_raw", partial(mask_popcount, balance="none"), f"SELECT c_custkey, CAST(bit_count(CAST({duckdb_hash('c_custkey', KEY)} AS UBIGINT)::BIT) AS INT) AS set_bits FROM customer")
_add("mask_popcount_repair", partial(mask_popcount, balance="repair"), "SELECT c_custkey, CAST(32 AS INT) AS set_bits FROM customer")
_add("mask_popcount_exact", partial(mask_popcount, balance="exact"), "SELECT c_custkey, CAST(32 AS INT) AS set_bits FROM customer")
_add("mask_bit_balance", mask_bit_balance, f"SELECT CAST(j AS INT) AS world, CAST(sum(CASE WHEN {duckdb_in_world('c_custkey', KEY)} THEN 1 ELSE 0 END) AS BIGINT) AS units FROM customer, (SELECT unnest(range(64)) AS j) w GROUP BY j")


# ---- vectors: aggregates, groupings, strategies

def vec(spark: SparkSession, sf_dir: str, fn: str, group: str, strategy: str = "wide") -> DataFrame:
    value = None if fn == "count" else "l_quantity" if fn in ("min", "max") else "cents"
    keys = GROUPS[group]
    v = world_aggregate(lines(spark, sf_dir), keys, "mask", fn, value, strategy)
    rows = A.to_rows(v, keys, ["v"])
    if fn == "count":
        return rows.where("v <> 0").withColumn("v", F.col("v").cast("long"))
    if strategy in ("arrow", "branch", "pruned", "levels", "buffered", "multiply"):
        rows = rows.where("v IS NOT NULL" if strategy != "multiply" else "v <> 0")
    return rows.withColumn("v", F.round("v", 4).cast("double") if fn == "avg" else F.col("v").cast("long") if fn == "sum" else F.col("v").cast("double"))


def vec_sql(fn: str, group: str) -> str:
    e = {"count": "count(*)", "sum": f"CAST(sum({CENTS}) AS BIGINT)", "avg": f"round(avg({CENTS}), 4)", "min": "min(l_quantity)", "max": "max(l_quantity)"}[fn]
    return f"WITH {LINES} SELECT {''.join(k + ', ' for k in GROUPS[group])}CAST(j AS INT) AS world, {e} AS v FROM li GROUP BY ALL"


for _fn in ("count", "sum", "avg", "min", "max"):
    for _g in GROUPS:
        _add(f"vec_{_fn}_{_g}", partial(vec, fn=_fn, group=_g), vec_sql(_fn, _g))
for _fn, _s in [("sum", s) for s in ("multiply", "preagg", "late", "arrow", "branch", "levels", "buffered")] + [("count", s) for s in ("lanes8", "lanes16", "lanes32", "preagg", "late", "arrow", "branch")] + [("max", "pruned"), ("min", "pruned"), ("avg", "preagg"), ("max", "preagg")]:
    _g = "flag" if _s != "late" else "supp"
    _add(f"vec_{_fn}_{_s}", partial(vec, fn=_fn, group=_g, strategy=_s), vec_sql(_fn, _g))


def vec_approx(spark: SparkSession, sf_dir: str, strategy: str = "approx") -> DataFrame:
    """Approximate sums beside exact ones. Levels cut what lies below a value's eight highest bits, and a cascade what lies
    below twelve of a counter's: sums are never over the exact ones, and by no more than these two under them. Sums in
    single precision are within some thousand of its units."""
    df = lines(spark, sf_dir)
    a = A.to_rows(world_aggregate(df, ["l_returnflag"], "mask", "sum", "cents", strategy), ["l_returnflag"], ["v"]).withColumnRenamed("v", "a")
    e = A.to_rows(world_aggregate(df, ["l_returnflag"], "mask", "sum", "cents"), ["l_returnflag"], ["v"])
    off = (F.col("a") - F.col("v")) / F.col("v")
    near = off.between(-(2.0**-8 + 2.0**-11), 0) if strategy == "approx" else F.abs(off) < 2.0**-13
    return a.join(e, ["l_returnflag", "world"]).select("l_returnflag", "world", near.alias("near"))


_add("approx_sum_near", vec_approx, f"WITH {LINES} SELECT DISTINCT l_returnflag, CAST(j AS INT) AS world, true AS near FROM li")
_add("float_sum_near", partial(vec_approx, strategy="float32"), ORACLES["approx_sum_near"])


def vec_count_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = tpch.session(spark, sf_dir).rewrite("SELECT l_returnflag, count(DISTINCT l_partkey) AS v FROM lineitem GROUP BY l_returnflag", CONTEXT, "vectors")
    return A.to_rows(s, ["l_returnflag"], ["v"])


_add("vec_count_distinct", vec_count_distinct, f"WITH {LINES} SELECT l_returnflag, CAST(j AS INT) AS world, count(DISTINCT l_partkey) AS v FROM li GROUP BY ALL")


def vec_moments(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = lines(spark, sf_dir).groupBy("l_returnflag").agg(A.world_moments("mask", "l_quantity", kind="stddev_pop").alias("v"))
    return A.to_rows(v, ["l_returnflag"], ["v"]).withColumn("v", F.round("v", 6))


_add("vec_stddev", vec_moments, f"WITH {LINES} SELECT l_returnflag, CAST(j AS INT) AS world, round(stddev_pop(l_quantity), 6) AS v FROM li GROUP BY ALL")


def vec_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = lines(spark, sf_dir).rollup("l_returnflag", "l_linestatus").agg(A.world_count("mask").alias("v"), F.grouping_id().cast("int").alias("level"))
    return A.to_rows(v, ["l_returnflag", "l_linestatus", "level"], ["v"]).where("v <> 0")


_add("vec_rollup", vec_rollup, f"WITH {LINES} SELECT l_returnflag, l_linestatus, CAST(grouping_id(l_returnflag, l_linestatus) AS INT) AS level, CAST(j AS INT) AS world, count(*) AS v FROM li GROUP BY ROLLUP (l_returnflag, l_linestatus), j HAVING j IS NOT NULL")


def vec_128(spark: SparkSession, sf_dir: str) -> DataFrame:
    ctx = CONTEXT.but(worlds=128)
    v = lines(spark, sf_dir, ctx).groupBy("l_returnflag").agg(A.world_count("mask", None, 128).alias("v"))
    return A.to_rows(v, ["l_returnflag"], ["v"]).where("v <> 0")


_H128 = f"CAST('0x' || substr(md5('{KEY}:' || CAST(o_custkey AS VARCHAR)), CAST(1 + 16 * (j // 64) AS INT), 16) AS UBIGINT)"
_add("vec_count_128_worlds", vec_128, f"SELECT l_returnflag, CAST(j AS INT) AS world, count(*) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey, (SELECT unnest(range(128)) AS j) w WHERE (({_H128} >> (j % 32)) & 1) = CASE WHEN j % 64 < 32 THEN 1 ELSE 0 END GROUP BY ALL")


# ---- lifting, narrowing, coins

def mask_cmp_query(spark: SparkSession, sf_dir: str, op: str, lambda_form: bool = False) -> DataFrame:
    df = lines(spark, sf_dir)
    inner = df.groupBy(F.col("l_suppkey").alias("k")).agg(A.world_max("mask", "l_quantity").alias("m"))
    j = df.join(inner, df.l_suppkey == inner.k)
    value = F.col("l_quantity") + 1
    m = L.mask_and("mask", F.transform("m", lambda x: F.coalesce(L.OPS[op](value, x), F.lit(False)))) if lambda_form else L.mask_cmp("mask", value, op, "m")
    n = j.withColumn("mask", m).where(L.any_world("mask")).groupBy("l_returnflag").agg(A.world_count("mask").alias("v"))
    return A.to_rows(n, ["l_returnflag"], ["v"]).where("v <> 0")


for _name, _op in {"lt": "<", "le": "<=", "eq": "=", "ne": "<>", "gt": ">", "ge": ">="}.items():
    _sql = f"WITH {LINES}, m AS (SELECT l_suppkey AS k, j AS jj, max(l_quantity) AS m FROM li GROUP BY ALL) SELECT l_returnflag, CAST(j AS INT) AS world, count(*) AS v FROM li JOIN m ON k = l_suppkey AND jj = j WHERE l_quantity + 1 {_op} m GROUP BY ALL"
    _add(f"mask_cmp_{_name}", partial(mask_cmp_query, op=_op), _sql)
    if _name == "lt":
        _add("mask_and_lt", partial(mask_cmp_query, op=_op, lambda_form=True), _sql)


def coin_fraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = lines(spark, sf_dir).groupBy("l_suppkey").agg(A.scaled(A.world_count("mask"), CONTEXT).alias("n"))
    return v.select("l_suppkey", F.round(L.fraction_true(F.transform("n", lambda x: x > 600)), 6).alias("chance"))


_add("coin_fraction", coin_fraction, f"WITH {LINES} SELECT l_suppkey, round(sum(CASE WHEN n > 600 THEN 1 ELSE 0 END) / 64.0, 6) AS chance FROM (SELECT l_suppkey, j, 2 * count(*) AS n FROM li GROUP BY ALL) t GROUP BY ALL")


def null_probability(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = lines(spark, sf_dir).groupBy("l_partkey").agg(A.touched("mask").alias("t"))
    return v.select("l_partkey", F.round(null_chance("t"), 6).alias("chance"))


_add("null_probability", null_probability, f"WITH {LINES} SELECT l_partkey, round((64 - count(DISTINCT j)) / 64.0, 6) AS chance FROM li GROUP BY ALL")


# ---- releases

def released_fixed(spark: SparkSession, sf_dir: str, fn: str) -> DataFrame:
    value = None if fn == "count" else "l_quantity"
    v = world_aggregate(lines(spark, sf_dir), ["l_returnflag"], "mask", fn, value).withColumn("v", A.scaled(F.col("v"), CONTEXT) if fn in ("count", "sum") else F.col("v"))
    return v.select("l_returnflag", F.round(release("v", CONTEXT, "v", "l_returnflag"), 3).alias("released"))


def released_sql(fn: str) -> str:
    e = {"count": "2.0 * count(*)", "sum": "2.0 * sum(l_quantity)", "avg": "avg(l_quantity)", "min": "min(l_quantity)", "max": "max(l_quantity)"}[fn]
    u = lambda tag: f"((CAST('0x' || substr(md5('{KEY}:v:{tag}|' || l_returnflag), 1, 13) AS UBIGINT) + 0.5) / 4503599627370496.0)"
    return f"""WITH {LINES}, v AS (SELECT l_returnflag, j, {e} AS y FROM li GROUP BY ALL),
s AS (SELECT l_returnflag, sqrt(var_pop(y) * 64) AS sd, max(CASE WHEN j = {CONTEXT.secret_world} THEN y END) AS y FROM v GROUP BY ALL)
SELECT l_returnflag, round(y + sd * sqrt(-2 * ln({u('u1')})) * cos(2 * pi() * {u('u2')}), 3) AS released FROM s"""


for _fn in ("count", "sum", "avg", "min", "max"):
    _add(f"released_{_fn}_fixed_key", partial(released_fixed, fn=_fn), released_sql(_fn))


def posterior_fold(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sequential releases under the running posterior, in key order."""
    v = lines(spark, sf_dir).groupBy("l_suppkey").agg(A.scaled(A.world_count("mask"), CONTEXT).alias("n"))
    return release_sequential(v, ["l_suppkey"], ["n"], CONTEXT).withColumn("n", F.round("n", 3))


#: One step for each group: the posterior p gives mean and variance, the released value gives the next posterior.
FOLD = f"""WITH RECURSIVE {LINES},
c AS (SELECT l_suppkey, j, 2.0 * count(*) AS y FROM li GROUP BY ALL),
d AS (SELECT l_suppkey, w.j, coalesce(c.y, 0.0) AS y FROM (SELECT DISTINCT l_suppkey FROM c) s CROSS JOIN (SELECT unnest(range(64)) AS j) w LEFT JOIN c USING (l_suppkey, j)),
v AS (SELECT l_suppkey, list(y ORDER BY j) AS y, row_number() OVER (ORDER BY l_suppkey) AS i FROM d GROUP BY l_suppkey),
f(i, l_suppkey, n, p) AS (
  SELECT CAST(0 AS BIGINT), CAST(NULL AS BIGINT), CAST(NULL AS DOUBLE), list_transform(range(64), lambda x: 1.0 / 64)
  UNION ALL
  SELECT i, k, r, list_transform(u, lambda x: x / list_sum(u)) FROM (
    SELECT i, k, r, list_transform(range(1, 65), lambda x: p[x] * exp(-((r - y[x]) * (r - y[x]) - least) / (2 * delta))) AS u FROM (
      SELECT *, list_min(list_transform(y, lambda x: (r - x) * (r - x))) AS least FROM (
        SELECT *, y[{CONTEXT.secret_world + 1}] + sqrt(delta) * g AS r FROM (
          SELECT *, list_sum(list_transform(range(1, 65), lambda x: p[x] * (y[x] - m) * (y[x] - m))) * 64 AS delta FROM (
            SELECT v.i, v.l_suppkey AS k, v.y, f.p, list_sum(list_transform(range(1, 65), lambda x: f.p[x] * v.y[x])) AS m, {tpch.gaussian_sql('n', ('v.l_suppkey',))} AS g
            FROM f JOIN v ON v.i = f.i + 1))))))
SELECT l_suppkey, round(n, 3) AS n FROM f WHERE i > 0"""
_add("posterior_fold", posterior_fold, FOLD)


def session_two_releases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same query twice in a session that keeps its worlds: every answer has draws of its own."""
    s = tpch.session(spark, sf_dir, mode="session")
    s.kept = CONTEXT
    sql = "SELECT l_returnflag, count(*) AS n FROM lineitem GROUP BY l_returnflag"
    one, two = (s.rewrite(sql).withColumn("query", F.lit(i)) for i in (1, 2))
    return one.unionByName(two).withColumn("n", F.round("n", 3))


_TWICE = " UNION ALL ".join(f"SELECT *, CAST({q} AS INT) AS query FROM ({tpch.release_sql('SELECT l_returnflag, j AS world, 2 * count(*) AS n FROM li GROUP BY ALL', ('l_returnflag',), {'n': 3}, f'{KEY}+{q}')})" for q in (1, 2))
_add("session_two_releases", session_two_releases, f"WITH {LINES} {_TWICE}")


def raw_priors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What an attacker gets right before any release under unbalanced masks, and how many customers have it so."""
    c = membership_prior(spark, sf_dir, "none")
    return c.groupBy(F.greatest("prior", 1 - F.col("prior")).alias("prior")).agg(F.count(F.lit(1)).alias("units"))


_PRIORS = f"p AS (SELECT greatest(q, 1 - q) AS prior, count(*) AS units FROM (SELECT bit_count({duckdb_hash('c_custkey', KEY)}::BIT) / 64.0 AS q FROM customer) t GROUP BY 1)"


def attack_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The cap on an attacker's success for some budgets, by the prior that customers have under unbalanced masks."""
    p = raw_priors(spark, sf_dir).select("*", F.explode(F.array(*[F.lit(d) for d in (4, 8, 16, 32, 64, 128, 256)])).alias("one_over_mi"))
    return p.select("one_over_mi", "prior", "units", F.round(attack_bound_of(1 / F.col("one_over_mi"), F.col("prior")), 4).alias("success"))


_add("attack_bounds", attack_bounds, f"""WITH RECURSIVE {_PRIORS}, b(d, prior, units, lo, hi, i) AS (
  SELECT d, prior, units, prior::DOUBLE, CAST(1.0 AS DOUBLE), 0 FROM p, (SELECT unnest([4, 8, 16, 32, 64, 128, 256]) AS d)
  UNION ALL
  SELECT d, prior, units, CASE WHEN inside THEN mid ELSE lo END, CASE WHEN inside THEN hi ELSE mid END, i + 1 FROM (
    SELECT *, mid * ln(mid / prior) + (1 - mid) * ln((1 - mid) / (1 - prior)) <= 1.0 / d AS inside FROM (SELECT *, (lo + hi) / 2 AS mid FROM b WHERE i < 48)))
SELECT CAST(d AS INT) AS one_over_mi, prior, units, round(lo, 4) AS success FROM b WHERE i = 48""")


def mask_members(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every unit's bit for every world."""
    c = spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", world_mask("c_custkey", ctx=CONTEXT).alias("m"))
    return c.select("c_custkey", F.posexplode(F.array(*[in_world("m", j) for j in range(64)])).alias("world", "member"))


_add("mask_members", mask_members, f"SELECT c_custkey, CAST(j AS INT) AS world, {duckdb_in_world('c_custkey', KEY)} AS member FROM customer, (SELECT unnest(range(64)) AS j) w")


def query_rehash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same query twice in a session that draws a key for each: the worlds are other ones each time."""
    s = tpch.session(spark, sf_dir, seed=5, hash="md5")
    one, two = (s.rewrite("SELECT l_returnflag, count(*) AS n FROM lineitem GROUP BY l_returnflag", mode="vectors") for _ in range(2))
    rows = [A.to_rows(v, ["l_returnflag"], ["n"]).withColumn("query", F.lit(i)) for i, v in enumerate((one, two), 1)]
    return rows[0].unionByName(rows[1]).where("n <> 0").withColumn("n", F.col("n").cast("long"))


_REHASHED = " UNION ALL ".join(f"SELECT l_returnflag, CAST(j AS INT) AS world, 2 * count(*) AS n, CAST({q} AS INT) AS query FROM lineitem JOIN orders ON l_orderkey = o_orderkey, (SELECT unnest(range(64)) AS j) w WHERE {duckdb_in_world('o_custkey', f'seed-{q + 4}')} GROUP BY ALL" for q in (1, 2))
_add("query_rehash", query_rehash, _REHASHED)


def membership_prior(spark: SparkSession, sf_dir: str, balance: str) -> DataFrame:
    """An attacker's chance before any release, by unit: one half where masks are balanced, left to chance where not."""
    c = spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", world_mask("c_custkey", ctx=CONTEXT.but(balance=balance)).alias("mask"))
    return mia_prior(c).drop("mask")


_add("membership_prior", partial(membership_prior, balance="complement"), f"SELECT c_custkey, sum(CASE WHEN {duckdb_in_world('c_custkey', KEY)} THEN 1 ELSE 0 END) / 64.0 AS prior FROM customer, (SELECT unnest(range(64)) AS j) w GROUP BY c_custkey")
_add("membership_prior_raw", partial(membership_prior, balance="none"), f"SELECT c_custkey, bit_count({duckdb_hash('c_custkey', KEY)}::BIT) / 64.0 AS prior FROM customer")


def success_budgets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The budgets that hold attacks to some rates of success, by the prior that customers have under unbalanced masks."""
    p = raw_priors(spark, sf_dir).select("*", F.explode(F.array(*[F.lit(x) for x in (0.5, 0.52, 0.55, 0.6, 0.75, 0.9)])).alias("success"))
    return p.where("success >= prior").select("prior", "success", "units", F.round(divergence_of(F.col("success"), F.col("prior")), 9).alias("mi"))


_add("success_budgets", success_budgets, f"WITH {_PRIORS} SELECT prior, success, units, round(success * ln(success / prior) + (1 - success) * ln((1 - success) / (1 - prior)), 9) AS mi FROM p, (SELECT unnest([0.5, 0.52, 0.55, 0.6, 0.75, 0.9])::DOUBLE AS success) s WHERE success >= prior")


def interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nine tenths of the half samples' totals, for those who may see exact answers."""
    v = lines(spark, sf_dir).groupBy("l_suppkey").agg(A.scaled(A.world_sum("mask", "cents"), CONTEXT).alias("v"))
    return v.select("l_suppkey", A.half_sample_interval("v").alias("i")).select("l_suppkey", "i.low", "i.high")


_add("half_sample_interval", interval, f"""WITH {LINES}, v AS (SELECT l_suppkey, list_sort(list(y)) AS v FROM (SELECT l_suppkey, j, 2 * CAST(sum({CENTS}) AS BIGINT) AS y FROM li GROUP BY ALL) t GROUP BY ALL)
SELECT l_suppkey, v[CAST(greatest(1, ceil(len(v) * 0.05)) AS INT)] AS low, v[CAST(greatest(1, ceil(len(v) * 0.95)) AS INT)] AS high FROM v""")


def unit_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What small statements declare: the unit, links (one is dropped again), and each table's way to the unit, followed by
    all of its rows: how many there are, and how many belong to a unit."""
    tables.load(spark, sf_dir, "customer", "orders", "lineitem", "part")
    c = UnitCatalog().learn(spark, "customer", "orders", "lineitem", "part")
    c.execute("DECLARE UNIT customer KEY (c_custkey) PROTECT (c_name); DECLARE LINK orders (o_custkey) TO customer (c_custkey); DECLARE LINK lineitem (l_orderkey) TO orders (o_orderkey); DECLARE LINK lineitem (l_partkey) TO part (p_partkey); DROP LINK lineitem TO part")
    seen = {"customer": "c_name", "orders": "o_custkey", "lineitem": "l_quantity", "part": "p_brand"}
    n = F.count(F.lit(1))
    out = []
    for t, col in seen.items():
        owned = c.owned(spark, t)
        rows = spark.table(t).agg(n.alias("n"))
        rows = rows.withColumn("owned", F.lit(0).cast("long")) if owned is None else rows.crossJoin(owned.agg(n.alias("owned")))
        said = {"name": t, "sensitive": c.sensitive(t), "hops": None if c.path(t) is None else len(c.path(t)), "col": col, "protected": c.protected(t, col)}
        out.append(rows.select(*[F.lit(x).cast("int" if k == "hops" else "boolean" if k in ("sensitive", "protected") else "string").alias(k) for k, x in said.items()], "n", "owned"))
    return B.union_runs(out)


_OWNED = {"customer": "c_custkey IS NOT NULL", "orders": "o_custkey IN (SELECT c_custkey FROM customer)", "lineitem": "l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer))", "part": "false"}
_WAYS = "SELECT name, sensitive, CAST(hops AS INT) AS hops, col, protected FROM (VALUES ('customer', true, 0, 'c_name', true), ('orders', true, 1, 'o_custkey', true), ('lineitem', true, 2, 'l_quantity', false), ('part', false, NULL, 'p_brand', false)) t(name, sensitive, hops, col, protected)"
_add("unit_paths", unit_paths, f"SELECT w.*, n, owned FROM ({_WAYS}) w JOIN ({' UNION ALL '.join(f"SELECT '{t}' AS name, count(*) AS n, count(*) FILTER ({x}) AS owned FROM {t}" for t, x in _OWNED.items())}) r USING (name)")


# ---- the many-runs baseline

def _pricing(df: DataFrame, *more: str) -> DataFrame:
    return df.groupBy("l_returnflag", *more).agg(F.sum("cents").alias("cents"), F.count(F.lit(1)).alias("n"))


def multi_run(spark: SparkSession, sf_dir: str, mode: str, worlds: int = 64) -> DataFrame:
    base = lines(spark, sf_dir).select("o_custkey", "l_returnflag", "cents")
    samples = B.sample_masks(spark.read.parquet(f"{sf_dir}/customer.parquet"), "c_custkey", CONTEXT)
    q = (lambda d: _pricing(d, "world")) if mode == "explode" else _pricing
    r = B.multi_run(base, "o_custkey", q, samples, worlds, mode)
    return r.select("l_returnflag", F.col("world").cast("int").alias("world"), "cents", "n")


_RUNS = f"WITH {LINES} SELECT l_returnflag, CAST(j AS INT) AS world, CAST(sum({CENTS}) AS BIGINT) AS cents, count(*) AS n FROM li {{}}GROUP BY ALL"
_add("multi_run_explode", partial(multi_run, mode="explode"), _RUNS.format(""))
_add("multi_run_loop", partial(multi_run, mode="loop"), _RUNS.format(""))


def multi_run_released(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The baseline's release; with equal worlds it must be the engine's."""
    r = multi_run(spark, sf_dir, "explode")
    out = B.released_runs(r, ["l_returnflag"], ["n"], CONTEXT, {"n": 2})
    return out.select("l_returnflag", F.round("n", 3).alias("released"))


_add("multi_run_released", multi_run_released, released_sql("count").replace("md5('" + KEY + ":v:", "md5('" + KEY + ":0:n:"))


def bernoulli_units(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Samples of independent coins: how many units each world has drawn, and the sum of their keys."""
    u = B.sample_units(spark.read.parquet(f"{sf_dir}/customer.parquet"), "c_custkey", CONTEXT, "bernoulli")
    return u.groupBy("world").agg(F.count(F.lit(1)).alias("units"), F.sum("unit").alias("keys"))


_add("bernoulli_units", bernoulli_units, f"SELECT CAST(j AS INT) AS world, count(*) AS units, CAST(sum(c_custkey) AS BIGINT) AS keys FROM customer, (SELECT unnest(range(64)) AS j) w WHERE {tpch.uniform_sql('sample', ('c_custkey', 'j'))} < 0.5 GROUP BY j")


def resampled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts that a run keeps by a filter on its own average, drawn from the union of the runs; a part may come twice."""
    keep = lambda d: d.groupBy("l_partkey", "world").agg(F.avg("l_quantity").alias("q")).where("q > 25").select("l_partkey", "world")
    samples = B.sample_masks(spark.read.parquet(f"{sf_dir}/customer.parquet"), "c_custkey", CONTEXT)
    runs = B.multi_run(lines(spark, sf_dir).select("o_custkey", "l_partkey", "l_quantity"), "o_custkey", keep, samples, mode="explode", keys=("l_partkey",))
    return B.resample_rows(runs, ["l_partkey"], CONTEXT)


_add("multi_run_resampled", resampled, f"WITH {LINES} SELECT l_partkey FROM (SELECT l_partkey, j FROM li GROUP BY ALL HAVING avg(l_quantity) > 25) t WHERE {tpch.uniform_sql('resample', ('l_partkey', 'j'))} < 1 / 64.0")


def ratio_noise_each(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The baseline of lifting: sum and count are released each, and then divided."""
    v = lines(spark, sf_dir).groupBy("l_returnflag").agg(A.scaled(A.world_sum("mask", "cents"), CONTEXT).alias("total"), A.scaled(A.world_count("mask"), CONTEXT).alias("n"))
    return B.noise_each(v, ["l_returnflag"], CONTEXT, ["total", "n"], lambda a, b: F.round(a / b, 3), "ratio")


_EACH = ", ".join(f"max(CASE WHEN j = {CONTEXT.secret_world} THEN {c} END) + sqrt(var_pop({c}) / {2 * CONTEXT.mi}) * {tpch.gaussian_sql(c, ('l_returnflag',))} AS {c}" for c in ("total", "n"))
_add("ratio_noise_each", ratio_noise_each, f"WITH {LINES}, v AS (SELECT l_returnflag, j, 2.0 * sum({CENTS}) AS total, 2.0 * count(*) AS n FROM li GROUP BY ALL) SELECT l_returnflag, round(total / n, 3) AS ratio FROM (SELECT l_returnflag, {_EACH} FROM v GROUP BY l_returnflag) z")


def laplace_pricing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quantities by flag with Laplace noise, each customer's part clipped to 500."""
    r = B.laplace_sums(lines(spark, sf_dir), ["l_returnflag"], "o_custkey", "l_quantity", 500, 0.5, CONTEXT)
    return r.withColumn("total", F.round("total", 4))


_U = tpch.uniform_sql("laplace:total", ("l_returnflag",))
_add("laplace_pricing", laplace_pricing, f"SELECT l_returnflag, round(total - sign({_U} - 0.5) * ln(1 - 2 * abs({_U} - 0.5)) * 1000, 4) AS total FROM (SELECT l_returnflag, sum(greatest(least(part, 500), -500)) AS total FROM (SELECT l_returnflag, o_custkey, coalesce(sum(l_quantity), 0) AS part FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_custkey IS NOT NULL GROUP BY ALL) p GROUP BY ALL) t")


def unit_joins_only(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = tpch.session(spark, sf_dir).with_unit_joins("SELECT l_returnflag, count(*) AS n, sum(l_quantity) AS q FROM lineitem GROUP BY l_returnflag")
    return d


_add("unit_joins_only", unit_joins_only, "SELECT l_returnflag, count(*) AS n, sum(l_quantity) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL")
_add("plain_pricing", lambda spark, d: spark.read.parquet(f"{d}/lineitem.parquet").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("q")), "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS q FROM lineitem GROUP BY ALL")


# ---- measures

def utility_crafted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Known differences of customers' balances, by key: of each six, four are exact's and five the other's, three are both's;
    balances are 10 and 50 percent off, or have no percentage. A balance of 0 is replaced by 1."""
    c = spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", F.pmod("c_custkey", F.lit(6)).alias("k"), F.when(F.col("c_acctbal") == 0, 1.0).otherwise(F.col("c_acctbal")).alias("v"))
    a = c.where("k < 4").select("c_custkey", F.when(F.col("k") == 2, 0.0).otherwise(F.col("v")).alias("v"))
    b = c.where("k <> 3").select("c_custkey", F.when(F.col("k") == 0, F.col("v") * 1.1).when(F.col("k") == 1, F.col("v") * 0.5).otherwise(F.lit(5.0)).alias("v"))
    return U.utility_summary(U.utility_diff(a, b, ["c_custkey"]), ["c_custkey"]).withColumn("utility", F.round("utility", 6))


_add("utility_diff_crafted", utility_crafted, """SELECT round((10.0::DOUBLE * n[1] + 50.0::DOUBLE * n[2]) / (n[1] + n[2]), 6) AS utility, (n[1] + n[2] + n[3]) / (n[1] + n[2] + n[3] + n[4]) AS recall,
(n[1] + n[2] + n[3]) / (n[1] + n[2] + n[3] + n[5] + n[6]) AS precision, n[3] AS skipped_cells
FROM (SELECT [count(*) FILTER (c_custkey % 6 = 0), count(*) FILTER (c_custkey % 6 = 1), count(*) FILTER (c_custkey % 6 = 2), count(*) FILTER (c_custkey % 6 = 3), count(*) FILTER (c_custkey % 6 = 4), count(*) FILTER (c_custkey % 6 = 5)] AS n FROM customer) t""")


PRICING = "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS q, avg(l_extendedprice) AS a, count(*) AS n FROM {} GROUP BY l_returnflag, l_linestatus"


def utility_pricing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Utility, recall and precision of one released pricing summary."""
    s, keys = tpch.session(spark, sf_dir), ["l_returnflag", "l_linestatus"]
    u = U.utility_summary(U.utility_diff(spark.sql(PRICING.format("lineitem")), s.rewrite(PRICING.format("lineitem"), CONTEXT), keys), keys)
    return u.withColumn("utility", F.round("utility", 5))


_CELLS = tpch.release_sql("SELECT l_returnflag, l_linestatus, j AS world, 2 * sum(l_quantity) AS q, avg(l_extendedprice) AS a, 2 * count(*) AS n FROM li GROUP BY ALL", ("l_returnflag", "l_linestatus"), {"q": 9, "a": 9, "n": 9})
_OFF = ", ".join(f"abs(p.{c} - e.{c}) / nullif(abs(e.{c}), 0) * 100" for c in "qan")
_add("utility_pricing", utility_pricing, f"""WITH {LINES}, p AS ({_CELLS}), e AS ({PRICING.format('lineitem')}),
d AS (SELECT e.n IS NOT NULL AS ine, p.l_returnflag IS NOT NULL AS inp, [{_OFF}] AS off FROM e FULL JOIN p ON e.l_returnflag IS NOT DISTINCT FROM p.l_returnflag AND e.l_linestatus IS NOT DISTINCT FROM p.l_linestatus)
SELECT round(sum(list_sum(off)) FILTER (ine AND inp) / sum(list_count(off)) FILTER (ine AND inp), 5) AS utility, sum(CAST(ine AND inp AS INT)) / sum(CAST(ine AS INT)) AS recall,
sum(CAST(ine AND inp AS INT)) / sum(CAST(inp AS INT)) AS precision, CAST(sum(CASE WHEN ine AND inp THEN 3 - list_count(off) ELSE 0 END) AS BIGINT) AS skipped_cells FROM d""")
def predicted_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The percentage error that each released count is to be expected to have, before anything is released."""
    v = lines(spark, sf_dir).groupBy("l_suppkey").agg(A.scaled(A.world_count("mask"), CONTEXT).alias("n"))
    return v.select("l_suppkey", F.round(U.predicted_percent("n", CONTEXT.mi), 6).alias("percent"))


_add("predicted_errors", predicted_errors, f"WITH {LINES} SELECT l_suppkey, round(100 * sqrt(2 / pi() * (sum(n * n) / 64.0 - (sum(n) / 64.0) * (sum(n) / 64.0)) * {1 + 1 / (2 * CONTEXT.mi)}) / abs(sum(n) / 64.0), 6) AS percent FROM (SELECT l_suppkey, j, 2.0::DOUBLE * count(*) AS n FROM li GROUP BY ALL) t GROUP BY ALL")
_add("utility_runs", lambda spark, d: experiments.utility_runs(spark, d, "SELECT o_orderpriority, count(*) AS n, avg(o_totalprice) AS a FROM orders GROUP BY o_orderpriority", ["o_orderpriority"], 30))
_add("mia_attacks", partial(experiments.attacks, runs=400))
_add("vec_sum_auto", partial(vec, fn="sum", group="flag", strategy="auto"), vec_sql("sum", "flag"))
_add("noise_each_vs_lift", partial(ratios.lift_against_each, n=20, seeds=10))
_add("approx_sum_study", distributions.study)
_add("storm_coverage", partial(storm.coverage_report, n=120))
_add("ablation_sum", lambda spark, d: experiments.ablation(spark, "sum", groups=(0, 1000), sf_dir=d))
_add("ablation_count", lambda spark, d: experiments.ablation(spark, "count", groups=(0, 1000), sf_dir=d))
_add("ablation_max", lambda spark, d: experiments.ablation(spark, "max", groups=(0, 1000), order="increasing", sf_dir=d))
_add("type_costs", experiments.type_costs)
_add("worlds_compared", experiments.worlds_compared)
_add("run_times", experiments.run_times)
_add("log_run_times", experiments.log_run_times)
_add("storm_times", experiments.storm_times)


# ---- workloads

for _k in tpch.WORLDS:
    _add(f"tpch_{_k}", partial(tpch.by_world, name=_k), tpch.worlds_sql(_k))
for _k in tpch.PASSED:
    _add(f"tpch_{_k}", partial(tpch.plain, name=_k), tpch.SQL[_k])
_add("tpch_h15", partial(tpch.released, name="h15", ctx=CONTEXT), tpch.top_supplier_sql())
_add("tpch_h20_released", partial(tpch.released, name="h20", ctx=CONTEXT), tpch.coins_sql())
for _k in tpch.RELEASED:
    _add(f"released_{_k}", partial(tpch.rounded, name=_k), tpch.released_sql(_k))
_add("ledger_cells", tpch.ledger_cells, tpch.ledger_sql())
_add("tpch_verdicts", tpch.verdicts, tpch.verdicts_sql())
for _k in hits.ACCEPTED:
    _add(f"hits_{_k}", partial(hits.by_world, name=_k), hits.worlds_sql(_k) if _k in hits.WORLDS else None)
_add("hits_q30_shared", hits.q30_shared, hits.worlds_sql("q30"))
_add("hits_verdicts", hits.verdicts, hits.verdicts_sql())


# ---- streams, in their batch form

def daily_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    w = windows.windowed(e, "user_id", CONTEXT, group=("event_type",))
    rows = A.to_rows(w.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "count"), ["day", "event_type"], ["count"])
    return rows.where("count <> 0").select("day", "event_type", "world", F.col("count").alias("n"))


_add("stream_daily_counts", daily_counts, f"SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, CAST(j AS INT) AS world, 2 * count(*) AS n FROM events, (SELECT unnest(range(64)) AS j) w WHERE {duckdb_in_world('user_id', KEY)} GROUP BY ALL")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pricing summary, released."""
    return tpch.rounded(spark, sf_dir, "h01")


_add("flagship_pricing", flagship, tpch.released_sql("h01"))
