"""The experiments as functions that return tables: run times, ablations, accuracy, attacks, worlds."""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from worldfold.context import QueryContext, attack_bound
from worldfold.functions import aggregates as A
from worldfold.functions.masks import world_mask
from worldfold.functions.release import simulate_attack
from worldfold.operators import utility as U
from worldfold.operators.kernels import bits, state_bytes
from worldfold.operators.strategies import world_aggregate
from worldfold.workloads import distributions, hits, storm, tpch


def _time(make: Callable[[], DataFrame], repeats: int = 1) -> float:
    best = None
    for _ in range(repeats):
        t = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        best = min(best or 1e9, time.perf_counter() - t)
    return best


def run_times(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("h01", "h06", "h08", "h13"), many_runs: bool = False) -> DataFrame:
    """Plain, key joins only and single-pass seconds of each query, their ratios, and the share that joins have in the rest."""
    s = tpch.session(spark, sf_dir)
    rows = []
    for k in names:
        plain, joins, one = _time(lambda k=k: spark.sql(tpch.SQL[k])), _time(lambda k=k: s.with_unit_joins(tpch.SQL[k])), _time(lambda k=k: s.rewrite(tpch.SQL[k]))
        rows.append((k, plain, joins, one, one / plain, U.breakdown(plain, joins, one)["joins"]))
    return spark.createDataFrame(rows, "query string, plain double, unit_joins double, private double, slowdown double, join_share double")


def log_run_times(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("q01", "q08", "q13", "q30")) -> DataFrame:
    s = hits.session(spark, sf_dir)
    rows = []
    for k in names:
        plain, one = _time(lambda k=k: spark.sql(hits.SQL[k])), _time(lambda k=k: s.rewrite(hits.SQL[k]))
        rows.append((k, plain, one, one / plain))
    return spark.createDataFrame(rows, "query string, plain double, private double, slowdown double")


def storm_times(spark: SparkSession, sf_dir: str, n: int = 40, limit_s: float = 5.0, seed: int = 1) -> DataFrame:
    """Slowdowns of the generated queries that are rewritten; those over the time limit are marked."""
    s = tpch.session(spark, sf_dir)
    rows = []
    for kind, sql in storm.generate(n, seed):
        if kind == "rewrite" and s.classify(sql).kind == "rewrite":
            plain, one = _time(lambda q=sql: spark.sql(q)), _time(lambda q=sql: s.rewrite(q))
            rows.append((sql[:120], plain, one, one / plain, one > limit_s))
    return spark.createDataFrame(rows, "query string, plain double, private double, slowdown double, over_limit boolean")


def ablation(spark: SparkSession, fn: str = "sum", n: int = 200_000, groups: tuple[int, ...] = (0, 10, 1000), order: str = "uniform", strategies: tuple[str, ...] | None = None, sf_dir: str | None = None) -> DataFrame:
    """Seconds and state bytes of each strategy over ``n`` generated rows or all given events, ungrouped and by numbers of groups."""
    names = strategies or {"sum": ("wide", "multiply", "preagg", "arrow", "levels", "buffered", "approx", "approx_single", "float32", "branch"), "count": ("wide", "lanes8", "lanes16", "lanes32", "preagg", "arrow", "branch"), "max": ("wide", "pruned", "preagg")}[fn]
    rows = []
    for k in groups:
        df = (distributions.given(spark, sf_dir, k, order) if sf_dir else distributions.frame(spark, n, k, order)).withColumn("mask", world_mask("pk", ctx=QueryContext.new(1)))
        keys = ["g"] if k else []
        plain = _time(lambda: df.groupBy(*keys).agg(F.count(F.lit(1)) if fn == "count" else getattr(F, fn)("v")))
        for s in names:
            took = _time(lambda s=s: world_aggregate(df, keys, "mask", fn, None if fn == "count" else "v", s))
            rows.append((fn, k, s, took, took / plain, state_bytes(s)))
    return spark.createDataFrame(rows, "fn string, groups int, strategy string, seconds double, of_plain double, state_bytes int")


def type_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of a world sum over each column type, on all events."""
    df = distributions.given(spark, sf_dir, 10).withColumn("mask", world_mask("pk", ctx=QueryContext.new(1)))
    kinds = ("tinyint", "smallint", "int", "bigint", "float", "double", "decimal(18,2)")
    rows = [(t, _time(lambda t=t: world_aggregate(df.withColumn("v", (F.col("v") % 100).cast(t)), ["g"], "mask", "sum", "v"))) for t in kinds]
    return spark.createDataFrame(rows, "type string, seconds double")


def utility_runs(spark: SparkSession, sf_dir: str, sql: str, keys: list[str], runs: int = 10, mi: float = 1 / 128) -> DataFrame:
    """Utility, recall and precision of repeated private runs, each with its own worlds.

    Runs are jobs of their own, eight at a time, and each gives one row: a plan of all runs would be too large for the engine.
    """
    s = tpch.session(spark, sf_dir, mi=mi)
    exact = spark.sql(sql).cache()
    jobs = [U.utility_summary(U.utility_diff(exact, s.rewrite(sql, QueryContext.new(1000 + i, mi=mi)), keys), keys) for i in range(runs)]
    with ThreadPoolExecutor(8) as pool:
        rows = [(*r, i) for i, r in enumerate(pool.map(lambda d: d.first(), jobs))]
    exact.unpersist()
    return spark.createDataFrame(rows, "utility double, recall double, precision double, skipped_cells long, run int")


def attacks(spark: SparkSession, sf_dir: str, runs: int = 400) -> DataFrame:
    """Measured success of the best attacker on the customers' balances by segment, against the bound, for some budgets:
    from the cell of the attacked customer's segment alone, and from the cells of all segments."""
    c = spark.read.parquet(f"{sf_dir}/customer.parquet").withColumn("mask", world_mask("c_custkey", ctx=QueryContext.new(3)))
    unit = c.orderBy("c_custkey").select("mask", "c_mktsegment").first()
    sums = c.groupBy("c_mktsegment").agg(A.world_sum("mask", "c_acctbal").alias("v")).orderBy(F.col("c_mktsegment") != unit["c_mktsegment"], "c_mktsegment").collect()  # one row a segment
    vectors = 2 * np.array([[x or 0.0 for x in r["v"]] for r in sums])
    inside = bits(np.array([unit["mask"]]))[0]
    rows = [(d, k, simulate_attack(vectors[:k], inside, 1 / d, runs), attack_bound(k / d)) for d in (4, 16, 64, 256) for k in sorted({1, len(vectors)})]
    return spark.createDataFrame(rows, "one_over_mi int, cells int, measured double, bound double")


def worlds_compared(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Time and predicted error of 64 and 128 worlds for one sum."""
    s = tpch.session(spark, sf_dir)
    sql = "SELECT sum(l_quantity) AS q FROM lineitem"
    rows = []
    for w in (64, 128):
        ctx = QueryContext.new(1, worlds=w)
        v = s.rewrite(sql, ctx, "vectors").first()["q"]
        rows.append((w, _time(lambda c=ctx: s.rewrite(sql, c)), U.predicted_mape(np.array(v), ctx.mi)))
    return spark.createDataFrame(rows, "worlds int, seconds double, predicted_percent double")
