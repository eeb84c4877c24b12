"""Ten value distributions for the study of approximate sums. Their parameters are ours."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from worldfold.context import QueryContext
from worldfold.functions.masks import world_mask
from worldfold.operators.kernels import approx_sum, matrix_sum
from worldfold.operators.strategies import world_aggregate
from worldfold.operators.utility import approx_error

NAMES = ("all_same", "bimodal", "exponential", "negative_mixed", "sparse_large", "uniform_bigint", "uniform_int", "uniform_smallint", "uniform_tinyint", "zipf_like")


def draw(name: str, n: int, seed: int = 0) -> np.ndarray:
    r = np.random.default_rng(seed)
    return {
        "all_same": lambda: np.full(n, 4351),
        "bimodal": lambda: np.where(r.random(n) < 0.5, r.normal(1000, 50, n), r.normal(100_000, 500, n)).astype(np.int64),
        "exponential": lambda: r.exponential(5000, n).astype(np.int64),
        "negative_mixed": lambda: r.integers(-100_000, 100_001, n),
        "sparse_large": lambda: np.where(r.random(n) < 0.001, r.integers(10**9, 10**10, n), r.integers(0, 10, n)),
        "uniform_bigint": lambda: r.integers(0, 2**50, n),
        "uniform_int": lambda: r.integers(0, 2**31, n),
        "uniform_smallint": lambda: r.integers(0, 2**15, n),
        "uniform_tinyint": lambda: r.integers(0, 2**7, n),
        "zipf_like": lambda: np.minimum(r.zipf(1.5, n), 10**9),
    }[name]().astype(np.int64)


def masks_of(n: int, seed: int = 1) -> np.ndarray:
    """A balanced mask for each row's own unit."""
    h = np.random.default_rng(seed).integers(0, 2**32, n, dtype=np.uint64)
    return (h | ((~h & np.uint64(0xFFFFFFFF)) << np.uint64(32))).view(np.int64)


def approx_study(name: str, n: int = 1_000_000, seed: int = 0, two_sided: bool = True) -> dict[str, float]:
    """Errors of the approximate world sums of ``n`` values."""
    m, v = masks_of(n, seed + 1), draw(name, n, seed)
    return approx_error(2 * matrix_sum(m, v).astype(float), 2 * approx_sum(m, v, two_sided))


def shapes() -> dict[str, Column]:
    """The ten distributions as columns of the event table: cents are exponential, k is even over 0 to 99, and the clock's
    microseconds are even below whatever power of two they are taken by. What is not a number is null."""
    cents, micros = F.round(F.col("value") * 100).try_cast("long"), F.unix_micros(F.col("ts").cast("timestamp"))
    k = F.get_json_object("props", "$.k").try_cast("long")
    below = lambda n: F.pmod(micros, F.lit(n))
    return {
        "all_same": F.lit(4351),
        "bimodal": cents + F.when(F.col("event_type").isin("purchase", "signup"), 100_000).otherwise(0),
        "exponential": cents,
        "negative_mixed": below(200_001) - 100_000,
        "sparse_large": F.when(F.col("value") > 345, 10**9 + below(9 * 10**9)).otherwise(k % 10),  # one in a thousand
        "uniform_bigint": below(2**41),
        "uniform_int": below(2**31),
        "uniform_smallint": below(2**15),
        "uniform_tinyint": k,
        "zipf_like": F.least(F.floor(F.exp(F.col("value") / 25)), F.lit(10**9)),
    }


def shaped(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each event once for each distribution: its name, the event's mask (an event is a unit) and v."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("mask", world_mask("event_id", ctx=QueryContext.new(1)))
    each = F.array(*[F.struct(F.lit(x).alias("distribution"), c.try_cast("long").alias("v")) for x, c in shapes().items()])
    return e.select("mask", F.inline(each))


def study(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Errors of the approximate world sums, in one state and in two, of all events by distribution."""
    df = shaped(spark, sf_dir)
    sums = {c: world_aggregate(df, ["distribution"], "mask", "sum", "v", s, c) for c, s in (("exact", "arrow"), ("single", "approx_single"), ("two", "approx"))}
    rows = sums["exact"].join(sums["single"], "distribution").join(sums["two"], "distribution")

    def run(batches):
        import pandas as pd

        for b in batches:
            out = []
            for x in b.itertuples():
                e = 2 * np.array([float(y) for y in x.exact])
                one, two = approx_error(e, 2 * np.array(x.single, float)), approx_error(e, 2 * np.array(x.two, float))
                out.append((x.distribution, one["percent"], one["z2"], one["variance_ratio"], two["percent"], two["z2"], two["variance_ratio"]))
            yield pd.DataFrame(out, columns=["distribution", "single_percent", "single_z2", "single_ratio", "two_percent", "two_z2", "two_ratio"])

    return rows.mapInPandas(run, "distribution string, single_percent double, single_z2 double, single_ratio double, two_percent double, two_z2 double, two_ratio double")


def given(spark: SparkSession, sf_dir: str, groups: int = 0, order: str = "uniform") -> DataFrame:
    """The columns of ``frame`` from the event table, a row an event: units are users, values cents, or (increasing) seconds of
    the clock, which rise along the table."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    v = {"uniform": F.round(F.col("value") * 100), "increasing": F.unix_seconds(F.col("ts").cast("timestamp"))}[order]
    g = F.pmod(F.xxhash64("event_id", F.lit(2)), F.lit(groups)) if groups else F.lit(0)
    return e.select(g.cast("long").alias("g"), F.col("user_id").alias("pk"), v.cast("long").alias("v"))


def frame(spark: SparkSession, n: int, groups: int = 0, order: str = "uniform", domain: int = 10_000, scattered: bool = True) -> DataFrame:
    """Rows for micro-benchmarks, made by the engine: g (group), pk (unit), v (value; uniform, increasing or decreasing)."""
    df = spark.range(n)
    v = {"uniform": F.pmod(F.xxhash64("id", F.lit(1)), F.lit(domain)), "increasing": F.col("id") * domain / n, "decreasing": (n - F.col("id")) * domain / n}[order]
    g = F.lit(0) if not groups else F.pmod(F.xxhash64("id", F.lit(2)), F.lit(groups)) if scattered else (F.col("id") * groups / n)
    return df.select(g.cast("long").alias("g"), F.pmod(F.xxhash64("id", F.lit(3)), F.lit(max(1, n // 10))).alias("pk"), v.cast("long").alias("v"))
