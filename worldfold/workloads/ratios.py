"""Ratio queries: lifting an expression and releasing once, against releasing each aggregate and combining the noise."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from worldfold.context import QueryContext
from worldfold.functions import aggregates as A
from worldfold.functions.lift import lift
from worldfold.functions.masks import world_mask
from worldfold.functions.release import release


#: Quantities above 50 are in the whole of a ratio only.
STEP = 2.5


def ratio_vectors(spark: SparkSession, sf_dir: str, n: int, ctx: QueryContext) -> DataFrame:
    """priority, ratio (0 to ``n`` - 1), part and whole: the vectors of ``n`` ratios by order priority.

    Part i takes the lines of up to 2.5 (i + 1) pieces, so parts are running sums over ``n`` buckets of quantities: one
    world sum for a priority and bucket is all that is aggregated over rows.
    """
    li = spark.read.parquet(f"{sf_dir}/lineitem.parquet").select("l_orderkey", "l_extendedprice", "l_quantity")
    od = spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_orderkey", "o_custkey", "o_orderpriority")
    j = li.join(od, li.l_orderkey == od.o_orderkey).withColumn("mask", world_mask("o_custkey", ctx=ctx)).where("mask IS NOT NULL")
    bucket = F.least(F.greatest(F.ceil(F.col("l_quantity") / STEP) - 1, F.lit(0)), F.lit(n)).cast("int")
    sums = j.groupBy("o_orderpriority", F.coalesce(bucket, F.lit(n)).alias("b")).agg(A.scaled(A.world_sum("mask", "l_extendedprice"), ctx).alias("v"))
    lists = sums.groupBy("o_orderpriority").agg(F.collect_list(F.struct("b", "v")).alias("held"))  # n + 1 buckets at most
    none = F.array_repeat(F.lit(0.0), ctx.worlds)
    add = lambda some: F.aggregate(some, none, lambda t, x: F.zip_with(t, x["v"], lambda p, q: p + F.coalesce(q, F.lit(0.0))))
    rows = lists.select("o_orderpriority", "held", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("ratio"))
    return rows.select("o_orderpriority", "ratio", add(F.filter("held", lambda x: x["b"] <= F.col("ratio"))).alias("part"), add(F.col("held")).alias("whole"))


def compare(vectors: DataFrame, ctx: QueryContext) -> DataFrame:
    """For each group and ratio: exact (mean of worlds), lifted and combined answers."""
    ratio = lift(lambda a, b: F.try_divide(a, b), "part", "whole")
    mean = F.aggregate(ratio, F.lit(0.0), lambda s, x: s + x) / ctx.worlds
    at = ("o_orderpriority", "ratio")
    each = release("part", ctx, "part", *at) / release("whole", ctx, "whole", *at)
    return vectors.select(*at, mean.alias("exact"), release(ratio, ctx, "lifted", *at).alias("lifted"), each.alias("combined"))


def lift_against_each(spark: SparkSession, sf_dir: str, n: int = 4, seeds: int = 3, mi: float = 1 / 128) -> DataFrame:
    """Mean percentage errors of both ways over ratios, groups and keys."""
    out = None
    for s in range(seeds):
        ctx = QueryContext.new(s, mi=mi)
        c = compare(ratio_vectors(spark, sf_dir, n, ctx), ctx)
        out = c if out is None else out.unionByName(c)
    error = lambda c: F.avg(F.abs(F.col(c) - F.col("exact")) / F.abs("exact") * 100)
    return out.groupBy("ratio").agg(error("lifted").alias("lifted_percent"), error("combined").alias("combined_percent"))
