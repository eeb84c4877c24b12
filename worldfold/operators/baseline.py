"""The many-runs baseline: samples of the units, the query run on each, then noise from all of the answers."""

from __future__ import annotations

from collections.abc import Callable

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from worldfold.context import QueryContext
from worldfold.functions.lift import uniform
from worldfold.functions.masks import in_world, world_mask
from worldfold.functions.release import release


def sample_units(units: DataFrame, key: str, ctx: QueryContext, sampler: str = "mask") -> DataFrame:
    """(key, world) for every world that a unit is in.

    mask: the worlds of the single-pass engine, so that both can be compared draw by draw. bernoulli: a coin for each
    unit and world. balanced: each unit in exactly half of the worlds. Coins are keyed, so a retried task repeats them.
    """
    one = units.select(F.col(key).alias("unit"))
    worlds = F.sequence(F.lit(0), F.lit(ctx.worlds - 1))
    if sampler == "mask":
        m = one.withColumn("m", world_mask("unit", ctx=ctx))
        word = lambda j: F.col("m") if ctx.worlds == 64 else F.element_at("m", (j / 64).cast("int") + 1)
        return m.select("unit", F.explode(F.filter(worlds, lambda j: F.call_function("getbit", word(j), F.pmod(j, F.lit(64)).cast("int")) == 1)).alias("world"))
    if sampler == "bernoulli":
        each = one.select("unit", F.explode(worlds).alias("world"))
        return each.where(uniform(ctx.but(query=0), "sample", "unit", "world") < 0.5)
    if sampler == "balanced":
        order = F.array_sort(F.transform(worlds, lambda j: F.struct(F.xxhash64("unit", j, F.lit(ctx.key)).alias("h"), j.alias("j"))))
        half = F.transform(F.slice(order, 1, ctx.worlds // 2), lambda x: x["j"])
        return one.select("unit", F.explode(half).alias("world"))
    raise ValueError(f"unknown sampler {sampler}")


def sample_masks(units: DataFrame, key: str, ctx: QueryContext) -> DataFrame:
    """(unit, mask): the mask sampler's worlds as they are, a row a unit (64 worlds)."""
    return units.select(F.col(key).alias("unit"), world_mask(key, ctx=ctx).alias("mask"))


Query = Callable[[DataFrame], DataFrame]


def multi_run(linked: DataFrame, unit: str, query: Query, samples: DataFrame, worlds: int = 64, mode: str = "loop", keys: tuple[str, ...] = ()) -> DataFrame:
    """The query's rows for each world, with a ``world`` column: the multiset union of its runs.

    ``linked`` is the data joined with its units. loop: one filtered query a world, as the baseline is described, united.
    explode: one job in which every row appears once for each world of its unit; ``query`` must then group by ``world``.
    ``samples`` are of ``sample_units`` or of ``sample_masks``. Masks are joined first, so rows are repeated behind the join;
    with ``keys``, which ``query`` must group by, rows are dealt by them before they are repeated, and repeated rows are not
    shuffled. Samples are not broadcast: the planner cannot see how many rows a sampler makes of a small table.

    The loop's runs are jobs of their own, done when this returns: in one plan the driver would hold, for each of its
    stages, a description of all runs. Rows joined with masks are kept on disk for that long.
    """
    packed = "mask" in samples.columns
    joined = linked.join(samples.hint("merge"), linked[unit] == samples["unit"]).drop("unit")
    if mode == "explode":
        if packed:
            joined = joined.repartition(*keys) if keys else joined
            each = joined.select("*", F.explode(F.sequence(F.lit(0), F.lit(63))).alias("world"))  # compiled, unlike a filter by lambda
            joined = each.where(F.call_function("getbit", F.col("mask"), F.col("world")) == 1).drop("mask")
        return query(joined)
    inside = (lambda j: in_world("mask", j)) if packed else (lambda j: F.col("world") == j)
    kept = joined.persist(StorageLevel.DISK_ONLY) if packed else joined
    try:
        runs = [_done(query(kept.where(inside(j)).drop("mask" if packed else "world")).withColumn("world", F.lit(j))) for j in range(worlds)]
    finally:
        if packed:
            kept.unpersist()
    return union_runs(runs)


def _done(run: DataFrame) -> DataFrame:
    """The run's rows, computed now: in the shared checkpoint folder, or on the executors where the session has none."""
    shared = run.sparkSession.sparkContext._jsc.sc().getCheckpointDir().isDefined()
    return run.checkpoint() if shared else run.localCheckpoint()


def union_runs(runs: list[DataFrame]) -> DataFrame:
    while len(runs) > 1:  # a balanced tree keeps the plan shallow
        runs = [runs[i].unionByName(runs[i + 1]) if i + 1 < len(runs) else runs[i] for i in range(0, len(runs), 2)]
    return runs[0]


def collect_worlds(rows: DataFrame, keys: list[str], values: list[str], worlds: int = 64, scale: dict[str, int] | None = None) -> DataFrame:
    """Vectors of the runs' values by group: element j is world j's, null where the world has no such group."""
    each = [F.array(*[F.max(F.when(F.col("world") == j, F.col(v) * (scale or {}).get(v, 1))) for j in range(worlds)]).alias(v) for v in values]
    return rows.groupBy(*keys).agg(*each)


def released_runs(rows: DataFrame, keys: list[str], values: list[str], ctx: QueryContext, scale: dict[str, int] | None = None) -> DataFrame:
    """Releases like the engine does, so that equal worlds give equal output."""
    v = collect_worlds(rows, keys, values, ctx.worlds, scale)
    return v.select(*keys, *[release(c, ctx, f"{i}:{c}", *keys).alias(c) for i, c in enumerate(values)])


def resample_rows(runs: DataFrame, keys: list[str], ctx: QueryContext) -> DataFrame:
    """The baseline's answer to a filter that differs between runs: a keyed draw of one in ``worlds`` rows of the union of
    all runs. A row that many runs keep is likely to come, and may come more than once."""
    return runs.where(uniform(ctx, "resample", *keys, "world") < 1.0 / ctx.worlds).drop("world")


def noise_each(vectors: DataFrame, keys: list[str], ctx: QueryContext, parts: list[str], combine: Callable, out: str) -> DataFrame:
    """The baseline of lifting: each aggregate is released on its own and the expression is applied to the noised values."""
    r = vectors.select(*keys, *[release(p, ctx, p, *keys).alias(p) for p in parts])
    return r.select(*keys, combine(*[F.col(p) for p in parts]).alias(out))


def run_plain(spark: SparkSession, sql: str) -> DataFrame:
    return spark.sql(sql)


def laplace_sums(rows: DataFrame, keys: list[str], unit: str, value: str, bound: float, epsilon: float, ctx: QueryContext, out: str = "total") -> DataFrame:
    """Sums with Laplace noise: differential privacy by a known bound, for orientation beside the other measures.

    A unit's part of a group is clipped to ``bound`` either way, so noise of scale ``bound / epsilon`` hides any one unit in
    one group; a unit that is in several groups pays ``epsilon`` for each. Null values add nothing. Rows are summed by unit
    before they are shuffled, and draws are keyed, so a retried task repeats them.
    """
    parts = rows.groupBy(*keys, unit).agg(F.sum(value).alias("__part"))
    clipped = F.least(F.greatest(F.coalesce(F.col("__part").cast("double"), F.lit(0.0)), F.lit(-float(bound))), F.lit(float(bound)))
    off = uniform(ctx, f"laplace:{out}", *keys) - 0.5
    noise = -F.signum(off) * F.log(1 - 2 * F.abs(off)) * (bound / epsilon)
    return parts.groupBy(*keys).agg(F.sum(clipped).alias(out)).withColumn(out, F.col(out) + noise)
