"""World aggregates: one value for each world, in one pass.

Each is a column for ``agg``: an array whose element j aggregates the rows whose mask has world j. They plan as ordinary
hash aggregates with partial sums, one buffer slot for each world, inside whole-stage code generation.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from worldfold.context import QueryContext
from worldfold.functions.masks import in_world

ColumnOrName = Column | str


def _col(c: ColumnOrName) -> Column:
    return F.col(c) if isinstance(c, str) else c


def _each(mask: ColumnOrName, worlds: int, make) -> Column:
    return F.array(*[make(in_world(_col(mask), j, worlds)) for j in range(worlds)])


def world_count(mask: ColumnOrName, expr: ColumnOrName | None = None, worlds: int = 64) -> Column:
    """Rows of each world, or those in which ``expr`` is not null. Worlds without any have 0."""
    if expr is None:
        return _each(mask, worlds, lambda b: F.sum(b.cast("long")))
    e = _col(expr).isNotNull()
    return _each(mask, worlds, lambda b: F.sum((b & e).cast("long")))


def world_sum(mask: ColumnOrName, expr: ColumnOrName, worlds: int = 64, multiply: bool = False) -> Column:
    """Sums of each world; worlds without any value are null.

    ``multiply`` adds value times bit instead of choosing: faster, but worlds without values are 0, and only for values
    that are never NaN or infinite.
    """
    e = _col(expr)
    if multiply:
        return _each(mask, worlds, lambda b: F.sum(e * b.cast("int")))
    return _each(mask, worlds, lambda b: F.sum(F.when(b, e)))


def world_avg(mask: ColumnOrName, expr: ColumnOrName, worlds: int = 64, mode: str = "per_world") -> Column:
    """Averages of each world, or ``global_count``: its doubled sum over the count of all rows."""
    e = _col(expr)
    if mode == "per_world":
        return _each(mask, worlds, lambda b: F.avg(F.when(b, e)))
    if mode != "global_count":
        raise ValueError(f"unknown mode {mode}")
    return F.transform(world_sum(mask, e, worlds), lambda x: x * 2 / F.count(e))


def world_min(mask: ColumnOrName, expr: ColumnOrName, worlds: int = 64) -> Column:
    return _each(mask, worlds, lambda b: F.min(F.when(b, _col(expr))))


def world_max(mask: ColumnOrName, expr: ColumnOrName, worlds: int = 64) -> Column:
    return _each(mask, worlds, lambda b: F.max(F.when(b, _col(expr))))


def world_moments(mask: ColumnOrName, expr: ColumnOrName, worlds: int = 64, kind: str = "stddev_samp") -> Column:
    """Deviation or variance of each world (an addition: a lifted combination of count, sum and sum of squares)."""
    e = _col(expr).cast("double")
    f = {"stddev_samp": F.stddev_samp, "stddev_pop": F.stddev_pop, "var_samp": F.var_samp, "var_pop": F.var_pop}[kind]
    return _each(mask, worlds, lambda b: f(F.when(b, e)))


def by_name(fn: str, mask: str, column: str | None, worlds: int = 64) -> Column:
    """Any of the aggregates above over named columns."""
    if fn == "count":
        return world_count(mask, column, worlds)
    if fn in ("sum", "avg", "min", "max"):
        return {"sum": world_sum, "avg": world_avg, "min": world_min, "max": world_max}[fn](mask, column, worlds)
    return world_moments(mask, column, worlds, fn)


def touched(mask: ColumnOrName, expr: ColumnOrName | None = None, worlds: int = 64) -> Column:
    """Worlds (a long, or an array of two) that at least one row, with a value where ``expr`` is given, has reached."""
    m = _col(mask)
    words = [m] if worlds == 64 else [F.element_at(m, w + 1) for w in range(worlds // 64)]
    reached = [F.bit_or(w if expr is None else F.when(_col(expr).isNotNull(), w)) for w in words]
    return reached[0] if worlds == 64 else F.array(*reached)


def touched_both(a: ColumnOrName, b: ColumnOrName, worlds: int = 64) -> Column:
    """Worlds that two touched columns have in common: those in which a combination of their aggregates has a value."""
    return _col(a).bitwiseAND(_col(b)) if worlds == 64 else F.zip_with(a, b, lambda x, y: x.bitwiseAND(y))


def worlds_touched(t: ColumnOrName, worlds: int = 64) -> Column:
    """How many worlds a touched column has; null (no row at all) is none."""
    if worlds == 64:
        return F.coalesce(F.bit_count(_col(t)), F.lit(0))
    return F.aggregate(_col(t), F.lit(0), lambda n, w: n + F.coalesce(F.bit_count(w), F.lit(0)))


def scaled(vector: Column, ctx: QueryContext) -> Column:
    """Counts and sums as estimates of the whole: doubled, since a world has half of the units."""
    return vector if ctx.factor == 1 else F.transform(vector, lambda x: x * ctx.factor)


def half_sample_interval(vector: ColumnOrName, level: float = 0.9) -> Column:
    """An interval from the worlds' values, as half samples of the rows; for those who may see exact answers only."""
    v = F.array_sort(F.filter(_col(vector), lambda x: x.isNotNull()))
    low = F.greatest(F.lit(1), F.ceil(F.size(v) * (1 - level) / 2).cast("int"))
    high = F.greatest(F.lit(1), F.ceil(F.size(v) * (1 + level) / 2).cast("int"))
    return F.when(F.size(v) > 0, F.struct(F.element_at(v, low).alias("low"), F.element_at(v, high).alias("high")))


def to_rows(df, keys: list[str], vectors: list[str]):
    """Vectors as rows (keys, world, value ...), for tests; worlds without any value are left out."""
    z = df.select(*keys, F.posexplode(F.arrays_zip(*vectors)).alias("world", "v"))
    out = z.select(*keys, "world", *[F.col(f"v.{v}").alias(v) for v in vectors])
    some = F.col(vectors[0]).isNotNull()
    for v in vectors[1:]:
        some = some | F.col(v).isNotNull()
    return out.where(some)
