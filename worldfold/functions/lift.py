"""Expressions over vectors of worlds, and filters whose condition differs from world to world."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

from worldfold.context import QueryContext
from worldfold.functions.masks import key_text

OPS: dict[str, Callable[[Column, Column], Column]] = {
    "<": lambda a, b: a < b,
    "<=": lambda a, b: a <= b,
    "=": lambda a, b: a == b,
    "<>": lambda a, b: a != b,
    ">": lambda a, b: a > b,
    ">=": lambda a, b: a >= b,
}


def _col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def lift(f: Callable[..., Column], *vectors: Column | str) -> Column:
    """``f`` applied world by world to one or more vectors; scalars are just used inside ``f``.

    Division by zero and the like should be written with ``try_divide``: a world whose value is null counts as 0 when
    noise is measured, and an error would tell about the data.
    """
    vs = [_col(v) for v in vectors]
    if len(vs) == 1:
        return F.transform(vs[0], lambda x: f(x))
    if len(vs) == 2:
        return F.zip_with(vs[0], vs[1], lambda x, y: f(x, y))
    return F.transform(F.arrays_zip(*[v.alias(f"v{i}") for i, v in enumerate(vs)]), lambda x: f(*[x[f"v{i}"] for i in range(len(vs))]))


def mask_cmp(mask: Column | str, value: Column | str, op: str, vector: Column | str, worlds: int = 64) -> Column:
    """The mask without the worlds in which ``value op vector[world]`` does not hold.

    One lambda over the vector. (A chain of 64 generated comparisons is too long a method for the JVM's compiler and was
    measured seven times slower.)
    """
    v = _col(value)
    return mask_and(mask, F.transform(_col(vector), lambda y: OPS[op](v, y)), worlds)


def mask_and(mask: Column | str, flags: Column | str, worlds: int = 64) -> Column:
    """The mask without the worlds whose flag is not true."""
    m, f = _col(mask), _col(flags)
    none = F.lit(0).cast("long")
    bit = lambda b, j: F.when(b, F.call_function("shiftleft", F.lit(1).cast("long"), j)).otherwise(none)
    packed = lambda part: F.aggregate(F.transform(part, bit), none, lambda a, x: a.bitwiseOR(x))
    if worlds == 64:
        return m.bitwiseAND(packed(f))
    return F.array(*[F.element_at(m, w + 1).bitwiseAND(packed(F.slice(f, 64 * w + 1, 64))) for w in range(worlds // 64)])


def any_world(mask: Column | str, worlds: int = 64) -> Column:
    m = _col(mask)
    return m != 0 if worlds == 64 else (F.element_at(m, 1) != 0) | (F.element_at(m, 2) != 0)


def fraction_true(flags: Column | str) -> Column:
    """Share of worlds whose flag is true; null is not."""
    f = _col(flags)
    return F.size(F.filter(f, lambda b: F.coalesce(b, F.lit(False)))) / F.size(f)


def uniform(ctx: QueryContext, tag: str, *keys: Column | str) -> Column:
    """A number between 0 and 1 that the query's key and number, the tag and the keys decide: the same on every retry."""
    text = key_text(F.lit(tag), *[F.coalesce(_col(k).cast("string"), F.lit("~")) for k in keys], key=ctx.draws)
    n = F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("double")
    return (n + 0.5) / float(1 << 52)


def coin_filter(flags: Column | str, ctx: QueryContext, *row_key: Column | str, tag: str = "coin") -> Column:
    """Keeps a row with the chance that its condition has among the worlds. Each filter of a query needs a tag of its own."""
    return uniform(ctx, tag, *row_key) < fraction_true(flags)
