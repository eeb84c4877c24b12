"""Releasing a vector of worlds as one noised value."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType

from worldfold.context import QueryContext
from worldfold.functions.aggregates import worlds_touched
from worldfold.functions.lift import uniform

ColumnOrName = Column | str


def _col(c: ColumnOrName) -> Column:
    return F.col(c) if isinstance(c, str) else c


def filled(vector: ColumnOrName) -> Column:
    """Worlds that were never reached count as 0 for the noise."""
    return F.transform(_col(vector), lambda x: F.coalesce(x.cast("double"), F.lit(0.0)))


def _bound(value: Column, use) -> Column:
    """``use`` of a value that is computed once: lambdas evaluate what they capture for every element."""
    return F.element_at(F.transform(F.array(value), lambda x: use(x)), 1)


def _sum(v: Column) -> Column:
    return F.aggregate(v, F.lit(0.0), lambda a, x: a + x)


def weighted_var(vector: ColumnOrName, weights: list[float] | None = None) -> Column:
    """Population variance over the worlds, under ``weights`` (a posterior) or evenly."""
    if weights is None:
        off = lambda v, m: F.aggregate(v, F.lit(0.0), lambda a, x: a + (x - m) * (x - m)) / F.size(v)
        return _bound(filled(vector), lambda v: _bound(_sum(v) / F.size(v), lambda m: off(v, m)))
    w = F.array(*[F.lit(float(x)) for x in weights])
    off = lambda v, m: _sum(F.zip_with(v, w, lambda x, p: p * (x - m) * (x - m)))
    return _bound(filled(vector), lambda v: _bound(_sum(F.zip_with(v, w, lambda x, p: x * p)), lambda m: off(v, m)))


def gaussian(ctx: QueryContext, tag: str, *keys: ColumnOrName) -> Column:
    """A standard normal number that key, tag and keys decide (two keyed uniforms)."""
    return F.sqrt(-2 * F.log(uniform(ctx, tag + ":u1", *keys))) * F.cos(2 * math.pi * uniform(ctx, tag + ":u2", *keys))


def null_chance(touched: ColumnOrName, worlds: int = 64) -> Column:
    """Chance that a cell is released as null: the share of worlds no row has reached."""
    return (worlds - worlds_touched(touched, worlds)) / float(worlds)


def release(vector: ColumnOrName, ctx: QueryContext, name: str, *group: ColumnOrName, touched: ColumnOrName | None = None) -> Column:
    """The secret world's value with Gaussian noise whose variance is the worlds' variance over twice the budget.

    Noise and null draws depend on the query's key and number, ``name`` and the group alone, so running the plan again or
    retrying a task gives the same value; ``name`` must differ between the columns of a query, or they would share a
    draw. Cells all worlds agree on get no noise. ``touched`` turns on the null draw, which does not depend on the secret.
    """
    y = F.coalesce(F.element_at(_col(vector), ctx.secret_world + 1).cast("double"), F.lit(0.0))
    if ctx.noise:
        y = y + F.sqrt(weighted_var(vector) / (2 * ctx.mi)) * gaussian(ctx, name, *group)
    if touched is None:
        return y
    return F.when(uniform(ctx, name + ":null", *group) >= null_chance(touched, ctx.worlds), y)


#: What a run says that refuses an aggregate.
FED_ALONE = "an aggregate was fed by a single privacy unit"


def single_unit(touched: ColumnOrName, updates: ColumnOrName, worlds: int = 64, min_updates: int = 64, tolerance: int = 2) -> Column:
    """Whether many rows have reached only about half of the worlds, as the rows of one unit do.

    Two units reach three quarters of the worlds on average; with balanced masks the chance that they reach no more than
    ``tolerance`` over a half is about 1e-7.
    """
    missed = worlds - worlds_touched(touched, worlds)
    return (_col(updates) >= min_updates) & (F.abs(missed - worlds // 2) <= tolerance * worlds // 64)


def diversity_guard(value: Column, touched: ColumnOrName, updates: ColumnOrName, worlds: int = 64, min_updates: int = 64, tolerance: int = 2) -> Column:
    """``value``, or a runtime error where a single unit's rows are all there is."""
    alone = single_unit(touched, updates, worlds, min_updates, tolerance)
    return F.when(alone, F.raise_error(F.lit(FED_ALONE)).cast("double")).otherwise(value)


def rounded(value: Column, kind: str, clamp: bool = False) -> Column:
    """Back to the exact answer's type, after the noise and so without cost."""
    v = F.greatest(value, F.lit(0.0)) if clamp else value
    return F.round(v).cast(kind) if kind in ("int", "bigint", "long", "smallint", "tinyint") else v.cast(kind)


class Posterior:
    """What an observer believes about the secret world, updated with every released value."""

    def __init__(self, worlds: int, secret: int, mi: float, seed: int = 0, log: list[float] | None = None):
        self.log = np.full(worlds, -math.log(worlds)) if log is None else np.array(log, float)
        self.secret, self.mi, self.random = secret, mi, np.random.default_rng(seed)

    @property
    def weights(self) -> np.ndarray:
        p = np.exp(self.log - self.log.max())
        return p / p.sum()

    def release(self, y: np.ndarray, noise: float | None = None) -> float:
        p = self.weights
        mean = float((p * y).sum())
        var = float((p * (y - mean) ** 2).sum())
        delta = var / (2 * self.mi)
        if delta <= 0 or not math.isfinite(delta):
            return float(y[self.secret])
        out = float(y[self.secret]) + math.sqrt(delta) * (self.random.standard_normal() if noise is None else noise)
        self.log = self.log - (out - y) ** 2 / (2 * delta)
        self.log -= self.log.max()
        return out


def release_sequential(df: DataFrame, keys: list[str], vectors: list[str], ctx: QueryContext, names: dict[str, str] | None = None, touched: dict[str, str] | None = None, start: list[float] | None = None, carry: bool = False) -> DataFrame:
    """Releases every cell in the order of the keys and then of ``vectors``, carrying the posterior along.

    ``names`` tag the draws, which are keyed as those of ``release`` are; ``touched`` turns on the null draw, and a cell
    that is drawn null teaches nothing. ``start`` is the posterior (as logarithms) that earlier releases have left;
    with ``carry`` the last row of each batch has the posterior after it in ``__posterior`` and its place in ``__place``.

    Serial by nature, as each cell's noise depends on all cells before: one task sees all groups, a batch at a time. It
    is meant for results of up to some 100,000 cells; ``release`` is for more.
    """
    names, touched = names or {}, touched or {}
    schema = df.select(*keys).schema
    for v in vectors:
        schema = schema.add(v, "double")
    if carry:
        schema = schema.add("__posterior", ArrayType(DoubleType())).add("__place", "long")
    read = []
    for i, v in enumerate(vectors):
        tag, t = names.get(v, v), touched.get(v)
        hidden = F.lit(False) if t is None else uniform(ctx, tag + ":null", *keys) < null_chance(t, ctx.worlds)
        read += [filled(v).alias(v), gaussian(ctx, tag, *keys).alias(f"__g{i}"), hidden.alias(f"__null{i}")]

    def fold(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        p, place = Posterior(ctx.worlds, ctx.secret_world, ctx.mi, log=start), 0
        for b in batches:
            out = b[keys].copy()
            cells = {v: np.full(len(b), np.nan) for v in vectors}
            columns = [(v, b[v].to_numpy(), b[f"__g{i}"].to_numpy(), b[f"__null{i}"].to_numpy()) for i, v in enumerate(vectors)]
            for r in range(len(b)):
                for v, y, g, hidden in columns:
                    if not hidden[r]:
                        cells[v][r] = p.release(np.asarray(y[r], float), g[r] if ctx.noise else 0.0)
            for v in vectors:
                out[v] = pd.Series(cells[v], index=out.index).astype(object).where(~np.isnan(cells[v]), None) if np.isnan(cells[v]).any() else cells[v]
            if carry:
                place += len(b)
                out["__posterior"] = [None] * (len(b) - 1) + [p.log.tolist()] if len(b) else []
                out["__place"] = place
            yield out

    return df.select(*keys, *read).repartition(1).sortWithinPartitions(*keys).mapInPandas(fold, schema)


def divergence_of(p: Column, q: Column) -> Column:
    """``context.divergence`` of columns, for ``q`` between 0 and 1."""
    part = lambda a, b: F.when(a == 0, F.lit(0.0)).otherwise(a * F.log(a / b))
    return part(p, q) + part(1 - p, 1 - q)


def attack_bound_of(mi: Column, prior: Column) -> Column:
    """``context.attack_bound`` of columns, by halving as often as doubles can be told apart."""
    start = F.struct(prior.alias("low"), F.lit(1.0).alias("high"))
    mid = lambda s: (s["low"] + s["high"]) / 2
    inside = lambda s: divergence_of(mid(s), prior) <= mi
    halve = lambda s, _: F.struct(F.when(inside(s), mid(s)).otherwise(s["low"]).alias("low"), F.when(inside(s), s["high"]).otherwise(mid(s)).alias("high"))
    halved = F.aggregate(F.sequence(F.lit(1), F.lit(54)), start, halve, lambda s: s["low"])
    return F.when(divergence_of(F.lit(1.0), prior) <= mi, F.lit(1.0)).otherwise(halved)


def simulate_attack(vectors: np.ndarray, masks: np.ndarray, mi: float, runs: int, seed: int = 0) -> float:
    """Success of an attacker who knows all worlds and guesses from the releases whether a unit was in the secret one.

    ``vectors``: cells x worlds; ``masks``: worlds (1 where the unit is in). Its share of right guesses estimates the
    posterior success, to be held against ``attack_bound``.
    """
    r = np.random.default_rng(seed)
    right = 0
    worlds = vectors.shape[1]
    for _ in range(runs):
        p = Posterior(worlds, int(r.integers(worlds)), mi, int(r.integers(1 << 31)))
        for y in vectors:
            p.release(y)
        guess = (p.weights * masks).sum() >= 0.5
        right += int(bool(guess) == bool(masks[p.secret]))
    return right / runs
