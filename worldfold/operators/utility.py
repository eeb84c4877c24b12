"""How far released answers are from exact ones. These read exact answers: they are tools for evaluation."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from worldfold.functions.release import filled, weighted_var


def utility_diff(exact: DataFrame, private: DataFrame, keys: list[str]) -> DataFrame:
    """Rows tagged "=", "-" (missing from the private answer) or "+" (extra), with a percentage error for each number.

    Keys must be unique on both sides. A cell whose exact value is 0 or null has no error (null).
    """
    numbers = [c for c in exact.columns if c not in keys]
    a = exact.select(*[F.col(k).alias(f"__a{k}") for k in keys], *[F.col(c).cast("double").alias(f"__a{c}") for c in numbers], F.lit(1).alias("__ina"))
    b = private.select(*[F.col(k).alias(f"__b{k}") for k in keys], *[F.col(c).cast("double").alias(f"__b{c}") for c in numbers], F.lit(1).alias("__inb"))
    on = F.lit(True)
    for k in keys:
        on = on & F.col(f"__a{k}").eqNullSafe(F.col(f"__b{k}"))
    j = a.join(b, on, "full")
    tag = F.when(F.col("__ina").isNull(), "+").when(F.col("__inb").isNull(), "-").otherwise("=")
    error = lambda c: F.when((F.col(f"__a{c}") != 0) & F.col("__inb").isNotNull(), F.abs(F.col(f"__b{c}") - F.col(f"__a{c}")) / F.abs(f"__a{c}") * 100)
    own = lambda k: F.when(F.col("__ina").isNull(), F.col(f"__b{k}")).otherwise(F.col(f"__a{k}"))
    return j.select(tag.alias("tag"), *[own(k).alias(k) for k in keys], *[error(c).alias(c) for c in numbers])


def utility_summary(diff: DataFrame, keys: list[str]) -> DataFrame:
    """One row: utility (mean percentage error over cells), recall, precision, cells without an error."""
    numbers = [c for c in diff.columns if c not in keys and c != "tag"]
    same, missing, extra = (F.sum((F.col("tag") == t).cast("long")) for t in ("=", "-", "+"))
    cells = [F.when(F.col("tag") == "=", F.col(c)) for c in numbers]
    total, n = F.lit(0.0), F.lit(0)
    for c in cells:
        total, n = total + F.coalesce(F.sum(c), F.lit(0.0)), n + F.count(c)
    d = diff.agg(F.try_divide(total, n).alias("utility"), F.try_divide(same, same + missing).alias("recall"), F.try_divide(same, same + extra).alias("precision"), (same * len(numbers) - n).alias("skipped_cells"))
    return d


def approx_error(exact: np.ndarray, approx: np.ndarray) -> dict[str, float]:
    """Percentage error, z squared and variance ratio of approximate world sums against exact ones."""
    e, a = np.asarray(exact, float), np.asarray(approx, float)
    some = e != 0
    var = float(a.var())
    return {
        "percent": float((np.abs(a - e)[some] / np.abs(e)[some]).mean() * 100) if some.any() else 0.0,
        "z2": float(((a - e) ** 2).mean() / var) if var else 0.0,
        "variance_ratio": float(e.var() / var) if var else math.nan,
    }


def predicted_mape(vector: np.ndarray, mi: float) -> float:
    """Expected percentage error of a released cell from its own worlds: noise of the calibrated width plus the world's draw."""
    v = np.asarray(vector, float)
    sd = math.sqrt(v.var() / (2 * mi) + v.var())
    return float(100 * math.sqrt(2 / math.pi) * sd / abs(v.mean()))


def predicted_percent(vector: Column | str, mi: float) -> Column:
    """``predicted_mape`` of every cell of a table of vectors; null where the worlds' mean is 0."""
    mean = F.aggregate(filled(vector), F.lit(0.0), lambda a, x: a + x) / F.size(vector)
    return F.try_divide(100 * F.sqrt(2 / F.pi() * weighted_var(vector) * (1 + 1 / (2 * mi))), F.abs(mean))


def slowdown(times: dict[str, float], plain: dict[str, float]) -> dict[str, float]:
    """Median and mean of times over plain times, and the share within some factors."""
    r = sorted(times[k] / plain[k] for k in times if plain.get(k))
    if not r:
        return {}
    return {"median": r[len(r) // 2], "mean": sum(r) / len(r), **{f"within_{x}": sum(v <= x for v in r) / len(r) for x in (2.5, 3, 10)}}


def breakdown(plain: float, with_joins: float, private: float) -> dict[str, float]:
    """How much of the added time is joins and how much aggregation."""
    added = max(private - plain, 1e-9)
    return {"joins": (with_joins - plain) / added, "aggregates": (private - with_joins) / added}
