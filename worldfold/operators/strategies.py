"""Physical strategies of the world aggregates. All exact ones give equal vectors; they differ in what is shuffled and added."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from decimal import Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import ArrayType, DecimalType, DoubleType

from worldfold.functions import aggregates as A
from worldfold.functions.masks import worlds_of
from worldfold.operators import kernels as K
from worldfold.operators.vectorized import _codes as codes

#: The most rows that a chunk may add up in a lane: the top lane must not reach the sign bit.
LANE_ROWS = {8: 127, 16: 32_767, 32: (1 << 31) - 1}


def world_aggregate(df: DataFrame, keys: list[str], mask: str, fn: str, value: str | None = None, strategy: str = "wide", out: str = "v") -> DataFrame:
    """keys and the vector ``out`` (64 worlds, not doubled) by one of the strategies.

    wide: one pass of 64 predicated aggregates. multiply: value times bit. lanes8/16/32: counts, several worlds to a
    long. preagg: rows of a unit are added up first. late: raw rows are shuffled and aggregated where they arrive, for
    groups so many that vectors would be more than rows. arrow: a bit-matrix product for each batch. branch: a row for
    each world it is in. pruned: extremes, skipping what can't improve any world. approx: approximate sums of whole
    numbers. levels: exact cascading sums; buffered: the same for groups of over three rows. float32: sums in single
    precision.
    """
    if strategy == "auto":
        strategy = choose_strategy(fn, shape_of(df, keys, mask))
        strategy = "wide" if strategy == "multiply" and dict(df.dtypes)[value] in ("double", "float") else strategy
    if strategy in ("wide", "multiply", "late"):
        if strategy == "late" and keys:
            df = df.select(*keys, mask, *([value] if value else [])).repartition(*keys)
        return df.groupBy(*keys).agg(_wide(fn, mask, value, strategy == "multiply").alias(out))
    if strategy.startswith("lanes"):
        if fn != "count":
            raise ValueError("lanes count only")
        return lanes(df if value is None else df.where(F.col(value).isNotNull()), keys, mask, int(strategy[5:]), out)
    if strategy == "preagg":
        return preaggregated(df, keys, mask, fn, value, out)
    if strategy == "branch":
        return branch(df, keys, mask, fn, value, out)
    if strategy in ("arrow", "pruned", "approx", "approx_single", "levels", "buffered", "float32"):
        return by_kernel(df, keys, mask, fn, value, strategy, out)
    raise ValueError(f"unknown strategy {strategy}")


def _wide(fn: str, mask: str, value: str | None, multiply: bool = False) -> Column:
    if fn == "count":
        return A.world_count(mask, value)
    if fn == "sum":
        return A.world_sum(mask, value, multiply=multiply)
    return {"avg": A.world_avg, "min": A.world_min, "max": A.world_max}[fn](mask, value)


def lanes(df: DataFrame, keys: list[str], mask: str, width: int, out: str) -> DataFrame:
    """Counts with 64/width worlds added up in one long; a chunk of rows is short enough for no lane to overflow.

    Chunks are runs of rows within a task, so the chunk sums are made before the shuffle.
    """
    per = 64 // width
    ones = sum(1 << (width * k) for k in range(per))
    ones = ones - (1 << 64) if ones >> 63 else ones
    chunk = F.expr(f"monotonically_increasing_id() div {LANE_ROWS[width]}")
    m = F.col(mask)
    # word w holds worlds w, w + width, w + 2 width ...: a shift and a mask put them at the lanes' lowest bits
    spread = [F.sum(F.shiftrightunsigned(m, w).bitwiseAND(F.lit(ones))).alias(f"__w{w}") for w in range(width)]
    part = df.groupBy(*keys, chunk.alias("__chunk")).agg(*spread)
    lane = (1 << width) - 1
    each = [F.sum(F.shiftrightunsigned(f"__w{j % width}", width * (j // width)).bitwiseAND(F.lit(lane))) for j in range(64)]
    return part.groupBy(*keys).agg(F.array(*each).alias(out))


def preaggregated(df: DataFrame, keys: list[str], mask: str, fn: str, value: str | None, out: str) -> DataFrame:
    """Rows with one mask are of one unit: they are added up first, and only units go wide."""
    by = df.groupBy(*keys, mask)
    if fn == "count":
        n = by.agg((F.count(F.lit(1)) if value is None else F.count(value)).alias("__n"))
        return n.groupBy(*keys).agg(F.transform(A.world_sum(mask, "__n"), lambda x: F.coalesce(x, F.lit(0))).alias(out))
    if fn == "avg":
        s = by.agg(F.sum(value).alias("__s"), F.count(value).alias("__n")).groupBy(*keys).agg(A.world_sum(mask, "__s").alias("__s"), A.world_sum(mask, "__n").alias("__n"))
        return s.select(*keys, F.zip_with("__s", "__n", lambda a, b: F.try_divide(a, b)).alias(out))
    s = by.agg(getattr(F, fn)(value).alias("__s"))
    return s.groupBy(*keys).agg(_wide(fn, mask, "__s").alias(out))


def branch(df: DataFrame, keys: list[str], mask: str, fn: str, value: str | None, out: str) -> DataFrame:
    """The unpredicated baseline: each row once for each of its worlds, 32 times the rows."""
    rows = df.select(*keys, *([value] if value else []), F.explode(worlds_of(mask)).alias("__j"))
    f = F.count(F.lit(1)) if fn == "count" and value is None else getattr(F, fn)(value)
    part = rows.groupBy(*keys, "__j").agg(f.alias("__v"))
    m = part.groupBy(*keys).agg(F.map_from_entries(F.collect_list(F.struct("__j", "__v"))).alias("__m"))
    each = F.transform(F.sequence(F.lit(0), F.lit(63)), lambda j: F.element_at("__m", j))
    if fn == "count":
        each = F.transform(each, lambda x: F.coalesce(x, F.lit(0)))
    return m.select(*keys, each.alias(out))


#: Groups a task holds before it gives them out.
HELD = 4096


def by_kernel(df: DataFrame, keys: list[str], mask: str, fn: str, value: str | None, strategy: str, out: str) -> DataFrame:
    """One NumPy state a group for a whole task (until it holds HELD groups), merged by group.

    Whole numbers stay exact: they travel and merge as decimals of 38 digits. Approximate states merge as their totals.
    """
    small = df.select(*keys, F.col(mask).alias("__mask"), *([F.col(value).alias("__value")] if value else [])).where("__mask is not null")
    whole = fn == "count" or fn == "sum" and value is not None and dict(small.dtypes)["__value"] in ("bigint", "int", "smallint", "tinyint")
    exact = whole and not strategy.startswith("approx") and strategy != "float32"
    schema = small.select(*keys).schema.add("__part", ArrayType(DecimalType(38, 0) if exact else DoubleType()))
    arrow = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, K.Running] = {}

        def given() -> pa.RecordBatch:
            parts = [[Decimal(int(x)) for x in s.total()] if exact else [float(x) for x in s.total()] for s in held.values()]
            cols = [pa.array([k[i] for k in held], f.type) for i, f in enumerate(arrow) if i < len(keys)]
            held.clear()
            return pa.RecordBatch.from_arrays([*cols, pa.array(parts, arrow.field("__part").type)], [*keys, "__part"])

        for b in batches:
            t = pa.Table.from_batches([b])
            if value:
                t = t.filter(t.column("__value").is_valid())
            if not t.num_rows:
                continue
            group, first = codes(t, keys)
            order = np.argsort(group, kind="stable")
            at = np.concatenate(([0], np.flatnonzero(np.diff(group[order])) + 1, [len(order)]))
            m = t.column("__mask").to_numpy()[order]
            v = t.column("__value").to_numpy()[order] if value else None
            firsts = t.select(keys).take(pa.array(first)).to_pydict() if keys else {}
            names = list(zip(*[firsts[k] for k in keys], strict=True)) if keys else [()]
            for name, s, e in zip(names, at[:-1], at[1:], strict=True):
                if name not in held:
                    held[name] = K.Running(fn, strategy, whole)
                held[name].add(m[s:e], None if v is None else v[s:e])
            if len(held) > HELD:
                yield given()
        if held:
            yield given()

    part = small.mapInArrow(run, schema)
    f = {"max": F.max, "min": F.min}.get(fn, F.sum)
    each = [F.element_at("__part", j + 1) for j in range(64)]
    if fn in ("max", "min"):
        each = [F.when(~F.isnan(e), e) for e in each]
    vector = F.array(*[f(e) for e in each])
    return part.groupBy(*keys).agg(vector.alias(out))


@dataclass(frozen=True)
class Shape:
    """What the chooser goes by: rows, groups, different (group, unit) pairs, tasks."""

    rows: int
    groups: int
    pairs: int
    tasks: int = 200


def shape_of(df: DataFrame, keys: list[str], mask: str) -> Shape:
    """Approximate counts, by one pass over keys and masks."""
    some = F.approx_count_distinct(F.struct(*keys)) if keys else F.lit(1)
    r = df.agg(F.count(F.lit(1)), some, F.approx_count_distinct(F.struct(*keys, mask))).first()
    return Shape(r[0], max(1, r[1]), max(1, r[2]), max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))))


def choose_strategy(fn: str, shape: Shape) -> str:
    """Raw rows are shuffled where vectors would be more bytes; rows are added up by unit where that leaves few; else wide."""
    if shape.groups * min(shape.tasks, max(1, shape.rows // max(1, shape.groups))) * K.state_bytes("wide") > shape.rows * K.state_bytes("late") and shape.rows < 22 * shape.groups * shape.tasks:
        return "late"
    if shape.pairs * 8 <= shape.rows:
        return "preagg"
    return "multiply" if fn == "sum" else "wide"
