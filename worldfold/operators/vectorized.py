"""All world aggregates of a query in one pass of NumPy kernels, for the rewriter.

64 worlds times a dozen aggregates are too many buffers for generated code: it is compiled for seconds and then runs
uncompiled. A kernel adds a batch of values times its bit matrix instead, for all aggregates at once. A task keeps one
state a group and gives it out when it ends, or when it holds many. Rows of groups that are rare in a batch are passed on
as they are, since states would be larger. States and rows of one group then meet in sorted order and are merged as they
stream by, so neither side holds more than a bounded number of groups, and a group with most rows is never shuffled as
rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import ArrayType, DoubleType, LongType, StructField, StructType

from worldfold.operators.kernels import WORLDS, bits

#: Groups a task holds before it gives them out.
HELD = 8192
WHOLE = ("tinyint", "smallint", "int", "bigint")
#: Rows a group must have in a batch for a state to be made before the shuffle.
DENSE = 16
#: Up to so many groups in a batch are multiplied one by one; more are summed as outer products.
FEW = 48


@dataclass(frozen=True)
class Spec:
    """One aggregate: its output column, sum, count, min or max, and the column it reads (None: rows are counted)."""

    out: str
    fn: str
    column: str | None
    whole: bool


def specs_of(df: DataFrame, wanted: list[tuple[str, str, str | None]]) -> list[Spec] | None:
    """Specs, or None where a column's type needs the engine's own arithmetic (decimals, strings)."""
    types = dict(df.dtypes)
    out = []
    for name, fn, col in wanted:
        t = types[col] if col else "bigint"
        if fn not in ("sum", "count", "min", "max") or (fn != "count" and t not in (*WHOLE, "double", "float")):
            return None
        out.append(Spec(name, fn, col, fn == "count" or t in WHOLE))
    return out


def _codes(t: pa.Table, keys: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Group number of each row and the first row of each group."""
    n = t.num_rows
    code, size = np.zeros(n, np.int64), 1
    for k in keys:
        d = t.column(k).combine_chunks()
        d = d.combine_chunks() if isinstance(d, pa.ChunkedArray) else d
        d = d.dictionary_encode(null_encoding="encode")
        if size * (len(d.dictionary) + 1) >= 1 << 62:  # several wide keys: numbers of the groups so far
            code = np.unique(code, return_inverse=True)[1]
            size = n
        code = code * (len(d.dictionary) + 1) + d.indices.to_numpy(zero_copy_only=False)
        size *= len(d.dictionary) + 1
    _, first, inverse = np.unique(code, return_index=True, return_inverse=True)
    return inverse, first


class _State:
    """Aggregates by group: arrays of groups x worlds for each spec; worlds touched and rows seen for each column read."""

    def __init__(self, specs: list[Spec]):
        self.specs = specs
        self.columns = list(dict.fromkeys(s.column for s in specs))
        self.clear()

    def clear(self) -> None:
        self.at: dict[tuple, int] = {}
        self.values = {s.out: np.zeros((0, WORLDS), np.int64 if s.whole else np.float64) for s in self.specs}
        self.touched = {c: np.zeros(0, np.int64) for c in self.columns}
        self.updates = {c: np.zeros(0, np.int64) for c in self.columns}

    def add(self, keys: list[tuple], values: dict[str, np.ndarray], touched: dict[str | None, np.ndarray], updates: dict[str | None, np.ndarray]) -> None:
        new = [k for k in keys if k not in self.at]
        for k in new:
            self.at[k] = len(self.at)
        if new:
            for s in self.specs:
                start = {"sum": 0, "count": 0, "min": _top(s.whole), "max": -_top(s.whole)}[s.fn]
                old = self.values[s.out]
                self.values[s.out] = np.concatenate((old, np.full((len(new), WORLDS), start, old.dtype)))
            for c in self.columns:
                self.touched[c] = np.concatenate((self.touched[c], np.zeros(len(new), np.int64)))
                self.updates[c] = np.concatenate((self.updates[c], np.zeros(len(new), np.int64)))
        to = np.array([self.at[k] for k in keys])
        for s in self.specs:
            v = self.values[s.out]
            v[to] = {"min": np.minimum, "max": np.maximum}.get(s.fn, np.add)(v[to], values[s.out])
        for c in self.columns:
            self.touched[c][to] |= touched[c]
            self.updates[c][to] += updates[c]

    def batch(self, key_schema: list[pa.Field], last_out: set | None = None) -> pa.RecordBatch:
        keys = list(self.at)
        cols = [pa.array([k[i] for k in keys], f.type) for i, f in enumerate(key_schema)]
        names = [f.name for f in key_schema]
        for s in self.specs:
            flat = self.values[s.out].ravel()
            gone = None if s.fn == "count" else bits(self.touched[s.column]).ravel() == 0
            cols.append(pa.ListArray.from_arrays(pa.array(np.arange(len(keys) + 1, dtype=np.int32) * WORLDS), pa.array(flat, mask=gone)))
            names.append(s.out)
        for i, c in enumerate(self.columns):
            cols += [pa.array(self.touched[c]), pa.array(self.updates[c])]
            names += [f"__touched{i}", f"__updates{i}"]
        return pa.RecordBatch.from_arrays(cols, names)


def _top(whole: bool):
    return np.iinfo(np.int64).max if whole else np.inf


def _partial(t: pa.Table | pa.RecordBatch, keys: list[str], state: _State) -> None:
    t = pa.Table.from_batches([t]) if isinstance(t, pa.RecordBatch) else t
    group, first = _codes(t, keys)
    order = np.argsort(group, kind="stable")
    starts = np.concatenate(([0], np.flatnonzero(np.diff(group[order])) + 1))
    ends = np.append(starts[1:], len(order))
    mask = t.column("__mask").to_numpy()[order]
    b64 = bits(mask)
    read: dict[str | None, tuple[np.ndarray | None, np.ndarray]] = {None: (None, np.ones(len(order), bool))}
    for c in state.columns:
        if c is not None:
            col = t.column(c).combine_chunks()
            col = col.combine_chunks() if isinstance(col, pa.ChunkedArray) else col
            ok = ~np.asarray(col.is_null())
            some = any(s.column == c and s.fn != "count" for s in state.specs)
            read[c] = (np.asarray(col.fill_null(0))[order] if some else None, ok[order])
    touched = {c: np.bitwise_or.reduceat(np.where(ok, mask, 0), starts) for c, (_, ok) in read.items() if c in state.columns}
    updates = {c: np.add.reduceat(ok.astype(np.int64), starts) for c, (_, ok) in read.items() if c in state.columns}
    out: dict[str, np.ndarray] = {}
    adds = [s for s in state.specs if s.fn in ("sum", "count")]
    floats = []
    for s in adds:
        v, ok = read[s.column]
        if s.fn == "count":
            floats.append((s, ok.astype(np.float64)))  # exact: a batch is far below 2**53 rows
        elif s.whole:
            v = np.where(ok, v.astype(np.int64), 0)
            if len(v) and np.abs(v).max() < 2**38:
                floats.append((s, v.astype(np.float64)))
            else:
                out[s.out] = np.add.reduceat(b64 * v[:, None], starts)
        else:
            v = np.where(ok, v.astype(np.float64), 0.0)
            if np.isfinite(v).all():
                floats.append((s, v))
            else:
                out[s.out] = np.add.reduceat(np.where(b64 == 1, v[:, None], 0.0), starts)
    if floats:
        matrix = np.stack([v for _, v in floats])
        f64 = b64.astype(np.float64)
        if len(starts) <= FEW:
            sums = np.stack([matrix[:, s:e] @ f64[s:e] for s, e in zip(starts.tolist(), ends.tolist(), strict=True)], axis=1)
        else:
            sums = np.stack([np.add.reduceat(f64 * row[:, None], starts) for row in matrix])
        for (s, _), x in zip(floats, sums, strict=True):
            out[s.out] = np.rint(x).astype(np.int64) if s.whole else x
    for s in state.specs:
        if s.fn in ("min", "max"):
            v, ok = read[s.column]
            start = _top(s.whole) if s.fn == "min" else -_top(s.whole)
            kind = np.int64 if s.whole else np.float64
            chosen = np.where((b64 == 1) & ok[:, None], v.astype(kind)[:, None], np.array(start, kind))
            out[s.out] = (np.minimum if s.fn == "min" else np.maximum).reduceat(chosen, starts)
    # groups are numbered in the order of their codes, which is also the order they are sorted in
    firsts = t.select(keys).take(pa.array(first)).to_pydict() if keys else {}
    names = list(zip(*[firsts[k] for k in keys], strict=True)) if keys else [()]
    state.add(names, out, touched, updates)


def _merge(t: pa.Table, keys: list[str], state: _State) -> None:
    group, first = _codes(t, keys)
    order = np.argsort(group, kind="stable")
    starts = np.concatenate(([0], np.flatnonzero(np.diff(group[order])) + 1))
    out, touched, updates = {}, {}, {}
    for i, c in enumerate(state.columns):
        touched[c] = np.bitwise_or.reduceat(t.column(f"__touched{i}").to_numpy()[order], starts)
        updates[c] = np.add.reduceat(t.column(f"__updates{i}").to_numpy()[order], starts)
    for s in state.specs:
        start = {"sum": 0, "count": 0, "min": _top(s.whole), "max": -_top(s.whole)}[s.fn]
        col = t.column(s.out).combine_chunks()
        col = col.combine_chunks() if isinstance(col, pa.ChunkedArray) else col
        flat = np.asarray(col.flatten().fill_null(start)).reshape(-1, WORLDS)[order]
        out[s.out] = {"min": np.minimum, "max": np.maximum}.get(s.fn, np.add).reduceat(flat, starts)
    firsts = t.select(keys).take(pa.array(first)).to_pydict() if keys else {}
    names = list(zip(*[firsts[k] for k in keys], strict=True)) if keys else [()]
    state.add(names, out, touched, updates)


def aggregate(df: DataFrame, keys: list[str], mask: str, specs: list[Spec]) -> tuple[DataFrame, dict[str, str], dict[str, str]]:
    """keys, a vector for each spec (not doubled; null where no value reached a world, counts 0), touched and updates columns.

    Returns the names of the touched column and of the number of rows for each spec's output, too. Without keys there is
    one row even for no input.
    """
    columns = list(dict.fromkeys(s.column for s in specs))
    small = df.select(*keys, df[mask].alias("__mask"), *[c for c in columns if c is not None and c not in keys]).where("__mask IS NOT NULL")
    raw = [c for c in small.columns if c not in keys]
    schema = StructType([StructField(f.name, f.dataType) for f in small.schema.fields])  # a state has no row's columns
    for s in specs:
        schema = schema.add(s.out, ArrayType(LongType() if s.whole else DoubleType()))
    for i in range(len(columns)):
        schema = schema.add(f"__touched{i}", LongType()).add(f"__updates{i}", LongType())

    result = StructType([f for f in schema.fields if f.name not in raw])
    arrow = to_arrow_schema(schema)

    def wide(b: pa.RecordBatch) -> pa.RecordBatch:
        """The columns that a batch of rows or of states lacks, as nulls."""
        return pa.RecordBatch.from_arrays([b.column(b.schema.get_field_index(f.name)) if f.name in b.schema.names else pa.nulls(b.num_rows, f.type) for f in arrow], schema=arrow)

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state, fields = _State(specs), [arrow.field(k) for k in keys]
        for b in batches:
            if not b.num_rows:
                continue
            if keys:
                group, _ = _codes(pa.Table.from_batches([b]), keys)
                many = np.bincount(group)[group] >= DENSE
                if not many.all():
                    yield wide(b.filter(pa.array(~many)))
                    b = b.filter(pa.array(many))
                    if not b.num_rows:
                        continue
            _partial(b, keys, state)
            if len(state.at) > HELD:
                yield wide(state.batch(fields))
                state.clear()
        if state.at:
            yield wide(state.batch(fields))
        elif not keys:
            state.add([()], {s.out: state.values[s.out][:0].sum(0)[None] if s.fn in ("sum", "count") else np.full((1, WORLDS), _top(s.whole) if s.fn == "min" else -_top(s.whole), state.values[s.out].dtype) for s in specs}, {c: np.zeros(1, np.int64) for c in columns}, {c: np.zeros(1, np.int64) for c in columns})
            yield wide(state.batch([]))

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state, fields = _State(specs), [arrow.field(k) for k in keys]
        for b in batches:
            if not b.num_rows:
                continue
            if len(state.at) > HELD:  # rows come sorted: only the last group can go on
                last = tuple(b.slice(0, 1).column(b.schema.get_field_index(k))[0].as_py() for k in keys)
                if last not in state.at:
                    yield state.batch(fields)
                    state.clear()
            rows = pa.Table.from_batches([b])
            of_rows = rows.column("__mask").is_valid()
            for t, add in ((rows.filter(of_rows), _partial), (rows.filter(pc.invert(of_rows)), _merge)):
                if t.num_rows:
                    add(t, keys, state)
        if state.at:
            yield state.batch(fields)

    parts = small.mapInArrow(part, schema)
    dealt = parts.repartition(*keys).sortWithinPartitions(*keys) if keys else parts.repartition(1)
    return dealt.mapInArrow(meet, result), {s.out: f"__touched{columns.index(s.column)}" for s in specs}, {s.out: f"__updates{columns.index(s.column)}" for s in specs}
