"""The ordered engine: sorted slots, one pass, cells closed where their prefix changes.

Rows of a slot arrive sorted by the chain's order.  For every member of the chain a change in its first dimensions closes a cell.  What an open cell keeps
is its running state: a count, sum, extreme or moments, and for MEDIAN each distinct value with its count; no rows are held, so a slot's memory does not
grow with the rows of a cell.  Measures are integers or floating point, in their own types; nulls are told from NaN by validity.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from latticecube.operators import materialize as M

FUNCTIONS = {"sum", "count", "min", "max", "avg", "median", "stddev", "variance"}

#: Sums of integers from here on are an error, as in the other engine's ANSI mode.
LARGEST = 2**63 - 2**11


# states: a tuple of arrays with one entry for each cell; MEDIAN has (values, counts) pairs for a batch's first and last cell, which may go on before or
# after it, and the value itself for those between


def _states(fn: str, values: np.ndarray | None, valid: np.ndarray | None, starts: np.ndarray, rows: int) -> tuple:
    """States of consecutive cells that start at ``starts``."""
    if values is None:
        return (np.diff([*starts, rows]).astype(np.int64),)
    n = np.add.reduceat(valid.astype(np.int64), starts)
    if fn == "count":
        return (n,)
    cell = np.repeat(np.arange(len(starts)), np.diff([*starts, rows]))[valid]
    x = values[valid]
    if fn == "median":
        x = x[np.lexsort((x, cell))]  # NaN is the largest
        ends = np.cumsum(n)
        out = np.empty(len(starts), object)
        if len(x):
            lo, hi = np.maximum(ends - n, 0) + np.maximum(n - 1, 0) // 2, np.maximum(ends - n, 0) + n // 2
            low, high = x[np.minimum(lo, len(x) - 1)].astype(np.float64), x[np.minimum(hi, len(x) - 1)].astype(np.float64)
            out[:] = np.where(lo == hi, low, (low + high) / 2).tolist()
        for i in np.flatnonzero(n == 0):
            out[i] = None
        for i in {0, len(starts) - 1}:
            out[i] = np.unique(x[ends[i] - n[i] : ends[i]], return_counts=True)
        return (out,)
    some = np.flatnonzero(n)  # cells with any value, and where theirs begin
    at = (np.cumsum(n) - n)[some]

    def spread(found, kind):
        out = np.zeros(len(starts), kind)
        out[some] = found
        return out

    if not len(some):
        return (n, *([np.zeros(len(starts), values.dtype if fn in ("min", "max") else np.float64 if fn != "sum" or values.dtype.kind == "f" else np.int64)] * (2 if fn in ("stddev", "variance") else 1)))
    if fn == "sum":
        kind = np.float64 if values.dtype.kind == "f" else np.int64
        if kind is np.int64 and np.abs(np.add.reduceat(x.astype(np.float64), at)).max() >= LARGEST:
            raise OverflowError("a sum exceeds 64 bits")
        return n, spread(np.add.reduceat(x.astype(kind), at), kind)
    if fn in ("min", "max"):
        f = np.fmin if fn == "min" else np.maximum  # NaN is larger than all
        return n, spread(f.reduceat(x, at), values.dtype)
    sums = spread(np.add.reduceat(x.astype(np.float64), at), np.float64)
    if fn == "avg":
        return n, sums
    mean = sums / np.maximum(n, 1)
    off = x.astype(np.float64) - mean[cell]
    return n, mean, spread(np.add.reduceat(off * off, at), np.float64)


def _joined(fn: str, a: tuple, b: tuple) -> tuple:
    """The state of one cell from two of its parts, each a tuple of scalars."""
    if fn == "median":
        (v, n), (w, m) = a[0], b[0]
        values, where = np.unique(np.concatenate([v, w]), return_inverse=True)
        return ((values, np.bincount(where, np.concatenate([n, m]), len(values)).astype(np.int64)),)
    if not a[0] or not b[0]:
        return a if a[0] else b
    n = a[0] + b[0]
    if fn == "count":
        return (n,)
    if fn == "sum" and isinstance(a[1], np.integer):
        total = int(a[1]) + int(b[1])
        if abs(total) >= LARGEST:
            raise OverflowError("a sum exceeds 64 bits")
        return n, np.int64(total)
    if fn in ("sum", "avg"):
        return n, a[1] + b[1]
    if fn in ("min", "max"):
        return n, (np.fmin if fn == "min" else np.maximum)(a[1], b[1])
    gap = b[1] - a[1]
    return n, a[1] + gap * (b[0] / n), a[2] + b[2] + gap * gap * (a[0] * (b[0] / n))


def _middle(values: np.ndarray, counts: np.ndarray) -> float:
    ends = np.cumsum(counts)
    lo, hi = np.searchsorted(ends, [(ends[-1] - 1) // 2, ends[-1] // 2], "right")
    return (float(values[lo]) + float(values[hi])) / 2 if lo != hi else float(values[lo])


def _final(fn: str, state: tuple, kind: pa.DataType) -> pa.Array:
    if fn == "count":
        return pa.array(state[0], kind)
    if fn == "median":
        return pa.array([(_middle(*p) if len(p[0]) else None) if isinstance(p, tuple) else p for p in state[0]], kind, from_pandas=False)
    n = state[0]
    if fn in ("sum", "min", "max"):
        return pa.array(state[1], mask=n == 0).cast(kind)
    if fn == "avg":
        return pa.array(state[1] / np.maximum(n, 1), kind, mask=n == 0)
    spread = state[2] / np.maximum(n - 1, 1)
    return pa.array(np.sqrt(spread) if fn == "stddev" else spread, kind, mask=n < 2)


def _same(a: pa.Array, b: pa.Array) -> np.ndarray:
    """Whether values are equal as group keys: nulls are, and NaN is."""
    flag = lambda x: x.to_numpy(zero_copy_only=False)
    out = flag(pc.fill_null(pc.equal(a, b), False)) | flag(pc.and_(pc.is_null(a), pc.is_null(b)))
    if pa.types.is_floating(a.type):
        out = out | flag(pc.fill_null(pc.and_(pc.is_nan(a), pc.is_nan(b)), False))
    return out.astype(bool)


class _Member:
    """One cuboid of a slot's chain: the open cell's key and states, and the cells that batches close."""

    def __init__(self, width: int, aggs: list[tuple[str, str | None]]):
        self.width, self.aggs, self.key, self.open = width, aggs, None, None

    def take(self, batch: pa.RecordBatch, columns: dict, changed: np.ndarray, goes_on: bool):
        """``(keys, states)`` of the cells that the batch closes, keys being rows with the cells' dimensions."""
        starts = np.flatnonzero(changed)
        keys = [batch.take(pa.array(starts))]
        states = [_states(fn, *(columns[m] if m else (None, None)), starts, batch.num_rows) for fn, m in self.aggs]
        if self.key is not None:
            first = [tuple(part[0] for part in s) for s in states]
            if goes_on:
                first = [_joined(fn, a, b) for (fn, _), a, b in zip(self.aggs, self.open, first, strict=True)]
                states = [tuple(_with_first(part, x) for part, x in zip(s, f, strict=True)) for s, f in zip(states, first, strict=True)]
            else:
                keys.insert(0, self.key)
                states = [tuple(np.concatenate([_one(part, x), part]) for part, x in zip(s, o, strict=True)) for s, o in zip(states, self.open, strict=True)]
        self.key = batch.slice(int(starts[-1]), 1)
        self.open = [tuple(part[-1] for part in s) for s in states]
        return pa.Table.from_batches(keys).combine_chunks().slice(0, len(states[0][0]) - 1), [tuple(part[:-1] for part in s) for s in states]

    def rest(self):
        return pa.Table.from_batches([self.key]), [tuple(_one(np.empty(0, object if fn == "median" else np.asarray(x).dtype), x) for x in s) for (fn, _), s in zip(self.aggs, self.open, strict=True)]


def _one(like: np.ndarray, x) -> np.ndarray:
    out = np.empty(1, like.dtype)
    out[0] = x
    return out


def _with_first(part: np.ndarray, x) -> np.ndarray:
    part = part.copy()
    part[0] = x
    return part


def _kind(fn: str, measure: T.DataType | None) -> T.DataType:
    if fn == "count":
        return T.LongType()
    if fn in ("min", "max"):
        return measure
    return T.LongType() if fn == "sum" and isinstance(measure, T.IntegralType) else T.DoubleType()


def cells(df: DataFrame, cube: M.CubePlan) -> DataFrame:
    """All cells of a cube, in the types of the levels engine."""
    spec = cube.spec
    if any(a.fn not in FUNCTIONS for a in spec.aggs):
        raise ValueError(f"the ordered engine knows {sorted(FUNCTIONS)}")
    if cube.slots.any_heavy:
        raise ValueError("a cell must lie in one slot here: use the levels engine for heavy keys")
    rows = spec.prepared(df)
    types = {f.name: f.dataType for f in rows.schema}
    for a in spec.aggs:
        if a.measure and a.fn != "count" and not isinstance(types[f"m_{a.measure}"], (T.IntegralType, T.FloatType, T.DoubleType)):
            raise ValueError(f"the ordered engine takes integers and floating point, not {types[f'm_{a.measure}'].simpleString()}: use the levels engine")
    measures = list(dict.fromkeys(f"m_{a.measure}" for a in spec.aggs if a.measure))
    # a measure that is only counted needs no value
    counted = {f"m_{a.measure}" for a in spec.aggs if a.measure} - {f"m_{a.measure}" for a in spec.aggs if a.measure and a.fn != "count"}
    rows = rows.select(*spec.dims, *[F.when(F.col(m).isNotNull(), F.lit(1)).alias(m) if m in counted else F.col(m) for m in measures])
    dealt = M.dealt(rows, cube)
    # a slot holds one chain, so the columns of the other chains' orders are constant there
    order = [F.when(F.col("__batch") == i, F.col(d)) for i, c in enumerate(cube.chains) for d in c.order]
    ordered = dealt.sortWithinPartitions("__batch", *order)
    dims, aggs = list(spec.dims), [(a.fn, f"m_{a.measure}" if a.measure else None) for a in spec.aggs]
    chains = [(list(c.order), [(len(m), spec.cuboid_id(m)) for m in c.members]) for c in cube.chains]
    kinds = [_kind(a.fn, types[f"m_{a.measure}"] if a.measure else None) for a in spec.aggs]
    schema = T.StructType([T.StructField("cuboid_id", T.IntegerType()), *[T.StructField(d, types[d]) for d in dims], *[T.StructField(a.name, k) for a, k in zip(spec.aggs, kinds, strict=True)]])

    def run(batches):
        out_kinds, names = None, [f.name for f in schema]
        members, order, before = None, None, None

        def emitted(member, cuboid_id, keys, states):
            kept = [keys.column(d).combine_chunks() if d in order[: member.width] else pa.nulls(keys.num_rows, keys.schema.field(d).type) for d in dims]
            made = [_final(fn, s, k) for (fn, _), s, k in zip(aggs, states, out_kinds, strict=True)]
            return pa.record_batch([pa.array(np.full(keys.num_rows, cuboid_id, np.int32)), *kept, *made], names)

        for batch in batches:
            if not batch.num_rows:
                continue
            if members is None:
                order, listed = chains[batch.column("__batch")[0].as_py()]
                members = [(_Member(k, aggs), cuboid_id) for k, cuboid_id in listed]
                kind_of = {f"m_{a.measure}": batch.schema.field(f"m_{a.measure}").type for a in spec.aggs if a.measure}
                out_kinds = [pa.int64() if isinstance(k, T.LongType) else pa.float64() if isinstance(k, T.DoubleType) else kind_of[m] for k, (_, m) in zip(kinds, aggs, strict=True)]
            columns = {}
            for m in measures:
                col = batch.column(m)
                valid = col.is_valid().to_numpy(zero_copy_only=False)
                columns[m] = (pc.fill_null(col, pa.scalar(0, col.type)).to_numpy(zero_copy_only=False), valid)
            changed, goes_on, upto = np.zeros(batch.num_rows, bool), before is not None, {}
            changed[0] = True
            for i, d in enumerate(order, 1):
                col = batch.column(d)
                if batch.num_rows > 1:
                    changed[1:] |= ~_same(col.slice(1), col.slice(0, len(col) - 1))
                goes_on = goes_on and bool(_same(col.slice(0, 1), before.column(d))[0])
                upto[i] = (changed.copy(), goes_on)
            heads = batch.select(dims)
            for member, cuboid_id in members:
                keys, states = member.take(heads, columns, *upto[member.width])
                if keys.num_rows:
                    yield emitted(member, cuboid_id, keys, states)
            before = heads.slice(batch.num_rows - 1, 1)
        for member, cuboid_id in members or []:
            yield emitted(member, cuboid_id, *member.rest())

    return ordered.mapInArrow(run, schema)
