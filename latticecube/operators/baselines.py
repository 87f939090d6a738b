"""The methods that shared-scan cubing is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from latticecube.operators import materialize as M
from latticecube.plans.slots import SlotPlan
from latticecube.spec import CubeSpec


def _rolled_up(cells: DataFrame, spec: CubeSpec, members: frozenset[str], types: dict) -> DataFrame:
    dims = [F.col(d) if d in members else F.lit(None).cast(types[d]).alias(d) for d in spec.dims]
    return cells.select(F.lit(spec.cuboid_id(members)).alias("cuboid_id"), *dims, *[a.name for a in spec.aggs])


def cuboid_jobs(df: DataFrame, spec: CubeSpec) -> list[DataFrame]:
    """One plan, with a scan and a shuffle of its own, for each cuboid."""
    rows = spec.prepared(df)
    types = {f.name: f.dataType for f in rows.schema}
    out = []
    for m in spec.wanted():
        own = [d for d in spec.dims if d in m]
        out.append(_rolled_up(M.finish(M.compress(rows, spec, own), spec, own), spec, m, types))
    return out


def per_cuboid_jobs(df: DataFrame, spec: CubeSpec, slots=None) -> M.CubeResult:
    """One job per cuboid, as a union; ``cuboid_jobs`` gives them singly, to be run one after another."""
    jobs = cuboid_jobs(df, spec)
    out = jobs[0]
    for j in jobs[1:]:
        out = out.unionByName(j)
    if spec.include_all:
        out = out.unionByName(M.grand_total(df, spec))
    return M.CubeResult(spec, out)


def fanout_unshared(df: DataFrame, spec: CubeSpec, slots=None) -> M.CubeResult:
    """One job without batching: a copy of each row for every cuboid, and nothing combined before the shuffle."""
    n = len(spec.wanted())
    return M.materialize(df, spec, slots=max(n, slots) if isinstance(slots, int) else slots if isinstance(slots, SlotPlan) else max(n, M.default_slots(df, n)), strategy="singletons", combine="off")


def native_cube(df: DataFrame, spec: CubeSpec, slots=None) -> M.CubeResult:
    """Spark's own grouping sets: one scan, one expansion, partial aggregates before the shuffle."""
    rows = spec.prepared(df)
    sets = [[F.col(d) for d in spec.dims if d in m] for m in spec.wanted()]
    if spec.include_all:
        sets.append([])
    values = [f"m_{m}" for m in spec.holistic_measures()]
    states = [init.alias(name) for a in spec.aggs for name, (init, _) in a.states().items()]
    if not values:
        cells = rows.groupingSets(sets, *[F.col(d) for d in spec.dims]).agg(F.grouping_id().cast("int").alias("cuboid_id"), *states)
        return M.CubeResult(spec, cells.select("cuboid_id", *spec.dims, *[a.final().alias(a.name) for a in spec.aggs]))
    plain = {"median": lambda x: F.median(x), "mode": lambda x: F.mode(x, True), "count_distinct": F.count_distinct}
    held = []
    for a in spec.aggs:
        if a.kind == "frequency":
            x = F.col(f"m_{a.measure}")
            held.append((F.percentile(x, a.p) if a.fn == "percentile" else plain[a.fn](x)).alias(a.name))
    cells = rows.groupingSets(sets, *[F.col(d) for d in spec.dims]).agg(F.grouping_id().cast("int").alias("cuboid_id"), *states, *held)
    return M.CubeResult(spec, cells.select("cuboid_id", *spec.dims, *[a.final().alias(a.name) for a in spec.aggs]))


METHODS = {"per_cuboid_jobs": per_cuboid_jobs, "fanout_unshared": fanout_unshared, "native_cube": native_cube}
