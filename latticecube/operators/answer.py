"""Answers from a cube: roll-up, drill-down, slice, dice, pivot, ranks, shares, top and iceberg cells, joins with versions and bands."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from latticecube.operators.materialize import CubeResult


def covering(cube: CubeResult, needed: set[str]) -> frozenset[str]:
    """The smallest materialized cuboid that has all needed dimensions: by its cells where the cube was written, else by its dimensions."""
    fits = [m for m in cube.spec.wanted() if needed <= m]
    if not fits:
        raise ValueError(f"no cuboid covers {sorted(needed)}")
    cells = lambda m: cube.cells.get(cube.spec.cuboid_id(m), 0) if cube.cells is not None else 0
    return min(fits, key=lambda m: (cells(m), len(m), cube.spec.cuboid_id(m)))


#: How a cell's value is made from values of finer cells.
REAGGREGATE = {"sum": F.sum, "count": F.sum, "min": F.min, "max": F.max}


def answer(cube: CubeResult, group_by: list[str], where: str | Column | None = None, filter_dims: set[str] = frozenset()) -> DataFrame:
    """Group by some dimensions under a filter, from the smallest cuboid that has them all."""
    own = covering(cube, set(group_by) | set(filter_dims))
    view = cube.df.where(F.col("cuboid_id") == cube.spec.cuboid_id(own))
    if where is not None:
        view = view.where(where)
    if own == frozenset(group_by):
        return view.select(*group_by, *[a.name for a in cube.spec.aggs])
    if any(a.fn not in REAGGREGATE for a in cube.spec.aggs):
        raise ValueError("only SUM, COUNT, MIN and MAX roll up from a finer cuboid")
    return view.groupBy(*group_by).agg(*[REAGGREGATE[a.fn](a.name).alias(a.name) for a in cube.spec.aggs])


def rollup_view(cube: CubeResult, dims: list[str]) -> DataFrame:
    return answer(cube, dims)


def drill(cube: CubeResult, cell: dict, into: str) -> DataFrame:
    """The cells one dimension below a cell."""
    dims = [*cell, into]
    return _at(answer(cube, [d for d in cube.spec.dims if d in dims]), cell)


def _at(df: DataFrame, cell: dict) -> DataFrame:
    for d, v in cell.items():
        df = df.where(F.col(d).eqNullSafe(F.lit(v)))
    return df


def slice_(cube: CubeResult, dims: list[str], at: dict) -> DataFrame:
    """A cuboid with some of its dimensions fixed."""
    return _at(answer(cube, dims), at)


def dice(cube: CubeResult, dims: list[str], within: dict[str, list]) -> DataFrame:
    out = answer(cube, dims)
    for d, values in within.items():
        out = out.where(F.col(d).isin(values))
    return out


def pivot_view(cube: CubeResult, rows: list[str], column: str, values: list, agg: str) -> DataFrame:
    """A cuboid with one dimension's listed values as columns."""
    return answer(cube, [d for d in cube.spec.dims if d in {*rows, column}]).groupBy(*rows).pivot(column, values).agg(F.first(agg))


def top_cells(cube: CubeResult, dims: list[str], k: int, by: str) -> DataFrame:
    return answer(cube, dims).orderBy(F.col(by).desc(), *dims).limit(k)


def iceberg(cube: CubeResult, by: str, least: float) -> DataFrame:
    """All cells that reach a threshold."""
    return cube.df.where(F.col(by) >= least)


def share_of_parent(cube: CubeResult, dims: list[str], parent: list[str], by: str) -> DataFrame:
    whole = Window.partitionBy(*parent)
    return answer(cube, dims).withColumn("share", F.col(by) / F.sum(by).over(whole)).withColumn("rank", F.rank().over(whole.orderBy(F.col(by).desc())))


def moving_sum(cube: CubeResult, dims: list[str], along: str, by: str, rows: int) -> DataFrame:
    """Sum over the last so many cells along a dimension, within the other ones."""
    others = [d for d in dims if d != along]
    w = Window.partitionBy(*others).orderBy(along).rowsBetween(-(rows - 1), 0)
    return answer(cube, dims).withColumn("moving", F.sum(by).over(w))


def cube_diff(a: CubeResult, b: CubeResult) -> DataFrame:
    """Cells that differ, marked with the side they are from."""
    left = a.df.exceptAll(b.df).withColumn("side", F.lit("a"))
    return left.unionByName(b.df.exceptAll(a.df).withColumn("side", F.lit("b")))


def _day_of(df: DataFrame, ts: str) -> Column:
    return F.col(ts).cast("date") if df.schema[ts].dataType.typeName() in ("date", "timestamp", "timestamp_ntz") else F.lit(0)


def cube_as_of(versions: DataFrame, probes: DataFrame, ts: str, keys: list[str], value: str, strictly: bool = False, bucket: Column | None = None) -> DataFrame:
    """For each probe the last version's value at its time, or strictly before it: a union and windows, no range join.

    Rows of a key are cut by ``bucket``, an expression of the time that never falls as time goes on (its day, if it has one), so that a hot key's rows are
    in many tasks.  What a key's earlier buckets leave comes from one pre-aggregated row of each, and opens the bucket.
    """
    b = lambda df: (bucket if bucket is not None else _day_of(df, ts)).alias("__b")
    v = versions.select(*keys, b(versions), F.lit(1).alias("__own"), F.col(ts).alias("__t"), F.lit(0).alias("__probe"), F.col(value).alias("__v"), F.lit(None).alias("__row"))
    p = probes.select(*keys, b(probes), F.lit(1).alias("__own"), F.col(ts).alias("__t"), F.lit(-1 if strictly else 1).alias("__probe"), F.lit(None).alias("__v"), F.struct(*probes.columns).alias("__row"))
    rows = v.unionByName(p)
    ends = rows.groupBy(*keys, "__b").agg(F.max_by("__v", F.when(F.col("__v").isNotNull(), F.struct("__t"))).alias("__v"))
    before = Window.partitionBy(*keys).orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)
    opening = ends.withColumn("__v", F.last("__v", ignorenulls=True).over(before)).withColumns({"__own": F.lit(0), "__t": F.lit(None), "__probe": F.lit(0), "__row": F.lit(None)})
    w = Window.partitionBy(*keys, "__b").orderBy("__own", "__t", "__probe").rowsBetween(Window.unboundedPreceding, 0)
    both = rows.unionByName(opening).withColumn("__last", F.last("__v", ignorenulls=True).over(w)).where("__probe <> 0")
    return both.select("__row.*", F.col("__last").alias(value))


def active_in(left: DataFrame, right: DataFrame, at: str, lo: str, hi: str, bucket_days: int = 32) -> DataFrame:
    """Interval join: rows of ``left`` at a time within [lo, hi) of ``right``, by equal time buckets and a filter."""
    day = lambda c: F.floor(F.datediff(F.col(c), F.lit("1970-01-01")) / bucket_days)
    spread = right.withColumn("__b", F.explode(F.sequence(day(lo), day(hi))))
    return left.withColumn("__b", day(at)).join(spread, "__b").where((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("__b")


def band(df: DataFrame, bands: list[tuple[str, float, float]], column: str, name: str = "band") -> DataFrame:
    """Label rows by half-open bands given as literals."""
    label = F.lit(None).cast("string")
    for text, lo, hi in reversed(bands):
        label = F.when((F.col(column) >= lo) & (F.col(column) < hi), F.lit(text)).otherwise(label)
    return df.withColumn(name, label)
