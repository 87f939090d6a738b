"""Cuboids from their smallest ancestors: a cascade of aggregates, each over the cells of a finer cuboid instead of the base."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from latticecube import files
from latticecube.operators import materialize as M
from latticecube.spec import CubeSpec


def choose_ancestor(member: frozenset[str], made: dict[frozenset[str], int]) -> frozenset[str] | None:
    """Of the cuboids that have all of a cuboid's dimensions the one with the fewest rows, or None for the base."""
    above = [m for m in made if member < m]
    return min(above, key=lambda m: (made[m], sorted(m))) if above else None


def from_ancestors(df: DataFrame, spec: CubeSpec) -> M.CubeResult:
    """Every cuboid in a written step of its own, large ones first; states and value counts travel, so all functions that compress work."""
    if spec.raw_only():
        raise ValueError("an own aggregate without a merge can't be made from another cuboid")
    spark, root, base = df.sparkSession, files.scratch_dir(df.sparkSession), spec.prepared(df)
    types = {f.name: f.dataType for f in base.schema}
    rows: dict[frozenset[str], int] = {}
    out, used = None, {}
    where = lambda m: f"{root}/{spec.cuboid_id(m)}"
    for m in sorted(spec.wanted(), key=lambda m: (-len(m), spec.cuboid_id(m))):
        own, above = [d for d in spec.dims if d in m], choose_ancestor(m, rows)
        made = M.compress(base, spec, own) if above is None else M.merge(spark.read.parquet(where(above)), spec, own)
        made.write.parquet(where(m))
        kept = spark.read.schema(made.schema).parquet(where(m))
        rows[m], used[spec.cuboid_id(m)] = kept.count(), None if above is None else spec.cuboid_id(above)  # counted from footers
        dims = [F.col(d) if d in m else F.lit(None).cast(types[d]).alias(d) for d in spec.dims]
        cells = M.finish(kept, spec, own).select(F.lit(spec.cuboid_id(m)).alias("cuboid_id"), *dims, *[a.name for a in spec.aggs])
        out = cells if out is None else out.unionByName(cells)
    if spec.include_all:
        out = out.unionByName(M.grand_total(df, spec))
    result = M.CubeResult(spec, out)
    result.ancestors = used
    return result
