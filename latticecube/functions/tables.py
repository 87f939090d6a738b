"""Table functions over the lattice's metadata."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from latticecube.functions.aggregates import Agg
from latticecube.operators import materialize as M
from latticecube.plans.chains import plan_chains
from latticecube.plans.lattice import Lattice
from latticecube.spec import CubeSpec


@udtf(returnType="number int, members string")
class CuboidsOf:
    """The members of a batch tag, written as a bit string, over comma-separated dimensions."""

    def eval(self, dims: str, tag: str):
        lattice = Lattice(dims.split(","))
        for c in lattice.of_tag(int(tag, 2)):
            yield lattice.number(c), ",".join(d for d in lattice.dims if d in c)


def fed_cuboids(df: DataFrame, spec: CubeSpec, measure: str) -> DataFrame:
    """The cuboids that a table's copies feed, from the batch tags of the chains that they were dealt to: copies and the sum of a measure of each."""
    cube, lattice = M.plan(spec, M.default_slots(df, len(plan_chains(spec.dims, spec.cuboids).chains))), Lattice(list(spec.dims))
    tags = F.array(*[F.lit(format(c.bitmap(lattice), f"0{2 ** len(spec.dims)}b")) for c in cube.chains])
    dealt = M.fan_out(spec.prepared(df), cube).groupBy("__batch").agg(F.count(F.lit(1)).alias("copies"), F.sum(f"m_{measure}").alias("total"))
    tagged = dealt.select(F.get(tags, F.col("__batch").cast("int")).alias("tag"), "copies", "total")
    return tagged.lateralJoin(CuboidsOf(F.lit(",".join(spec.dims)), F.col("tag").outer())).select("number", "members", "copies", "total")


def cuboid_sizes(df: DataFrame, spec: CubeSpec) -> DataFrame:
    """``cuboid_id, n_cells`` of all cuboids of a table: one scan, aggregated at all dimensions first."""
    cells = M.materialize(df, CubeSpec(spec.dims, (Agg("count", alias="n"),), spec.cuboids, derived=spec.derived, where=spec.where), feed="finest").df
    return cells.groupBy("cuboid_id").agg(F.count(F.lit(1)).alias("n_cells"))


def lattice_table(df: DataFrame, spec: CubeSpec) -> DataFrame:
    """The cuboids of a table in the lattice's order, each with its number of cells."""
    lattice = Lattice(list(spec.dims))
    rows = [(spec.cuboid_id(c), lattice.number(c), len(c), ",".join(d for d in spec.dims if d in c)) for level in lattice.levels() for c in level]
    named = df.sparkSession.createDataFrame(rows, "cuboid_id int, number int, n_dims int, members string")
    return named.join(cuboid_sizes(df, spec), "cuboid_id", "left").select("number", "n_dims", "members", F.coalesce("n_cells", F.lit(0)).alias("n_cells"))


def chain_table(df: DataFrame, spec: CubeSpec, strategy: str = "auto") -> DataFrame:
    """The chains of a table's cube, each with the number of distinct keys that it is dealt by, the most slots that can get rows, and of its longest member's cells."""
    lattice, dims = Lattice(list(spec.dims)), spec.dims
    rows = [
        (i, ",".join(c.sort_dims), ",".join(c.part_dims), len(c.members), format(c.bitmap(lattice), f"0{2 ** len(dims)}b"), spec.cuboid_id(frozenset(c.part_dims)), spec.cuboid_id(frozenset(c.sort_dims)))
        for i, c in enumerate(plan_chains(dims, strategy=strategy).chains)
    ]
    planned = df.sparkSession.createDataFrame(rows, "chain int, sort_dims string, part_dims string, members int, tag string, dealt_by int, longest int")
    of = F.map_from_entries(F.collect_list(F.struct("cuboid_id", "n_cells"))).alias("of")  # one entry a cuboid
    size = lambda c: F.coalesce(F.col("of")[F.col(c)], F.lit(0))
    return planned.crossJoin(cuboid_sizes(df, spec).agg(of)).select("chain", "sort_dims", "part_dims", "members", "tag", size("dealt_by").alias("n_keys"), size("longest").alias("n_cells"))
