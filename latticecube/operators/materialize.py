"""Shared-scan materialization: one scan, one copy of a row for each chain, one shuffle, all cuboids.

The map side copies each row once per chain, with the slot it goes to; dimensions that the chain doesn't have are null.  After the one
exchange everything is local to a slot.  The levels engine aggregates at the chain's full key, explodes the chain's members, and merges;
the ordered engine sorts and closes cells in one pass over Arrow batches.
"""

from __future__ import annotations

import json
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from latticecube.files import Files
from latticecube.plans.chains import Chain, ChainPlan, plan_chains
from latticecube.plans.slots import SlotPlan, allocate_slots, bucket_keys, even_slots, is_heavy, slot_expr
from latticecube.spec import CubeSpec

#: Distinct keys over rows, above which aggregating before the copies doesn't pay.
COMBINE_RATIO = 0.8


@dataclass
class CubePlan:
    """What a cube will do: its chains and slots."""

    spec: CubeSpec
    chains: list[Chain]
    slots: SlotPlan
    stats: dict

    def explain(self) -> str:
        from latticecube.plans.lattice import Lattice

        lattice = Lattice(self.spec.dims)
        lines = [f"{self.spec.name}: {len(self.spec.wanted())} cuboids in {len(self.chains)} chains, {self.slots.total} slots, {self.stats}"]
        for c, start, width in zip(self.chains, self.slots.starts, self.slots.widths, strict=True):
            lines.append(f"  sort by {','.join(c.sort_dims)}; deal by {','.join(c.part_dims)} to slots {start}..{start + width - 1}; members {len(c.members)}; tag {c.bitmap(lattice):0{2 ** len(self.spec.dims)}b}")
        lines.append(f"  copies of a row: {len(self.chains)}, unshared {len(self.spec.wanted())}")
        return "\n".join(lines)


@dataclass
class CubeResult:
    spec: CubeSpec
    df: DataFrame
    plan: CubePlan | None = None
    cells: dict[int, int] | None = None
    ancestors: dict[int, int | None] | None = None

    def cuboid(self, *dims: str) -> DataFrame:
        """One cuboid's cells with its own dimensions only."""
        own = self.df.where(F.col("cuboid_id") == self.spec.cuboid_id(set(dims)))
        return own.select(*dims, *[a.name for a in self.spec.aggs])

    def write(self, path: str) -> CubeResult:
        """One folder for each cuboid, whose rows stay where they are, and the number of cells of each; returns the cube as it is read from there."""
        self.df.write.mode("overwrite").partitionBy("cuboid_id").parquet(path)
        spark = self.df.sparkSession
        written = spark.read.schema(self.df.schema).parquet(path)
        sizes = {r["cuboid_id"]: r["n"] for r in written.groupBy("cuboid_id").agg(F.count("*").alias("n")).collect()}  # one row a cuboid, from footers
        Files(spark, path).create("_cells.json", json.dumps({"cells": {str(k): v for k, v in sizes.items()}, "schema": json.loads(self.df.schema.json())}))
        return CubeResult.read(spark, path, self.spec)

    @staticmethod
    def read(spark: SparkSession, path: str, spec: CubeSpec) -> CubeResult:
        """A written cube: its answers read only the folders of their cuboid."""
        known = json.loads(Files(spark, path).read("_cells.json"))
        df = spark.read.schema(T.StructType.fromJson(known["schema"])).parquet(path)
        return CubeResult(spec, df.select(*spec.output_columns()), cells={int(k): v for k, v in known["cells"].items()})

    def views(self) -> list[str]:
        """Temporary views ``<name>_<dims>`` for each cuboid."""
        names = []
        for m in self.spec.wanted():
            own = [d for d in self.spec.dims if d in m]
            names.append("_".join([self.spec.name, *own]))
            self.cuboid(*own).createOrReplaceTempView(names[-1])
        return names


def default_slots(df: DataFrame, chains: int) -> int:
    return max(chains, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))


def plan(spec: CubeSpec, slots: SlotPlan | list[int] | int, chains: list[Chain] | None = None, strategy: str = "auto") -> CubePlan:
    made = plan_chains(spec.dims, spec.cuboids, strategy) if chains is None else ChainPlan(chains, "given", {"chains": len(chains)})
    if isinstance(slots, int):
        slots = even_slots(len(made.chains), slots)
    if not isinstance(slots, SlotPlan):
        slots = SlotPlan(tuple(slots))
    if len(slots.widths) != len(made.chains):
        raise ValueError("a slot range is needed for each chain")
    return CubePlan(spec, made.chains, slots, made.stats)


# rows and states


def _counted(spec: CubeSpec) -> bool:
    """Frequency functions need how often each value comes; others carry no count."""
    return bool(spec.holistic_measures())


def compress(rows: DataFrame, spec: CubeSpec, keys: list[str | Column]) -> DataFrame:
    """Aggregate prepared rows at some keys into mergeable rows: states, and values with counts for frequency functions.

    A spec with an aggregate that needs raw rows leaves them as they are.
    """
    if spec.raw_only():
        return rows
    values = [f"m_{m}" for m in spec.holistic_measures()]
    states = [init.alias(name) for a in spec.aggs for name, (init, _) in a.states().items()]
    return rows.groupBy(*keys, *values).agg(*([F.count(F.lit(1)).alias("__cnt")] if _counted(spec) else []), *states)


def _centred(rows: DataFrame, spec: CubeSpec, keys: list[str]) -> DataFrame:
    """With the means that moments are merged around: a window over the merge's own keys, so nothing is shuffled for it."""
    own = Window.partitionBy(*keys)
    centres = {name: F.sum(above).over(own) / F.sum(below).over(own) for a in spec.aggs for name, (above, below) in a.centres().items()}
    return rows.withColumns(centres) if centres else rows


def merge(rows: DataFrame, spec: CubeSpec, keys: list[str], with_values: bool = True) -> DataFrame:
    """Merge compressed rows of equal keys."""
    if spec.raw_only():
        return rows
    values = [f"m_{m}" for m in spec.holistic_measures()] if with_values else []
    states = [m.alias(name) for a in spec.aggs for name, (_, m) in a.states().items()]
    return _centred(rows, spec, [*keys, *values]).groupBy(*keys, *values).agg(*([F.sum("__cnt").alias("__cnt")] if _counted(spec) else []), *states)


def _ranked(rows: DataFrame, spec: CubeSpec, keys: list[str]) -> DataFrame:
    """With how many values of a cell come up to each row's and in all, for MEDIAN and percentiles: one sort of the cells' distinct values."""
    added, cell = {}, Window.partitionBy(*keys)
    for m in dict.fromkeys(a.measure for a in spec.aggs if a.fn in ("median", "percentile")):
        n = F.when(F.col(f"m_{m}").isNotNull(), F.col("__cnt")).otherwise(0)
        added |= {f"upto_{m}": F.sum(n).over(cell.orderBy(f"m_{m}").rowsBetween(Window.unboundedPreceding, 0)), f"all_{m}": F.sum(n).over(cell)}
    return rows.withColumns(added) if added else rows


def finish(rows: DataFrame, spec: CubeSpec, keys: list[str], raw: bool = False) -> DataFrame:
    """Cells from compressed rows, or from ``raw`` ones: merged states and frequency functions in one aggregate."""
    raw = raw or spec.raw_only()
    if spec.raw_only():
        rows = rows.withColumn("__cnt", F.lit(1).cast("long")) if _counted(spec) else rows
    elif _counted(spec):
        # a value's count must be whole before values are ranked
        rows, raw = compress(rows, spec, keys) if raw else merge(rows, spec, keys), False
    states = [pair[0 if raw else 1].alias(name) for a in spec.aggs for name, pair in a.states().items()]
    held = [a.from_frequencies().alias(a.name) for a in spec.aggs if a.kind == "frequency"]
    rows = _ranked(rows if raw else _centred(rows, spec, keys), spec, keys)
    return rows.groupBy(*keys).agg(*states, *held).select(*keys, *[a.final().alias(a.name) for a in spec.aggs])


def masked(spec: CubeSpec, cuboid_id: Column, kept: frozenset[str] | None = None) -> list[Column]:
    """Each dimension where the cuboid has it, null where it is rolled up."""
    n = len(spec.dims)
    return [F.when(cuboid_id.bitwiseAND(F.lit(1 << (n - 1 - i))) == 0, F.col(d)).alias(d) for i, d in enumerate(spec.dims)]


def fan_out(rows: DataFrame, cube: CubePlan) -> DataFrame:
    """Copy each row once per chain: its slot, the chain's number, and only the chain's dimensions.

    Where the plan names heavy keys, ``__hot`` marks their copies, which are dealt over all of the chain's slots.
    """
    whole = [*cube.spec.dims, *[c for c in rows.columns if c.startswith("m_") and c not in cube.spec.dims]]
    copies = F.array(*[
        F.struct(F.lit(i).cast("smallint").alias("batch"), slot_expr(c, start, width, cube.slots.bounds[i] if cube.slots.bounds else None, cube.slots.heavy_of(i), whole).alias("slot"), is_heavy(c, cube.slots.heavy_of(i)).alias("hot"))
        for i, (c, start, width) in enumerate(zip(cube.chains, cube.slots.starts, cube.slots.widths, strict=True))
    ])
    rest = [c for c in rows.columns if c not in cube.spec.dims]
    spread = rows.select(*cube.spec.dims, *rest, F.explode(copies).alias("__copy"))
    dims = []
    for d in cube.spec.dims:
        without = [i for i, c in enumerate(cube.chains) if d not in c.order]
        dims.append((F.when(~F.col("__copy.batch").isin(without), F.col(d)) if without else F.col(d)).alias(d))
    hot = [F.col("__copy.hot").alias("__hot")] if cube.slots.any_heavy else []
    return spread.select(F.col("__copy.slot").alias("__slot"), F.col("__copy.batch").alias("__batch"), *hot, *dims, *rest)


def dealt(rows: DataFrame, cube: CubePlan, keyed: bool = False) -> DataFrame:
    """Prepared rows in their slots, by the one shuffle; ``keyed`` names slots by what a bucketed table deals by."""
    spread = fan_out(rows, cube)
    if not keyed:
        return spread.repartitionById(cube.slots.total, F.col("__slot"))
    keys = F.array(*[F.lit(k) for k in bucket_keys(cube.slots.total)])
    return spread.withColumn("__slot", F.get(keys, F.col("__slot"))).repartition(cube.slots.total, "__slot")


def levels(rows: DataFrame, cube: CubePlan) -> DataFrame:
    """Explode each compressed row to its chain's members; the partitioning stays."""
    spec = cube.spec
    ids = F.element_at(F.array(*[F.array(*[F.lit(spec.cuboid_id(m)) for m in c.members]) for c in cube.chains]), F.col("__batch").cast("int") + 1)
    rest = [c for c in rows.columns if c not in ("__slot", "__batch", *spec.dims)]
    spread = rows.select("__slot", "__batch", F.explode(ids).alias("cuboid_id"), *spec.dims, *rest)
    return spread.select("__slot", "__batch", "cuboid_id", *masked(spec, F.col("cuboid_id")), *rest)


def whole_in_slot(cube: CubePlan) -> Column:
    """Whether a levelled row's cell lies in one slot: all but a heavy key's, and of those the chain's longest if it has dimensions to deal by."""
    longest = [cube.spec.cuboid_id(c.members[0]) for c in cube.chains if len(c.order) > len(c.part_dims)]
    return ~F.col("__hot") | F.col("cuboid_id").isin(longest)


def cells_of(rows: DataFrame, cube: CubePlan, raw: bool = False) -> DataFrame:
    """Cells of levelled rows: in their slots, and for heavy keys by a second shuffle of what each slot made of them."""
    spec = cube.spec
    keys = ["__slot", "cuboid_id", *spec.dims]
    if not cube.slots.any_heavy:
        return finish(rows, spec, keys, raw).select(*spec.output_columns())
    own = finish(rows.where(whole_in_slot(cube)).drop("__hot"), spec, keys, raw)
    apart = rows.where(~whole_in_slot(cube)).drop("__hot")
    parts = compress(apart, spec, keys) if raw else merge(apart, spec, keys)
    return own.select(*spec.output_columns()).unionByName(finish(parts, spec, keys[1:]).select(*spec.output_columns()))


def _combined(rows: DataFrame, spec: CubeSpec, combine: str) -> tuple[DataFrame, bool]:
    """Aggregate equal full keys before the copies, if asked, or if a sketch says that it pays."""
    if combine == "auto":
        keys = [*spec.dims, *[f"m_{m}" for m in spec.holistic_measures()]]
        r = rows.agg(F.count("*").alias("n"), F.approx_count_distinct(F.xxhash64(*keys)).alias("d")).first()
        combine = "on" if r["n"] and r["d"] < COMBINE_RATIO * r["n"] else "off"
    if combine == "on" and not spec.raw_only():
        return compress(rows, spec, list(spec.dims)), True
    if combine not in ("on", "off"):
        raise ValueError("combine is auto, on or off")
    return rows, False


def shuffled(df: DataFrame, cube: CubePlan, combine: str = "off", prepared: bool = False, keyed: bool = False) -> DataFrame:
    """Compressed rows at each chain's full key, in their slots: what a cache of the reduce input holds."""
    spec = cube.spec
    rows = df if prepared else spec.prepared(df)
    rows, done = _combined(rows, spec, combine)
    keys = ["__slot", "__batch", *(["__hot"] if cube.slots.any_heavy else []), *spec.dims]
    placed = dealt(rows, cube, keyed)
    return merge(placed, spec, keys) if done else compress(placed, spec, keys)


def grand_total(df: DataFrame, spec: CubeSpec) -> DataFrame:
    """The cell of everything, by one small aggregate; none for an empty base, as with grouping sets."""
    rows = compress(spec.prepared(df), spec, [])
    cell = finish(rows.withColumn("cuboid_id", F.lit((1 << len(spec.dims)) - 1)), spec, ["cuboid_id"])
    types = {f.name: f.dataType for f in spec.prepared(df).schema}
    return cell.select("cuboid_id", *[F.lit(None).cast(types[d]).alias(d) for d in spec.dims], *[a.name for a in spec.aggs])


def materialize(df: DataFrame, spec: CubeSpec, method: str = "shared_scan", slots: SlotPlan | list[int] | int | None = None, chains: list[Chain] | None = None, strategy: str = "auto", combine: str = "off", engine: str = "levels", feed: str = "base", waves: int = 1) -> CubeResult:
    """Compute a cube.

    ``feed="finest"`` aggregates the base once at all dimensions and fans that out; ``feed="ancestor"`` makes each cuboid from the smallest one above
    it that is there already, in written steps.  ``waves`` > 1 runs the chains in so many groups,
    each with a shuffle of its own, which bounds the size of one exchange.
    """
    from latticecube.operators import ancestors, baselines

    if feed == "ancestor":
        return ancestors.from_ancestors(df, spec)
    if method in baselines.METHODS:
        return baselines.METHODS[method](df, spec, slots)
    if method != "shared_scan":
        raise ValueError(f"no method {method}")
    if slots is None:
        made = plan_chains(spec.dims, spec.cuboids, strategy).chains if chains is None else chains
        slots = default_slots(df, len(made))
    cube = plan(spec, slots, chains, strategy)
    if waves > 1:
        out, n = None, len(cube.chains)
        for w in range(min(waves, n)):
            own = [i for i in range(n) if i % waves == w]
            part = CubePlan(spec, [cube.chains[i] for i in own], cube.slots.part(own), cube.stats)
            cells = _cells(df, part, combine, engine, feed)
            out = cells if out is None else out.unionByName(cells)
    else:
        out = _cells(df, cube, combine, engine, feed)
    if spec.include_all:
        out = out.unionByName(grand_total(df, spec))
    return CubeResult(spec, out, cube)


def _cells(df: DataFrame, cube: CubePlan, combine: str, engine: str, feed: str) -> DataFrame:
    from latticecube.operators import ordered

    if engine == "ordered":
        return ordered.cells(df, cube)
    if engine != "levels":
        raise ValueError(f"no engine {engine}")
    if feed == "finest":
        combine = "on"
    if combine == "off":
        # rows are aggregated once, at each member's key
        return cells_of(levels(dealt(cube.spec.prepared(df), cube), cube), cube, raw=True)
    return cells_of(levels(shuffled(df, cube, combine), cube), cube)


__all__ = ["CubePlan", "CubeResult", "allocate_slots", "compress", "fan_out", "finish", "grand_total", "levels", "materialize", "merge", "plan", "shuffled"]
