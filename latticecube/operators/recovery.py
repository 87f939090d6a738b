"""Recovery of lost slots: from the published views, or from the last snapshot and the deltas since."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from latticecube.operators import materialize as M
from latticecube.operators.maintain import state_rows
from latticecube.operators.store import SlotStore, slot_keys
from latticecube.plans.slots import bucket_keys, slot_expr


def damaged(store: SlotStore) -> list[int]:
    """Numbers of the slots that miss files of their state; a single lost file is enough."""
    return sorted(store.damaged(store.manifest()["runs"]))


def slots_of(cube: M.CubePlan, numbers: list[int]) -> list[int]:
    """All slots of some chains."""
    return [s for i in numbers for s in range(cube.slots.starts[i], cube.slots.starts[i] + cube.slots.widths[i])]


def _slot_of_cell(cube: M.CubePlan) -> Column:
    """The slot of a published cell, from its cuboid's chain and its partition dimensions."""
    out = F.lit(None).cast("int")
    for c, start, width in zip(cube.chains, cube.slots.starts, cube.slots.widths, strict=True):
        out = F.when(F.col("cuboid_id").isin([cube.spec.cuboid_id(m) for m in c.members]), slot_expr(c, start, width)).otherwise(out)
    return out


def recover(store: SlotStore, slots: list[int], manner: str, published: DataFrame | None = None, base: DataFrame | None = None) -> dict:
    """Build the state of some slots anew and commit it as a new version; the other slots' files stay in use.

    ``incremental``: from ``published`` view states (``cuboid_id``, dimensions, states), filtered to the slots.
    ``recompute``: from the last snapshot's slots where they are whole, or from ``base``, and the deltas kept since; of these only rows of the lost
    slots are shuffled.
    """
    m, spec = store.manifest(), store.spec
    cube, lost = store.plan(m), set(slots)
    keys = store.keys_of(lost, cube.slots.total)
    wanted = F.col("__slot").isin(keys)
    if manner == "incremental":
        if published is None or m["kind"] == "input":
            raise ValueError("incremental recovery needs published views and a store of view states")
        if cube.slots.any_heavy:
            raise ValueError("cells of heavy keys have parts in many slots: recover by recomputation")
        every = F.array(*[F.lit(k) for k in bucket_keys(cube.slots.total)])
        of_run = [f.name for f in store.state(m).schema if f.name != "__slot"]
        rows = published.withColumn("__slot", F.get(every, _slot_of_cell(cube))).where(wanted).select("__slot", *of_run).repartition(cube.slots.total, "__slot")
    elif manner == "recompute":
        kept = bool(m["snapshot"]) and not lost & store.damaged(m["snapshot"]["runs"])
        if len(m["deltas"]) != m["updates"] - (m["snapshot"]["updates"] if kept else 0):
            raise ValueError("not every delta since was kept: recover from published views, or make the state anew")
        if kept:
            rows = store.table_over(m["snapshot"]["runs"]).where(wanted)
        elif base is not None:
            rows = state_rows(base, cube, m["kind"], lost)
        else:
            raise ValueError("neither a whole snapshot nor a base to recover from")
        for path in m["deltas"]:
            rows = rows.unionByName(state_rows(store.spark.read.parquet(path), cube, m["kind"], lost))
        rows = rows.repartition(cube.slots.total, "__slot")  # of lost slots only
        rows = M.merge(rows, spec, slot_keys(spec, m["kind"]) + (["__hot"] if cube.slots.any_heavy else []))
    else:
        raise ValueError("manner is incremental or recompute")
    new = store.write_run(rows, cube.slots.total, m["kind"])
    old = [r | {"without": sorted(lost | set(r["without"]))} for r in m["runs"]]
    return store.commit(m, runs=[*old, new])
