"""View maintenance for appended data: recomputation and incremental, each with and without the slot store.

recompute_reload    the cube of base and delta from files
recompute_reuse     only the delta is shuffled; the state of the reduce input is read where it lies, and cells are made again
incremental_reload  the delta's cube is written, then old and new views are read, shuffled and merged
incremental_reuse   only the delta is shuffled; its states merge with the cached views of the same buckets
incremental_counts  the same for MEDIAN and other frequency functions: cells keep each distinct value with its count
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from latticecube.operators import materialize as M
from latticecube.operators.store import SlotStore, cell_keys, slot_keys
from latticecube.plans.slots import SlotPlan, bucket_keys
from latticecube.spec import CubeSpec

#: Numbers of applied batches that a manifest remembers: a stream repeats only its last one.
REMEMBERED = 1_000
MANNERS = ("recompute_reload", "recompute_reuse", "incremental_reload", "incremental_reuse", "incremental_counts")
#: The kind of state that each manner with a store works on.
KIND = {"recompute_reuse": "input", "incremental_reuse": "view", "incremental_counts": "counts"}


@dataclass
class Refreshed:
    """The refreshed cube, the version it belongs to, and the manner."""

    cube: M.CubeResult
    version: int
    manner: str


def _keys(spec: CubeSpec, cube: M.CubePlan, kind: str) -> list[str]:
    return slot_keys(spec, kind) + (["__hot"] if cube.slots.any_heavy else [])


def state_rows(df: DataFrame, cube: M.CubePlan, kind: str, only: set[int] | None = None) -> DataFrame:
    """State of all chains in their slots: one scan, one shuffle.  ``only`` keeps some slots, before the shuffle."""
    spec = cube.spec
    rows = M.dealt(spec.prepared(df), cube, keyed=True)
    if only is not None:
        every = bucket_keys(cube.slots.total)
        rows = rows.where(F.col("__slot").isin([every[s] for s in sorted(only)]))
    if kind != "input":
        rows = M.levels(rows, cube).drop("__batch")
    return M.compress(rows, spec, _keys(spec, cube, kind))


def _finals(states: DataFrame, spec: CubeSpec) -> DataFrame:
    return states.select("cuboid_id", *spec.dims, *[a.final().alias(a.name) for a in spec.aggs])


def materialize_cached(df: DataFrame, spec: CubeSpec, store: SlotStore, cache: str, slots: SlotPlan | int | None = None, strategy: str = "auto", batch_id: str | None = None) -> M.CubeResult:
    """The first job: write the state of all chains in one job, and make the cube from what was written.

    ``cache="input"`` keeps the reduce input, ``"view"`` the states of the views, ``"counts"`` the same with values and counts for frequency functions,
    ``"none"`` nothing.  A ``batch_id`` is noted in the same commit.
    """
    if cache == "none":
        return M.materialize(df, spec, slots=slots, strategy=strategy)
    if cache not in KIND.values():
        raise ValueError("cache is none, input, view or counts")
    if cache == "view" and not spec.mergeable():
        raise ValueError("a view cache needs aggregates that merge; use the input cache")
    if cache == "counts" and not spec.countable():
        raise ValueError("some aggregate merges neither by states nor by counts; use the input cache")
    old = store.manifest()
    if old["version"]:
        raise ValueError("the store has a state already")
    if isinstance(slots, SlotPlan) and any(slots.bounds):
        raise ValueError("a store deals by hash: ranges would not suit later deltas")
    cube = M.plan(spec, slots or M.default_slots(df, len(M.plan_chains(spec.dims, spec.cuboids, strategy).chains)), strategy=strategy)
    run = store.write_run(state_rows(df, cube, cache), cube.slots.total, cache)
    m = store.commit(old, kind=cache, runs=[run], batches=[batch_id] if batch_id is not None else [], **store.described(cube))
    return M.CubeResult(spec, _with_all(current(store, m), spec, store, m), cube)


def current(store: SlotStore, m: dict | None = None) -> DataFrame:
    """The cube as the store's state has it: one bucketed scan, and no shuffle but for heavy keys."""
    m = m or store.manifest()
    cube, spec, state = store.plan(m), store.spec, store.state(m)
    if m["kind"] == "input":
        return M.cells_of(M.levels(state, cube), cube)
    if cube.slots.any_heavy or m["kind"] == "counts":
        return M.cells_of(state, cube)
    return _finals(state if len(m["runs"]) == 1 else M.merge(state, spec, _keys(spec, cube, "view")), spec)


def _with_all(cells: DataFrame, spec: CubeSpec, store: SlotStore, m: dict) -> DataFrame:
    """Add the grand total from the first chain's state, merged in its slots first: every row is in each chain once."""
    if not spec.include_all:
        return cells
    cube, state = store.plan(m), store.state(m)
    first = F.col("__batch") == 0 if m["kind"] == "input" else F.col("cuboid_id") == spec.cuboid_id(cube.chains[0].members[0])
    top = M.merge(state.where(first).drop("cuboid_id"), spec, ["__slot"]).withColumn("cuboid_id", F.lit((1 << len(spec.dims)) - 1))
    top = M.finish(top, spec, ["cuboid_id"])
    types = {f.name: f.dataType for f in state.schema}
    return cells.unionByName(top.select("cuboid_id", *[F.lit(None).cast(types[x]).alias(x) for x in spec.dims], *[a.name for a in spec.aggs]))


def refresh(store: SlotStore, delta: DataFrame, manner: str, base: DataFrame | None = None, batch_id: str | None = None, keep_delta: str | None = None) -> Refreshed:
    """Bring the cube up to base and delta.

    ``incremental_reuse`` is one job: the state's scan and the dealt delta meet in their slots and the merged state is written once; the cube is read
    from that.  With a store that merges on read only the delta's run is written.  ``recompute_reuse`` writes the delta's run and makes the cells anew
    from all runs.  Manners that reload need ``base`` and leave the store alone.  A ``batch_id`` among the last ``REMEMBERED`` applied ones changes nothing.  With
    ``keep_delta`` the delta is kept under that path until the next snapshot, for recovery.
    """
    spec, m = store.spec, store.manifest()
    if manner not in MANNERS:
        raise ValueError(f"no manner {manner}")
    if manner == "recompute_reload":
        return Refreshed(M.materialize(base.unionByName(delta), spec), m["version"], manner)
    if manner.startswith("incremental") and manner != "incremental_counts" and not spec.mergeable():
        raise ValueError("some aggregate doesn't merge: use recomputation, or counts")
    if manner == "incremental_reload":
        raise ValueError("incremental_reload works on published views: use incremental_reload()")
    kind = KIND[manner]
    if m["kind"] != kind:
        raise ValueError(f"{manner} needs a store of kind {kind}")
    if batch_id is not None and batch_id in m["batches"]:
        return Refreshed(M.CubeResult(spec, _with_all(current(store, m), spec, store, m), store.plan(m)), m["version"], manner)
    cube = store.plan(m)
    fresh = state_rows(delta, cube, kind)
    if kind != "input" and store.merge_when == "on_write":
        runs = [store.write_run(M.merge(store.state(m).unionByName(fresh), spec, _keys(spec, cube, kind)), cube.slots.total, kind)]
    else:
        runs = [*m["runs"], store.write_run(fresh, cube.slots.total, kind)]
    updates = m["updates"] + 1
    changes = {"runs": runs, "updates": updates, "batches": [*m["batches"], *([batch_id] if batch_id is not None else [])][-REMEMBERED:]}
    if keep_delta:
        delta.write.mode("overwrite").parquet(keep_delta)
        changes["deltas"] = [*m["deltas"], keep_delta]
    new = store.commit(m, **changes)
    if store.policy.every and updates % store.policy.every == 0:
        new = snapshot(store)
    return Refreshed(M.CubeResult(spec, _with_all(current(store, new), spec, store, new), cube), new["version"], manner)


def compact(store: SlotStore) -> dict:
    """Merge all runs into one, where the slots lie."""
    m = store.manifest()
    cube = store.plan(m)
    rows = M.merge(store.state(m), store.spec, _keys(store.spec, cube, m["kind"]))
    return store.commit(m, runs=[store.write_run(rows, cube.slots.total, m["kind"])])


def snapshot(store: SlotStore) -> dict:
    """Copy the state; deltas from before it are no longer needed for recovery, and the snapshot before it is dropped in time."""
    m = store.manifest()
    copy = store.write_run(store.state(m), store.plan(m).slots.total, "snapshot")
    new = store.commit(m, snapshot={"updates": m["updates"], "runs": [copy]}, deltas=[])
    for path in m["deltas"]:
        store.files.delete(path)
    return new


def refresh_many(store: SlotStore, deltas: list[DataFrame], manner: str, compact_every: int = 4) -> Refreshed:
    out = None
    for i, delta in enumerate(deltas, 1):
        out = refresh(store, delta, manner)
        if compact_every and i % compact_every == 0 and len(store.manifest()["runs"]) > 1:
            m = compact(store)
            out = Refreshed(M.CubeResult(store.spec, _with_all(current(store, m), store.spec, store, m), out.cube.plan), m["version"], manner)
    return out


# without the store


def view_states(df: DataFrame, spec: CubeSpec, slots: int | None = None) -> DataFrame:
    """Merged states of all cells: what is published for incremental maintenance from files."""
    cube = M.plan(spec, slots or M.default_slots(df, len(M.plan_chains(spec.dims, spec.cuboids).chains)))
    rows = M.levels(M.dealt(spec.prepared(df), cube), cube)
    return M.compress(rows, spec, ["__slot", *cell_keys(spec)]).drop("__slot")


def incremental_reload(view_path: str, delta: DataFrame, spec: CubeSpec, delta_path: str, new_path: str | None = None) -> M.CubeResult:
    """Two jobs: the delta's view is written; then both views are read and merged by a shuffle."""
    if not spec.mergeable():
        raise ValueError("some aggregate doesn't merge: use recomputation")
    spark = delta.sparkSession
    view_states(delta, spec).write.mode("overwrite").parquet(delta_path)
    merged = M.merge(spark.read.parquet(view_path).unionByName(spark.read.parquet(delta_path)), spec, cell_keys(spec))
    if new_path:
        merged.write.mode("overwrite").parquet(new_path)
        merged = spark.read.parquet(new_path)
    return M.CubeResult(spec, _finals(merged, spec))


#: Cost of a byte that is read, written and shuffled, against each other: a shuffled byte is written, sent and read.
WEIGHTS = {"read": 1.0, "write": 1.5, "shuffle": 3.0}


def refresh_costs(spec: CubeSpec, base_bytes: int, state_bytes: int, view_bytes: int, delta_bytes: int, chains: int, weights: dict[str, float] = WEIGHTS) -> dict[str, float]:
    """Weighted bytes that each manner that works for the spec reads, writes and shuffles; all of them publish the whole new view.

    The delta's view is as large against the view as the delta is against the base, and its input state likewise.
    """
    r, w, s = weights["read"], weights["write"], weights["shuffle"]
    part = delta_bytes / max(1, base_bytes)
    dealt, delta_view, delta_state, new_view = chains * delta_bytes, part * view_bytes, part * state_bytes, (1 + part) * view_bytes
    out = {
        "recompute_reload": r * (base_bytes + delta_bytes) + s * chains * (base_bytes + delta_bytes) + w * new_view,
        "recompute_reuse": r * (delta_bytes + state_bytes + delta_state) + s * dealt + w * (delta_state + new_view),
    }
    if spec.mergeable():
        out["incremental_reload"] = r * (delta_bytes + view_bytes + delta_view) + s * (dealt + view_bytes + delta_view) + w * (delta_view + new_view)
        out["incremental_reuse"] = r * (delta_bytes + view_bytes) + s * dealt + w * new_view
    return out


def choose_manner(spec: CubeSpec, base_bytes: int, state_bytes: int, view_bytes: int, delta_bytes: int, chains: int, weights: dict[str, float] = WEIGHTS) -> str:
    """The manner of least cost; ``state_bytes`` of 0 or ``view_bytes`` of 0 don't mean that there is no such state."""
    costs = refresh_costs(spec, base_bytes, state_bytes, view_bytes, delta_bytes, chains, weights)
    return min(costs, key=costs.__getitem__)


def merge_views(old: M.CubeResult, new: M.CubeResult) -> DataFrame:
    """Cells of base and delta from their two published cubes by one full outer join; for SUM, COUNT, MIN and MAX."""
    spec = old.spec
    add = {"sum": lambda a, b: F.coalesce(a + b, a, b), "count": lambda a, b: F.coalesce(a + b, a, b), "min": F.least, "max": F.greatest}
    if any(a.fn not in add for a in spec.aggs):
        raise ValueError("published cells of other functions don't merge: keep their states")
    a, b = old.df, new.df
    keys = [F.coalesce(a[k], b[k]).alias(k) for k in cell_keys(spec)]
    return a.join(b, _same_cell(a, b, spec), "full_outer").select(*keys, *[add[x.fn](a[x.name], b[x.name]).alias(x.name) for x in spec.aggs])


# cells that a delta touches


def _delta_cells(delta: DataFrame, spec: CubeSpec) -> DataFrame:
    cube = M.plan(spec, M.default_slots(delta, len(M.plan_chains(spec.dims, spec.cuboids).chains)))
    return M.levels(M.dealt(spec.prepared(delta), cube), cube).select("__slot", *cell_keys(spec)).distinct().drop("__slot")  # where they lie


def _same_cell(a: DataFrame, b: DataFrame, spec: CubeSpec):
    out = a["cuboid_id"] == b["cuboid_id"]
    for d in spec.dims:
        out = out & a[d].eqNullSafe(b[d])
    return out


def delta_new_cells(cube: M.CubeResult, delta: DataFrame) -> DataFrame:
    """Cells of the delta that the cube hasn't got."""
    cells = _delta_cells(delta, cube.spec)
    return cells.join(cube.df, _same_cell(cells, cube.df, cube.spec), "left_anti")


def touched_cells(cube: M.CubeResult, delta: DataFrame) -> DataFrame:
    """Cells of the cube that the delta changes."""
    cells = _delta_cells(delta, cube.spec)
    return cube.df.join(cells, _same_cell(cube.df, cells, cube.spec), "left_semi")
