import random
import statistics
from collections import defaultdict
from datetime import date, datetime, timedelta
from decimal import Decimal

import pytest
from pyspark.sql import functions as F

from latticecube import metrics, sqlfront
from latticecube.functions.aggregates import Agg, UserAgg
from latticecube.operators import answer, maintain, recovery
from latticecube.operators import materialize as M
from latticecube.operators.store import SlotStore, SnapshotPolicy
from latticecube.plans import slots as S
from latticecube.plans.chains import plan_chains
from latticecube.spec import CubeSpec
from latticecube.sources import tables as T
from latticecube.streaming import stream

SF = "/root/testdata/sf0.001"
SUM, MEDIAN, COUNT = Agg("sum", "m", alias="s"), Agg("median", "m", alias="md"), Agg("count", "m", alias="n")


def brute(rows, dims, fns, cuboids=None):
    """Cells by a dictionary over all rows; rows are dicts."""
    n, out = len(dims), {}
    for cid in range((1 << n) - 1):
        kept = [d for i, d in enumerate(dims) if not cid >> (n - 1 - i) & 1]
        if cuboids is not None and frozenset(kept) not in cuboids:
            continue
        cells = defaultdict(list)
        for r in rows:
            cells[tuple(r[d] if d in kept else None for d in dims)].append(r["m"])
        for key, values in cells.items():
            real = [v for v in values if v is not None]
            out[(cid, *key)] = tuple(f(real) for f in fns)
    return out


def cells(df, n):
    rows = [tuple(r) for r in df.collect()]
    out = {r[: n + 1]: r[n + 1 :] for r in rows}
    assert len(out) == len(rows), "a cell came twice"
    return out


total = lambda v: sum(v) if v else None
middle = lambda v: statistics.median(v) if v else None

ROWS = [
    ("x", 1, date(2024, 1, 1), 3.0), ("x", 1, date(2024, 1, 1), 5.0), ("x", None, date(2024, 1, 2), -2.0), (None, 2, None, 7.0), (None, None, None, None),
    ("y", 2, date(2024, 1, 1), 0.0), ("y", 2, date(2024, 1, 1), 0.0), ("x", 1, date(2024, 1, 1), 3.0),
] + [("hot", i % 3, date(2024, 2, 1), float(i % 7)) for i in range(90)]


def frame(spark, rows=ROWS):
    return spark.createDataFrame(rows, "a string, b int, c date, m double")


@pytest.mark.parametrize("how", [{}, {"engine": "ordered"}, {"combine": "on"}, {"combine": "auto"}, {"feed": "finest"}, {"waves": 2}, {"strategy": "symmetric"}, {"strategy": "singletons"}, {"method": "per_cuboid_jobs"}, {"method": "fanout_unshared"}, {"method": "native_cube"}, {"slots": 3}, {"slots": [5, 1, 2]}], ids=str)
@pytest.mark.parametrize("rows", [ROWS, ROWS[:1], [], ROWS[4:5]], ids=["many", "one", "none", "null"])
def test_methods_equal_brute_force(spark, how, rows):
    if not rows and how.get("engine") == "ordered":
        how = {**how}
    got = cells(M.materialize(frame(spark, rows), CubeSpec(("a", "b", "c"), (SUM, MEDIAN, COUNT)), **how).df, 3)
    assert got == brute([dict(zip("abcm", r, strict=True)) for r in rows], ["a", "b", "c"], [total, middle, len])


def test_partial_cube_and_total(spark):
    want = (frozenset("a"), frozenset("bc"), frozenset("c"))
    spec = CubeSpec(("a", "b", "c"), (SUM,), want, include_all=True)
    got = cells(M.materialize(frame(spark), spec, strategy="exact").df, 3)
    grand = got.pop((7, None, None, None))
    assert grand == (total([r[3] for r in ROWS if r[3] is not None]),)
    assert got == brute([dict(zip("abcm", r, strict=True)) for r in ROWS], ["a", "b", "c"], [total], set(want))


def test_types_of_dimensions(spark):
    df = spark.createDataFrame([(Decimal("1.50"), True, 1.0), (Decimal("1.50"), False, 2.0), (None, True, 4.0)], "a decimal(12,2), b boolean, m double")
    got = cells(M.materialize(df, CubeSpec(("a", "b"), (SUM,))).df, 2)
    assert got[(1, Decimal("1.50"), None)] == (3.0,) and got[(2, None, True)] == (5.0,) and got[(1, None, None)] == (4.0,)
    for engine in ("levels", "ordered"):
        nan = spark.createDataFrame([("p", float("nan")), ("p", 1.0), ("q", -0.0)], "a string, m double")
        assert M.materialize(nan, CubeSpec(("a",), (COUNT,)), engine=engine).df.count() == 2


def test_one_exchange_and_cells_in_one_slot(spark):
    spec = CubeSpec(("a", "b", "c"), (SUM,))
    result = M.materialize(frame(spark), spec, slots=7)
    assert metrics.exchanges(result.df) == 1
    where = M.levels(M.shuffled(frame(spark), result.plan), result.plan).select("cuboid_id", *spec.dims, F.spark_partition_id().alias("p"))
    assert where.groupBy("cuboid_id", *spec.dims).agg(F.count_distinct("p").alias("k")).where("k > 1").count() == 0
    assert "copies of a row: 3" in result.plan.explain()


def test_specs_are_checked(spark):
    for bad in (lambda: CubeSpec((), (SUM,)), lambda: CubeSpec(("a", "a"), (SUM,)), lambda: CubeSpec(("a",), (Agg("sum", "m", alias="a"),)), lambda: CubeSpec(("a",), (SUM,), (frozenset("z"),)), lambda: Agg("nope", "m"), lambda: Agg("sum")):
        with pytest.raises(ValueError):
            bad()
    with pytest.raises(ValueError):
        M.materialize(frame(spark), CubeSpec(("zz",), (SUM,)))
    with pytest.raises(ValueError):
        M.materialize(frame(spark), CubeSpec(("b",), (Agg("sum", "a"),)))
    with pytest.raises(ValueError):
        M.materialize(frame(spark), CubeSpec(("a", "b", "c"), (SUM,)), slots=2)


BASE = [("a1", 3.0), ("a1", 5.0), ("a1", 9.0), ("a2", 4.0), ("a2", 5.0), ("a2", 7.0)]
DELTA = [("a1", 2.0), ("a1", 4.0), ("a2", 4.0)]


def test_worked_refresh_example(spark, tmp_path):
    f = lambda rows: spark.createDataFrame(rows, "a string, m double")
    sums, medians = CubeSpec(("a",), (SUM,)), CubeSpec(("a",), (MEDIAN,))
    store = SlotStore(spark, f"file://{tmp_path}/s", sums)
    first = maintain.materialize_cached(f(BASE), sums, store, "view", slots=2)
    assert cells(first.df, 1) == {(0, "a1"): (17.0,), (0, "a2"): (16.0,)}
    assert cells(maintain.refresh(store, f(DELTA), "incremental_reuse").cube.df, 1) == {(0, "a1"): (23.0,), (0, "a2"): (20.0,)}
    store = SlotStore(spark, f"file://{tmp_path}/m", medians)
    first = maintain.materialize_cached(f(BASE), medians, store, "input", slots=2)
    assert cells(first.df, 1) == {(0, "a1"): (5.0,), (0, "a2"): (5.0,)}
    assert cells(maintain.refresh(store, f(DELTA), "recompute_reuse").cube.df, 1) == {(0, "a1"): (4.0,), (0, "a2"): (4.5,)}
    with pytest.raises(ValueError):
        maintain.refresh(store, f(DELTA), "incremental_reuse")


@pytest.mark.parametrize("delta", [[], [("new", 9, None, 1.0)], ROWS[:3], ROWS[4:9] + [("z", 1, None, 2.0)]], ids=["none", "new cells", "old cells", "both"])
@pytest.mark.parametrize("manner", ["recompute_reuse", "incremental_reuse"])
def test_refresh_equals_rebuild(spark, tmp_path, delta, manner):
    spec = CubeSpec(("a", "b", "c"), (SUM, COUNT) if manner == "incremental_reuse" else (SUM, MEDIAN), include_all=True)
    store = SlotStore(spark, f"file://{tmp_path}", spec, SnapshotPolicy(1))
    maintain.materialize_cached(frame(spark), spec, store, "view" if manner == "incremental_reuse" else "input", slots=4)
    done = maintain.refresh(store, frame(spark, delta), manner, batch_id="7")
    want = cells(M.materialize(frame(spark, ROWS + delta), spec).df, 3)
    assert cells(done.cube.df, 3) == want
    assert maintain.refresh(store, frame(spark, delta), manner, batch_id="7").version == done.version
    maintain.compact(store)
    assert cells(maintain.current(store), 3) == {k: v for k, v in want.items() if k[0] != 7}
    assert store.storage_report()["state"] > 0 and store.storage_report()["snapshot"] > 0


def test_state_is_read_without_a_shuffle(spark, tmp_path):
    spec = CubeSpec(("a", "b", "c"), (MEDIAN,))
    store = SlotStore(spark, f"file://{tmp_path}", spec)
    maintain.materialize_cached(frame(spark), spec, store, "input", slots=6)
    done = maintain.refresh(store, frame(spark, ROWS[:4]), "recompute_reuse")
    assert metrics.exchanges(done.cube.df) == 0
    # another session knows the runs from the manifest alone
    again = SlotStore(spark.newSession(), f"file://{tmp_path}", spec)
    assert cells(maintain.current(again), 3) == cells(done.cube.df, 3)


def test_failed_job_leaves_the_old_version(spark, tmp_path, monkeypatch):
    spec = CubeSpec(("a", "b", "c"), (SUM,))
    store = SlotStore(spark, f"file://{tmp_path}", spec)
    maintain.materialize_cached(frame(spark), spec, store, "view", slots=3)
    before = cells(maintain.current(store), 3)
    monkeypatch.setattr(store, "commit", lambda *a, **k: (_ for _ in ()).throw(OSError("lost")))
    with pytest.raises(OSError):
        maintain.refresh(store, frame(spark, ROWS[:4]), "incremental_reuse")
    assert cells(maintain.current(SlotStore(spark, f"file://{tmp_path}", spec)), 3) == before


def test_recovery(spark, tmp_path):
    spec = CubeSpec(("a", "b", "c"), (SUM,))
    for kind, manner, how in (("view", "incremental_reuse", "incremental"), ("input", "recompute_reuse", "recompute"), ("view", "incremental_reuse", "recompute")):
        root = f"file://{tmp_path}/{kind}-{how}"
        store = SlotStore(spark, root, spec)
        maintain.materialize_cached(frame(spark), spec, store, kind, slots=6)
        maintain.refresh(store, frame(spark, ROWS[:4]), manner, keep_delta=f"{root}/d1")
        want = cells(maintain.current(store), 3)
        m = store.manifest()
        slot = m["runs"][0]["files"][0][0]  # one file of one slot is enough to be seen
        store.drop_slot(m, slot)
        assert recovery.damaged(store) == [slot]
        published = maintain.view_states(frame(spark, ROWS + ROWS[:4]), spec)
        recovery.recover(store, [slot], how, published=published, base=frame(spark))
        assert recovery.damaged(store) == [] and cells(maintain.current(store), 3) == want
        # the rebuilt state takes deltas, and can be lost again
        maintain.refresh(store, frame(spark, ROWS[:2]), manner)
        assert cells(maintain.current(store), 3) == cells(M.materialize(frame(spark, ROWS + ROWS[:4] + ROWS[:2]), spec).df, 3)
    with pytest.raises(ValueError):  # the last delta wasn't kept
        recovery.recover(store, [0], "recompute", base=frame(spark))


def test_superseded_files_and_tables_go(spark, tmp_path):
    spec = CubeSpec(("a", "b"), (SUM,))
    store = SlotStore(spark, f"file://{tmp_path}", spec, SnapshotPolicy(1))
    before = {t.name for t in spark.catalog.listTables()}
    maintain.materialize_cached(frame(spark), spec, store, "view", slots=3)
    for i in range(5):
        maintain.refresh(store, frame(spark, ROWS[i : i + 2]), "incremental_reuse")
    # the last two versions: two runs at most, and the snapshots that they name
    assert len(list((tmp_path / "runs").iterdir())) <= 4 and len(store.versions()) == 2
    assert len({t.name for t in spark.catalog.listTables() if t.name.startswith("lc_state_")} - before) <= 3
    assert cells(maintain.current(store), 2) == cells(M.materialize(frame(spark, ROWS + [r for i in range(5) for r in ROWS[i : i + 2]]), spec).df, 2)


def test_a_refresh_is_one_scan_and_one_exchange(spark, tmp_path, monkeypatch):
    spec, plans = CubeSpec(("a", "b", "c"), (SUM,)), []
    store = SlotStore(spark, f"file://{tmp_path}", spec)
    write = store.write_run
    monkeypatch.setattr(store, "write_run", lambda rows, *a: plans.append((metrics.exchanges(rows), rows._jdf.queryExecution().executedPlan().toString())) or write(rows, *a))
    frame(spark).write.parquet(f"file://{tmp_path}/base")
    maintain.materialize_cached(spark.read.parquet(f"file://{tmp_path}/base"), spec, store, "view", slots=6)
    maintain.refresh(store, frame(spark, ROWS[:4]), "incremental_reuse")
    assert [n for n, _ in plans] == [1, 1] and plans[0][1].count("FileScan") == 1 and plans[1][1].count("FileScan") == 1 and "Bucketed: true" in plans[1][1]


def test_bucket_keys_are_where_spark_hashes_them(spark):
    for n in (1, 2, 7, 24, 333):
        rows = spark.createDataFrame([(k,) for k in S.bucket_keys(n)], "k int")
        assert [r[0] for r in rows.select(F.pmod(F.hash("k"), F.lit(n))).collect()] == list(range(n))


FAR = [("p", 1e9), ("p", 1e9 + 1), ("p", 1e9 + 2), ("q", None), ("q", -1e12), ("r", 5.0), ("r", 7.0)]
MOMENTS = (Agg("variance", "m", alias="v"), Agg("stddev", "m", alias="d"))


def test_moments_far_from_zero(spark, tmp_path):
    df = spark.createDataFrame(FAR, "a string, m double")
    want = {"p": (1.0, 1.0), "q": (None, None), "r": (2.0, 2.0**0.5)}
    spec = CubeSpec(("a",), MOMENTS)

    def right(found):
        got = {k[1]: v for k, v in cells(found, 1).items()}
        return got.keys() == want.keys() and all(got[k] == pytest.approx(want[k]) for k in want)

    for how in ({}, {"engine": "ordered"}, {"combine": "on"}, {"method": "native_cube"}, {"method": "fanout_unshared"}):
        assert right(M.materialize(df, spec, **how).df), how
    for kind, manner, when in (("view", "incremental_reuse", "on_write"), ("view", "incremental_reuse", "on_read"), ("input", "recompute_reuse", "on_write")):
        store = SlotStore(spark, f"file://{tmp_path}/{kind}{when}", spec, merge=when)
        maintain.materialize_cached(df.where("m is null or m not in (1e9, 5)"), spec, store, kind, slots=2)
        assert right(maintain.refresh(store, df.where("m in (1e9, 5)"), manner).cube.df)
    pairs = spark.createDataFrame([("p", 1e9 + x, 2.0 * x - 1e8) for x in (1.0, 2.0, 4.0)], "a string, m double, k double")
    got = M.materialize(pairs, CubeSpec(("a",), (Agg("corr", "k", "m", alias="c"), Agg("regr_slope", "k", "m", alias="s")))).df.first()
    assert (got.c, got.s) == (pytest.approx(1.0), pytest.approx(2.0))


def test_own_aggregate_without_a_merge(spark, tmp_path):
    own = UserAgg(lambda x: {"r": F.max(x) - F.min(x)}, None, lambda r: r)
    spec = CubeSpec(("a", "b"), (Agg("user", "m", alias="r", user=own), MEDIAN, SUM))
    spread = lambda v: max(v) - min(v) if v else None
    want = brute([dict(zip("abcm", r, strict=True)) for r in ROWS], ["a", "b"], [spread, middle, total])
    assert cells(M.materialize(frame(spark), spec).df, 2) == want
    store = SlotStore(spark, f"file://{tmp_path}", spec)
    with pytest.raises(ValueError):
        maintain.materialize_cached(frame(spark), spec, store, "view")
    maintain.materialize_cached(frame(spark, ROWS[:7]), spec, store, "input", slots=3)
    assert cells(maintain.refresh(store, frame(spark, ROWS[7:]), "recompute_reuse").cube.df, 2) == want


def test_ordered_engine_keeps_types_and_nan(spark):
    nan = float("nan")
    rows = [(i % 3, nan if i % 4 == 0 else None if i % 5 == 0 else float(i % 11), 9007199254740993 if i % 50 == 0 else i % 7) for i in range(400)]
    df = spark.createDataFrame(rows, "a int, m double, k long")
    aggs = tuple(Agg(f, c, alias=f"{f}_{c}") for f in ("sum", "min", "max", "median", "count") for c in "mk")
    old = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "17")  # cells go on over many batches
    try:
        got, want = (M.materialize(df, CubeSpec(("a", "m"), aggs), engine=e).df for e in ("ordered", "levels"))
        assert got.dtypes == want.dtypes
        text = lambda x: sorted(str(tuple(r)) for r in x.collect())
        assert text(got) == text(want)
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", old)
    with pytest.raises(ValueError):
        M.materialize(spark.createDataFrame([(1, Decimal("1.5"))], "a int, m decimal(9,2)"), CubeSpec(("a",), (SUM,)), engine="ordered")


def test_heavy_keys_are_dealt_out(spark):
    rows = spark.range(20_000).selectExpr("case when id % 3 = 0 then 0 else id % 997 end AS a", "id % 1009 AS b", "cast(id % 13 as double) AS m")
    spec = CubeSpec(("a", "b"), (SUM, MEDIAN))
    chains = plan_chains(spec.dims).chains
    widths = S.even_slots(len(chains), 16)
    plan = S.heavy_keys(rows, spec, chains, widths)
    assert [len(h) for h in plan.heavy] == [1, 0]
    spread = []
    for p in (S.SlotPlan(tuple(widths)), plan):
        cube = M.plan(spec, p)
        counts = [r["count"] for r in M.fan_out(spec.prepared(rows), cube).groupBy("__slot").count().collect()]
        spread.append(metrics.slot_balance([(0.0, n) for n in counts], widths)["max_over_mean_records"])
    assert spread[0] > 2 and spread[1] < 1.3
    want = cells(M.materialize(rows, spec, method="native_cube").df, 2)
    assert cells(M.materialize(rows, spec, slots=plan).df, 2) == want
    with pytest.raises(ValueError):
        M.materialize(rows, spec, slots=plan, engine="ordered")


def test_answers_read_one_folder_of_a_written_cube(spark, tmp_path):
    spec = CubeSpec(("a", "b", "c"), (SUM,), tuple(map(frozenset, ("ab", "bc", "abc"))))
    cube = M.materialize(frame(spark), spec).write(f"file://{tmp_path}/w")
    assert cube.cells == {i: M.materialize(frame(spark), spec).df.where(f"cuboid_id = {i}").count() for i in (0, 1, 4)}
    few = min((1, 4), key=cube.cells.__getitem__)
    assert spec.cuboid_id(answer.covering(cube, {"b"})) == few
    plan = answer.answer(cube, ["b"])._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(cuboid_id" in plan and f"= {few})]" in plan
    again = M.CubeResult.read(spark, f"file://{tmp_path}/w", spec)
    assert cells(again.df, 3) == cells(cube.df, 3)
    empty = M.materialize(frame(spark, []), spec).write(f"file://{tmp_path}/e")
    assert answer.answer(empty, ["b"]).count() == 0


def test_profiles_are_kept(spark, tmp_path, monkeypatch):
    spec, kept = CubeSpec(("a", "b"), (SUM,), name="job"), S.ProfileStore(spark, f"file://{tmp_path}")
    chains = plan_chains(spec.dims).chains
    first = S.profiled_slots(frame(spark), spec, chains, 4, lambda d: d, kept)
    monkeypatch.setattr(S, "profile_chains", None)  # not run again
    assert S.profiled_slots(frame(spark), spec, chains, 4, lambda d: d, kept) == first
    assert sum(S.profiled_slots(frame(spark), spec, chains, 9, lambda d: d, kept)) == 9
    assert kept.load("job", list(reversed(chains))) is None


def test_ancestors(spark):
    from latticecube.operators import ancestors

    f = frozenset
    assert ancestors.choose_ancestor(f("a"), {f("abc"): 9, f("ab"): 5, f("ac"): 4, f("bc"): 1}) == f("ac")
    assert ancestors.choose_ancestor(f("abc"), {f("ab"): 1}) is None
    spec = CubeSpec(("a", "b", "c"), (SUM, MEDIAN, COUNT))
    made = M.materialize(frame(spark), spec, feed="ancestor")
    assert cells(made.df, 3) == cells(M.materialize(frame(spark), spec).df, 3) and made.ancestors[0] is None


def test_experiments_run(spark):
    from latticecube import workloads as W

    rows = T.read_table(spark, SF, "lineitem")
    w1 = W.w1_materialization(rows.limit(500), {"sum": W.SUM_QTY}, [1, 2], repeats=1)
    assert {r["method"] for r in w1} == {"per_cuboid_jobs", "fanout_unshared", "native_cube", "shared_scan"} and len(w1) == 8
    shared, unshared = (next(r["shuffle"]["records"] for r in w1 if r["method"] == m and r["size"] == "2x") for m in ("shared_scan", "fanout_unshared"))
    assert unshared - shared == (15 - 6) * 1000
    assert set(W.w2_cache_overhead(rows, {"median": W.MEDIAN_QTY}, 1)["median"]) == {"plain_s", "cached_s", "overhead"}
    balance = W.w3_load_balance(rows, 8, 5)
    assert set(balance) == {"profiled", "even", "model", "range", "heavy"} and all(sum(b["widths"]) == 8 for b in balance.values())
    assert [(r["dims"], r["method"]) for r in W.w4_dimensions(rows.limit(300), 1)][::2] == [(3, "fanout_unshared"), (4, "fanout_unshared"), (5, "fanout_unshared")]
    refreshed = W.w5_w6_maintenance(rows, W.SUM_QTY, ["recompute_reuse", "incremental_reuse", "incremental_reload", "recompute_reload"], [5], 1)
    read = {r["manner"]: r["shuffle"]["records"] for r in refreshed}
    assert read["incremental_reuse"] == read["recompute_reuse"] < read["recompute_reload"] < read["incremental_reload"]
    assert all(r["cost"]["written_bytes"] > 0 for r in refreshed)


def test_paper_classes_refuse_incremental():
    assert CubeSpec(("a",), (Agg("stddev", "m"),)).mergeable()
    assert not CubeSpec(("a",), (Agg("stddev", "m", classification="paper"),)).mergeable()
    assert not CubeSpec(("a",), (MEDIAN,)).mergeable()
    sums, medians = CubeSpec(("a",), (SUM,)), CubeSpec(("a",), (MEDIAN,))
    choose = lambda spec, **k: maintain.choose_manner(spec, **({"base_bytes": 1000, "state_bytes": 4000, "view_bytes": 100, "delta_bytes": 10, "chains": 4} | k))
    assert choose(sums) == "incremental_reuse" and choose(sums, state_bytes=200, view_bytes=5000) == "recompute_reuse"
    assert choose(medians) == "recompute_reuse" and choose(medians, state_bytes=10**6) == "recompute_reload"
    # the delta counts: a large one makes dealing the rest as well no great matter; so do the weights
    costs = lambda delta: maintain.refresh_costs(sums, 1000, 4000, 100, delta, 4)
    gain = [costs(d)["recompute_reload"] / costs(d)["incremental_reuse"] for d in (10, 1000)]
    assert gain[0] > gain[1] > 1
    assert choose(sums, state_bytes=7000, view_bytes=6000, weights={"read": 1.0, "write": 0.0, "shuffle": 0.0}) == "recompute_reload"


def test_profile_and_metrics(spark):
    rows = T.read_table(spark, SF, "lineitem")
    spec = CubeSpec(("l_partkey", "l_orderkey", "l_suppkey"), (Agg("sum", "l_quantity"),))
    chains = plan_chains(spec.dims).chains
    for sampler in (lambda d: S.systematic_sample(d, 3), lambda d: S.hashed_sample(d, 3), lambda d: S.bernoulli_sample(d, 0.3), lambda d: S.window_sample(d, "l_shipdate", "1993-01-01", "1996-01-01")):
        profile = S.profile_chains(rows, spec, chains, sampler)
        assert len(profile) == 3 and all(p.records > 0 for p in profile)
    with metrics.watch(spark) as seen:
        metrics.drain(M.materialize(rows, spec, slots=6).df)
    assert seen.shuffle_cost()["records"] == 3 * rows.count() and seen.read_cost()["records"] == rows.count()
    balance = metrics.slot_balance(seen.slots(6), [2, 2, 2])
    assert 0 <= balance["near_median_records"] <= 1 and len(balance["chain_mean_s"]) == 3
    assert sum(n for _, n in seen.slots(6)) == 3 * rows.count()


def test_sql_front_and_answers(spark):
    frame(spark).createOrReplaceTempView("t")
    made = sqlfront.cube_sql(spark, "SELECT a, b, SUM(m) AS s, PERCENTILE(m, 0.5) AS p FROM t WHERE m >= 0 GROUP BY GROUPING SETS ((a, b), (a), ())")
    assert {r.cuboid_id for r in made.df.collect()} == {0, 1, 3}
    assert sqlfront.cube_sql(spark, "SELECT 1 AS x").collect()[0].x == 1
    cube = M.materialize(frame(spark), CubeSpec(("a", "b", "c"), (SUM,), (frozenset("ab"), frozenset("abc"))))
    assert {r.a: r.s for r in answer.answer(cube, ["a"]).collect()}["x"] == 9.0
    with pytest.raises(ValueError):
        answer.answer(M.materialize(frame(spark), CubeSpec(("a", "b"), (MEDIAN,), (frozenset("ab"),))), ["a"])
    assert cube.cuboid("a", "b").count() == len({(r[0], r[1]) for r in ROWS})


def test_written_by_cuboid(spark, tmp_path):
    cube = M.materialize(frame(spark), CubeSpec(("a", "b", "c"), (SUM,), name="w"))
    cube.write(f"file://{tmp_path}/w")
    assert {p.name for p in (tmp_path / "w").iterdir() if p.is_dir()} == {f"cuboid_id={i}" for i in range(7)}
    assert "w_a_b" in cube.views() and spark.table("w_a").count() == 4


def test_streams(spark, tmp_path):
    events = T.read_table(spark, SF, "events")
    src = str(tmp_path / "in")
    for i in range(3):
        events.where(f"event_id % 3 = {i}").coalesce(1).write.mode("append").parquet(src)
    spec = CubeSpec(("user_id", "event_type"), (Agg("count", alias="n"), Agg("max", "value", alias="hi")))
    store = SlotStore(spark, f"file://{tmp_path}/store", spec)
    for _ in range(2):  # the second run finds nothing new
        stream.stream_refresh(T.read_events_stream(spark, src), store, "incremental_reuse", str(tmp_path / "c1"), compact_every=2).awaitTermination()
    want = cells(M.materialize(events, spec).df, 2)
    assert cells(maintain.current(store), 2) == want
    timed = stream.with_watermark(stream.with_event_time(T.read_events_stream(spark, src)), "ts", "40 days", "event_id")
    stream.run_to_table(stream.native_stream_cube(timed, spec, stream.TimeDim("ts", "1 day")), "by_day", "append", str(tmp_path / "c2"))
    native = stream.native_stream_cube(T.read_events_stream(spark, src), spec)
    stream.run_to_table(native, "native", "complete", str(tmp_path / "c3"))
    assert cells(spark.table("native"), 2) == want
    with pytest.raises(ValueError):
        stream.native_stream_cube(events, spec, stream.SessionDim("ts", "1 hour", ("user_id",)))


@pytest.mark.parametrize("name", ["events_sessions", "events_windows", "events_late"])
def test_appended_windows_come_from_files(spark, name):
    from latticecube import workloads

    out = workloads.queries()[name](spark, SF)
    assert out.inputFiles() and "LocalTableScan" not in out._jdf.queryExecution().executedPlan().toString()
    assert spark.conf.get("spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage", None) in (None, "false")
    n_events = T.read_table(spark, SF, "events").count()
    counted = out.where("cuboid_id = 1") if name == "events_sessions" else out
    assert name == "events_late" or counted.agg(F.sum("n_events")).first()[0] == n_events * (2 if name == "events_windows" else 1)


def test_queries_have_sql(spark):
    from latticecube import workloads

    assert set(workloads.queries()) == set(workloads.oracle_sql())


@pytest.mark.parametrize("percents", [[5], [20], [50], [5, 5, 10], [20] * 5], ids=str)
def test_base_and_deltas_are_the_whole_table(spark, percents):
    rows = T.read_table(spark, SF, "lineitem").select("l_orderkey", "l_linenumber").unionByName(spark.createDataFrame([(None, 1), (-7, 3)], "l_orderkey long, l_linenumber int"))
    parts = T.whole_parts(rows, percents)
    numbered = parts[0].withColumn("part", F.lit(0))
    for i, p in enumerate(parts[1:], 1):
        numbered = numbered.unionByName(p.withColumn("part", F.lit(i)))
    sizes = {r.part: r.n for r in numbered.groupBy("part").agg(F.count("*").alias("n")).collect()}
    assert sum(sizes.values()) == rows.count() and numbered.drop("part").exceptAll(rows).isEmpty()
    assert all(abs(sizes[i] / sizes[0] - p / 100) < 0.05 for i, p in enumerate(percents, 1))


@pytest.mark.parametrize("name", ["refresh_sum_incr_on_read", "refresh_sum_incr_reload", "recover_incremental", "cube_diff"])
def test_maintenance_covers_the_whole_table(spark, name):
    from latticecube import workloads

    spec = CubeSpec(workloads.POSD[:3], (workloads.SUM_QTY,)) if name == "recover_incremental" else workloads.spec4(workloads.SUM_QTY) if "reload" in name else workloads.flag_spec(workloads.SUM_QTY)
    n = len(spec.dims)
    want = cells(M.materialize(T.read_table(spark, SF, "lineitem"), spec).df, n)
    got = workloads.queries()[name](spark, SF)
    if name == "cube_diff":
        got = {k: v[:-1] for k, v in cells(got.where("side = 'b'"), n).items()}
        assert got and all(want[k] == v for k, v in got.items())
    else:
        assert cells(got, n) == want


def test_a_replayed_first_batch_counts_once(spark, tmp_path, monkeypatch):
    src, spec = str(tmp_path / "in"), CubeSpec(("a",), (SUM,))
    frame(spark, ROWS[:3]).coalesce(1).write.parquet(src)
    store = SlotStore(spark, f"file://{tmp_path}/s", spec)
    source = lambda: spark.readStream.schema("a string, b int, c date, m double").parquet(src)
    commit = store.commit

    def killed(old, **changes):
        commit(old, **changes)
        raise OSError("killed after the commit")

    monkeypatch.setattr(store, "commit", killed)
    with pytest.raises(Exception, match="killed"):
        stream.stream_refresh(source(), store, "incremental_reuse", str(tmp_path / "c")).awaitTermination()
    monkeypatch.setattr(store, "commit", commit)
    stream.stream_refresh(source(), store, "incremental_reuse", str(tmp_path / "c")).awaitTermination()
    assert cells(maintain.current(store), 1) == {(0, "x"): (6.0,)} and store.manifest()["batches"] == ["0"]


def test_own_state_gives_the_median(spark, tmp_path):
    from latticecube.streaming import statecube

    assert statecube.weighted_median([]) is None
    assert statecube.weighted_median([(3.0, 1), (1.0, 2)]) == 1.0 and statecube.weighted_median([(4.0, 2), (1.0, 2)]) == 2.5
    src, spec = str(tmp_path / "in"), CubeSpec(("b",), (MEDIAN,))
    for rows in (ROWS[:5], ROWS[5:30]):
        frame(spark, rows).coalesce(1).write.mode("append").parquet(src)
    session = spark.newSession()
    session.conf.set("spark.sql.streaming.stateStore.providerClass", statecube.PROVIDER)
    session.conf.set("spark.sql.shuffle.partitions", "2")
    source = session.readStream.schema("a string, b int, c date, m double").option("maxFilesPerTrigger", 1).parquet(src)
    got = {}
    q = statecube.state_cube(source, spec, "m").writeStream.foreachBatch(lambda df, _: got.update({r.cell: (r.median, r.n) for r in df.collect()}))
    q.outputMode("update").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination()
    want = brute([{"b": r[1], "m": r[3]} for r in ROWS[:30]], ["b"], [middle, len])
    assert sorted(got.values(), key=str) == sorted(want.values(), key=str)


def test_as_of_over_buckets(spark):
    """A hot key's times in many buckets, keys without an earlier version, null values, keys and times, against a scan of all versions."""
    rng, start = random.Random(8), datetime(2024, 2, 27)
    at = lambda: start + timedelta(hours=rng.randrange(120))
    made = {(rng.choice(["hot", "hot", "hot", "a", None]), at()): rng.choice([None, 1.0, 2.0, 3.0]) for _ in range(150)}
    versions = spark.createDataFrame([(k, t, x) for (k, t), x in made.items()], "k string, ts timestamp_ntz, v double")
    asked = [(i, rng.choice(["hot", "a", None, "unseen"]), at()) for i in range(100)] + [(100, "hot", None)]
    probes = spark.createDataFrame(asked, "id int, k string, ts timestamp_ntz")
    for strictly in (False, True):
        got = {r.id: r.v for r in answer.cube_as_of(versions, probes, "ts", ["k"], "v", strictly).collect()}
        for i, k, t in asked:
            known = [(u, x) for (key, u), x in made.items() if key == k and x is not None and t is not None and (u < t or (u == t and not strictly))]
            assert got[i] == (max(known)[1] if known else None)
    numbers = answer.cube_as_of(spark.sql("SELECT 'a' AS k, id AS ts, id * 10 AS v FROM range(50)"), spark.sql("SELECT 'a' AS k, id + 40 AS ts FROM range(20)"), "ts", ["k"], "v", bucket=F.floor(F.col("ts") / 7))
    assert {r.ts: r.v for r in numbers.collect()} == {t: min(t, 49) * 10 for t in range(40, 60)}


def test_far_values_against_exact_arithmetic(spark):
    """Double arithmetic near 1e9 errs by about 1e-5 of a small correlation: sums of whole quantities and cents don't."""
    from fractions import Fraction

    from latticecube import workloads

    sums = defaultdict(lambda: [0] * 6)
    rows = T.read_table(spark, SF, "lineitem").select("l_returnflag", "l_linestatus", F.year("l_shipdate"), "l_quantity", F.round(F.col("l_extendedprice") * 100).cast("long")).collect()
    for *dims, q, cents in rows:
        x = Fraction(q)
        for m in range(7):
            key = (m, *[None if m >> (2 - i) & 1 else d for i, d in enumerate(dims)])
            for i, v in enumerate((1, x, x * x, cents, cents * cents, x * cents)):
                sums[key][i] += v
    got = {tuple(r)[:4]: tuple(r)[4:] for r in workloads.queries()["agg_far"](spark, SF).collect()}
    assert set(got) == set(sums)
    for key, (n, x, xx, y, yy, xy) in sums.items():
        vx, vy, c = xx - Fraction(x * x, n), yy - Fraction(y * y, n), xy - Fraction(x * y, n)
        var = vx / (n - 1)
        want = (float(var) ** 0.5, float(var), float(c) / float(vx * vy) ** 0.5, float(c / vx / 100))
        assert all(abs(a - b) <= 0.0005 + 1e-6 for a, b in zip(got[key], want, strict=True)), key


def test_recovered_slots_grow_with_the_partitions(spark, monkeypatch):
    from latticecube import workloads

    made, given = maintain.materialize_cached, spark.conf.get("spark.sql.shuffle.partitions")
    used = []
    monkeypatch.setattr(maintain, "materialize_cached", lambda *a, **b: (r := made(*a, **b), used.append(r.plan.slots.total))[0])
    spark.conf.set("spark.sql.shuffle.partitions", "15")
    try:
        got = cells(workloads.queries()["recover_incremental"](spark, SF), 3)
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", given)
    assert used == [15] and got == cells(M.materialize(T.read_table(spark, SF, "lineitem"), CubeSpec(workloads.POSD[:3], (workloads.SUM_QTY,))).df, 3)


def test_native_cells_come_from_files_and_their_last_batch(spark, tmp_path):
    from latticecube import workloads

    out = workloads.queries()["events_native_stream"](spark, SF)
    assert out.inputFiles() and "__batch" in out._jdf.queryExecution().executedPlan().toString()
    assert out.where("cuboid_id = 6").agg(F.sum("n_events")).first()[0] == T.read_table(spark, SF, "events").count()
    assert out.select("cuboid_id", "user_id", "event_type", "day").distinct().count() == out.count()
    spec, src = CubeSpec(("a", "b"), (Agg("count", alias="n"), Agg("median", "m", alias="mid"))), str(tmp_path / "in")
    for part in (ROWS[:3], ROWS[3:]):
        frame(spark, part).coalesce(1).write.mode("append").parquet(src)
    source = spark.readStream.schema("a string, b int, c date, m double").option("maxFilesPerTrigger", 1).parquet(src)
    got = stream.run_to_latest(stream.native_stream_cube(source, spec), ["cuboid_id", "a", "b"], str(tmp_path / "out"), str(tmp_path / "check"))
    assert cells(got, 2) == cells(M.materialize(frame(spark), spec).df, 2)


def test_lattice_counts_the_cells_of_a_table(spark):
    from latticecube import workloads

    out = workloads.queries()["lattice_table"](spark, SF)
    rows = T.read_table(spark, SF, "lineitem").withColumn("ship_year", F.year("l_shipdate"))
    assert out.inputFiles() and out.count() == 15
    assert all(r.n_cells == rows.select(*r.members.split(",")).distinct().count() for r in out.collect())


def test_chains_count_the_keys_of_a_table(spark):
    from latticecube import workloads

    out = workloads.queries()["chain_plan_table"](spark, SF)
    rows = T.read_table(spark, SF, "lineitem").withColumn("ship_year", F.year("l_shipdate"))
    size = lambda dims: rows.select(*dims.split(",")).distinct().count()
    assert out.inputFiles() and out.count() == 6
    assert all((r.n_keys, r.n_cells) == (size(r.part_dims), size(r.sort_dims)) for r in out.collect())


def test_batch_tags_name_the_cuboids_that_a_table_feeds(spark):
    from latticecube import workloads

    out = workloads.queries()["cuboids_of"](spark, SF)
    n, total = T.read_table(spark, SF, "lineitem").agg(F.count("*"), F.sum("l_quantity")).first()
    got = out.collect()
    assert out.inputFiles() and sorted(r.number for r in got) == list(range(1, 16)) and len({r.members for r in got}) == 15
    assert all((r.copies, r.total) == (n, total) for r in got)
