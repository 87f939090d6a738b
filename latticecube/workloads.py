"""Registered queries with their SQL, and the experiments of the evaluation."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from latticecube import files, metrics, sqlfront
from latticecube.functions.aggregates import Agg, UserAgg
from latticecube.functions.tables import chain_table, fed_cuboids, lattice_table
from latticecube.operators import answer, maintain, recovery
from latticecube.operators import materialize as M
from latticecube.operators.baselines import cuboid_jobs
from latticecube.operators.store import SlotStore, SnapshotPolicy
from latticecube.plans import slots as S
from latticecube.plans.chains import plan_chains
from latticecube.sources import tables as T
from latticecube.spec import CubeSpec
from latticecube.streaming import statecube, stream

POSD = ("l_partkey", "l_orderkey", "l_suppkey", "l_shipdate")
FLAGS = ("l_returnflag", "l_linestatus", "ship_year")
SUM_QTY, MEDIAN_QTY = Agg("sum", "l_quantity", alias="sum_qty"), Agg("median", "l_quantity", alias="median_qty")


def spec4(*aggs: Agg, **more) -> CubeSpec:
    return CubeSpec(POSD, aggs, **more)


def flag_spec(*aggs: Agg, **more) -> CubeSpec:
    return CubeSpec(FLAGS, aggs, derived={"ship_year": "year(l_shipdate)"}, **more)


#: Four dimensions of few values, for the tables of the lattice and its chains.
LINES = (*FLAGS, "l_linenumber")


def line_spec(*aggs: Agg) -> CubeSpec:
    return CubeSpec(LINES, aggs, derived={"ship_year": "year(l_shipdate)"})


def lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.read_table(spark, sf_dir, "lineitem")


def rounded(df: DataFrame, *names: str) -> DataFrame:
    """Six digits, without a negative zero."""
    return df.withColumns({n: F.round(F.col(n), 6) + F.lit(0.0) for n in names})


def _cube(spec: CubeSpec, **how) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf: M.materialize(lineitem(spark, sf), spec, **how).df


def _new_store(spark: SparkSession, spec: CubeSpec, **more) -> SlotStore:
    return SlotStore(spark, files.scratch_dir(spark), spec, **more)


def _refreshed(spec: CubeSpec, manner: str, percents: list[int], **more) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark: SparkSession, sf: str) -> DataFrame:
        base, *deltas = T.whole_parts(lineitem(spark, sf), percents)
        store = _new_store(spark, spec, **more)
        maintain.materialize_cached(base, spec, store, maintain.KIND[manner])
        return maintain.refresh_many(store, deltas, manner, compact_every=2).cube.df

    return query


def _reloaded(spec: CubeSpec, percent: int) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark: SparkSession, sf: str) -> DataFrame:
        (base, delta), root = T.whole_parts(lineitem(spark, sf), [percent]), files.scratch_dir(spark)
        maintain.view_states(base, spec).write.parquet(f"{root}/view")
        return maintain.incremental_reload(f"{root}/view", delta, spec, f"{root}/delta").df

    return query


def _recompute_reload(spec: CubeSpec, percent: int) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark: SparkSession, sf: str) -> DataFrame:
        base, delta = T.whole_parts(lineitem(spark, sf), [percent])
        return maintain.refresh(_new_store(spark, spec), delta, "recompute_reload", base=base).cube.df

    return query


def _recovered(spec: CubeSpec, manner: str) -> Callable[[SparkSession, str], DataFrame]:
    """Lose one slot of the first chain and all of the last chain after a refresh, rebuild them, and read the cube from the state.

    The incremental manner reads the views that the refresh published before the loss.
    """

    def query(spark: SparkSession, sf: str) -> DataFrame:
        base, delta = T.whole_parts(lineitem(spark, sf), [20])
        kind = "view" if manner == "incremental" else "input"
        store = _new_store(spark, spec)
        # more slots where the session has more partitions: a slot's cells are aggregated by one task
        slots = max(12, M.default_slots(base, len(plan_chains(spec.dims).chains)))
        maintain.materialize_cached(base, spec, store, kind, slots=slots)
        if manner == "recompute":
            maintain.snapshot(store)
        root = store.root
        maintain.refresh(store, delta, "incremental_reuse" if kind == "view" else "recompute_reuse", keep_delta=f"{root}/deltas/1")
        m = store.manifest()
        if kind == "view":
            store.state(m).drop("__slot").write.parquet(f"{root}/published")
        cube = store.plan(m)
        for slot in [1, *recovery.slots_of(cube, [len(cube.chains) - 1])]:
            store.drop_slot(m, slot)
        m = recovery.recover(store, recovery.damaged(store), manner, published=spark.read.parquet(f"{root}/published") if kind == "view" else None)
        return maintain.current(store, m)

    return query


def _events_spec(*aggs: Agg) -> CubeSpec:
    return CubeSpec(("user_id", "event_type", "day"), aggs, derived={"day": "cast(ts as date)"})


def _events_cube(spark: SparkSession, sf: str) -> DataFrame:
    """The average is rounded a little above, as its last digits depend on the order of the sum."""
    cells = M.materialize(T.read_table(spark, sf, "events"), _events_spec(Agg("count", alias="n_events"), Agg("median", "value", alias="median_value"), Agg("avg", "value", alias="avg_value"))).df
    return rounded(cells, "median_value").withColumn("avg_value", F.round(F.col("avg_value") + 1e-9, 6) + F.lit(0.0))


def _profiled(spark: SparkSession, sf: str) -> DataFrame:
    """Slots by a stored profile: a first allocation runs it, another number of slots uses it again."""
    rows, spec = lineitem(spark, sf), spec4(SUM_QTY)
    chains, kept = plan_chains(spec.dims).chains, S.ProfileStore(spark, files.scratch_dir(spark))
    sampler = lambda df: S.systematic_sample(df, 20)
    S.profiled_slots(rows, spec, chains, 12, sampler, kept)
    return M.materialize(rows, spec, slots=S.profiled_slots(rows, spec, chains, 24, sampler, kept)).df


#: A third of the line items as one part, for skew.
SKEWED = {"part": "CASE WHEN l_orderkey % 3 = 0 THEN 0 ELSE l_partkey END"}


def skewed_spec(*aggs: Agg) -> CubeSpec:
    return CubeSpec(("part", "l_orderkey", "l_suppkey"), aggs, derived=SKEWED)


def _heavy(*aggs: Agg) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark: SparkSession, sf: str) -> DataFrame:
        rows, spec = lineitem(spark, sf), skewed_spec(*aggs)
        chains = plan_chains(spec.dims).chains
        return M.materialize(rows, spec, slots=S.heavy_keys(rows, spec, chains, S.even_slots(len(chains), 24))).df

    return query


def _heavy_refreshed(spark: SparkSession, sf: str) -> DataFrame:
    """A store that deals out the base's heavy keys, refreshed."""
    spec = skewed_spec(SUM_QTY)
    base, delta = T.whole_parts(lineitem(spark, sf), [20])
    chains, store = plan_chains(spec.dims).chains, _new_store(spark, spec)
    maintain.materialize_cached(base, spec, store, "view", slots=S.heavy_keys(base, spec, chains, S.even_slots(len(chains), 24)))
    return maintain.refresh(store, delta, "incremental_reuse").cube.df


def _modelled(spark: SparkSession, sf: str) -> DataFrame:
    rows, spec = lineitem(spark, sf), spec4(SUM_QTY)
    return M.materialize(rows, spec, slots=S.model_slots(rows, spec, plan_chains(spec.dims).chains, 24)).df


def _ranged(spark: SparkSession, sf: str) -> DataFrame:
    rows, spec = lineitem(spark, sf), spec4(SUM_QTY)
    chains = plan_chains(spec.dims).chains
    return M.materialize(rows, spec, slots=S.range_bounds(rows, spec, chains, S.even_slots(len(chains), 24))).df


def _balance(spark: SparkSession, sf: str) -> DataFrame:
    """The slots of each chain by number of copies dealt to it: all of a chain's slots together hold every row once."""
    rows, spec = lineitem(spark, sf), spec4(SUM_QTY)
    cube = M.plan(spec, 24)
    return M.fan_out(spec.prepared(rows), cube).groupBy(F.col("__batch").cast("int").alias("chain")).agg(F.count("*").alias("copies"), F.sum("m_l_quantity").alias("quantity"))


def _stream_cube(spark: SparkSession, sf: str) -> DataFrame:
    """Six days of the events at a time through the micro-batch refresh of a store."""
    root, spec = files.scratch_dir(spark), _events_spec(Agg("sum", "n", alias="sum_n"), Agg("count", alias="n_events"), Agg("min", "value", alias="min_value"), Agg("max", "value", alias="max_value"))
    events = T.read_table(spark, sf, "events")
    events.withColumn("part", F.floor((F.dayofmonth("ts") - 1) / 6)).write.partitionBy("part").parquet(f"{root}/in")
    schema = events.schema
    source = spark.readStream.schema(schema).option("maxFilesPerTrigger", 2).option("recursiveFileLookup", True).parquet(f"{root}/in").withColumn("n", F.col("event_id") % 10)
    store = SlotStore(spark, f"{root}/store", spec)
    stream.stream_refresh(source, store, "incremental_reuse", f"{root}/check").awaitTermination()
    return maintain.current(store)


def _native_stream(spark: SparkSession, sf: str) -> DataFrame:
    root, spec = files.scratch_dir(spark), _events_spec(Agg("median", "value", alias="median_value"), Agg("count", alias="n_events"))
    # three batches, of several files each, so that a batch is read by several tasks
    T.read_table(spark, sf, "events").repartition(18).write.parquet(f"{root}/in")
    cells = stream.native_stream_cube(stream.with_event_time(T.read_events_stream(spark, f"{root}/in", 6)), spec)
    return stream.run_to_latest(cells, ["cuboid_id", *spec.dims], f"{root}/out", f"{root}/check")


#: A last event long after all others: it moves the watermark past every window, so that append mode emits them all.
FLUSH = "SELECT -1L AS event_id, TIMESTAMP_NTZ '2999-01-01 00:00:00' AS ts, -1L AS user_id, 'flush' AS event_type, CAST(NULL AS DOUBLE) AS value, CAST(NULL AS STRING) AS props"


def _streamed(spark: SparkSession, parts: list[DataFrame]) -> tuple[DataFrame, str]:
    """Parts as the files of a stream, one micro-batch each in this order, and a last one that closes all windows."""
    root = files.scratch_dir(spark)
    flush = spark.sql(FLUSH)
    for part in [*parts, flush]:
        # one file a batch: its time of writing is its place in the stream
        part.select(flush.columns).coalesce(1).write.mode("append").parquet(f"{root}/in")
    return T.read_events_stream(spark, f"{root}/in"), root


def _emitted(cells: DataFrame, root: str) -> DataFrame:
    """What a stream appends, all of it, from files."""
    return stream.run_to_files(cells, f"{root}/out", f"{root}/check")


def _windows(spark: SparkSession, sf: str) -> DataFrame:
    """Sliding windows over a stream with a watermark, in which every event is delivered twice and counts once."""
    events = T.read_table(spark, sf, "events")
    source, root = _streamed(spark, [events, events])
    timed = stream.with_watermark(stream.with_event_time(source), "ts", "400 days", "event_id")
    spec = CubeSpec(("event_type",), (Agg("count", alias="n_events"), Agg("max", "value", alias="max_value")))
    cells = _emitted(stream.native_stream_cube(timed, spec, stream.TimeDim("ts", "2 days", "1 day")), root)
    return cells.select("event_type", F.col("window.start").cast("timestamp_ntz").alias("start"), "n_events", "max_value")


def _sessions(spark: SparkSession, sf: str) -> DataFrame:
    """Each user's sessions, with gaps of six hours at most, by event type and over all types."""
    source, root = _streamed(spark, [T.read_table(spark, sf, "events")])
    timed = stream.with_watermark(stream.with_event_time(source), "ts", "1 day")
    spec = CubeSpec(("user_id", "event_type"), (Agg("count", alias="n_events"),), tuple(map(frozenset, (("user_id",), ("user_id", "event_type")))))
    cells = _emitted(stream.native_stream_cube(timed, spec, stream.SessionDim("ts", "6 hours", ("user_id",))), root)
    return cells.select("cuboid_id", "user_id", "event_type", F.col("session.start").cast("timestamp_ntz").alias("start"), "n_events")


def _late(spark: SparkSession, sf: str) -> DataFrame:
    """Daily counts of events that come in three batches over the same days: the last one's are late where the watermark that the first one set has
    passed their day.  (A batch is judged by the watermark that the batch before it ran with.)"""
    events = T.read_table(spark, sf, "events")
    source, root = _streamed(spark, [events.where(f"event_id % 3 = {i}") for i in range(3)])
    timed = stream.with_watermark(stream.with_event_time(source), "ts", "5 days")
    cells = _emitted(stream.native_stream_cube(timed, CubeSpec(("event_type",), (Agg("count", alias="n_events"),)), stream.TimeDim("ts", "1 day")), root)
    return cells.select("event_type", F.col("window.start").cast("timestamp_ntz").alias("start"), "n_events")


def _state_median(spark: SparkSession, sf: str) -> DataFrame:
    """MEDIAN from own state: each batch appends the cells that it changed, and a cell's last batch counts."""
    session = spark.newSession()
    session.conf.set("spark.sql.streaming.stateStore.providerClass", statecube.PROVIDER)
    root, spec = files.scratch_dir(spark), CubeSpec(("event_type",), (Agg("median", "value", alias="median_value"),))
    T.read_table(session, sf, "events").repartition(2).write.parquet(f"{root}/in")
    changed = statecube.state_cube(T.read_events_stream(session, f"{root}/in"), spec, "value")
    write = lambda df, batch: df.withColumn("batch", F.lit(batch)).write.mode("overwrite").parquet(f"{root}/out/{batch}")
    changed.writeStream.foreachBatch(write).outputMode("update").option("checkpointLocation", f"{root}/check").trigger(availableNow=True).start().awaitTermination()
    out = spark.read.option("recursiveFileLookup", True).parquet(f"{root}/out")
    last = out.groupBy("cell").agg(F.max_by(F.struct("median", "n"), "batch").alias("x"))
    return last.select(F.get_json_object("cell", "$.event_type").alias("event_type"), F.round("x.median", 6).alias("median_value"), F.col("x.n").alias("n"))


def _user(spark: SparkSession, sf: str) -> DataFrame:
    """An own aggregate that merges: the sum of squares."""
    own = UserAgg(lambda x: {"q": F.sum(x * x)}, lambda s: F.sum(s), lambda q: q)
    return M.materialize(lineitem(spark, sf), flag_spec(Agg("user", "l_quantity", alias="squares", user=own))).df


def _user_raw(spark: SparkSession, sf: str) -> DataFrame:
    """An own aggregate without a merge, next to others: the number of distinct quantities below the largest."""
    own = UserAgg(lambda x: {"d": F.count_distinct(x)}, None, lambda d: d - 1)
    return M.materialize(lineitem(spark, sf), flag_spec(Agg("user", "l_quantity", alias="below", user=own), SUM_QTY, MEDIAN_QTY)).df


def _approx(spark: SparkSession, sf: str) -> DataFrame:
    """Exact values where the sketches are near them, within ten percent of distinct parts and two ranks in a hundred, else the estimates."""
    cells = M.materialize(lineitem(spark, sf), flag_spec(Agg("approx_distinct", "l_partkey", alias="a"), Agg("approx_median", "l_quantity", alias="m"))).df
    held = (Agg("count_distinct", "l_partkey", alias="ed"), Agg("percentile", "l_quantity", p=0.48, alias="lo"), Agg("percentile", "l_quantity", p=0.52, alias="hi"), Agg("median", "l_quantity", alias="em"))
    exact = M.materialize(lineitem(spark, sf), flag_spec(*held[:1])).df
    ranks = M.materialize(lineitem(spark, sf), flag_spec(*held[1:])).df
    same = lambda x, y: [x[c].eqNullSafe(y[c]) for c in ("cuboid_id", *FLAGS)]
    both = cells.join(exact, same(cells, exact)).join(ranks, same(cells, ranks))
    distinct = F.when(F.abs(F.col("a") - F.col("ed")) <= 0.1 * F.col("ed"), F.col("ed")).otherwise(F.col("a"))
    middle = F.when((F.col("m") >= F.col("lo") - 1) & (F.col("m") <= F.col("hi") + 1), F.col("em")).otherwise(F.col("m"))
    return both.select(cells["cuboid_id"], *[cells[d] for d in FLAGS], distinct.alias("distinct_parts"), middle.alias("median_qty"))


#: A measure far from zero, whose squares would lose every digit of its spread.
FAR = "l_quantity + 1e9"
FAR_AGGS = (Agg("stddev", "far", alias="stddev_far"), Agg("variance", "far", alias="var_far"), Agg("corr", "far", "l_extendedprice", alias="corr_far"), Agg("regr_slope", "l_extendedprice", "far", alias="slope_far"))


def far_spec(*aggs: Agg) -> CubeSpec:
    return CubeSpec(FLAGS, aggs, derived={"ship_year": "year(l_shipdate)", "far": FAR})


def _far(refreshed: bool) -> Callable[[SparkSession, str], DataFrame]:
    make = _refreshed(far_spec(*FAR_AGGS), "incremental_reuse", [20, 20]) if refreshed else _cube(far_spec(*FAR_AGGS))
    return lambda spark, sf: make(spark, sf).select("cuboid_id", *FLAGS, *[(F.round(a.name, 3) + F.lit(0.0)).alias(a.name) for a in FAR_AGGS])


def _sql(spark: SparkSession, sf: str) -> DataFrame:
    lineitem(spark, sf).createOrReplaceTempView("lc_lineitem")
    made = sqlfront.cube_sql(spark, "SELECT l_returnflag, l_linestatus, SUM(l_quantity) AS sum_qty, COUNT(*) AS n FROM lc_lineitem WHERE l_discount < 0.05 GROUP BY CUBE(l_returnflag, l_linestatus)")
    return made.df


def _touched(which) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark: SparkSession, sf: str) -> DataFrame:
        (base, delta), spec = T.whole_parts(lineitem(spark, sf), [20]), CubeSpec(POSD[:3], (SUM_QTY,))
        return which(M.materialize(base, spec), delta).select("cuboid_id", *spec.dims)

    return query


def _diff(spark: SparkSession, sf: str) -> DataFrame:
    """Cells that a delta of five percent changes or makes, old and new."""
    (base, delta), spec = T.whole_parts(lineitem(spark, sf), [5]), flag_spec(SUM_QTY)
    return answer.cube_diff(M.materialize(base, spec), M.materialize(base.unionByName(delta), spec))


def _outer_merged(spark: SparkSession, sf: str) -> DataFrame:
    """Published cubes of base and delta, merged by a full outer join."""
    (base, delta), spec = T.whole_parts(lineitem(spark, sf), [20]), CubeSpec(POSD[:3], (SUM_QTY, Agg("count", alias="n"), Agg("min", "l_quantity", alias="min_qty"), Agg("max", "l_quantity", alias="max_qty")))
    root = files.scratch_dir(spark)
    return maintain.merge_views(M.materialize(base, spec).write(f"{root}/old"), M.materialize(delta, spec).write(f"{root}/new"))


def _moments() -> Callable[[SparkSession, str], DataFrame]:
    spec = flag_spec(Agg("avg", "l_quantity", alias="avg_qty"), Agg("stddev", "l_quantity", alias="stddev_qty"))
    return lambda spark, sf: rounded(_refreshed(spec, "incremental_reuse", [50])(spark, sf), "avg_qty", "stddev_qty")


def _delta_view(spark: SparkSession, sf: str) -> DataFrame:
    """The cube of a delta of twenty percent, as incremental maintenance makes it; the base is the rest of the table."""
    return M.materialize(T.whole_parts(lineitem(spark, sf), [20])[1], spec4(SUM_QTY)).df


def _stored(spec: CubeSpec, use) -> Callable[[SparkSession, str], DataFrame]:
    """An answer from a written cube: only the folder of its cuboid is read."""
    return lambda spark, sf: use(M.materialize(lineitem(spark, sf), spec).write(files.scratch_dir(spark)))


def _on(spec: CubeSpec, use) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf: use(M.materialize(lineitem(spark, sf), spec))


def _star(spark: SparkSession, sf: str) -> DataFrame:
    spec = CubeSpec(("r_name", "c_mktsegment", "ship_year", "l_returnflag"), (Agg("sum", "revenue", alias="revenue"), Agg("avg", "l_discount", alias="avg_discount"), MEDIAN_QTY), derived={"ship_year": "year(l_shipdate)", "revenue": "l_extendedprice * (1 - l_discount)"})
    out = M.materialize(T.star_fact(spark, sf), spec, feed="finest").df
    return out.withColumn("revenue", F.round("revenue", 1)).withColumn("avg_discount", F.round(F.col("avg_discount") + 1e-9, 5))


def _corpus(spark: SparkSession, sf: str) -> DataFrame:
    docs = T.read_table(spark, sf, "documents").select("doc_id", "lang", "source", "n_chars").join(T.read_table(spark, sf, "labels"), "doc_id", "left")
    spec = CubeSpec(("lang", "source", "quality"), (Agg("count", alias="n_docs"), Agg("sum", "n_chars", alias="sum_chars"), Agg("median", "n_chars", alias="median_chars")), include_all=True)
    return M.materialize(docs, spec).df


def _as_of(spark: SparkSession, sf: str) -> DataFrame:
    """For each event the last value of its user strictly before it."""
    events = T.read_table(spark, sf, "events").select("event_id", "ts", "user_id", "value")
    versions = events.groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    return answer.cube_as_of(versions, events.select("event_id", "ts", "user_id"), "ts", ["user_id"], "value", strictly=True).select("event_id", "user_id", "value")


def _active(spark: SparkSession, sf: str) -> DataFrame:
    """Line items shipped within sixty days from their order's date."""
    orders = T.read_table(spark, sf, "orders").select("o_orderkey", F.col("o_orderdate").alias("lo"), (F.col("o_orderdate") + F.expr("INTERVAL 60 DAYS")).alias("hi"))
    items = lineitem(spark, sf).select("l_orderkey", "l_linenumber", "l_shipdate")
    found = answer.active_in(items, orders, "l_shipdate", "lo", "hi").where("l_orderkey = o_orderkey")
    return found.groupBy("l_orderkey").agg(F.count("*").alias("n"))


BANDS = [("low", 0.0, 1000.0), ("middle", 1000.0, 1500.0), ("high", 1500.0, 1e9)]


def _bands(spark: SparkSession, sf: str) -> DataFrame:
    parts = answer.band(T.read_table(spark, sf, "part"), BANDS, "p_retailprice")
    return M.materialize(parts, CubeSpec(("band", "p_brand"), (Agg("count", alias="n"), Agg("max", "p_size", alias="max_size")))).df


ALL_AGGS = (
    Agg("count", alias="n"), Agg("min", "l_quantity", alias="min_qty"), Agg("max", "l_quantity", alias="max_qty"), Agg("avg", "l_quantity", alias="avg_qty"), SUM_QTY,
)
HELD_AGGS = (MEDIAN_QTY, Agg("percentile", "l_quantity", p=0.9, alias="p90_qty"), Agg("mode", "l_quantity", alias="mode_qty"), Agg("count_distinct", "l_quantity", alias="distinct_qty"))
PAIR_AGGS = tuple(Agg(fn, "l_quantity", "l_extendedprice", alias=fn) for fn in ("corr", "regr_slope", "regr_intercept", "regr_r2"))
PARTIAL = tuple(map(frozenset, (("l_partkey", "l_suppkey"), ("l_orderkey",), ("l_shipdate", "l_suppkey"), ("l_suppkey",))))
AGE = {"l_shipdate"}


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    five = CubeSpec((*POSD, "receiptdate"), (SUM_QTY,))
    three = CubeSpec(POSD[:3], (SUM_QTY,))
    flags = flag_spec(SUM_QTY, Agg("count", alias="n"))
    return {
        "cube_sum_posd": _cube(spec4(SUM_QTY)),
        "cube_median_posd": _cube(spec4(MEDIAN_QTY)),
        "cube_sum_3d": _cube(three),
        "cube_sum_5d": lambda spark, sf: M.materialize(T.with_receipt_date(lineitem(spark, sf)), five).df,
        "cube_multi_agg": _cube(spec4(SUM_QTY, MEDIAN_QTY, Agg("count", alias="n"), Agg("max", "l_linenumber", alias="max_line"))),
        "cube_partial": _cube(spec4(SUM_QTY, cuboids=PARTIAL), strategy="exact"),
        "cube_all_cell": _cube(CubeSpec(POSD[:3], (SUM_QTY, MEDIAN_QTY), include_all=True)),
        "cube_ordered_engine": _cube(spec4(SUM_QTY, MEDIAN_QTY), engine="ordered"),
        "cube_symmetric": _cube(spec4(SUM_QTY), strategy="symmetric"),
        "cube_greedy": _cube(spec4(SUM_QTY), strategy="greedy"),
        "cube_waves": _cube(spec4(SUM_QTY), waves=3),
        "cube_combine": _cube(flags, combine="on"),
        "cube_combine_auto": _cube(flags, combine="auto"),
        "cube_finest_feed": _cube(flag_spec(SUM_QTY, MEDIAN_QTY), feed="finest"),
        "cube_filtered": _cube(spec4(SUM_QTY, where="l_discount >= 0.05 AND l_returnflag = 'R'")),
        "cube_profiled_slots": _profiled,
        "cube_model_slots": _modelled,
        "cube_range_slots": _ranged,
        "cube_heavy_keys": _heavy(SUM_QTY, MEDIAN_QTY),
        "refresh_heavy_keys": _heavy_refreshed,
        "cube_ancestor_feed": _cube(CubeSpec(POSD[:3], (SUM_QTY, MEDIAN_QTY)), feed="ancestor"),
        "slot_copies": _balance,
        "base_per_cuboid": _cube(spec4(SUM_QTY), method="per_cuboid_jobs"),
        "base_fanout": _cube(spec4(SUM_QTY), method="fanout_unshared"),
        "base_fanout_median": _cube(CubeSpec(POSD[:3], (MEDIAN_QTY,)), method="fanout_unshared"),
        "base_native": _cube(spec4(SUM_QTY), method="native_cube"),
        "base_native_median": _cube(CubeSpec(POSD[:3], (MEDIAN_QTY,)), method="native_cube"),
        "refresh_sum_incr_reuse": _refreshed(spec4(SUM_QTY), "incremental_reuse", [20]),
        "refresh_sum_incr_on_read": _refreshed(flag_spec(SUM_QTY), "incremental_reuse", [5, 5, 10], merge="on_read"),
        "refresh_sum_incr_reload": _reloaded(spec4(SUM_QTY), 20),
        "refresh_sum_recompute_reuse": _refreshed(spec4(SUM_QTY), "recompute_reuse", [20]),
        "refresh_sum_recompute_reload": _recompute_reload(spec4(SUM_QTY), 20),
        "refresh_median_recompute_reuse": _refreshed(spec4(MEDIAN_QTY), "recompute_reuse", [20]),
        "refresh_median_recompute_reload": _recompute_reload(spec4(MEDIAN_QTY), 20),
        "refresh_multi_delta": _refreshed(CubeSpec(POSD[:3], (SUM_QTY,)), "incremental_reuse", [20, 20, 20, 20, 20], snapshots=SnapshotPolicy(2)),
        "refresh_median_counts": _refreshed(CubeSpec(POSD[:3], (MEDIAN_QTY, SUM_QTY)), "incremental_counts", [20]),
        "refresh_moments": _moments(),
        "refresh_far": _far(True),
        "merge_full_outer": _outer_merged,
        "recover_incremental": _recovered(CubeSpec(POSD[:3], (SUM_QTY,)), "incremental"),
        "recover_recompute": _recovered(CubeSpec(POSD[:3], (MEDIAN_QTY,)), "recompute"),
        "agg_minmaxavg": lambda spark, sf: rounded(_cube(flag_spec(*ALL_AGGS))(spark, sf), "avg_qty"),
        "agg_stddev": lambda spark, sf: rounded(_cube(flag_spec(Agg("stddev", "l_quantity", alias="stddev_qty"), Agg("variance", "l_quantity", alias="var_qty")))(spark, sf), "stddev_qty", "var_qty"),
        "agg_corr_regr": lambda spark, sf: rounded(_cube(flag_spec(*PAIR_AGGS))(spark, sf), "corr", "regr_slope", "regr_r2").withColumn("regr_intercept", F.round("regr_intercept", 4)),
        "agg_median_mode_distinct": _cube(flag_spec(*HELD_AGGS)),
        "agg_far": _far(False),
        "agg_user": _user,
        "agg_user_raw": _user_raw,
        "agg_sketches": _approx,
        "delta_view": _delta_view,
        "new_cells": _touched(maintain.delta_new_cells),
        "touched_cells": _touched(maintain.touched_cells),
        "cube_diff": _diff,
        "answer_rollup": _stored(flags, lambda c: answer.rollup_view(c, ["l_returnflag", "ship_year"])),
        "answer_filtered": _stored(flags, lambda c: answer.answer(c, ["l_returnflag"], "ship_year >= 1995", {"ship_year"})),
        "answer_drill": _stored(flags, lambda c: answer.drill(c, {"l_returnflag": "R"}, "ship_year")),
        "answer_slice": _stored(flags, lambda c: answer.slice_(c, ["l_returnflag", "l_linestatus"], {"l_linestatus": "F"})),
        "answer_dice": _stored(flags, lambda c: answer.dice(c, ["l_returnflag", "ship_year"], {"l_returnflag": ["A", "R"], "ship_year": [1994, 1995, 1996]})),
        "top_cells": _stored(flags, lambda c: answer.top_cells(c, ["l_returnflag", "ship_year"], 7, "sum_qty")),
        "iceberg": _stored(CubeSpec(POSD[:3], (Agg("count", alias="n"),)), lambda c: answer.iceberg(c, "n", 33)),
        "window_share": _stored(flags, lambda c: rounded(answer.share_of_parent(c, ["l_returnflag", "ship_year"], ["l_returnflag"], "sum_qty"), "share")),
        "window_moving": _stored(flags, lambda c: answer.moving_sum(c, ["l_returnflag", "ship_year"], "ship_year", "sum_qty", 3)),
        "pivot_view": _stored(flags, lambda c: answer.pivot_view(c, ["ship_year"], "l_returnflag", ["A", "N", "R"], "sum_qty")),
        "sql_front": _sql,
        "star_cube": _star,
        "band_cube": _bands,
        "events_cube": _events_cube,
        "events_stream_cube": _stream_cube,
        "events_native_stream": lambda spark, sf: rounded(_native_stream(spark, sf), "median_value"),
        "events_windows": _windows,
        "events_sessions": _sessions,
        "events_late": _late,
        "events_state_median": _state_median,
        "corpus_cube": _corpus,
        "as_of": _as_of,
        "interval_join": _active,
        "lattice_table": lambda spark, sf: lattice_table(lineitem(spark, sf), line_spec(SUM_QTY)),
        "chain_plan_table": lambda spark, sf: chain_table(lineitem(spark, sf), line_spec(SUM_QTY)),
        "cuboids_of": lambda spark, sf: fed_cuboids(lineitem(spark, sf), line_spec(SUM_QTY), "l_quantity"),
    }


# the same by SQL


def _cube_sql(dims, aggs: str, source: str = "lineitem", where: str = "", sets=None, include_all: bool = False) -> str:
    """Grouping sets; the id is the same bitmap in both engines."""
    dims = list(dims)
    if sets is None:
        sets = [[d for i, d in enumerate(dims) if not m >> (len(dims) - 1 - i) & 1] for m in range((1 << len(dims)) - 1)]
    listed = ", ".join("(" + ", ".join(s) + ")" for s in [*sets, *([[]] if include_all else [])])
    return f"SELECT CAST(grouping({', '.join(dims)}) AS INTEGER) AS cuboid_id, {', '.join(dims)}, {aggs} FROM {source} {('WHERE ' + where) if where else ''} GROUP BY GROUPING SETS ({listed})"


def oracle_sql() -> dict[str, str]:
    s, m = "sum(l_quantity) AS sum_qty", "median(l_quantity) AS median_qty"
    # the part of a delta of p percent: the base is the rest, and together they are the whole table
    in_base = lambda p: f"coalesce((l_orderkey * 31 + l_linenumber) % 200, 0) * {100 + p} < 20000"
    posd, pos = POSD, POSD[:3]
    year = "(SELECT *, CAST(year(l_shipdate) AS INTEGER) AS ship_year FROM lineitem)"
    sums = "sum(l_quantity) AS sum_qty, count(*) AS n"
    flags = _cube_sql(FLAGS, sums, year)
    r = lambda e, n=6: f"round({e}, {n}) + 0.0"
    cube = _cube_sql(posd, s)
    events = "(SELECT *, CAST(ts AS DATE) AS day, event_id % 10 AS n FROM events)"
    event_dims = ("user_id", "event_type", "day")
    pairs = ", ".join(f"{r(f'{fn}(l_quantity, l_extendedprice)', 4 if fn == 'regr_intercept' else 6)} AS {fn}" for fn in ("corr", "regr_slope", "regr_intercept", "regr_r2"))
    star = "(SELECT r_name, c_mktsegment, CAST(year(l_shipdate) AS INTEGER) AS ship_year, l_returnflag, l_quantity, l_discount, l_extendedprice * (1 - l_discount) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"
    cells = lambda where: _cube_sql(pos, s, where=where)
    same = " AND ".join(f"a.{c} IS NOT DISTINCT FROM b.{c}" for c in ("cuboid_id", *pos))
    base, delta = cells(in_base(20)), cells(f"NOT {in_base(20)}")
    old, new = _cube_sql(FLAGS, s, year, where=in_base(5)), _cube_sql(FLAGS, s, year)
    far = "(SELECT *, CAST(year(l_shipdate) AS INTEGER) AS ship_year, l_quantity + 1e9 AS far FROM lineitem)"
    far_aggs = f"{r('stddev_samp(far)', 3)} AS stddev_far, {r('var_samp(far)', 3)} AS var_far, {r('corr(far, l_extendedprice)', 3)} AS corr_far, {r('regr_slope(l_extendedprice, far)', 3)} AS slope_far"
    skewed = "(SELECT *, CASE WHEN l_orderkey % 3 = 0 THEN 0 ELSE l_partkey END AS part FROM lineitem)"
    minmax = "min(l_quantity) AS min_qty, max(l_quantity) AS max_qty"
    top = lambda dims: f"SELECT {', '.join(dims)}, {sums} FROM {year} GROUP BY {', '.join(dims)}"
    ry = top(["l_returnflag", "ship_year"])
    mode = "(SELECT l_returnflag, l_linestatus, CAST(year(l_shipdate) AS INTEGER) AS ship_year, l_quantity FROM lineitem)"
    held = _cube_sql(FLAGS, f"{m}, quantile_cont(l_quantity, 0.9) AS p90_qty, list_max(list_transform(list_filter(map_entries(histogram(l_quantity)), lambda e: e.value = list_max(map_values(histogram(l_quantity)))), lambda e: e.key)) AS mode_qty, count(DISTINCT l_quantity) AS distinct_qty", mode)
    lattice = ["A", "B", "C", "D", "A,B", "B,C", "C,D", "A,D", "A,C", "B,D", "A,B,C", "B,C,D", "A,C,D", "A,B,D", "A,B,C,D"]
    plan = [("A,B,C,D", "A", 4, (1, 5, 11, 15)), ("B,C,D", "B", 3, (2, 6, 12)), ("C,D,A", "C", 3, (3, 7, 13)), ("D,A,B", "D", 3, (4, 8, 14)), ("A,C", "A,C", 1, (9,)), ("B,D", "B,D", 1, (10,))]
    named = lambda letters: ",".join(LINES["ABCD".index(x)] for x in letters.split(","))
    id_of = lambda letters: sum(8 >> i for i, x in enumerate("ABCD") if x not in letters)
    sizes = f"SELECT cuboid_id, count(*) AS n_cells FROM ({_cube_sql(LINES, 'count(*) AS n', year)}) GROUP BY cuboid_id"
    partial = [[d for d in posd if d in c] for c in PARTIAL]
    return {
        "cube_sum_posd": cube,
        "cube_median_posd": _cube_sql(posd, m),
        "cube_sum_3d": _cube_sql(pos, s),
        "cube_sum_5d": _cube_sql([*posd, "receiptdate"], s, "(SELECT *, l_shipdate + to_days(CAST(1 + (l_orderkey * 7 + l_linenumber) % 30 AS INTEGER)) AS receiptdate FROM lineitem)"),
        "cube_multi_agg": _cube_sql(posd, f"{s}, {m}, count(*) AS n, max(l_linenumber) AS max_line"),
        "cube_partial": _cube_sql(posd, s, sets=partial),
        "cube_all_cell": _cube_sql(pos, f"{s}, {m}", include_all=True),
        "cube_ordered_engine": _cube_sql(posd, f"{s}, {m}"),
        **dict.fromkeys(("cube_symmetric", "cube_greedy", "cube_waves", "cube_profiled_slots", "cube_model_slots", "cube_range_slots", "base_per_cuboid", "base_fanout", "base_native"), cube),
        **dict.fromkeys(("cube_combine", "cube_combine_auto"), flags),
        "cube_finest_feed": _cube_sql(FLAGS, f"{s}, {m}", year),
        "cube_filtered": _cube_sql(posd, s, where="l_discount >= 0.05 AND l_returnflag = 'R'"),
        "slot_copies": "SELECT CAST(i AS INTEGER) AS chain, count(*) AS copies, sum(l_quantity) AS quantity FROM lineitem, range(6) t(i) GROUP BY i",
        **dict.fromkeys(("base_fanout_median", "base_native_median"), _cube_sql(pos, m)),
        **dict.fromkeys(("refresh_sum_incr_reuse", "refresh_sum_incr_reload", "refresh_sum_recompute_reuse", "refresh_sum_recompute_reload"), cube),
        "refresh_sum_incr_on_read": new,
        **dict.fromkeys(("refresh_median_recompute_reuse", "refresh_median_recompute_reload"), _cube_sql(posd, m)),
        "refresh_median_counts": _cube_sql(pos, f"{m}, {s}"),
        "refresh_multi_delta": cells(""),
        "refresh_heavy_keys": _cube_sql(["part", "l_orderkey", "l_suppkey"], s, skewed),
        "refresh_far": _cube_sql(FLAGS, far_aggs, far),
        "merge_full_outer": _cube_sql(pos, f"{s}, count(*) AS n, {minmax}"),
        "refresh_moments": _cube_sql(FLAGS, f"{r('avg(l_quantity)')} AS avg_qty, {r('stddev_samp(l_quantity)')} AS stddev_qty", year),
        "recover_incremental": cells(""),
        "recover_recompute": _cube_sql(pos, m),
        "agg_minmaxavg": _cube_sql(FLAGS, f"count(*) AS n, min(l_quantity) AS min_qty, max(l_quantity) AS max_qty, {r('avg(l_quantity)')} AS avg_qty, {s}", year),
        "agg_stddev": _cube_sql(FLAGS, f"{r('stddev_samp(l_quantity)')} AS stddev_qty, {r('var_samp(l_quantity)')} AS var_qty", year),
        "agg_corr_regr": _cube_sql(FLAGS, pairs, year),
        "agg_median_mode_distinct": held,
        "agg_user": _cube_sql(FLAGS, "sum(l_quantity * l_quantity) AS squares", year),
        "agg_far": _cube_sql(FLAGS, far_aggs, far),
        "agg_user_raw": _cube_sql(FLAGS, f"count(DISTINCT l_quantity) - 1 AS below, {s}, {m}", year),
        "agg_sketches": _cube_sql(FLAGS, f"count(DISTINCT l_partkey) AS distinct_parts, {m}", year),
        "delta_view": _cube_sql(posd, s, where=f"NOT {in_base(20)}"),
        "cube_heavy_keys": _cube_sql(["part", "l_orderkey", "l_suppkey"], f"{s}, {m}", skewed),
        "cube_ancestor_feed": _cube_sql(pos, f"{s}, {m}"),
        "new_cells": f"SELECT cuboid_id, {', '.join(pos)} FROM ({delta}) a WHERE NOT EXISTS (SELECT 1 FROM ({base}) b WHERE {same})",
        "touched_cells": f"SELECT cuboid_id, {', '.join(pos)} FROM ({base}) a WHERE EXISTS (SELECT 1 FROM ({delta}) b WHERE {same})",
        "cube_diff": f"SELECT *, 'a' AS side FROM (({old}) EXCEPT ALL ({new})) UNION ALL SELECT *, 'b' AS side FROM (({new}) EXCEPT ALL ({old}))",
        "answer_rollup": ry,
        "answer_filtered": f"SELECT l_returnflag, {sums} FROM {year} WHERE ship_year >= 1995 GROUP BY l_returnflag",
        "answer_drill": f"{ry} HAVING l_returnflag = 'R'",
        "answer_slice": f"{top(['l_returnflag', 'l_linestatus'])} HAVING l_linestatus = 'F'",
        "answer_dice": f"{ry} HAVING l_returnflag IN ('A', 'R') AND ship_year IN (1994, 1995, 1996)",
        "top_cells": f"{ry} ORDER BY sum_qty DESC, l_returnflag, ship_year LIMIT 7",
        "iceberg": f"{_cube_sql(pos, 'count(*) AS n')} HAVING count(*) >= 33",
        "window_share": f"SELECT *, {r('sum_qty / sum(sum_qty) OVER (PARTITION BY l_returnflag)')} AS share, CAST(rank() OVER (PARTITION BY l_returnflag ORDER BY sum_qty DESC) AS INTEGER) AS rank FROM ({ry})",
        "window_moving": f"SELECT *, sum(sum_qty) OVER (PARTITION BY l_returnflag ORDER BY ship_year ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS moving FROM ({ry})",
        "pivot_view": f"SELECT ship_year, {', '.join(f'sum(l_quantity) FILTER (l_returnflag = {v!r}) AS {v}' for v in 'ANR')} FROM {year} GROUP BY ship_year",
        "sql_front": _cube_sql(["l_returnflag", "l_linestatus"], sums, where="l_discount < 0.05", include_all=True),
        "star_cube": _cube_sql(["r_name", "c_mktsegment", "ship_year", "l_returnflag"], f"round(sum(revenue), 1) AS revenue, round(avg(l_discount) + 1e-9, 5) AS avg_discount, {m}", star),
        "band_cube": _cube_sql(["band", "p_brand"], "count(*) AS n, max(p_size) AS max_size", "(SELECT *, CASE WHEN p_retailprice >= 0 AND p_retailprice < 1000 THEN 'low' WHEN p_retailprice >= 1000 AND p_retailprice < 1500 THEN 'middle' WHEN p_retailprice >= 1500 AND p_retailprice < 1e9 THEN 'high' END AS band FROM part)"),
        "events_cube": _cube_sql(event_dims, f"count(*) AS n_events, {r('median(value)')} AS median_value, {r('avg(value) + 1e-9')} AS avg_value", events),
        "events_stream_cube": _cube_sql(event_dims, "CAST(sum(n) AS BIGINT) AS sum_n, count(*) AS n_events, min(value) AS min_value, max(value) AS max_value", events),
        "events_native_stream": _cube_sql(event_dims, f"{r('median(value)')} AS median_value, count(*) AS n_events", events),
        "events_windows": "SELECT event_type, start, count(*) AS n_events, max(value) AS max_value FROM (SELECT event_type, value, date_trunc('day', ts) - to_days(CAST(k AS INTEGER)) AS start FROM events, range(2) t(k)) GROUP BY event_type, start",
        "events_sessions": " UNION ALL ".join(f"SELECT CAST({i} AS INTEGER) AS cuboid_id, user_id, {e} AS event_type, min(ts) AS start, count(*) AS n_events FROM (SELECT *, sum(CASE WHEN ts < before + INTERVAL 6 HOUR THEN 0 ELSE 1 END) OVER (PARTITION BY {k} ORDER BY ts, event_id) AS session FROM (SELECT *, lag(ts) OVER (PARTITION BY {k} ORDER BY ts, event_id) AS before FROM events)) GROUP BY {k}, session" for i, e, k in ((0, "event_type", "user_id, event_type"), (1, "NULL", "user_id"))),
        "events_late": "SELECT event_type, date_trunc('day', ts) AS start, count(*) AS n_events FROM events WHERE event_id % 3 < 2 OR date_trunc('day', ts) + INTERVAL 1 DAY > (SELECT max(ts) - INTERVAL 5 DAY FROM events WHERE event_id % 3 = 0) GROUP BY ALL",
        "events_state_median": f"SELECT event_type, {r('median(value)')} AS median_value, count(value) AS n FROM events GROUP BY event_type",
        "corpus_cube": _cube_sql(["lang", "source", "quality"], "count(*) AS n_docs, CAST(sum(n_chars) AS BIGINT) AS sum_chars, median(n_chars) AS median_chars", "(SELECT d.lang, d.source, d.n_chars, l.quality FROM documents d LEFT JOIN labels l USING (doc_id))", include_all=True),
        "as_of": "SELECT p.event_id, p.user_id, v.value FROM events p ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events GROUP BY user_id, ts) v ON p.user_id = v.user_id AND p.ts > v.ts",
        "interval_join": "SELECT l_orderkey, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_shipdate >= o_orderdate AND l_shipdate < o_orderdate + INTERVAL 60 DAY GROUP BY l_orderkey",
        "lattice_table": "SELECT CAST(number AS INTEGER) AS number, CAST(n_dims AS INTEGER) AS n_dims, members, n_cells FROM (VALUES " + ", ".join(f"({i}, {c.count(',') + 1}, '{named(c)}', {id_of(c)})" for i, c in enumerate(lattice, 1)) + f") t(number, n_dims, members, cuboid_id) JOIN ({sizes}) USING (cuboid_id)",
        "chain_plan_table": f"WITH s AS ({sizes}) SELECT CAST(chain AS INTEGER) AS chain, sort_dims, part_dims, CAST(members AS INTEGER) AS members, tag, p.n_cells AS n_keys, l.n_cells AS n_cells FROM (VALUES " + ", ".join(f"({i}, '{named(o)}', '{named(p)}', {n}, '{sum(1 << b for b in bits):016b}', {id_of(p)}, {id_of(o)})" for i, (o, p, n, bits) in enumerate(plan)) + ") t(chain, sort_dims, part_dims, members, tag, dealt_by, longest) JOIN s p ON p.cuboid_id = dealt_by JOIN s l ON l.cuboid_id = longest",
        "cuboids_of": "SELECT CAST(number AS INTEGER) AS number, members, copies, total FROM (VALUES " + ", ".join(f"({i}, '{named(c)}')" for i, c in enumerate(lattice, 1)) + ") t(number, members), (SELECT count(*) AS copies, sum(l_quantity) AS total FROM lineitem)",
    }


# the experiments


def _sizes(rows: DataFrame, copies: list[int]) -> dict[str, DataFrame]:
    return {f"{k}x": T.replicated(rows, k) if k > 1 else rows for k in copies}


def run_per_cuboid(rows: DataFrame, spec: CubeSpec) -> None:
    """The baseline as the experiment runs it: the jobs one after another."""
    for job in cuboid_jobs(rows, spec):
        metrics.drain(job)


def w1_materialization(rows: DataFrame, aggs: dict[str, Agg], copies: list[int], repeats: int = 3) -> list[dict]:
    """Time and shuffle of each method, function and size."""
    out, spark = [], rows.sparkSession
    for size, df in _sizes(rows, copies).items():
        for fn, agg in aggs.items():
            spec = spec4(agg)
            methods = {
                "per_cuboid_jobs": lambda df=df, spec=spec: run_per_cuboid(df, spec),
                "fanout_unshared": lambda df=df, spec=spec: metrics.drain(M.materialize(df, spec, method="fanout_unshared").df),
                "native_cube": lambda df=df, spec=spec: metrics.drain(M.materialize(df, spec, method="native_cube").df),
                "shared_scan": lambda df=df, spec=spec: metrics.drain(M.materialize(df, spec).df),
            }
            for name, fn_run in methods.items():
                with metrics.watch(spark) as seen:
                    fn_run()
                out.append({"size": size, "fn": fn, "method": name, **metrics.timed(fn_run, repeats), "shuffle": seen.shuffle_cost(), "read": seen.read_cost()})
    return out


def w2_cache_overhead(rows: DataFrame, aggs: dict[str, Agg], repeats: int = 3) -> dict[str, dict]:
    """What a cache adds to a job that publishes its views as files.  A view cache is itself the published views; an input cache comes on top of them."""
    spark, out = rows.sparkSession, {}
    for fn, agg in aggs.items():
        spec = spec4(agg)
        kind = "view" if spec.mergeable() else "input"

        def cached(spec=spec, kind=kind):
            cube = maintain.materialize_cached(rows, spec, _new_store(spark, spec), kind)
            if kind == "input":
                published(cube.df)

        plain = metrics.timed(lambda spec=spec: published(M.materialize(rows, spec).df), repeats)
        with_cache = metrics.timed(cached, repeats)
        out[fn] = {"plain_s": plain["min"], "cached_s": with_cache["min"], "overhead": metrics.overhead(with_cache["min"], plain["min"])}
    return out


def published(cells: DataFrame) -> None:
    """Write cells as files, as a job does whose views others read."""
    cells.write.mode("overwrite").parquet(files.scratch_dir(cells.sparkSession))


def w3_load_balance(rows: DataFrame, r: int = 24, s: int = 20, spec: CubeSpec | None = None) -> dict[str, dict]:
    """Evenness of slots by each allocation."""
    spec = spec or spec4(SUM_QTY)
    chains = plan_chains(spec.dims).chains
    profile = S.profiled_slots(rows, spec, chains, r, lambda df: S.systematic_sample(df, s))
    heavy = S.heavy_keys(rows, spec, chains, profile)
    plans = {"profiled": S.SlotPlan(tuple(profile)), "even": S.SlotPlan(tuple(S.even_slots(len(chains), r))), "model": S.SlotPlan(tuple(S.model_slots(rows, spec, chains, r))), "range": S.range_bounds(rows, spec, chains, profile), "heavy": heavy}
    out = {}
    for name, p in plans.items():
        with metrics.watch(rows.sparkSession) as seen:
            metrics.drain(M.materialize(rows, spec, slots=p).df)
        out[name] = {"widths": list(p.widths), **metrics.slot_balance(seen.slots(r), list(p.widths))}
    return out


def w4_dimensions(rows: DataFrame, repeats: int = 3) -> list[dict]:
    out = []
    for n, df in ((3, rows), (4, rows), (5, T.with_receipt_date(rows))):
        spec = CubeSpec((*POSD, "receiptdate")[:n], (SUM_QTY,))
        for method in ("fanout_unshared", "shared_scan"):
            out.append({"dims": n, "method": method, **metrics.timed(lambda df=df, spec=spec, method=method: metrics.drain(M.materialize(df, spec, method=method).df), repeats)})
    return out


def parts_as_files(rows: DataFrame, percent: int, tasks: int = 16) -> tuple[DataFrame, DataFrame]:
    """A base and a delta of so many percent of it, together the whole table, each as files of its own."""
    spark, out = rows.sparkSession, []
    for part in T.whole_parts(rows, [percent]):
        path = files.scratch_dir(spark)
        part.repartition(tasks).write.parquet(path)
        out.append(spark.read.schema(rows.schema).parquet(path))
    return out[0], out[1]


def one_refresh(spec: CubeSpec, manner: str, base: DataFrame, delta: DataFrame) -> Callable[[], Callable[[], None]]:
    """A function that prepares a manner's state and returns its refresh, which ends when the new views are published as files.

    ``incremental_reuse`` publishes by writing its merged state; the others write the views.
    """
    spark = base.sparkSession

    def prepare() -> Callable[[], None]:
        root, store = files.scratch_dir(spark), _new_store(spark, spec)
        if manner == "recompute_reload":
            return lambda: published(maintain.refresh(store, delta, manner, base=base).cube.df)
        if manner == "incremental_reload":
            maintain.view_states(base, spec).write.parquet(f"{root}/view")
            return lambda: maintain.incremental_reload(f"{root}/view", delta, spec, f"{root}/delta", f"{root}/new") and None
        maintain.materialize_cached(base, spec, store, maintain.KIND[manner])
        if manner == "recompute_reuse":
            return lambda: published(maintain.refresh(store, delta, manner).cube.df)
        return lambda: maintain.refresh(store, delta, manner) and None

    return prepare


def w5_w6_maintenance(rows: DataFrame, agg: Agg, manners: list[str], percents: list[int], repeats: int = 3) -> list[dict]:
    """Refresh time of each manner and delta size, least of some runs, until the new views are published; making the first state isn't in it."""
    spark, spec, out = rows.sparkSession, spec4(agg), []
    for p in percents:
        base, delta = parts_as_files(rows, p)
        for manner in manners:
            prepare, best, seen = one_refresh(spec, manner, base, delta), None, None
            for _ in range(repeats):
                run = prepare()
                with metrics.watch(spark) as seen:
                    run()
                best = seen.seconds if best is None else min(best, seen.seconds)
            out.append({"delta": p, "manner": manner, "refresh_s": best, "shuffle": seen.shuffle_cost(), "read": seen.read_cost(), "cost": seen.breakdown()})
    return out
