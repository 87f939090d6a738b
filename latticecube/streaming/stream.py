"""Near-real-time maintenance: micro-batch refresh of a slot store, and native stateful cubes."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StreamingQuery

from latticecube.files import Files
from latticecube.operators import maintain
from latticecube.operators import materialize as M
from latticecube.operators.store import SlotStore
from latticecube.spec import CubeSpec


@dataclass(frozen=True)
class TimeDim:
    """A tumbling, or with ``slide`` a sliding, time dimension; a row counts once in each window it is in."""

    column: str
    duration: str
    slide: str | None = None
    name: str = "window"

    def expr(self) -> Column:
        return F.window(self.column, self.duration, self.slide) if self.slide else F.window(self.column, self.duration)


@dataclass(frozen=True)
class SessionDim:
    """A session window by keys, which every cuboid must keep."""

    column: str
    gap: str
    by: tuple[str, ...]
    name: str = "session"


def with_event_time(df: DataFrame, column: str = "ts") -> DataFrame:
    """A time without zone read as UTC, so that it can carry a watermark; the session's zone must be UTC."""
    if df.sparkSession.conf.get("spark.sql.session.timeZone") not in ("UTC", "Etc/UTC", "Z"):
        raise ValueError("set spark.sql.session.timeZone to UTC first")
    return df.withColumn(column, F.col(column).cast("timestamp"))


def with_watermark(df: DataFrame, column: str, lateness: str, dedup_key: str | None = None) -> DataFrame:
    """Event time with a bound on lateness; with a key, repeated deliveries within it are dropped."""
    out = df.withWatermark(column, lateness)
    return out.dropDuplicatesWithinWatermark([dedup_key]) if dedup_key else out


def native_stream_cube(source: DataFrame, spec: CubeSpec, time: TimeDim | SessionDim | None = None) -> DataFrame:
    """A streaming cube by Spark's stateful aggregation; all cuboids of ``spec`` and, with ``time``, each by window."""
    dims = list(spec.dims)
    keep = [time.column] if time else []
    rows = source
    if spec.where:
        rows = rows.where(spec.where)
    for name, e in spec.derived.items():
        rows = rows.withColumn(name, F.expr(e) if isinstance(e, str) else e)
    measures = list(dict.fromkeys(m for a in spec.aggs for m in a.measures))
    rows = rows.select(*dims, *keep, *[F.col(m).alias(f"m_{m}") for m in measures])
    ids = F.array(*[F.lit(spec.cuboid_id(m)) for m in spec.wanted()])
    spread = rows.select("*", F.explode(ids).alias("cuboid_id"))
    spread = spread.select("cuboid_id", *M.masked(spec, F.col("cuboid_id")), *keep, *[f"m_{m}" for m in measures])
    keys: list = ["cuboid_id", *dims]
    if isinstance(time, SessionDim):
        if any(not set(time.by) <= m for m in spec.wanted()):
            raise ValueError("a session's keys must be in every cuboid")
        keys.append(F.session_window(time.column, time.gap).alias(time.name))
    elif time:
        keys.append(time.expr().alias(time.name))
    states = [init.alias(name) for a in spec.aggs for name, (init, _) in a.states().items()]
    plain = {"median": F.median, "mode": lambda x: F.mode(x, True)}
    held = [(F.percentile(F.col(f"m_{a.measure}"), a.p) if a.fn == "percentile" else plain[a.fn](F.col(f"m_{a.measure}"))).alias(a.name) for a in spec.aggs if a.kind == "frequency"]
    cells = spread.groupBy(*keys).agg(*states, *held)
    return cells.select("cuboid_id", *dims, *([time.name] if time else []), *[a.final().alias(a.name) for a in spec.aggs])


def stream_refresh(source: DataFrame, store: SlotStore, manner: str, checkpoint: str, compact_every: int = 8) -> StreamingQuery:
    """Refresh the store with each micro-batch; a batch that is delivered again changes nothing.

    The first batch of an empty store makes its state.
    """
    spec = store.spec

    def apply(batch: DataFrame, batch_id: int) -> None:
        m = store.manifest()
        if m["version"] == 0:
            # the state and the batch's number become visible in one commit, so a replay finds both or neither
            maintain.materialize_cached(batch, spec, store, "view" if manner == "incremental_reuse" else "input", batch_id=str(batch_id))
            return
        maintain.refresh(store, batch, manner, batch_id=str(batch_id))
        m = store.manifest()
        if compact_every and m["updates"] % compact_every == 0 and len(m["runs"]) > 1:
            maintain.compact(store)

    return source.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def run_to_table(stream: DataFrame, name: str, mode: str, checkpoint: str) -> None:
    """Run a streaming frame over what there is into a memory table."""
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()


#: State on the executors' disks, in bounded memory, instead of on their heaps.
ROCKSDB = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true",
    "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "300",
}


@contextmanager
def session_conf(spark: SparkSession, conf: dict[str, str]) -> Iterator[None]:
    """Settings for the queries that are started meanwhile; the session's own are put back."""
    old = {k: spark.conf.get(k, None) for k in conf}
    for k, v in conf.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in old.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def run_to_files(stream: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """Run a streaming frame over what there is and read what it appends: tasks write it to files, and nothing passes through the driver."""
    spark = stream.sparkSession
    with session_conf(spark, ROCKSDB):
        q = stream.writeStream.format("parquet").outputMode("append").option("checkpointLocation", checkpoint).trigger(availableNow=True).start(path)
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def run_to_latest(stream: DataFrame, keys: list[str], path: str, checkpoint: str) -> DataFrame:
    """Run a streaming aggregate over what there is in update mode, and read its cells: tasks write the cells that a batch changes to files, a batch that
    runs again writes over its own, and a cell's last batch counts.  Nothing passes through the driver, and a batch doesn't give unchanged cells again."""
    spark = stream.sparkSession
    write = lambda df, batch: df.write.mode("overwrite").parquet(f"{path}/__batch={batch}")
    with session_conf(spark, ROCKSDB):
        q = stream.writeStream.foreachBatch(write).outputMode("update").option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    if not Files(spark, path).names("."):
        return spark.createDataFrame([], stream.schema)
    changed = spark.read.schema(T.StructType([*stream.schema, T.StructField("__batch", T.LongType())])).parquet(path)
    last = [F.max_by(c, "__batch").alias(c) for c in stream.columns if c not in keys]
    return changed.groupBy(*keys).agg(*last).select(*stream.columns)


def dropped_late(query: StreamingQuery) -> int:
    """Rows that came after the watermark, from the query's progress."""
    return sum(s.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for s in p["stateOperators"])
