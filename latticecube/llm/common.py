"""Helpers shared by the operators: splits, shared folders, written tables, bounded joins."""

from __future__ import annotations

import tempfile
import time
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words are maximal runs of anything but the six ASCII white-space characters.
WORD_CLASS = r"[^\x20\x09-\x0D]+"

#: Rows up to which a table of fixed-width rows may be broadcast (about 64 MB).
BROADCAST_ROWS = 1_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def held_out(doc_id: Column | str = "doc_id") -> Column:
    """True where a document belongs to the third of the ids that nothing may be learned from.

    A null id has no remainder; such rows count as held out, so nothing is learned from them.
    """
    key = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.coalesce(F.crc32(key.cast("string")) % 3 == 1, F.lit(True))


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``; only a local master may do without, with a folder of its machine."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        jsc = spark.sparkContext._jsc.sc()
        known = jsc.getCheckpointDir()
        if known.isDefined():
            root = known.get()
        elif spark.sparkContext.master.startswith("local"):
            root = "file://" + tempfile.mkdtemp(prefix="latticecube-")
            spark.sparkContext.setCheckpointDir(root)
            root = jsc.getCheckpointDir().get()
        else:
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    return root.rstrip("/")


def scratch(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/latticecube/{label}-{uuid.uuid4().hex}"


def written(df: DataFrame, label: str, *partition_by: str) -> DataFrame:
    """Cut the lineage: write to the shared folder and read back with the declared schema."""
    spark = df.sparkSession
    path = scratch(spark, label)
    out = df.write.mode("overwrite")
    if partition_by:
        out = out.partitionBy(*partition_by)
    out.parquet(path)
    if time.monotonic() - _given_back[0] >= GIVE_BACK_S:
        _given_back[0] = time.monotonic()
        driver_gives_back(spark)
    return spark.read.schema(df.schema).parquet(path)


#: Seconds between two times at least that the driver's JVM gives memory back while tables are written, and when it last did.
GIVE_BACK_S = 5
_given_back = [0.0]


def driver_gives_back(spark: SparkSession) -> str:
    """Return the native memory that the driver's JVM has freed to the machine; what the JVM answers, empty if it can't.

    Operators of many small jobs plan and compile in hundreds of threads, and the C library keeps what each of them has freed.
    """
    from py4j.protocol import Py4JError

    jvm, gateway = spark._jvm, spark.sparkContext._gateway

    def array(kind, *items):
        out = gateway.new_array(kind, len(items))
        for i, x in enumerate(items):
            out[i] = x
        return out

    try:
        kind = jvm.java.lang.Class
        of = [kind.forName(n) for n in ("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")]
        call = kind.forName("javax.management.MBeanServer").getMethod("invoke", array(kind, *of))
        name = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand")
        server = jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer()
        return call.invoke(server, array(jvm.java.lang.Object, name, "systemTrimNativeHeap", array(jvm.java.lang.Object), array(jvm.java.lang.String)))
    except Py4JError:  # an older JVM, or another C library
        return ""


def free_name(df: DataFrame, base: str) -> str:
    """A column name that the frame doesn't have, in any case."""
    taken = {c.lower() for c in df.columns}
    while base.lower() in taken:
        base = f"_{base}"
    return base


def small_side(df: DataFrame, rows: int | None = None, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Mark ``df`` for broadcast only if it has at most ``limit`` rows; otherwise leave the join to shuffle."""
    n = df.count() if rows is None else rows
    return F.broadcast(df) if n <= limit else df


#: Rows from which on a key is dealt apart, and how many such keys there may be: their number is bounded as their rows add up to the table's.
HOT_ROWS, HOT_KEYS = 1_000, 200_000


def join_by_key(left: DataFrame, right: DataFrame, key: str, size: str, how: str = "inner") -> DataFrame:
    """Join a written table with one row for each key that says how many rows of ``left`` have it, so that no key lands in one task.

    The rows of hot keys meet them by broadcast where they lie; the others are shuffled.  ``how`` is inner or left_semi.
    """
    total = right.agg(F.sum(size)).first()[0] or 0
    least = max(HOT_ROWS, total // HOT_KEYS)
    few = right.where(F.col(size) >= least)  # HOT_KEYS rows at most
    if few.isEmpty():
        return left.join(right, key, how)
    rest = left.join(F.broadcast(few.select(key)), key, "left_anti").join(right.where(F.col(size) < least), key, how)
    return left.join(F.broadcast(few), key, how).unionByName(rest)


_memos: dict[str, object] = {}


def claim(owner: str, clear) -> None:
    """Say that a Python worker now remembers for one operator, and free what it remembers for others.

    Workers outlive tasks and serve several operators in turn; without this their dictionaries would add up.
    """
    for other in [k for k in _memos if k != owner]:
        _memos.pop(other)()
        give_back()
    _memos[owner] = clear


def give_back() -> None:
    """Return freed memory to the machine, where the C library can."""
    import ctypes
    import gc

    gc.collect()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):
        pass


#: Rows of an Arrow batch: texts are long, and both sides of the pipe hold a whole batch.
BATCH_ROWS = 1_000


def arrow_map(df: DataFrame, fn, schema: str) -> DataFrame:
    """``mapInArrow`` with batches that fit long texts; this lowers the session's (runtime) batch size if it is larger."""
    conf = df.sparkSession.conf
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(conf.get(name)) <= BATCH_ROWS:
        conf.set(name, str(BATCH_ROWS))
    return df.mapInArrow(fn, schema)


def slices(batch, rows: int = 256):
    """Cut an Arrow batch so that only a few rows are Python objects at a time."""
    for at in range(0, batch.num_rows, rows):
        yield batch.slice(at, rows)


def put_bytes(uri: str, data: bytes) -> None:
    """Write a whole object atomically: a temporary name first, then a move."""
    with replaced(uri) as out:
        out.write(data)


class replaced:
    """Context manager around an output stream that becomes visible under ``uri`` only when complete.

    A retried or speculative task writes under a name of its own and moves it over the
    same final name, so a lost executor leaves no half-written file that a reader sees.
    """

    def __init__(self, uri: str):
        from pyarrow import fs

        self.fs, self.path = fs.FileSystem.from_uri(uri)
        self.tmp = f"{self.path}.{uuid.uuid4().hex}.tmp"

    def __enter__(self):
        self.fs.create_dir(self.path.rpartition("/")[0], recursive=True)
        self.out = self.fs.open_output_stream(self.tmp)
        return self.out

    def __exit__(self, kind, *_):
        self.out.close()
        if kind is None:
            self.fs.move(self.tmp, self.path)
        else:
            self.fs.delete_file(self.tmp)


def get_file(uri: str):
    from pyarrow import fs

    store, path = fs.FileSystem.from_uri(uri)
    return store.open_input_file(path)
