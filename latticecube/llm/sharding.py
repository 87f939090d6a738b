"""Operator 5, sharding by size-tiered compaction with a versioned manifest.

Arrivals are appended as small immutable Parquet shards.  A shard's tier is the whole part of the logarithm of its size to the base
``fanout`` over the smallest size.  Where a tier holds ``fanout`` shards or more, its shards are merged into files of about the target size:
as many output tasks as the tier's bytes need read the shards and write, with nothing shuffled.  Shards that have reached the target
are not touched again, so a row is rewritten about as often as there are tiers.

A version is a manifest: an immutable list of shards.  Files are written first; then the manifest is moved to the next version's name, which fails if
another writer got there first; an append or a merge then starts again from the new version, a merge only if its shards are still there.  Readers open the
newest manifest, and files of older versions stay until ``expire``, which deletes only what older manifests list: files that a writer has not committed yet
are never touched, and a writer that fails for good removes its own.

Edge cases: an empty arrival adds a version without shards; null ids and texts and repeated rows are stored as they come; all arrivals of
a store have one schema, otherwise an error is raised; a store without a version reads as an error.
"""

from __future__ import annotations

import json
import math
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


#: Times that a commit starts again after another writer's.
RETRIES = 20


class Conflict(RuntimeError):
    """Another writer committed the version first."""


class ShardStore:
    def __init__(self, spark: SparkSession, root: str, target_bytes: int = 128 << 20, smallest: int = 1 << 20, fanout: int = 4):
        self.spark, self.root, self.target, self.smallest, self.fanout = spark, root.rstrip("/"), target_bytes, smallest, fanout
        self.jvm = spark.sparkContext._jvm
        self.conf = spark.sparkContext._jsc.hadoopConfiguration()

    # files, by the store's own file system

    def _path(self, name: str):
        return self.jvm.org.apache.hadoop.fs.Path(name)

    def _fs(self):
        return self._path(self.root).getFileSystem(self.conf)

    def _listed(self, folder: str) -> list[tuple[str, int]]:
        fs, path = self._fs(), self._path(folder)
        if not fs.exists(path):
            return []
        return sorted((s.getPath().toString(), int(s.getLen())) for s in fs.listStatus(path) if s.isFile())

    def _write_new(self, name: str, body: str) -> None:
        """Create a file under a name that must not exist; the move is one step."""
        fs, tmp, to = self._fs(), self._path(f"{name}.{uuid.uuid4().hex}.tmp"), self._path(name)
        out = fs.create(tmp, True)
        out.write(bytearray(body.encode()))
        out.close()
        try:
            context = self.jvm.org.apache.hadoop.fs.FileContext.getFileContext(fs.getUri(), self.conf)
            none = self.spark.sparkContext._gateway.new_array(self.jvm.org.apache.hadoop.fs.Options.Rename, 0)
            context.rename(tmp, to, none)
        except Exception as e:
            fs.delete(tmp, False)
            raise Conflict(name) from e

    def _read_text(self, name: str) -> str:
        stream = self._fs().open(self._path(name))
        try:
            return self.jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        finally:
            stream.close()

    # versions

    def version(self) -> int:
        names = [n.rsplit("/", 1)[1] for n, _ in self._listed(f"{self.root}/manifests")]
        return max((int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json")), default=0)

    def manifest(self, version: int | None = None) -> dict:
        at = self.version() if version is None else version
        if at == 0:
            return {"version": 0, "shards": [], "schema": None}
        return json.loads(self._read_text(f"{self.root}/manifests/v{at:012d}.json"))

    def commit(self, old: dict, shards: list[dict], schema: str) -> dict:
        """Publish the next version; raises Conflict if it exists by now."""
        new = {"version": old["version"] + 1, "shards": shards, "schema": schema}
        self._write_new(f"{self.root}/manifests/v{new['version']:012d}.json", json.dumps(new))
        return new

    # shards

    def _stored(self, df: DataFrame, folder: str, rows: int = 0) -> list[dict]:
        df.write.mode("errorifexists").option("maxRecordsPerFile", rows).parquet(folder)
        return [{"uri": n, "bytes": b, "tier": self.tier(b)} for n, b in self._listed(folder) if n.endswith(".parquet")]

    def tier(self, size: int) -> int:
        return max(0, int(math.log(max(1, size / self.smallest), self.fanout)))

    def _drop(self, shards: list[dict]) -> None:
        for x in shards:
            self._fs().delete(self._path(x["uri"]), False)

    def _added(self, new: list[dict], schema: str) -> dict:
        """Commit new shards on top of whatever version is the newest."""
        for _ in range(RETRIES):
            old = self.manifest()
            if old["schema"] not in (None, schema):
                self._drop(new)
                raise ValueError("the arrival's schema differs from the store's")
            try:
                return self.commit(old, old["shards"] + new, schema)
            except Conflict:
                continue
        self._drop(new)
        raise Conflict("too many other writers")

    def append(self, arrival: DataFrame) -> dict:
        """Store an arrival as new shards and commit."""
        schema = arrival.schema.json()
        if self.manifest()["schema"] not in (None, schema):
            raise ValueError("the arrival's schema differs from the store's")
        return self._added(self._stored(arrival, f"{self.root}/data/{uuid.uuid4().hex}"), schema)

    def append_split(self, docs: DataFrame, arrivals: int, shards: int = 2) -> int:
        """Store one frame as so many arrivals, each a commit of its own, in one pass without a shuffle; returns the number of shards.

        Tasks start a new file after so many rows that there are at least about ``shards`` of them an arrival, none larger than an eighth of the target.
        """
        folder, schema = f"{self.root}/data/{uuid.uuid4().hex}", docs.schema.json()
        if self.manifest()["schema"] not in (None, schema):
            raise ValueError("the arrival's schema differs from the store's")
        n = docs.count()
        size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))  # of the files that are read
        rows = max(1, min(-(-n // (arrivals * shards)), self.target * n // max(1, 8 * size)))
        files = self._stored(docs, folder, rows)
        for a in range(arrivals):
            self._added(files[a::arrivals], schema)
        return len(files)

    def plan(self, shards: list[dict]) -> list[list[dict]]:
        """The runs to merge: all shards of a tier that holds enough of them and is below the target."""
        tiers: dict[int, list[dict]] = {}
        for s in shards:
            if s["bytes"] < 0.75 * self.target:
                tiers.setdefault(s["tier"], []).append(s)
        return [sorted(t, key=lambda s: s["uri"]) for _, t in sorted(tiers.items()) if len(t) >= self.fanout]

    def compact(self) -> int:
        """Merge until no tier has a run that gains from it; each merge is one job and one commit.  Returns the number of merges."""
        merges, useless = 0, set()
        while True:
            old = self.manifest()
            run = next((r for r in self.plan(old["shards"]) if frozenset(s["uri"] for s in r) not in useless), None)
            if run is None:
                return merges
            gone = frozenset(s["uri"] for s in run)
            files = max(1, round(sum(s["bytes"] for s in run) / self.target))
            if files >= len(run):  # nothing to gain: leave the run alone and go on with the next
                useless.add(gone)
                continue
            rows = self.spark.read.schema(T.StructType.fromJson(json.loads(old["schema"]))).parquet(*[s["uri"] for s in run])
            new = self._stored(rows.coalesce(files), f"{self.root}/data/{uuid.uuid4().hex}")
            if self._replaced(gone, new):
                merges += 1

    def _replaced(self, gone: frozenset[str], new: list[dict]) -> bool:
        """Commit new shards in place of others, unless another writer has merged one of these meanwhile."""
        for _ in range(RETRIES):
            old = self.manifest()
            if not gone <= {s["uri"] for s in old["shards"]}:
                break
            try:
                self.commit(old, [s for s in old["shards"] if s["uri"] not in gone] + new, old["schema"])
                return True
            except Conflict:
                continue
        self._drop(new)
        return False

    def read(self, version: int | None = None) -> DataFrame:
        m = self.manifest(version)
        if m["schema"] is None:
            raise ValueError("the store has no version")
        schema = T.StructType.fromJson(json.loads(m["schema"]))
        if not m["shards"]:
            return self.spark.createDataFrame([], schema)
        return self.spark.read.schema(schema).parquet(*[s["uri"] for s in m["shards"]])

    def expire(self, keep: int = 1) -> int:
        """Delete files that only manifests before the newest ``keep`` ones list, and those manifests; returns how many files."""
        newest = self.version()
        versions = sorted(int(n.rsplit("/v", 1)[1][:-5]) for n, _ in self._listed(f"{self.root}/manifests") if n.endswith(".json"))
        used = {s["uri"] for v in versions if v > newest - keep for s in self.manifest(v)["shards"]}
        old = [v for v in versions if v <= newest - keep]
        gone = {s["uri"] for v in old for s in self.manifest(v)["shards"]} - used
        self._drop([{"uri": u} for u in gone])
        for v in old:
            self._fs().delete(self._path(f"{self.root}/manifests/v{v:012d}.json"), False)
        return len(gone)


def sharded(docs: DataFrame, root: str, arrivals: int, target_bytes: int, smallest: int, fanout: int = 4) -> tuple[ShardStore, int, int]:
    """Append ``docs`` as arrivals, compact, and drop what no reader needs.

    Returns the store, the number of shards that arrived, and the number of merges.
    """
    store = ShardStore(docs.sparkSession, root, target_bytes, smallest, fanout)
    shards = store.append_split(docs, arrivals)
    merges = store.compact()
    store.expire()
    return store, shards, merges
