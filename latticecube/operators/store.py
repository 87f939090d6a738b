"""The slot store: co-partitioned state that later jobs read without shuffling it again.

A run is one bucketed table of all chains: bucket i is what slot i of the shuffle got, so one job with one scan and one shuffle writes it.  The
bucket column ``__slot`` holds, for slot i, an integer that Spark's own bucket hash sends to bucket i.  Two kinds are kept: ``input`` holds
compressed rows at each chain's full key (for recomputation), ``view`` holds the states of all cells (for incremental maintenance).  A later job
reads the runs as one bucketed scan next to a delta that is dealt the same way, and only the delta is shuffled.

A version is a manifest that is created in one step after its run is written; a failed job leaves the version before readable.  A manifest names
the files of its runs with their sizes, so that the loss of a single slot's file is seen.  Files of versions older than the last ``keep`` ones,
superseded snapshots and the tables put over them are deleted after each commit; a frame of an older version can't be read any more then.
"""

from __future__ import annotations

import hashlib
import json
import re
import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from latticecube.files import Files
from latticecube.operators.materialize import CubePlan
from latticecube.plans.chains import Chain
from latticecube.plans.slots import SlotPlan, bucket_keys
from latticecube.spec import CubeSpec

#: What the files of one write have in common in their names, and the bucket's number.
_FILE = re.compile(r"part-\d+-([0-9a-f-]{36})_(\d+)\.")


@dataclass(frozen=True)
class SnapshotPolicy:
    """A snapshot after every so many updates: 1 is eager, None is never."""

    every: int | None = 4


class SlotStore:
    def __init__(self, spark: SparkSession, root: str, spec: CubeSpec, snapshots: SnapshotPolicy | None = None, merge: str = "on_write", keep: int = 2):
        if merge not in ("on_write", "on_read"):
            raise ValueError("merge is on_write or on_read")
        if keep < 1:
            raise ValueError("the last version is always kept")
        self.spark, self.spec, self.files, self.keep = spark, spec, Files(spark, root), keep
        self.root, self.policy, self.merge_when = self.files.root, snapshots or SnapshotPolicy(None), merge

    # versions

    def versions(self) -> list[int]:
        return sorted(int(n[1:-5]) for n in self.files.names("manifests") if n.endswith(".json"))

    def version(self) -> int:
        return max(self.versions(), default=0)

    def manifest(self, version: int | None = None) -> dict:
        at = self.version() if version is None else version
        if at == 0:
            return {"version": 0, "kind": None, "chains": [], "heavy": [], "runs": [], "updates": 0, "batches": [], "deltas": [], "snapshot": None}
        return json.loads(self.files.read(f"manifests/v{at:09d}.json"))

    def commit(self, old: dict, **changes) -> dict:
        new = old | changes | {"version": old["version"] + 1}
        self.files.create(f"manifests/v{new['version']:09d}.json", json.dumps(new))
        self.expire()
        return new

    def plan(self, m: dict | None = None) -> CubePlan:
        """The chains and slot ranges that the state was dealt by: later jobs place rows as the first one did."""
        m = m or self.manifest()
        chains = [Chain(tuple(c["order"]), tuple(frozenset(x) for x in c["members"])) for c in m["chains"]]
        return CubePlan(self.spec, chains, SlotPlan(tuple(c["width"] for c in m["chains"]), (), tuple(tuple(h) for h in m["heavy"])), {"chains": len(chains)})

    def described(self, cube: CubePlan) -> dict:
        return {"chains": [{"order": list(c.order), "members": [sorted(x) for x in c.members], "width": w} for c, w in zip(cube.chains, cube.slots.widths, strict=True)], "heavy": [list(h) for h in cube.slots.heavy]}

    # runs

    def write_run(self, rows: DataFrame, slots: int, label: str) -> dict:
        """Write rows that lie in their slots as one bucketed run, one file for each slot that has any."""
        name = f"lc_{label}_{uuid.uuid4().hex}"
        path = f"{self.root}/runs/{name}"
        rows.write.bucketBy(slots, "__slot").option("path", path).format("parquet").saveAsTable(name)
        self.spark.sql(f"DROP TABLE {name}")  # the files stay: tables are put over sets of runs
        files = [[int(_FILE.match(n)[2]), n, size] for n, size in self.files.sizes(f"runs/{name}").items() if _FILE.match(n)]
        return {"path": path, "files": files, "schema": rows.schema.json(), "slots": slots, "without": []}

    def table_over(self, runs: list[dict]) -> DataFrame:
        """Runs as one bucketed table: a slot's files of all runs are read by one task, and nothing is shuffled."""
        schema = T.StructType.fromJson(json.loads(runs[0]["schema"]))
        marks = []
        for r in runs:
            out, uuids = set(r["without"]), sorted({_FILE.match(n)[1] for _, n, _ in r["files"]})
            marks += [f"{u}_{s:05d}." for u in uuids for s in sorted({s for s, _, _ in r["files"]} - out)] if out else uuids
        if not marks:
            return self.spark.createDataFrame([], schema)
        name = self._table_name(runs)
        if not self.spark.catalog.tableExists(name):
            columns = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in schema)
            glob = "*{" + ",".join(sorted(marks)) + "}*"
            self.spark.sql(f"CREATE TABLE {name} ({columns}) USING parquet OPTIONS (path '{self.root}/runs', recursiveFileLookup 'true', pathGlobFilter '{glob}') CLUSTERED BY (`__slot`) INTO {runs[0]['slots']} BUCKETS")
        return self.spark.table(name)

    def _table_name(self, runs: list[dict]) -> str:
        parts = [self.root, *sorted(f"{r['path']}{r['without']}" for r in runs)]
        return "lc_state_" + hashlib.blake2b("|".join(parts).encode(), digest_size=12).hexdigest()

    def state(self, m: dict) -> DataFrame:
        """All runs of a version."""
        return self.table_over(m["runs"])

    def damaged(self, runs: list[dict]) -> set[int]:
        """Slots that miss a file of a run, or have one of another size."""
        lost = set()
        for r in runs:
            there = self.files.sizes(r["path"].removeprefix(f"{self.root}/"))
            lost |= {s for s, n, size in r["files"] if s not in r["without"] and there.get(n) != size}
        return lost

    def drop_run(self, r: dict) -> None:
        self.files.delete(r["path"])

    def drop_slot(self, m: dict, slot: int) -> None:
        """Lose one slot's files, as a failed machine would."""
        for r in m["runs"]:
            for s, n, _ in r["files"]:
                if s == slot:
                    self.files.delete(f"{r['path']}/{n}")

    @staticmethod
    def _listed(m: dict) -> list[dict]:
        return m["runs"] + (m["snapshot"] or {"runs": []})["runs"]

    def expire(self) -> int:
        """Delete manifests before the last ``keep`` ones and the runs, tables and snapshots that only they list; returns the runs deleted."""
        at = self.versions()
        old, kept = [self.manifest(v) for v in at[: -self.keep]], [self.manifest(v) for v in at[-self.keep :]]
        used = {r["path"] for m in kept for r in self._listed(m)}
        tables = {self._table_name(m["runs"]) for m in kept if m["runs"]}
        gone = set()
        for m in old:
            if m["runs"] and (name := self._table_name(m["runs"])) not in tables:
                self.spark.sql(f"DROP TABLE IF EXISTS {name}")
            gone |= {r["path"] for r in self._listed(m)} - used
        for path in gone:
            self.files.delete(path)
        for m in old:
            self.files.delete(f"{self.root}/manifests/v{m['version']:09d}.json")
        return len(gone)

    def keys_of(self, slots: set[int], total: int) -> list[int]:
        every = bucket_keys(total)
        return [every[s] for s in sorted(slots)]

    def retire_base(self) -> dict:
        """Note that the base may be dropped, as the state can stand for it; no file of the user's is touched."""
        return self.commit(self.manifest(), base_retired=True)

    def storage_report(self, base_path: str | None = None, view_path: str | None = None) -> dict[str, int]:
        """Bytes of state, snapshots, deltas, and of base and views where their paths are given."""
        m = self.manifest()
        size = lambda runs: sum(n for r in runs for s, _, n in r["files"] if s not in r["without"])
        out = {"state": size(m["runs"]), "snapshot": size((m["snapshot"] or {"runs": []})["runs"]), "deltas": sum(self.files.size(d) for d in m["deltas"]), "files": self.files.size(f"{self.root}/runs")}
        return out | ({"base": self.files.size(base_path)} if base_path else {}) | ({"views": self.files.size(view_path)} if view_path else {})


def cell_keys(spec: CubeSpec) -> list[str]:
    return ["cuboid_id", *spec.dims]


def slot_keys(spec: CubeSpec, kind: str) -> list[str]:
    """What identifies a row of the state within its slot."""
    return ["__slot", "__batch", *spec.dims] if kind == "input" else ["__slot", "cuboid_id", *spec.dims]
