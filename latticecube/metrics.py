"""Cost measures: wall time, shuffled and read data, time of each slot.

Stage and task figures come from Spark's status store, which is a developer API; everything that touches it is here.  Where it can't be read, ``watch``
raises: figures are never silently empty.
"""

from __future__ import annotations

import contextlib
import re
import statistics
import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession


@dataclass
class Seen:
    """What the stages that ran inside a ``watch`` did."""

    seconds: float = 0.0
    stages: list[dict] = field(default_factory=list)
    timers: dict[str, float] = field(default_factory=dict)

    def total(self, key: str) -> int:
        return sum(s[key] for s in self.stages)

    def shuffle_cost(self) -> dict[str, int]:
        return {"records": self.total("shuffle_records"), "bytes": self.total("shuffle_bytes")}

    def read_cost(self) -> dict[str, int]:
        return {"records": self.total("input_records"), "bytes": self.total("input_bytes")}

    def breakdown(self) -> dict[str, float]:
        """Task seconds by part of a batch's cost: shuffle (write, wait), sort, write of the result, and processing (the rest); garbage; bytes spilled.

        Sort and write times are the plan's own SQL metrics.
        """
        shuffle, run = (self.total("shuffle_write_ms") + self.total("fetch_wait_ms")) / 1e3, self.total("run_ms") / 1e3
        sort, write = self.timers.get("sort time", 0.0), self.timers.get("task commit time", 0.0)
        return {"shuffle_s": shuffle, "sort_s": sort, "write_s": write, "process_s": max(0.0, run - shuffle - sort - write), "gc_s": self.total("gc_ms") / 1e3, "spilled": self.total("spilled"), "written_bytes": self.total("output_bytes")}

    def slots(self, n: int) -> list[tuple[float, int]]:
        """``(seconds, records read)`` of each task of the stage with n tasks that read most from a shuffle."""
        own = [s for s in self.stages if len(s["tasks"]) == n and s["shuffle_read"] > 0] or [s for s in self.stages if len(s["tasks"]) == n]
        if not own:
            return [(0.0, 0)] * n
        best = max(own, key=lambda s: s["shuffle_read"])
        return [(t["run_ms"] / 1e3, t["read"]) for t in sorted(best["tasks"], key=lambda t: t["index"])]


def _stages(spark: SparkSession):
    store = spark.sparkContext._jsc.sc().statusStore()
    gateway = spark.sparkContext._gateway
    none = gateway.jvm.java.util.ArrayList()
    seq = store.stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), none)
    return store, [seq.apply(i) for i in range(seq.size())]


def _ids(spark: SparkSession) -> set[tuple[int, int]]:
    return {(s.stageId(), s.attemptId()) for s in _stages(spark)[1]}


def _queries(spark: SparkSession) -> int:
    return spark._jsparkSession.sharedState().statusStore().executionsCount()


def _seconds(text: str) -> float:
    """The first duration in a metric's text, as Spark prints it: a total, then least, median and most in brackets."""
    found = re.search(r"([\d.,]+) (ms|s|m|h)\b", text)
    return float(found[1].replace(",", "")) * {"ms": 1e-3, "s": 1.0, "m": 60.0, "h": 3600.0}[found[2]] if found else 0.0


def _timers(spark: SparkSession, after: int) -> dict[str, float]:
    """Seconds by name of the SQL time metrics of queries since: "sort time", "task commit time" and so on."""
    store = spark._jsparkSession.sharedState().statusStore()
    out: dict[str, float] = {}
    for i in range(after, store.executionsCount()):
        run = store.executionsList(i, 1)
        if run.isEmpty():
            continue
        values, listed = store.executionMetrics(run.head().executionId()), run.head().metrics()
        for j in range(listed.size()):
            m = listed.apply(j)
            if m.metricType() in ("timing", "nsTiming"):
                text = values.get(m.accumulatorId())
                if text.isDefined():
                    out[m.name()] = out.get(m.name(), 0.0) + _seconds(text.get())
    return out


@contextlib.contextmanager
def watch(spark: SparkSession):
    """Collect the figures of all stages that run inside."""
    before, queries_before, seen, began = _ids(spark), _queries(spark), Seen(), time.perf_counter()
    yield seen
    seen.seconds = time.perf_counter() - began
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(60_000)
    store, stages = _stages(spark)
    for s in stages:
        if (s.stageId(), s.attemptId()) in before or s.numCompleteTasks() == 0:
            continue
        tasks = []
        listed = store.taskList(s.stageId(), s.attemptId(), s.numTasks() + s.numFailedTasks() + s.numKilledTasks())
        if listed.size() < s.numCompleteTasks():
            raise RuntimeError("tasks of a stage are no longer in the status store: raise spark.ui.retainedTasks")
        for i in range(listed.size()):
            t = listed.apply(i)
            m = t.taskMetrics()
            if m.isDefined():
                m = m.get()
                r = m.shuffleReadMetrics()
                tasks.append({"index": t.index(), "run_ms": m.executorRunTime(), "read": r.recordsRead()})
        seen.stages.append({
            "id": s.stageId(), "tasks": tasks, "run_ms": s.executorRunTime(), "gc_ms": s.jvmGcTime(), "fetch_wait_ms": s.shuffleFetchWaitTime(), "spilled": s.diskBytesSpilled(),
            "shuffle_write_ms": s.shuffleWriteTime() / 1e6, "output_bytes": s.outputBytes(), "output_records": s.outputRecords(),
            "shuffle_records": s.shuffleWriteRecords(), "shuffle_bytes": s.shuffleWriteBytes(), "shuffle_read": s.shuffleReadRecords(), "input_records": s.inputRecords(), "input_bytes": s.inputBytes(),
        })
    seen.timers = _timers(spark, queries_before)


def drain(df: DataFrame) -> None:
    """Compute all rows and keep none."""
    df.write.format("noop").mode("overwrite").save()


def timed(fn, repeats: int = 3) -> dict[str, float]:
    """Mean and least wall seconds of so many runs."""
    took = []
    for _ in range(repeats):
        began = time.perf_counter()
        fn()
        took.append(time.perf_counter() - began)
    return {"mean": statistics.mean(took), "min": min(took), "repeats": repeats}


def slot_balance(slots: list[tuple[float, int]], widths: list[int], band_s: float = 10.0, share: float = 0.25) -> dict:
    """How even slots are: share of them within a band of seconds, and within a share of the median; largest over mean; mean by chain."""
    times, reads = [t for t, _ in slots], [n for _, n in slots]
    mid, mid_n = statistics.median(times), statistics.median(reads)
    by_chain, at = [], 0
    for w in widths:
        by_chain.append(statistics.mean(times[at : at + w]))
        at += w
    return {
        "in_band": sum(abs(t - mid) <= band_s / 2 for t in times) / len(times),
        "near_median_time": sum(abs(t - mid) <= share * mid for t in times) / len(times),
        "near_median_records": sum(abs(n - mid_n) <= share * mid_n for n in reads) / len(reads),
        "max_over_mean_time": max(times) / max(1e-9, statistics.mean(times)),
        "max_over_mean_records": max(reads) / max(1e-9, statistics.mean(reads)),
        "chain_mean_s": by_chain,
    }


def overhead(with_cache: float, without: float) -> float:
    return (with_cache - without) / without


def scaleup(points: list[tuple[int, float]]) -> list[dict[str, float]]:
    """Speed-up over the first point and efficiency of each ``(cores, seconds)``; efficiency 1 is linear."""
    if not points:
        return []
    c0, t0 = points[0]
    return [{"cores": c, "seconds": t, "speedup": t0 / t, "efficiency": t0 * c0 / (t * c)} for c, t in points]


def exchanges(df: DataFrame) -> int:
    """Exchanges of the planned query."""
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange ")
