"""Cells with a state of one's own: the counts of each value of a cell, kept between micro-batches.

Spark's stateful aggregation holds all values of a cell for MEDIAN; here each distinct value is one entry of the cell's state, so a batch
touches only the entries of its own values.  Exact, and incremental for functions that don't merge.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from latticecube.operators import materialize as M
from latticecube.spec import CubeSpec

PROVIDER = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def weighted_median(counts: list[tuple[float, int]]) -> float | None:
    """The median of values with their counts; the mean of the middle two where the number is even."""
    counts = sorted(counts)
    n = sum(k for _, k in counts)
    if not n:
        return None
    lo = hi = None
    seen = 0
    for value, k in counts:
        seen += k
        if lo is None and 2 * seen >= n:
            lo = value
        if 2 * seen > n:
            hi = value
            break
    return (lo + hi) / 2


class FrequencyCells(StatefulProcessor):
    """Adds a batch's counts to each cell's state and gives the cell's new median."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.counts = handle.getMapState("counts", "value double", "n long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        for part in rows:
            for value, k in part.dropna(subset=["value"]).groupby("value").size().items():
                at = (float(value),)
                old = self.counts.getValue(at)[0] if self.counts.containsKey(at) else 0
                self.counts.updateValue(at, (int(old) + int(k),))
        found = [(v[0], k[0]) for v, k in self.counts.iterator()]
        yield pd.DataFrame({"cell": [key[0]], "median": [weighted_median(found)], "n": [sum(k for _, k in found)]})

    def close(self) -> None:
        pass


def state_cube(source: DataFrame, spec: CubeSpec, measure: str) -> DataFrame:
    """``cell, median, n`` of each cell that a batch changes; ``cell`` is ``cuboid_id`` and the dimensions as JSON.

    Null measures make a cell but don't count; run it in update mode.  The session's state store must be RocksDB (``PROVIDER``).
    """
    ids = F.array(*[F.lit(spec.cuboid_id(m)) for m in spec.wanted()])
    rows = source.select(*spec.dims, F.col(measure).cast("double").alias("value"), F.explode(ids).alias("cuboid_id"))
    cell = F.to_json(F.struct("cuboid_id", *M.masked(spec, F.col("cuboid_id"))))
    schema = T.StructType([T.StructField("cell", T.StringType()), T.StructField("median", T.DoubleType()), T.StructField("n", T.LongType())])
    return rows.select(cell.alias("cell"), "value").groupBy("cell").transformWithStateInPandas(FrequencyCells(), schema, "Update", "None")
