"""What a cube is asked for: dimensions, aggregates, cuboids, derived columns and a filter."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from latticecube.functions.aggregates import Agg


@dataclass(frozen=True)
class CubeSpec:
    """A cube request.

    ``cuboids`` lists dimension subsets for a partial cube (all non-empty ones if None); ``include_all`` adds the grand total.
    ``derived`` maps new column names to SQL expressions or columns; ``where`` filters the base before anything else.
    """

    dims: tuple[str, ...]
    aggs: tuple[Agg, ...]
    cuboids: tuple[frozenset[str], ...] | None = None
    include_all: bool = False
    derived: dict[str, str | Column] = field(default_factory=dict)
    where: str | None = None
    name: str = "cube"

    def __post_init__(self):
        if len(set(self.dims)) != len(self.dims) or not self.dims:
            raise ValueError("dimensions must be distinct and at least one")
        names = [a.name for a in self.aggs]
        if not names or len(set(names)) != len(names) or set(names) & set(self.dims) or "cuboid_id" in (*names, *self.dims):
            raise ValueError("aggregate names must be distinct and differ from the dimensions and cuboid_id")
        for c in self.cuboids or ():
            if not c or not c <= set(self.dims):
                raise ValueError(f"no such cuboid: {sorted(c)}")
        if any(a.fn == "mode" for a in self.aggs) and len(self.holistic_measures()) > 1:
            raise ValueError("MODE needs the only frequency measure of a cube")
        if self.raw_only() and any(a.fn == "mode" for a in self.aggs):
            raise ValueError("MODE and an own aggregate without a merge can't be in one cube")

    # cuboid ids follow grouping_id: the leftmost dimension is the most significant bit, 1 means rolled up

    def cuboid_id(self, members) -> int:
        n = len(self.dims)
        return sum(1 << (n - 1 - i) for i, d in enumerate(self.dims) if d not in members)

    def members(self, cuboid_id: int) -> frozenset[str]:
        n = len(self.dims)
        return frozenset(d for i, d in enumerate(self.dims) if not cuboid_id >> (n - 1 - i) & 1)

    def wanted(self) -> list[frozenset[str]]:
        if self.cuboids is not None:
            return list(dict.fromkeys(self.cuboids))
        return [self.members(i) for i in range((1 << len(self.dims)) - 1)]

    def holistic_measures(self) -> list[str]:
        return list(dict.fromkeys(a.measure for a in self.aggs if a.kind == "frequency"))

    def raw_only(self) -> bool:
        """Whether some aggregate needs raw rows, so that nothing may be compressed on the way."""
        return any(a.raw_only for a in self.aggs)

    def mergeable(self) -> bool:
        return all(a.kind != "frequency" and a.incremental for a in self.aggs)

    def countable(self) -> bool:
        """Whether old and new cells merge if frequency functions keep each value with its count."""
        return all(a.kind == "frequency" or a.incremental for a in self.aggs)

    def validate(self, schema: T.StructType) -> None:
        """Raise unless every needed column exists and has a type that works."""
        have = {f.name: f.dataType for f in schema}
        for d in self.dims:
            if d not in have:
                raise ValueError(f"no dimension column {d}")
            if isinstance(have[d], (T.MapType, T.VariantType)):
                raise ValueError(f"a {have[d].simpleString()} can't be a dimension: {d}")
        for a in self.aggs:
            for m in a.measures:
                if m not in have:
                    raise ValueError(f"no measure column {m}")
                if a.numeric and not isinstance(have[m], T.NumericType):
                    raise ValueError(f"{a.fn} needs a numeric measure: {m}")

    def prepared(self, df: DataFrame) -> DataFrame:
        """Filter, derive, and prune to the columns that the cube reads."""
        if self.where:
            df = df.where(self.where)
        for name, e in self.derived.items():
            df = df.withColumn(name, F.expr(e) if isinstance(e, str) else e)
        self.validate(df.schema)
        measures = list(dict.fromkeys(m for a in self.aggs for m in a.measures))
        return df.select(*self.dims, *[F.col(m).alias(f"m_{m}") for m in measures])

    def output_columns(self) -> list[str]:
        return ["cuboid_id", *self.dims, *[a.name for a in self.aggs]]
