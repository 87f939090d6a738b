"""The aggregate registry: how each function is kept as a state, merged and finished.

``kind`` says which state works: "state" functions keep a few columns that merge by plain aggregates; "frequency" functions need each
distinct value with its count, so the value itself becomes part of the compressed rows.  ``classification`` of STDDEV, CORR and REGR
may be "algebraic" (they merge) or "paper" (counted as holistic and refused by incremental maintenance).

Moments are kept as counts, means and sums of squared deviations from the mean, made by Spark's own functions and merged around the mean of the
merged rows, so values far from zero lose no digits.  An own aggregate without a merge is made from raw rows only.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

FREQUENCY = {"median", "percentile", "mode", "count_distinct"}
MOMENTS = {"stddev", "variance"}
PAIRS = {"corr", "regr_slope", "regr_intercept", "regr_r2"}
PLAIN = {"sum", "count", "min", "max", "avg"}
SKETCHES = {"approx_distinct", "approx_median"}


@dataclass(frozen=True)
class UserAgg:
    """An own aggregate: column expressions for the state, its merge and its end; without merge it is recompute-only."""

    init: Callable[[Column], dict[str, Column]]
    merge: Callable[[str], Column] | None
    final: Callable[..., Column]


@dataclass(frozen=True)
class Agg:
    fn: str
    measure: str | None = None
    second: str | None = None
    alias: str | None = None
    p: float = 0.5
    classification: str = "algebraic"
    user: UserAgg | None = None

    def __post_init__(self):
        if self.fn not in FREQUENCY | MOMENTS | PAIRS | PLAIN | SKETCHES | {"user"}:
            raise ValueError(f"no aggregate {self.fn}")
        if (self.fn in PAIRS) != (self.second is not None):
            raise ValueError(f"{self.fn}: two measures are for correlation and regression only")
        if self.measure is None and self.fn != "count":
            raise ValueError(f"{self.fn} needs a measure")
        if self.fn == "user" and self.user is None:
            raise ValueError("an own aggregate needs its expressions")

    @property
    def name(self) -> str:
        return self.alias or "_".join(x for x in (self.fn, self.measure, self.second) if x)

    @property
    def measures(self) -> list[str]:
        return [m for m in (self.measure, self.second) if m]

    @property
    def kind(self) -> str:
        return "frequency" if self.fn in FREQUENCY else "state"

    @property
    def numeric(self) -> bool:
        return self.fn in MOMENTS | PAIRS | {"sum", "avg", "median", "percentile", "approx_median"}

    @property
    def raw_only(self) -> bool:
        """Whether the aggregate has no state that merges, so that every cell needs its raw rows."""
        return self.fn == "user" and self.user.merge is None

    @property
    def incremental(self) -> bool:
        """Whether old and new states merge into the state of the union."""
        if self.fn in FREQUENCY:
            return False
        if self.fn in MOMENTS | PAIRS:
            return self.classification == "algebraic"
        return self.fn != "user" or self.user.merge is not None

    # state columns: name -> (aggregate over raw rows, aggregate over states)

    def states(self) -> dict[str, tuple[Column, Column]]:
        x = F.col(f"m_{self.measure}") if self.measure else None
        s = lambda part: f"s_{self.name}_{part}"
        add = lambda part, e: {s(part): (F.sum(e), F.sum(s(part)))}
        tally = lambda part, e: {s(part): (F.count(e), F.sum(s(part)))}
        if self.fn == "sum":
            return add("sum", x)
        if self.fn == "count":
            return tally("n", F.lit(1) if x is None else x)
        if self.fn in ("min", "max"):
            f = F.min if self.fn == "min" else F.max
            return {s(self.fn): (f(x), f(s(self.fn)))}
        if self.fn == "avg":
            return add("sum", x) | tally("n", x)
        if self.fn in MOMENTS:
            d = x.cast("double")
            return tally("n", x) | self._centre("mean", F.avg(d)) | self._spread("m2", F.var_pop(d) * F.count(x), "mean", "mean")
        if self.fn in PAIRS:
            y = F.col(f"m_{self.second}").cast("double")
            a = F.when(y.isNotNull(), x.cast("double"))
            b = F.when(x.isNotNull(), y)
            n = F.count(a)
            return (
                tally("n", a) | self._centre("x", F.avg(a)) | self._centre("y", F.avg(b)) | self._spread("xx", F.var_pop(a) * n, "x", "x")
                | self._spread("yy", F.var_pop(b) * n, "y", "y") | self._spread("xy", F.covar_pop(a, b) * n, "x", "y")
            )
        if self.fn == "approx_distinct":
            return {s("hll"): (F.hll_sketch_agg(x), F.hll_union_agg(s("hll")))}
        if self.fn == "approx_median":
            return {s("kll"): (F.kll_sketch_agg_double(x.cast("double")), F.kll_merge_agg_double(s("kll")))}
        if self.fn == "user":
            return {s(k): (e, self.user.merge(s(k)) if self.user.merge else None) for k, e in self.user.init(x).items()}
        return {}

    def _centre(self, part: str, of_raw: Column) -> dict[str, tuple[Column, Column]]:
        own, n = f"s_{self.name}_{part}", F.col(f"s_{self.name}_n")
        return {own: (of_raw, F.sum(n * F.col(own)) / F.sum(F.when(n > 0, n)))}

    def _spread(self, part: str, of_raw: Column, p: str, q: str) -> dict[str, tuple[Column, Column]]:
        """A sum of products of deviations from the means p and q, moved to the means of the merged rows."""
        own, n = f"s_{self.name}_{part}", F.col(f"s_{self.name}_n")
        off = lambda m: F.col(f"s_{self.name}_{m}") - F.col(f"g_{self.name}_{m}")
        return {own: (of_raw, F.sum(F.col(own) + n * off(p) * off(q)))}

    def centres(self) -> dict[str, tuple[Column, Column]]:
        """Means of the merged rows that deviations are moved to, as a sum over a sum: name -> (summed above, summed below)."""
        if self.fn not in MOMENTS | PAIRS:
            return {}
        n = F.col(f"s_{self.name}_n")
        return {f"g_{self.name}_{m}": (n * F.col(f"s_{self.name}_{m}"), F.when(n > 0, n)) for m in (("mean",) if self.fn in MOMENTS else ("x", "y"))}

    def final(self) -> Column:
        """The value of a cell from its merged states."""
        c = lambda part: F.col(f"s_{self.name}_{part}")
        if self.fn in PLAIN - {"avg"}:
            return c({"sum": "sum", "count": "n"}.get(self.fn, self.fn))
        if self.fn == "avg":
            return F.when(c("n") > 0, c("sum") / c("n"))
        if self.fn in MOMENTS:
            variance = F.greatest(F.lit(0.0), c("m2")) / (c("n") - 1)
            return F.when(c("n") > 1, F.sqrt(variance) if self.fn == "stddev" else variance)
        if self.fn in PAIRS:
            xx, yy, xy = c("xx"), c("yy"), c("xy")
            if self.fn == "corr":
                return F.when((xx > 0) & (yy > 0), xy / F.sqrt(xx * yy))
            # regr_*(measure, second): the first is the dependent variable, as in SQL
            if self.fn == "regr_slope":
                return F.when(yy > 0, xy / yy)
            if self.fn == "regr_intercept":
                return F.when(yy > 0, c("x") - xy / yy * c("y"))
            return F.when(yy > 0, F.when(xx > 0, xy * xy / (xx * yy)).otherwise(F.lit(1.0)))
        if self.fn == "approx_distinct":
            return F.hll_sketch_estimate(c("hll"))
        if self.fn == "approx_median":
            return F.kll_sketch_get_quantile_double(c("kll"), F.lit(0.5))
        if self.fn == "user":
            return self.user.final(*[F.col(k) for k in self.states()])
        return F.col(self.name)

    def from_frequencies(self) -> Column:
        """The aggregate over a cell's rows of distinct values ``m_…`` with their counts ``__cnt`` and, where values are ranked, ``upto_…`` and ``all_…``."""
        x = F.col(f"m_{self.measure}")
        if self.fn in ("median", "percentile"):
            upto, n = F.col(f"upto_{self.measure}"), F.col(f"all_{self.measure}")
            place = (n - 1) * F.lit(float(0.5 if self.fn == "median" else self.p))
            lo, hi = F.floor(place), F.ceil(place)
            at = lambda i: F.max(F.when(x.isNotNull() & (upto - F.col("__cnt") <= i) & (i < upto), x.cast("double")))
            place, lo, hi, low, high = F.max(place), F.max(lo), F.max(hi), at(lo), at(hi)
            return F.when((lo == hi) | (low == high), low).otherwise((hi - place) * low + (place - lo) * high)
        if self.fn == "count_distinct":
            return F.count_distinct(x)
        return F.max(F.when(x.isNotNull(), F.struct(F.col("__cnt"), x.alias("v")))).getField("v")  # mode: the largest of the most frequent
