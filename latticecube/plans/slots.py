"""Slots: which shuffle partitions belong to which chain, and where in them a row goes."""

from __future__ import annotations

import json
from collections.abc import Callable
from dataclasses import asdict, dataclass
from functools import lru_cache

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from latticecube import metrics
from latticecube.files import Files
from latticecube.plans.chains import Chain
from latticecube.spec import CubeSpec

Sampler = Callable[[DataFrame], DataFrame]


@dataclass(frozen=True)
class SlotPlan:
    """``widths[i]`` slots from ``starts[i]`` on belong to chain i; ``bounds[i]`` are its range boundaries, if any, as tuples of literals.

    ``heavy[i]`` has hashes of the partition keys of chain i that hold more rows than a slot should; their rows are dealt over all slots of the chain.
    """

    widths: tuple[int, ...]
    bounds: tuple[tuple | None, ...] = ()
    heavy: tuple[tuple[int, ...], ...] = ()

    @property
    def starts(self) -> tuple[int, ...]:
        return tuple(sum(self.widths[:i]) for i in range(len(self.widths)))

    @property
    def total(self) -> int:
        return sum(self.widths)

    @property
    def any_heavy(self) -> bool:
        return any(self.heavy)

    def heavy_of(self, i: int) -> tuple[int, ...]:
        return self.heavy[i] if self.heavy else ()

    def part(self, own: list[int]) -> SlotPlan:
        """The plan of some chains."""
        of = lambda x: tuple(x[i] for i in own) if x else ()
        return SlotPlan(of(self.widths), of(self.bounds), of(self.heavy))


@lru_cache(maxsize=8)
def bucket_keys(n: int) -> tuple[int, ...]:
    """For each of n buckets the least integer that Spark's bucket hash (Murmur3 of an int, seed 42) sends there."""
    found: dict[int, int] = {}
    at, step = 0, max(1024, 8 * n)
    with np.errstate(over="ignore"):
        while len(found) < n:
            x = np.arange(at, at + step, dtype=np.uint32)
            k = x * np.uint32(0xCC9E2D51)
            k = ((k << np.uint32(15)) | (k >> np.uint32(17))) * np.uint32(0x1B873593)
            h = np.uint32(42) ^ k
            h = ((h << np.uint32(13)) | (h >> np.uint32(19))) * np.uint32(5) + np.uint32(0xE6546B64)
            h ^= np.uint32(4)
            h = (h ^ (h >> np.uint32(16))) * np.uint32(0x85EBCA6B)
            h = (h ^ (h >> np.uint32(13))) * np.uint32(0xC2B2AE35)
            h ^= h >> np.uint32(16)
            buckets, first = np.unique(h.view(np.int32).astype(np.int64) % n, return_index=True)
            for b, i in zip(buckets.tolist(), first.tolist(), strict=True):
                found.setdefault(b, at + i)
            at += step
    return tuple(found[b] for b in range(n))


def allocate_slots(times: list[float], r: int) -> list[int]:
    """Split r slots in proportion to times: largest remainders, at least one each."""
    b = len(times)
    if r < b:
        raise ValueError(f"{r} slots for {b} chains: each chain needs one")
    total = sum(times)
    ideal = [r * t / total if total > 0 else r / b for t in times]
    out = [max(1, int(x)) for x in ideal]
    by_rest = sorted(range(b), key=lambda i: (int(ideal[i]) - ideal[i], i))
    i = 0
    while sum(out) < r:
        out[by_rest[i % b]] += 1
        i += 1
    while sum(out) > r:  # the floor of one gave out too many: take from where the surplus is largest
        out[max((j for j in range(b) if out[j] > 1), key=lambda j: out[j] - ideal[j])] -= 1
    return out


def even_slots(b: int, r: int) -> list[int]:
    return allocate_slots([1.0] * b, r)


# samplers for the profiling run


def systematic_sample(df: DataFrame, s: int) -> DataFrame:
    """Every s-th record of each input partition; nothing is shuffled."""
    return df.where(F.monotonically_increasing_id() % s == 0)


def hashed_sample(df: DataFrame, s: int) -> DataFrame:
    """One in s records by a hash of the row: the same rows whatever the partitions are."""
    return df.where(F.pmod(F.xxhash64(*df.columns), F.lit(s)) == 0)


def window_sample(df: DataFrame, ts_col: str, lo, hi) -> DataFrame:
    return df.where((F.col(ts_col) >= F.lit(lo)) & (F.col(ts_col) < F.lit(hi)))


def bernoulli_sample(df: DataFrame, fraction: float, seed: int = 1) -> DataFrame:
    return df.sample(fraction, seed)


def stratified_sample(df: DataFrame, col: str, fractions: dict, seed: int = 1) -> DataFrame:
    return df.sampleBy(col, fractions, seed)


@dataclass(frozen=True)
class ChainProfile:
    order: tuple[str, ...]
    seconds: float
    records: int


def profile_chains(df: DataFrame, spec: CubeSpec, chains: list[Chain], sampler: Sampler, repeats: int = 1) -> list[ChainProfile]:
    """Cube a sample with one slot for each chain and time each slot; the first pass warms up and doesn't count."""
    from latticecube.operators.materialize import materialize

    sample = sampler(df)
    plan = SlotPlan(tuple(1 for _ in chains))
    runs = []
    for i in range(repeats + 1):
        with metrics.watch(df.sparkSession) as seen:
            materialize(sample, spec, chains=chains, slots=plan).df.write.format("noop").mode("overwrite").save()
        if i:
            runs.append(seen.slots(len(chains)))
    out = []
    for c, chain in enumerate(chains):
        times = sorted(r[c][0] for r in runs)
        out.append(ChainProfile(chain.order, times[len(times) // 2], runs[-1][c][1]))
    return out


class ProfileStore:
    """Profiles of named jobs, kept for later runs: any number of slots can be allocated from one."""

    def __init__(self, spark, root: str):
        self.files = Files(spark, root)

    def load(self, job: str, chains: list[Chain]) -> list[ChainProfile] | None:
        """The newest profile of a job, if it is of the same chains."""
        names = self.files.names(f"profiles/{job}")
        if not names:
            return None
        found = [ChainProfile(tuple(p["order"]), p["seconds"], p["records"]) for p in json.loads(self.files.read(f"profiles/{job}/{names[-1]}"))]
        return found if [p.order for p in found] == [c.order for c in chains] else None

    def save(self, job: str, profile: list[ChainProfile]) -> None:
        n = len(self.files.names(f"profiles/{job}"))
        self.files.create(f"profiles/{job}/p{n + 1:06d}.json", json.dumps([asdict(p) for p in profile]))


def profiled_slots(df: DataFrame, spec: CubeSpec, chains: list[Chain], r: int, sampler: Sampler, kept: ProfileStore | None = None) -> list[int]:
    """Proportional allocation from a profile; where all times are 0, from the cells made.

    With ``kept`` the profile of an earlier run of the job (the spec's name) is used again, and a new one is stored.
    """
    profile = kept.load(spec.name, chains) if kept else None
    if profile is None:
        profile = profile_chains(df, spec, chains, sampler)
        if kept:
            kept.save(spec.name, profile)
    times = [p.seconds for p in profile]
    return allocate_slots(times if sum(times) > 0 else [float(p.records) for p in profile], r)


def model_slots(df: DataFrame, spec: CubeSpec, chains: list[Chain], r: int) -> list[int]:
    """Allocation without timing: a chain weighs its rows and the cells of its members, estimated in one pass."""
    base = spec.prepared(df)
    members = list(dict.fromkeys(m for c in chains for m in c.members))
    counts = base.agg(F.count("*").alias("n"), *[F.approx_count_distinct(F.struct(*sorted(m))).alias(f"c{i}") for i, m in enumerate(members)]).first()
    cells = {m: counts[f"c{i}"] for i, m in enumerate(members)}
    return allocate_slots([float(counts["n"] + sum(cells[m] for m in c.members)) for c in chains], r)


def range_bounds(df: DataFrame, spec: CubeSpec, chains: list[Chain], widths: list[int], sample_rows: int = 20_000) -> SlotPlan:
    """Boundaries over all partition dimensions of each chain, from a bounded sample; equal keys share a slot."""
    base = spec.prepared(df)
    total = max(1, base.count())
    sample = base.sample(min(1.0, sample_rows / total), 7)
    bounds = []
    for chain, width in zip(chains, widths, strict=True):
        key = F.struct(*chain.part_dims)
        cuts = sample.select(F.ntile(width).over(_by(key)).alias("t"), key.alias("k")).groupBy("t").agg(F.min("k").alias("lo")).where("t > 1").orderBy("t").collect()
        bounds.append(tuple(dict.fromkeys(tuple(r["lo"]) for r in cuts)))
    return SlotPlan(tuple(widths), tuple(bounds))


def _by(key: Column):
    from pyspark.sql import Window

    return Window.orderBy(key)


def heavy_keys(df: DataFrame, spec: CubeSpec, chains: list[Chain], widths: list[int], share: float = 1.0, sample_rows: int = 200_000) -> SlotPlan:
    """A plan that deals out heavy keys: those that hold more than ``share`` of an even slot's rows in a bounded sample.

    Any choice of keys gives right cells; a key that the sample misses only stays in one slot.
    """
    base = spec.prepared(df)
    total = max(1, base.count())
    rate = min(1.0, sample_rows / total)
    sample = base.sample(rate, 11) if rate < 1 else base
    keys = F.array(*[F.struct(F.lit(i).alias("chain"), _key_hash(c).alias("key")) for i, c in enumerate(chains)])
    counted = sample.select(F.explode(keys).alias("k")).groupBy("k.chain", "k.key").agg(F.count("*").alias("n"))
    least = F.element_at(F.array(*[F.lit(share * rate * total / w) for w in widths]), F.col("chain") + 1)
    found = counted.where(F.col("n") > least).collect()  # fewer than a slot each, so at most the slots' number
    return SlotPlan(tuple(widths), (), tuple(tuple(sorted(r["key"] for r in found if r["chain"] == i and widths[i] > 1)) for i in range(len(chains))))


def _key_hash(chain: Chain) -> Column:
    return F.xxhash64(*chain.part_dims)


def is_heavy(chain: Chain, heavy: tuple[int, ...] = ()) -> Column:
    return _key_hash(chain).isin(list(heavy)) if heavy else F.lit(False)


def slot_expr(chain: Chain, start: int, width: int, bounds: tuple | None = None, heavy: tuple[int, ...] = (), whole: list[str] | None = None) -> Column:
    """The chain's first slot plus a hash, or the range, of the partition dimensions.

    Heavy keys go by a hash of all the chain's dimensions, or of the ``whole`` row where the chain has no others.
    """
    if bounds is not None:
        key = F.struct(*chain.part_dims)
        above = sum((F.when(key >= F.struct(*[F.lit(x).alias(d) for x, d in zip(b, chain.part_dims, strict=True)]), 1).otherwise(0) for b in bounds), F.lit(0))
        own = F.least(above, F.lit(width - 1))
    else:
        own = F.pmod(_key_hash(chain), F.lit(width))
    if heavy:
        by = list(chain.order) if len(chain.order) > len(chain.part_dims) else (whole or list(chain.order))
        own = F.when(is_heavy(chain, heavy), F.pmod(F.xxhash64(F.lit(1), *by), F.lit(width))).otherwise(own)
    return (F.lit(start) + own).cast("int")
