"""Connected components of an edge table by alternating large-star and small-star steps.

Each step sends every node's neighbours to their least one; no step gathers a node's neighbours in one row,
the minimum of a large neighbourhood is pre-aggregated before it is shuffled, and the edges of a node with very many
neighbours meet that minimum by broadcast, where they lie.  Repeated edges are one edge.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

MAX_STEPS = 60


def _with_least(pairs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """pairs(u, v) with m, the least of u's neighbours and u; and the table of u, m."""
    least = common.written(pairs.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("size")).select("u", F.least("u", "m").alias("m"), "size"), "least")
    return common.join_by_key(pairs, least, "u", "size").drop("size"), least


def _toward_least(pairs: DataFrame) -> DataFrame:
    """The small step: connect every v, and u, with the least of u's neighbours and u."""
    met, least = _with_least(pairs)
    out = met.select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v")))
    return out.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """``node, component`` (the least node reachable) for every node of an edge; self-loops and repeats are harmless."""
    now = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct()
    now = common.written(now, "edges")
    seen = None
    for _ in range(MAX_STEPS):
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        met, _ = _with_least(both)
        large = common.written(met.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct(), "large")
        now = common.written(_toward_least(large), "edges")
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if seen == tuple(mark):
            break
        seen = tuple(mark)
    else:
        raise RuntimeError("components did not settle")
    roots = now.select(F.col("v").alias("node")).distinct()
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(roots.select("node", F.col("node").alias("component")))
