"""Operator 4, mixing sources to target weights by hierarchical budgeting; DataFrame functions only.

The tree is domain - language - source.  Each node's capacity is the number of tokens (words) under it times the epochs allowed.  The root's
budget goes down level by level: children share it by weight, but none gets more than its capacity; what such a child
leaves goes to its siblings by weight.  As a parent never gets more than its own capacity, a shortage is made up among siblings first, and
reaches the parent's siblings only if the whole subtree is short.  The share of a level is closed: in the order of capacity over
weight, the first children are filled, and the rest split what is left by weight.

A leaf takes its budget from seeded epochs: in each, its documents are in the order of a keyed hash of their ids, and the tokens of
that stream are taken from the front; the last document may give only its first words.  The running totals are made of two window passes,
over hash buckets and within each, so that no task holds a leaf.

Edge cases: nulls in domain, language or source are values of their own (the empty string); null and empty texts have no tokens and are
never taken; children that the weights don't name get weight 0 and are used only when all others are full; a budget above the
capacity takes everything; rows that share an id follow each other in order of their token count; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

LEVELS = ("domain", "lang", "source")
#: Documents of a leaf that share a hash bucket, about.
BUCKET_ROWS = 1_000
#: Weight of a child that the weights don't name: used only when named ones are full.
LEFTOVER = 1e-9


def tokens(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(common.WORD_CLASS)), F.lit(0)).cast("long")


def weight_of(level: str, weights: dict) -> Column:
    """Weights by value; ``None`` as a key is the weight of any other value."""
    out = F.lit(float(weights.get(None, LEFTOVER)))
    for value, w in weights.items():
        if value is not None:
            out = F.when(F.col(level) == value, F.lit(float(max(w, LEFTOVER)))).otherwise(out)
    return out


def share_out(children: DataFrame, parent: list[str]) -> DataFrame:
    """Add ``budget`` to ``children(…, w, cap, parent_budget)``: shares by weight w, at most cap, short ones made up by siblings."""
    ratio = F.col("cap") / F.col("w")
    order = Window.partitionBy(*parent).orderBy("ratio", *[c for c in LEVELS if c in children.columns]) if parent else Window.orderBy("ratio", *[c for c in LEVELS if c in children.columns])
    upto = order.rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy(*parent) if parent else Window.partitionBy()
    steps = children.withColumn("ratio", ratio)
    steps = steps.withColumn("cap_before", F.coalesce(F.sum("cap").over(upto), F.lit(0))).withColumn("w_before", F.coalesce(F.sum("w").over(upto), F.lit(0.0))).withColumn("w_all", F.sum("w").over(whole))
    level = (F.col("parent_budget") - F.col("cap_before")) / F.greatest(F.col("w_all") - F.col("w_before"), F.lit(1e-300))
    # a child is filled while the level that its successors would share is above its own ratio
    steps = steps.withColumn("level", level).withColumn("full", F.col("level") >= F.col("ratio"))
    open_level = F.min(F.when(~F.col("full"), F.struct(F.col("ratio"), F.col("level")))).over(whole)
    budget = F.when(F.col("full"), F.col("cap")).otherwise(F.least(F.col("cap"), F.floor(F.col("w") * F.col("open.level") + 1e-6))).cast("long")
    return steps.withColumn("open", open_level).withColumn("budget", budget).drop("ratio", "cap_before", "w_before", "w_all", "level", "full", "open")


def budgets(leaves: DataFrame, total: Column, weights: dict[str, dict], epochs: int) -> DataFrame:
    """``domain, lang, source, n_docs, n_tokens, budget`` from ``leaves(domain, lang, source, n_docs, n_tokens)``."""
    caps = leaves.withColumn("cap", F.col("n_tokens") * epochs)
    node = None
    for depth, level in enumerate(LEVELS):
        path = list(LEVELS[: depth + 1])
        own = caps.groupBy(*path).agg(F.sum("cap").alias("cap")).withColumn("w", weight_of(level, weights.get(level, {None: 1.0})))
        if node is None:
            own = own.withColumn("parent_budget", F.least(F.sum("cap").over(Window.partitionBy()), total).cast("long"))
        else:
            own = own.join(node.select(*path[:-1], F.col("budget").alias("parent_budget")), path[:-1])
        node = share_out(own, path[:-1]).drop("w", "cap", "parent_budget")
    return leaves.join(node, list(LEVELS))


def counted(docs: DataFrame, domain: Column) -> DataFrame:
    text = lambda c: F.coalesce(c.cast("string"), F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text(domain).alias("domain"), text(F.col("lang")).alias("lang"), text(F.col("source")).alias("source"), tokens(F.col("text")).alias("n_tokens"))


def order_key(seed: int, epoch: Column, doc_id: Column) -> Column:
    return F.md5(F.concat_ws(":", F.lit(str(seed)), epoch.cast("string"), F.coalesce(doc_id.cast("string"), F.lit(""))).cast("binary"))


def mix(docs: DataFrame, weights: dict[str, dict], share: float, domain: Column, epochs: int = 1, seed: int = 17) -> DataFrame:
    """``doc_id, epoch, domain, lang, source, n_tokens, take_tokens``: what a mix of share times all tokens is made of."""
    rows = common.written(counted(docs, domain).where("n_tokens > 0"), "counted")
    leaves = rows.groupBy(*LEVELS).agg(F.count("*").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"))
    leaves = common.written(leaves, "leaves")
    total = F.floor(F.sum("n_tokens").over(Window.partitionBy()) * F.lit(share))
    planned = common.written(budgets(leaves, F.lit(leaves.select(total.alias("t")).agg(F.max("t")).first()[0] or 0), weights, epochs).where("budget > 0"), "budgets")
    n_leaves = planned.count()
    side = common.small_side(planned.select(*LEVELS, "n_docs", F.col("n_tokens").alias("leaf_tokens"), "budget"), n_leaves)
    # the epochs that a leaf's budget reaches into, and the key of each document in each of them
    last = F.ceil(F.col("budget") / F.col("leaf_tokens")).cast("int")
    spread = rows.join(side, list(LEVELS)).withColumn("epoch", F.explode(F.sequence(F.lit(0), last - 1)))
    spread = spread.withColumn("key", order_key(seed, F.col("epoch"), F.col("doc_id")))
    parts = F.greatest(F.lit(1), F.ceil(F.col("n_docs") / BUCKET_ROWS))
    place = F.conv(F.substring("key", 1, 8), 16, 10).cast("double") / F.lit(float(1 << 32))
    spread = spread.withColumn("bucket", F.floor(place * parts).cast("long"))
    group = [*LEVELS, "epoch"]
    sums = spread.groupBy(*group, "bucket").agg(F.sum("n_tokens").alias("s"))
    before = sums.withColumn("base", F.coalesce(F.sum("s").over(Window.partitionBy(*group).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("s")
    inner = Window.partitionBy(*group, "bucket").orderBy("key", "n_tokens").rowsBetween(Window.unboundedPreceding, -1)
    run = spread.withColumn("inner", F.coalesce(F.sum("n_tokens").over(inner), F.lit(0))).join(before, [*group, "bucket"])
    at = F.col("epoch") * F.col("leaf_tokens") + F.col("base") + F.col("inner")
    taken = F.least(F.col("n_tokens"), F.col("budget") - at).cast("long")
    return run.withColumn("take_tokens", taken).where("take_tokens > 0").select("doc_id", "epoch", *LEVELS, "n_tokens", "take_tokens")


def oracle(weights: dict[str, dict], share: float, domain_sql: str, epochs: int, seed: int) -> str:
    """The same by SQL: budgets level by level, then one running total for each leaf and epoch."""

    def weight(level: str) -> str:
        w = weights.get(level, {None: 1.0})
        cases = " ".join(f"WHEN {level} = '{v}' THEN CAST({max(x, LEFTOVER)!r} AS DOUBLE)" for v, x in w.items() if v is not None)
        rest = f"CAST({float(w.get(None, LEFTOVER))!r} AS DOUBLE)"
        return f"CASE {cases} ELSE {rest} END" if cases else rest

    ctes, parent = [], None
    for depth, level in enumerate(LEVELS):
        path, up = ", ".join(LEVELS[: depth + 1]), ", ".join(LEVELS[:depth])
        part = f"PARTITION BY {up}" if up else ""
        grand = "(SELECT CAST(least(sum(cap), floor(sum(n_tokens) * {share})) AS BIGINT) FROM leaf)".format(share=share)
        source = f"SELECT c.*, p.budget AS pb FROM (SELECT {path}, sum(cap) AS cap FROM leaf GROUP BY {path}) c JOIN b{depth - 1} p USING ({up})" if up else f"SELECT {path}, sum(cap) AS cap, {grand} AS pb FROM leaf GROUP BY {path}"
        ctes.append(f"""c{depth} AS (SELECT *, {weight(level)} AS w FROM ({source})),
r{depth} AS (SELECT *, cap / w AS ratio, coalesce(sum(cap) OVER (u ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS cb, coalesce(sum(w) OVER (u ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS wb, sum(w) OVER ({part}) AS wa FROM c{depth} WINDOW u AS ({part} ORDER BY cap / w, {path})),
l{depth} AS (SELECT *, (pb - cb) / greatest(wa - wb, 1e-300) AS lv FROM r{depth}),
o{depth} AS (SELECT *, min(CASE WHEN lv < ratio THEN {{'r': ratio, 'l': lv}} END) OVER ({part}) AS op FROM l{depth}),
b{depth} AS (SELECT {path}, CAST(CASE WHEN lv >= ratio THEN cap ELSE least(cap, floor(w * op.l + 1e-6)) END AS BIGINT) AS budget FROM o{depth})""")
        parent = f"b{depth}"
    return f"""
WITH d AS (SELECT doc_id, coalesce({domain_sql}, '') AS domain, coalesce(lang, '') AS lang, coalesce(source, '') AS source,
                  len(regexp_extract_all(coalesce(text, ''), '{common.WORD_CLASS}')) AS n_tokens FROM documents),
leaf AS (SELECT domain, lang, source, CAST(sum(n_tokens) AS BIGINT) AS n_tokens, CAST(sum(n_tokens) * {epochs} AS BIGINT) AS cap FROM d WHERE n_tokens > 0 GROUP BY ALL),
{", ".join(ctes)},
e AS (SELECT d.*, leaf.n_tokens AS leaf_tokens, budget, unnest(range(0, CAST(ceil(budget / leaf.n_tokens) AS BIGINT))) AS epoch
      FROM d JOIN leaf USING (domain, lang, source) JOIN {parent} USING (domain, lang, source) WHERE d.n_tokens > 0 AND budget > 0),
t AS (SELECT *, CAST(least(n_tokens, budget - epoch * leaf_tokens - coalesce(sum(n_tokens) OVER (PARTITION BY domain, lang, source, epoch
        ORDER BY md5('{seed}:' || epoch || ':' || coalesce(CAST(doc_id AS VARCHAR), '')), n_tokens ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS BIGINT) AS take_tokens FROM e)
SELECT doc_id, CAST(epoch AS INTEGER) AS epoch, domain, lang, source, CAST(n_tokens AS BIGINT) AS n_tokens, take_tokens FROM t WHERE take_tokens > 0
"""
