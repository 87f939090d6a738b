"""Operator 9, benchmark decontamination by spaced-seed hashing; DataFrame functions only.

Fixed masks over ``SPAN`` consecutive words keep some positions and ignore the others, so a copied passage with single words
replaced still yields equal hashes.  Every window of every document is hashed under every mask inside one generated-code stage and
looked up among the benchmark's hashes; a hit fixes an alignment of an item with a document, along which equal words are counted.
An item is found in any of three ways: at least half of its words, and eight (all, if it is shorter), agree on one alignment; or
``LOCAL`` words agree within some ``LOCAL / SHARE`` words in a row of one alignment, which finds an excerpt of a longer item; or the
words that agree in the hits' own windows reach the first bar over all alignments of the item with the document, which finds a copy
with words inserted or deleted.  ``matched_words`` counts the best single alignment of the found items.

The seeds find less than the bar accepts.  Copies with words replaced at random places that meet the bar and have no hit, of 4,000 each:
10-word items 8.6 % with 2 words replaced; 15-word items 0.7 %, 8.5 % and 56 % with 3, 4 and 6; 30-word items 0.0 %, 0.1 % and 9.5 % with
6, 9 and 12; 45-word items 0.0 %, 0.0 % and 0.9 % with 9, 14 and 18.  A copy of an item of eleven words
or more with every third word replaced is always hit, wherever the replacing starts.

Items shorter than the span get a mask of their own length that ignores nothing; each distinct length below ``SPAN`` is one more mask.

Edge cases: words are maximal runs of anything but ASCII white space, in lower case; null and empty texts and items have none and are
clean; a document shorter than a mask has no window for it; rows that repeat an id are judged together; rows with a null id are
judged too, as one document per text; an empty benchmark leaves all clean.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

#: The seeds; 1 keeps a position, 0 ignores it.
MASKS = ("110110011", "101011101", "111001011", "110110110", "101111010", "100101111")
SPAN = 9
SHARE = 0.5
LEAST = 8
LOCAL = 13


def words_of(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[\x20\x09-\x0D]+"), lambda w: w != "")


def _seed(codes: Column, at: Column, mask: str, number: int) -> Column:
    return F.xxhash64(F.lit(number), *[F.get(codes, at + i) for i, keep in enumerate(mask) if keep == "1"])


def seeds(rows: DataFrame, masks: tuple[str, ...], id_column: str) -> DataFrame:
    """``id, at, mask, seed`` for each window and mask of ``rows(id, words)``, mask being its number; a word is hashed once, not once a window."""
    least = min(len(m) for m in masks)
    coded = rows.where(F.size("words") >= least).select(id_column, F.transform("words", lambda w: F.xxhash64(w)).alias("codes"))
    placed = coded.select(id_column, "codes", F.explode(F.sequence(F.lit(0), F.size("codes") - least)).alias("at"))
    each = F.array(*[F.when(F.col("at") + len(m) <= F.size("codes"), _seed(F.col("codes"), F.col("at"), m, i)) for i, m in enumerate(masks)])
    return placed.select(id_column, "at", F.posexplode(each).alias("mask", "seed")).where(F.col("seed").isNotNull())


def overlaps(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """``doc, item_id, matched``: items found, with the best alignment's count, doc being ``struct(doc_id, text hash of rows without id)``."""
    items = common.written(benchmark.select(F.col("item_id").cast("long").alias("item_id"), words_of(F.col("text")).alias("words")).where(F.size("words") > 0), "items")
    short = sorted(r["n"] for r in items.select(F.size("words").alias("n")).where(F.col("n") < SPAN).distinct().collect())  # at most SPAN - 1 values
    masks = (*MASKS, *("1" * n for n in short))
    # a long item doesn't need the masks of short ones, but they do no harm: the overlap decides
    wanted = common.written(seeds(items, masks, "item_id").select("seed", "item_id", "mask", F.col("at").alias("item_at")).distinct(), "seeds")
    key = F.struct(F.col("doc_id").cast("long").alias("doc_id"), F.when(F.col("doc_id").isNull(), F.xxhash64("text")).alias("null_key"))
    rows = docs.select(key.alias("doc"), words_of(F.col("text").cast("string")).alias("words"))
    # hits of the masks of short items fix alignments, but are too short to add up
    spot = F.when(F.col("mask") < len(MASKS), F.col("item_at"))
    hits = seeds(rows, masks, "doc").drop("mask").join(common.small_side(wanted), "seed").select("doc", "item_id", (F.col("at") - F.col("item_at")).alias("start"), spot.alias("spot"))
    hits = hits.groupBy("doc", "item_id", "start").agg(F.collect_set("spot").alias("spots"))
    hits = common.written(hits, "hits")
    found = common.written(hits.select("doc").distinct(), "hit-docs")
    texts = rows.join(common.small_side(found), "doc", "left_semi")
    both = hits.join(texts, "doc").join(items.select("item_id", F.col("words").alias("item")), "item_id")
    agree = F.filter(F.sequence(F.lit(0), F.size("item") - 1), lambda i: F.coalesce(F.when(F.col("start") + i >= 0, F.get("words", F.col("start") + i)) == F.get("item", i), F.lit(False)))
    placed = both.select("doc", "item_id", "spots", agree.alias("agree"), F.size("item").alias("n"))
    bar = F.greatest(F.ceil(F.col("n") * SHARE), F.least(F.lit(LEAST), F.col("n")))
    dense = F.exists(F.sequence(F.lit(0), F.size("agree") - LOCAL), lambda k: F.get("agree", k + (LOCAL - 1)) - F.get("agree", k) < int(LOCAL / SHARE))
    alone = (F.size("agree") >= bar) | F.when(F.size("agree") >= LOCAL, dense).otherwise(False)
    near = F.filter("agree", lambda i: F.exists("spots", lambda a: (i >= a) & (i < a + SPAN)))
    counted = placed.select("doc", "item_id", F.size("agree").alias("matched"), alone.alias("alone"), near.alias("near"), bar.alias("bar"))
    # equal sets are added once, so a passage repeated many times stays small
    added = counted.groupBy("doc", "item_id").agg(F.max("matched").alias("matched"), F.bool_or("alone").alias("alone"), F.size(F.array_distinct(F.flatten(F.collect_set("near")))).alias("total"), F.first("bar").alias("bar"))
    return added.where(F.col("alone") | (F.col("total") >= F.col("bar"))).select("doc", "item_id", "matched")


def contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """``doc_id, n_items, matched_words, contaminated`` of every row of docs."""
    found = overlaps(docs, benchmark).groupBy("doc").agg(F.count_distinct("item_id").alias("n_items"), F.max("matched").cast("long").alias("matched_words"))
    found = common.written(found, "contaminated")
    key = F.struct(F.col("doc_id").cast("long").alias("doc_id"), F.when(F.col("doc_id").isNull(), F.xxhash64("text")).alias("null_key"))
    rows = docs.select(key.alias("doc"))
    out = rows.join(common.small_side(found), "doc", "left")
    return out.select("doc.doc_id", F.coalesce("n_items", F.lit(0)).cast("long").alias("n_items"), F.coalesce("matched_words", F.lit(0)).cast("long").alias("matched_words"), F.col("n_items").isNotNull().alias("contaminated"))


def clean(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of docs that no benchmark item is found in, with their columns."""
    found = common.written(overlaps(docs, benchmark).select("doc").distinct(), "contaminated")
    key = F.struct(F.col("doc_id").cast("long").alias("doc_id"), F.when(F.col("doc_id").isNull(), F.xxhash64("text")).alias("null_key"))
    own = common.free_name(docs, "doc")
    return docs.withColumn(own, key).join(common.small_side(found.withColumnRenamed("doc", own)), own, "left_anti").drop(own)


def oracle() -> str:
    """By SQL, over all windows of all documents, for items of ``SPAN`` words or more; excerpts and shifted copies below the first bar are not in it."""
    split = r"list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[\x20\x09-\x0D]+'), lambda w: w <> '')"
    key = lambda m: "list_value(" + ", ".join(f"words[pos + {i + 1}]" for i, c in enumerate(m) if c == "1") + ")"
    windows = lambda table, key_column: " UNION ALL ".join(f"SELECT {key_column}, pos, {i} AS mask, {key(m)} AS seed FROM (SELECT *, unnest(range(0, len(words) - {SPAN - 1})) AS pos FROM {table} WHERE len(words) >= {SPAN})" for i, m in enumerate(MASKS))
    return f"""
WITH d AS (SELECT doc_id, {split} AS words FROM documents),
b AS (SELECT item_id, {split} AS words FROM benchmark),
ds AS ({windows('d', 'doc_id')}),
bs AS (SELECT DISTINCT item_id, pos, mask, seed FROM ({windows('b', 'item_id')})),
h AS (SELECT DISTINCT ds.doc_id, bs.item_id, ds.pos - bs.pos AS start FROM ds JOIN bs ON ds.mask = bs.mask AND ds.seed = bs.seed),
m AS (SELECT h.doc_id, h.item_id, len(b.words) AS n,
             len(list_filter(range(0, len(b.words)), lambda i: h.start + i >= 0 AND d.words[h.start + i + 1] = b.words[i + 1])) AS matched
      FROM h JOIN d USING (doc_id) JOIN b USING (item_id)),
f AS (SELECT doc_id, count(DISTINCT item_id) AS n_items, max(matched) AS matched_words FROM m
      WHERE matched >= ceil(n * {SHARE}) AND matched >= least({LEAST}, n) GROUP BY doc_id)
SELECT d.doc_id, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items, CAST(coalesce(matched_words, 0) AS BIGINT) AS matched_words, n_items IS NOT NULL AS contaminated
FROM d LEFT JOIN f USING (doc_id)
"""
