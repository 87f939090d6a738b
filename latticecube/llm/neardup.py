"""Operator 8, near-duplicates by bottom-k sketches from one hash function.

1. Each text becomes the set of hashes of its distinct five-word shingles; the k least hashes are its sketch.
   Texts of equal sets are one class, stood for by the smallest id; what follows is about classes.
2. The retained values are an inverted index.  Values are ordered by the number of classes that retain
   them.  Two sets of similarity 0.75 share at least t of their retained values, so they share at least ``OVERLAPS`` of
   the values that are left when each drops its t - ``OVERLAPS`` most frequent ones.  Passages that many texts
   hold are thereby dropped from most lists, and texts with too few shared values from all.
3. First every class is compared with the best-overlapping of the hubs of its lists, a list's hub being the member with the
   least share of values of its own; this links the bulk of a large group without its pairs.  For members of crowded lists
   that are still apart, whole sets are indexed: the hubs are chosen once more, from exact shares, and a pair counts only if
   what follows its first common value, in the order of rising frequency, can still reach 3/7 (n1 + n2).  Other lists give
   pairs only if they hold more than one component, and only pairs from different components.
4. The sketch of the union of two sets estimates their similarity and filters; the exact Jaccard of the
   full sets, made again from the texts, decides.

t is exact for sets of up to 3k/4 shingles.  For larger ones the number of shared values in the union's sketch is hypergeometric
and t lies ``SIGMAS`` standard deviations under its mean, so a pair at the very threshold is lost with a probability of about 1e-8.

Edge cases: null, empty and blank texts have no shingles, are their own component and kept; fewer words than five make one shingle;
rows that share an id are one vertex, through which their texts are in one component, and each row has its own text's number of shingles;
a row with a null id links with nothing, has a null component and is kept; an empty table gives an empty result.  (Different texts of a
repeated id get numbers above the largest id inside; ids up to 2**62 leave room for these.)  ``survivors`` judges texts, not ids: of each
component of texts one row stays, so no text is lost by an id that it shares with another.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common, graph

WORDS = 5
SKETCH = 64
OVERLAPS = 4
#: Members from which on an open list's texts are looked at whole before it gives pairs.
CROWD = 32
#: Sets of a crowd up to which a value counts as the members' own.
RARE = 16
SIGMAS = 6.0
#: What a worker remembers of words at most: so many, none longer than that.
MEMO_ENTRIES, MEMO_WORD = 400_000, 64
NUM, DEN = 75, 100

#: Odd multipliers of the shingle hash, one for each word position.
_POSITION = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD], np.uint64)

_words: dict[bytes, int] = {}


def _mixed(x: np.ndarray, salt: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = x + np.uint64(salt)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def shingle_set(text: str | None) -> np.ndarray:
    """The sorted distinct 64-bit hashes (signed) of a text's shingles."""
    words = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    if not words:
        return np.zeros(0, np.int64)
    if len(_words) > MEMO_ENTRIES:
        _words.clear()
    try:
        hashes = np.fromiter(map(_words.__getitem__, words), np.uint64, len(words))
    except KeyError:
        import xxhash

        for w in words:
            if w not in _words and len(w) <= MEMO_WORD:
                _words[w] = xxhash.xxh3_64_intdigest(w)
        hashes = np.fromiter((_words[w] if len(w) <= MEMO_WORD else xxhash.xxh3_64_intdigest(w) for w in words), np.uint64, len(words))
    width = min(WORDS, len(words))
    n = len(words) - width + 1
    with np.errstate(over="ignore"):
        sums = hashes[:n] * _POSITION[0]
        for j in range(1, width):
            # mixing between positions, so that no linear relation among words survives
            sums = _mixed(sums, j) + hashes[j : j + n] * _POSITION[j]
    return np.unique(_mixed(sums, width).view(np.int64))


def sketches(docs: DataFrame, k: int = SKETCH) -> DataFrame:
    """``doc_id, n, f1, f2, sketch``: set size, a 128-bit fingerprint of the set, and its k least values."""

    def make(batches):
        common.claim("shingles", _words.clear)
        for batch in batches:
            for part in common.slices(batch):
                ns, f1, f2, least = [], [], [], []
                for text in part.column(1).to_pylist():
                    s = shingle_set(text)
                    u = s.view(np.uint64)
                    ns.append(len(s))
                    f1.append(int(_mixed(u, 0x51ED).sum(dtype=np.uint64).view(np.int64)))
                    f2.append(int(_mixed(u, 0xA5A5F00D).sum(dtype=np.uint64).view(np.int64)))
                    least.append(s[:k])
                ends = np.concatenate([[0], np.cumsum([len(x) for x in least])]).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(least) if least else np.zeros(0, np.int64)))
                yield pa.record_batch([part.column(0), pa.array(ns, pa.int32()), pa.array(f1, pa.int64()), pa.array(f2, pa.int64()), lists], ["doc_id", "n", "f1", "f2", "sketch"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return common.arrow_map(rows, make, "doc_id long, n int, f1 long, f2 long, sketch array<long>")


def full_sets(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """``doc_id, items`` of the listed documents, made anew from their texts."""

    def make(batches):
        common.claim("shingles", _words.clear)
        for batch in batches:
            for part in common.slices(batch):
                sets = [shingle_set(t) for t in part.column(1).to_pylist()]
                ends = np.concatenate([[0], np.cumsum([len(x) for x in sets])]).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(sets) if sets else np.zeros(0, np.int64)))
                yield pa.record_batch([part.column(0), lists], ["doc_id", "items"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return common.arrow_map(rows.join(common.small_side(ids), "doc_id", "left_semi"), make, "doc_id long, items array<long>")


def least_shared(n, k: int):
    """t: how many retained values a set of n shingles shares at least with any set of similarity 0.75."""
    exact = F.ceil(n * NUM / DEN)
    union = n * DEN / NUM
    mean = k * NUM / DEN
    spread = F.sqrt(F.greatest(F.lit(0.0), k * (NUM / DEN) * (1 - NUM / DEN) * (1 - (k - 1) / F.greatest(union - 1, F.lit(float(k))))))
    sure = F.lit(k) - F.ceil(n / 3)
    likely = F.floor(mean - SIGMAS * spread) - 1
    return F.when(n <= k * NUM // DEN, exact).otherwise(F.least(exact, F.greatest(F.lit(1), sure, likely))).cast("int")


def shared_lists(classes: DataFrame, k: int) -> DataFrame:
    """``value, rep, n, need, alone``: the lists of the index that can lead to a link, need of which a pair must share.

    alone is the share of a class's retained values that no other class retains.
    """
    values = classes.select("rep", "n", F.explode("sketch").alias("value"))
    counts = common.written(values.groupBy("value").agg(F.count("*").alias("df")).where("df > 1"), "counts")
    shared = common.join_by_key(values, counts, "value", "df")
    t = least_shared(F.col("n"), k)
    per = shared.groupBy("rep", "n").agg(F.sort_array(F.collect_list(F.struct("df", "value"))).alias("by_df"))  # at most k of a class
    per = per.withColumn("need", F.least(F.lit(OVERLAPS), t))
    single = F.least(F.lit(k), F.col("n")) - F.size("by_df")  # values of this class alone come first
    left = F.least(F.lit(k), F.col("n")) - t + F.col("need") - single
    alone = (single / F.least(F.lit(k), F.col("n"))).alias("alone")
    return per.where(left > 0).select(F.explode(F.slice("by_df", F.lit(1), left)).alias("x"), "rep", "n", "need", alone).select("x.value", "rep", "n", "need", "alone")


def _estimated(pairs: DataFrame, classes: DataFrame, k: int) -> DataFrame:
    """Keep pairs whose union sketch allows a similarity of 0.75."""
    of = lambda side: classes.select(F.col("rep").alias(side), F.col("n").alias(f"n_{side}"), F.col("sketch").alias(f"s_{side}"))
    both = pairs.join(of("a"), "a").join(of("b"), "b")
    union = F.slice(F.array_sort(F.array_union("s_a", "s_b")), 1, k)
    both = both.withColumn("shared", F.size(F.array_intersect(union, F.array_intersect("s_a", "s_b")))).withColumn("seen", F.size(union))
    whole = (F.col("n_a") <= k) & (F.col("n_b") <= k) & (F.col("seen") < k)
    return both.where(F.when(whole, F.col("shared") * DEN >= F.col("seen") * NUM).otherwise(F.col("shared") >= least_shared(F.greatest("n_a", "n_b"), k))).select("a", "b")


def _verified(pairs: DataFrame, docs: DataFrame, sets: DataFrame | None = None) -> DataFrame:
    """Keep pairs whose full sets have an exact similarity of 0.75 or more."""
    if sets is None:
        ids = common.written(pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")).distinct(), "ids")
        sets = common.written(full_sets(docs, ids), "sets")
    of = lambda side: sets.select(F.col("doc_id").alias(side), F.col("items").alias(f"s_{side}"))
    both = pairs.join(of("a"), "a").join(of("b"), "b")
    shared = F.size(F.array_intersect("s_a", "s_b"))
    return both.withColumn("i", shared).where(F.col("i") * DEN >= (F.size("s_a") + F.size("s_b") - F.col("i")) * NUM).select("a", "b").distinct()


def _toward_hubs(lists: DataFrame, classes: DataFrame | None, docs: DataFrame, k: int, apart: bool = False, sets: DataFrame | None = None) -> DataFrame:
    """Verified links of each class with the hub it overlaps most: of a list, the member with the least share of values of its own."""
    hubs = common.written(lists.groupBy("value").agg(F.min(F.struct("alone", "rep", *(["comp"] if apart else []))).alias("hub"), F.count("*").alias("size")), "hubs")
    toward = common.join_by_key(lists, hubs, "value", "size").where(F.col("rep") != F.col("hub.rep"))
    if apart:
        toward = toward.where(F.col("comp") != F.col("hub.comp"))
    toward = toward.groupBy("rep", F.col("hub.rep").alias("hub"), "need").agg(F.count("*").alias("c")).where("c >= need")
    best = toward.groupBy("rep").agg(F.max_by("hub", F.struct("c", -F.col("hub"))).alias("hub")).select(F.col("rep").alias("a"), F.col("hub").alias("b"))
    if classes is not None:
        best = _estimated(best, classes, k)
    return common.written(_verified(common.written(best, "pairs"), docs, sets), "links")


def _still_open(lists: DataFrame, found: DataFrame) -> DataFrame:
    """The lists whose members are in more than one component, with ``comp`` of each member."""
    found = common.written(found, "components")
    rest = [F.col(c) for c in lists.columns if c != "comp"]
    placed = common.written(lists.join(found, lists["rep"] == found["node"], "left").select(*rest, F.coalesce("component", "rep").alias("comp")), "placed")
    mixed = placed.groupBy("value").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count("*").alias("size")).where("lo <> hi")
    return common.join_by_key(placed, common.written(mixed.select("value", "size"), "mixed"), "value", "size", "left_semi")


def _whole_lists(sets: DataFrame) -> DataFrame:
    """``value, rep, n, pos, need, alone``: an index of whole sets, each in the order of rising frequency.

    Two sets of similarity 0.75 share one of their first n - 0.75 n + 1 values; only these are kept.
    pos counts all values before, alone is the share of values that at most ``RARE`` sets have.
    """
    values = sets.select(F.col("doc_id").alias("rep"), F.explode("items").alias("value"))
    counts = common.written(values.groupBy("value").agg(F.count("*").alias("df")), "counts")
    ordered = common.join_by_key(values, counts, "value", "df").groupBy("rep").agg(F.sort_array(F.collect_list(F.struct("df", "value"))).alias("by_df"))
    n = F.size("by_df")
    rare = F.size(F.filter("by_df", lambda x: x.df <= RARE))
    first = F.slice("by_df", F.lit(1), n - F.ceil(n * NUM / DEN).cast("int") + 1)
    kept = ordered.select("rep", n.alias("n"), (rare / n).alias("alone"), F.posexplode(first).alias("pos", "x")).where("x.df > 1")
    return kept.select("x.value", "rep", "n", "pos", F.lit(1).alias("need"), "alone")


def _within_bound(lists: DataFrame) -> DataFrame:
    """Pairs of an index of whole sets that may reach the similarity: the values from their first common one on must suffice."""
    of = lambda side: lists.select("value", *(F.col(c).alias(f"{c}_{side}") for c in ("rep", "n", "pos", "comp")))
    rest = F.least(F.col("n_a") - F.col("pos_a"), F.col("n_b") - F.col("pos_b"))
    met = of("a").join(of("b"), "value").where((F.col("rep_a") < F.col("rep_b")) & (F.col("comp_a") != F.col("comp_b")) & (rest * (NUM + DEN) >= (F.col("n_a") + F.col("n_b")) * NUM))
    return met.select(F.col("rep_a").alias("a"), F.col("rep_b").alias("b")).distinct()


def _linked(docs: DataFrame, k: int, more_links: DataFrame | None = None) -> DataFrame:
    """``doc_id, n, component`` of every row of docs, whose ids are distinct or null."""
    made = common.written(sketches(docs, k), "sketches")
    has = made.where("n > 0 AND doc_id IS NOT NULL")
    classes = common.written(has.groupBy("n", "f1", "f2").agg(F.min("doc_id").alias("rep"), F.first("sketch").alias("sketch")), "classes")
    lists = common.written(shared_lists(classes, k), "lists")

    # hubs first: each class against the hub that it overlaps most
    links = _toward_hubs(lists, classes, docs, k)
    lists = common.written(_still_open(lists, graph.components(links)), "open")

    # members of crowded lists that are still open: whole sets, hubs nearer to the group's middle, then a positional bound
    crowded = common.written(lists.groupBy("value").agg(F.count("*").alias("size")).where(F.col("size") >= CROWD), "crowded")
    crowd = common.written(common.join_by_key(lists, crowded, "value", "size", "left_semi").select(F.col("rep").alias("doc_id")).distinct(), "crowd")
    if not crowd.isEmpty():
        sets = common.written(full_sets(docs, crowd), "sets")
        whole = common.written(_whole_lists(sets), "whole")
        comps = graph.components(links)
        links = links.union(_toward_hubs(common.written(_still_open(whole, comps), "still"), None, docs, k, apart=True, sets=sets))
        pairs = common.written(_within_bound(_still_open(whole, graph.components(links))), "pairs")
        links = links.union(_verified(pairs, docs, sets))
        lists = common.written(lists.join(common.small_side(crowd.select(F.col("doc_id").alias("rep"), F.lit(True).alias("crowd"))), "rep", "left"), "marked")
    else:
        lists = lists.withColumn("crowd", F.lit(None).cast("boolean"))

    # then the pairs that the hubs left apart, one of which at least is in no crowded list: its lists are all shorter than CROWD,
    # and only these lists are joined
    own = lists.where(F.col("crowd").isNull())
    short = common.written(lists.join(own.select("value").distinct(), "value", "left_semi"), "short")
    of = lambda side, rows: rows.select("value", *(F.col(c).alias(f"{c}_{side}") for c in ("rep", "n", "need", "comp", "crowd")))
    similar = F.least("n_a", "n_b") * DEN >= F.greatest("n_a", "n_b") * NUM
    once = (F.col("rep_a") < F.col("rep_b")) | F.col("crowd_b").isNotNull()
    apart = of("a", short.where(F.col("crowd").isNull())).join(of("b", short), "value").where((F.col("rep_a") != F.col("rep_b")) & once & (F.col("comp_a") != F.col("comp_b")) & similar)
    pairs = apart.groupBy(F.least("rep_a", "rep_b").alias("a"), F.greatest("rep_a", "rep_b").alias("b")).agg(F.count("*").alias("c"), F.min(F.least("need_a", "need_b")).alias("need")).where("c >= need").select("a", "b")
    more = _verified(common.written(_estimated(pairs, classes, k), "pairs"), docs)

    reps = classes.select("n", "f1", "f2", "rep")
    links = links.union(more)
    if more_links is not None:
        rep_of = made.select("doc_id", "n", "f1", "f2").join(reps, ["n", "f1", "f2"], "left").select(F.col("doc_id").alias("x"), F.coalesce("rep", "doc_id").alias("y"))
        ends = more_links.join(rep_of.withColumnsRenamed({"x": "a", "y": "ra"}), "a").join(rep_of.withColumnsRenamed({"x": "b", "y": "rb"}), "b")
        links = links.union(ends.select("ra", "rb"))
    found = graph.components(links)
    placed = reps.join(found, reps["rep"] == found["node"], "left").select("n", "f1", "f2", F.coalesce("component", "rep").alias("component"))
    out = made.select("doc_id", "n", "f1", "f2").join(placed, ["n", "f1", "f2"], "left").select("doc_id", "n", "component")
    if more_links is not None:
        # texts without shingles are nodes of their own
        alone = found.select(F.col("node").alias("doc_id"), F.col("component").alias("through"))
        out = out.join(alone, "doc_id", "left").select("doc_id", "n", F.coalesce("component", "through").alias("component"))
    return out.select("doc_id", "n", F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id")).alias("component"))


def _numbered(docs: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """Rows ``doc_id, text`` with distinct ids, and ``doc_id, text, number`` of the rows whose id was repeated (None if there are none).

    The first text of a repeated id keeps the id, the others get numbers above the largest one.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    known = rows.where(F.col("doc_id").isNotNull())
    again = common.written(known.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1"), "repeated")
    if again.isEmpty():
        return rows, None
    twins = known.join(common.small_side(again.select("doc_id")), "doc_id", "left_semi")
    largest = known.agg(F.max("doc_id")).first()[0]
    texts = twins.groupBy("doc_id", "text").agg(F.lit(1).alias("one"))
    first = texts.groupBy("doc_id").agg(F.min(F.struct(F.xxhash64("text").alias("h"), F.col("text"))).alias("first"))
    numbered = texts.join(first, "doc_id").withColumn("number", F.when(F.col("text").eqNullSafe(F.col("first.text")), F.col("doc_id")).otherwise(F.lit(largest + 1) + F.monotonically_increasing_id()))
    numbered = common.written(numbered.select("doc_id", "text", "number"), "numbered")
    rest = rows.join(common.small_side(again.select("doc_id")), "doc_id", "left_anti")
    return rest.unionByName(numbered.select(F.col("number").alias("doc_id"), "text")), numbered


def near_duplicates(docs: DataFrame, k: int = SKETCH) -> DataFrame:
    """``doc_id, n_shingles, component_id, kept`` of every row of ``docs(doc_id, text)``."""
    rows, numbered = _numbered(docs)
    links = None if numbered is None else numbered.where("number <> doc_id").select(F.col("doc_id").alias("a"), F.col("number").alias("b"))
    out = _linked(rows, k, links)
    if numbered is not None:
        own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
        back = common.written(numbered.join(common.written(out, "linked").withColumnRenamed("doc_id", "number"), "number").select("doc_id", "text", "n", "component"), "back")
        same = own["doc_id"].eqNullSafe(back["doc_id"]) & own["text"].eqNullSafe(back["text"])
        twins = own.join(common.small_side(back), same).select(own["doc_id"], "n", "component")
        out = out.join(common.small_side(numbered.select(F.col("number").alias("doc_id"))), "doc_id", "left_anti").unionByName(twins)
    component = F.col("component")
    return out.select("doc_id", F.col("n").cast("long").alias("n_shingles"), component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))


def survivors(docs: DataFrame, k: int = SKETCH) -> DataFrame:
    """The rows of docs that stay, with all their columns: one of each component of texts, and all without shingles or without an id."""
    rows, numbered = _numbered(docs)
    gone_id, twin_id, twin_text = (common.free_name(docs, n) for n in ("gone_id", "twin_id", "twin_text"))
    gone = common.written(_linked(rows, k).where("doc_id IS NOT NULL AND component <> doc_id").select(F.col("doc_id").alias(gone_id)), "gone")
    left = lambda df: df.join(common.small_side(gone), df["doc_id"].cast("long") == gone[gone_id], "left_anti")
    if numbered is None:
        return left(docs)
    ids = common.small_side(numbered.select(F.col("doc_id").alias(twin_id)).distinct())
    single = left(docs.join(ids, docs["doc_id"].cast("long") == ids[twin_id], "left_anti"))
    stay = numbered.join(common.small_side(gone), numbered["number"] == gone[gone_id], "left_anti").select(F.col("doc_id").alias(twin_id), F.col("text").alias(twin_text))
    twins = docs.join(common.small_side(stay), docs["doc_id"].cast("long").eqNullSafe(stay[twin_id]) & docs["text"].cast("string").eqNullSafe(stay[twin_text]))
    return single.unionByName(twins.dropDuplicates([twin_id, twin_text]).drop(twin_id, twin_text))
