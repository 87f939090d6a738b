"""Operator 7, toxicity by a counterfactual-regularised linear classifier.

A text is the set of its words and of their beginnings of ``PREFIXES`` letters.  Informative members of that set are picked from the
labelled sample by how much more often either class has them; a logistic model over them is fitted with two penalties: on squared
weights, and on the squared score change between a labelled text and its counterfactual, in which identity terms are swapped for
others of their group.  The same is asked of a bare mention of each term, so a neutral mention does not move the score.

Training reads at most about ``PER_CLASS`` labelled documents of each class that are not held out, picked by a hash of the id; both classes
weigh alike.  This bound is a parameter.  Scoring reads every whole text.

Edge cases: null and empty texts get the model's base score; with nothing to learn from, or one class only, every score is 0 or 1 as
that class says (0 if there is none); null ids count as held out and are scored; labels that are null or repeated with both values are not learned from.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: Identity terms by group; a counterfactual takes the next term of the group.
IDENTITY = {
    "faith": ["muslim", "christian", "jewish", "hindu", "buddhist", "sikh", "atheist", "catholic"],
    "origin": ["african", "asian", "european", "american", "arab", "latino", "mexican", "chinese", "indian", "german", "french", "spanish"],
    "colour": ["black", "white", "brown"],
    "gender": ["women", "men"],
    "person": ["woman", "man"],
    "orientation": ["gay", "straight", "lesbian", "bisexual", "heterosexual", "homosexual"],
    "age": ["old", "young", "elderly"],
    "ability": ["disabled", "deaf", "blind", "autistic"],
    "status": ["immigrants", "refugees", "citizens", "migrants"],
}
SWAP = {term: group[(i + 1) % len(group)] for group in IDENTITY.values() for i, term in enumerate(group)}
PREFIXES = (3, 4, 5, 6, 7)
PER_CLASS = 3_000
FEATURES = 800
MEMO_ENTRIES = 400_000

_word = re.compile(r"\w+").findall


def words(text: str | None) -> set[str]:
    return set(_word(text.lower())) if text else set()


def parts(word: str) -> list[str]:
    """A word and its beginnings; the mark tells a beginning from a whole word."""
    word = word[:64]
    return [word, *(word[:n] + "~" for n in PREFIXES if len(word) > n)]


def text_features(found: set[str]) -> set[str]:
    return {p for w in found for p in parts(w)}


def counterfactual(found: set[str]) -> set[str] | None:
    """The words with identity terms swapped; None where there is none."""
    if not any(w in SWAP for w in found):
        return None
    return {SWAP.get(w, w) for w in found}


class Model:
    def __init__(self, names: list[str], weights: np.ndarray, bias: float):
        self.place = {n: i for i, n in enumerate(names)}
        self.weights, self.bias = weights, bias
        self.memo: dict[str, tuple[int, ...]] = {}

    def indices(self, word: str) -> tuple[int, ...]:
        if (got := self.memo.get(word)) is None:
            if len(self.memo) > MEMO_ENTRIES:
                self.memo.clear()
            place = self.place
            got = self.memo[word] = tuple(place[p] for p in parts(word) if p in place)
        return got

    def present(self, found: set[str]) -> set[int]:
        out: set[int] = set()
        for w in found:
            if got := self.indices(w):
                out.update(got)
        return out

    def score(self, text: str | None) -> float:
        z = self.bias + float(sum(self.weights[i] for i in self.present(words(text))))
        return float(1 / (1 + np.exp(-np.clip(z, -40, 40))))


def fit(x: np.ndarray, y: np.ndarray, weight: np.ndarray, pairs: np.ndarray, ridge: float = 3e-4, fairness: float = 2.0, steps: int = 12) -> tuple[np.ndarray, float]:
    """Logistic weights by Newton steps; pairs holds the feature differences between texts and their counterfactuals."""
    n = x.shape[1]
    x1 = np.hstack([x, np.ones((len(x), 1), np.float32)])
    weight = (weight / weight.sum()).astype(np.float32)
    penalty = np.zeros((n + 1, n + 1))
    penalty[:n, :n] = ridge * np.eye(n) + fairness * (pairs.T @ pairs) / max(1, len(pairs))
    penalty[n, n] = 1e-9
    w = np.zeros(n + 1)
    share = float(np.clip(np.average(y, weights=weight), 1e-6, 1 - 1e-6))
    w[n] = np.log(share / (1 - share))

    def loss(v):
        z = np.clip(x1 @ v.astype(np.float32), -60, 60)
        return float((weight * (np.logaddexp(0, z) - y * z)).sum() + 0.5 * v @ penalty @ v)

    now = loss(w)
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x1 @ w.astype(np.float32), -60, 60)))
        bend = (weight * np.maximum(p * (1 - p), 1e-6)).astype(np.float32)
        step = np.linalg.solve((x1.T @ (bend[:, None] * x1)).astype(np.float64) + penalty, x1.T @ (weight * (p - y)) + penalty @ w)
        size = 1.0
        while (then := loss(w - size * step)) > now and size > 1e-3:
            size /= 2
        done = now - then < 1e-7
        w, now = w - size * step, min(now, then)
        if done:
            break
    return w[:n], float(w[n])


def train(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS, features: int = FEATURES) -> Model:
    spark = docs.sparkSession
    usable = labels.where(~common.held_out()).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min("toxic").alias("lo"), F.max("toxic").alias("hi")).where("lo = hi").select("doc_id", (F.col("lo") != 0).cast("int").alias("toxic"))
    counts = {r["toxic"]: r["n"] for r in usable.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    if len(counts) < 2:
        return Model([], np.zeros(0), 40.0 if 1 in counts else -40.0)
    place = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) / F.lit(float(1 << 30))
    share = {c: min(1.0, per_class / n) for c, n in counts.items()}
    picked = usable.withColumn("place", place).where(F.col("place") < F.when(F.col("toxic") == 1, share[1]).otherwise(share[0])).orderBy("place", "doc_id").limit(4 * per_class).select("doc_id", "toxic")

    def found(batches):
        for batch in batches:
            for part in common.slices(batch, 64):
                sets = [words(t) for t in part.column(1).to_pylist()]
                lists = [sorted(text_features(s)) for s in sets]
                other = [None if (c := counterfactual(s)) is None else sorted(text_features(c)) for s in sets]
                yield pa.record_batch([part.column(0), pa.array(lists, pa.list_(pa.string())), pa.array(other, pa.list_(pa.string()))], ["toxic", "own", "other"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    # the sample is bounded by its parameter, so it may be broadcast
    sample = common.written(common.arrow_map(rows.join(F.broadcast(picked), "doc_id").select("toxic", "text"), found, "toxic int, own array<string>, other array<string>"), "toxic-sample")
    n = {r["toxic"]: r["n"] for r in sample.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    if len(n) < 2:
        return Model([], np.zeros(0), 40.0 if 1 in n else -40.0)
    tally = sample.select("toxic", F.explode("own").alias("f")).groupBy("f").agg(F.sum("toxic").alias("bad"), F.sum(1 - F.col("toxic")).alias("good"))
    gain = F.abs(F.sqrt(F.col("bad") / n[1]) - F.sqrt(F.col("good") / n[0]))
    names = [r["f"] for r in tally.where("bad + good >= 5").orderBy(gain.desc(), "f").limit(features).collect()]
    names += [p for p in sorted({p for t in SWAP for p in parts(t)}) if p not in set(names)]
    model = Model(names, np.zeros(len(names)), 0.0)
    keep = spark.sparkContext.broadcast(model.place)

    def narrow(batches):
        for batch in batches:
            place = keep.value
            at = lambda v: None if v is None else [place[f] for f in v if f in place]  # noqa: B023, E731
            yield pa.record_batch([batch.column(0), pa.array(map(at, batch.column(1).to_pylist()), pa.list_(pa.int32())), pa.array(map(at, batch.column(2).to_pylist()), pa.list_(pa.int32()))], ["toxic", "own", "other"])

    got = sorted(sample.mapInArrow(narrow, "toxic int, own array<int>, other array<int>").collect(), key=str)
    x = np.zeros((len(got), len(names)), np.float32)
    pairs = []
    for i, r in enumerate(got):
        x[i, list(r["own"])] = 1
        if r["other"] is not None:
            changed = -x[i]
            changed[list(r["other"])] += 1
            if changed.any():
                pairs.append(changed)
    for term, other in SWAP.items():  # a bare mention: swapping it, and making it, must not matter
        mention, swapped = np.zeros(len(names), np.float32), np.zeros(len(names), np.float32)
        mention[[model.place[p] for p in parts(term)]] = 1
        swapped[[model.place[p] for p in parts(other)]] = 1
        pairs += [mention - swapped, mention]
    y = np.array([r["toxic"] for r in got], np.float32)
    weight = np.where(y == 1, 1 / n[1], 1 / n[0])  # both classes count alike: the threshold asks for clear cases
    model.weights, model.bias = fit(x, y, weight, np.stack(pairs))
    model.memo.clear()
    return model


def score(docs: DataFrame, model: Model, threshold: float = 0.7) -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every row; one narrow pass."""
    sent = docs.sparkSession.sparkContext.broadcast(model)  # bounded by FEATURES

    def run(batches):
        m = sent.value
        common.claim("toxicity", m.memo.clear)
        of = m.score
        for batch in batches:
            for part in common.slices(batch):
                s = np.array([of(t) for t in part.column(2).to_pylist()])
                yield pa.record_batch([part.column(0), part.column(1), pa.array(s, pa.float64()), pa.array((s >= threshold).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), common.held_out().alias("held_out"), F.col("text").cast("string").alias("text"))
    return common.arrow_map(rows, run, "doc_id long, held_out boolean, score double, predicted int")
