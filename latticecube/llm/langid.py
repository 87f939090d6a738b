"""Operator 10, language identification by hierarchical discrimination.

A text becomes hashed letter trigrams of its UTF-8 bytes (digits, signs and white space are one separator), as square
roots of their shares.  A softmax over language families decides first; within the family, linear support vector
machines, one for each pair of its languages (squared hinge loss), vote.  The score is the family's
probability times the least of the winner's pairwise logistic margins.

Training reads at most about ``PER_LANGUAGE`` documents of each language, picked by a hash of the id from all rows that may be
learned from; this bound is a parameter.  Prediction reads every whole text.

Edge cases: null texts and texts without a letter are ``und`` with score 0; so is everything if there is nothing to learn from;
a single learned language wins with the score 1 for every text with a letter; languages outside ``FAMILIES`` are families of
their own; null ids count as held out; repeated rows are predicted each.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: Language families by ISO 639-1 code.
FAMILIES = {
    "germanic": ["en", "de", "nl", "af", "sv", "da", "no", "nb", "nn", "is"],
    "romance": ["fr", "es", "it", "pt", "ca", "gl", "ro", "oc"],
    "slavic": ["ru", "uk", "be", "pl", "cs", "sk", "sl", "hr", "sr", "bs", "bg", "mk"],
    "uralic": ["fi", "et", "hu"],
    "turkic": ["tr", "az", "kk", "uz"],
    "semitic": ["ar", "he", "mt"],
    "indic": ["hi", "ur", "bn", "mr", "gu", "pa", "ne"],
}
PER_LANGUAGE = 1_000
WIDTH = 2_048
UNKNOWN = "und"

_LETTERS = bytes(c if 97 <= c <= 122 or c >= 128 else c + 32 if 65 <= c <= 90 else 32 for c in range(256))


def family_of(lang: str) -> str:
    return next((f for f, members in FAMILIES.items() if lang in members), lang)


def has_letter(text: str | None) -> bool:
    return bool(text) and any(map(str.isalpha, text))


def trigrams(text: str, width: int = WIDTH) -> np.ndarray:
    """How often each hashed trigram occurs."""
    words = b" ".join(text.encode("utf-8", "surrogatepass").translate(_LETTERS).split())
    b = np.frombuffer(b" " + words + b"  ", np.uint8).astype(np.uint32)
    code = (b[:-2] * np.uint32(0x9E3779B1) ^ b[1:-1] * np.uint32(0x85EBCA77) ^ b[2:] * np.uint32(0xC2B2AE3D)) * np.uint32(0x27D4EB2F)
    return np.bincount((code >> np.uint32(16)) % np.uint32(width), minlength=width)


def shares(counts: np.ndarray) -> np.ndarray:
    return np.sqrt(counts / max(1, counts.sum(dtype=np.int64))).astype(np.float32)


def features(text: str, width: int = WIDTH) -> np.ndarray:
    return shares(trigrams(text, width))


def packed(counts: np.ndarray) -> bytes:
    """Counts in the least whole bytes that hold the largest of them, one or two for most texts instead of a float's four."""
    return counts.astype(np.min_scalar_type(counts.max()).newbyteorder("<")).tobytes()


def unpacked(x: bytes, width: int) -> np.ndarray:
    return np.frombuffer(x, f"<u{len(x) // width}")


def _descend(grad, start: np.ndarray, steps: int, rate: float) -> np.ndarray:
    """Gradient descent with Nesterov momentum."""
    w, v = start.copy(), np.zeros_like(start)
    for _ in range(steps):
        v = 0.9 * v - rate * grad(w + 0.9 * v)
        w = w + v
    return w


class Model:
    """Family softmax and pairwise machines; plain arrays, so that it travels to the workers."""

    def __init__(self, x1: np.ndarray, langs: list[str]):
        """x1: features of each text, and a last column of ones."""
        self.langs = sorted(set(langs))
        self.families = sorted({family_of(v) for v in self.langs})
        y = np.array([self.families.index(family_of(v)) for v in langs])
        self.family = np.zeros((x1.shape[1], len(self.families)), np.float32)
        if len(self.families) > 1:
            target = np.eye(len(self.families), dtype=np.float32)[y]
            share = target.mean(axis=0)
            weight = (1 / (len(share) * share))[y][:, None].astype(np.float32)

            def grad(w):
                return x1.T @ (weight * (self._softmax(x1 @ w) - target)) / len(x1) + 1e-5 * w

            self.family = _descend(grad, self.family, 300, 4.0).astype(np.float32)
        self.pairs: dict[tuple[str, str], np.ndarray] = {}
        lang = np.array(langs)
        for f in self.families:
            own = [v for v in self.langs if family_of(v) == f]
            for i, a in enumerate(own):
                for b in own[i + 1 :]:
                    rows = (lang == a) | (lang == b)
                    sign = np.where(lang[rows] == a, 1.0, -1.0).astype(np.float32)
                    weight = np.where(sign > 0, 1 / (sign > 0).mean(), 1 / (sign < 0).mean()).astype(np.float32) / 2
                    xs = x1[rows]

                    def hinge(w, xs=xs, sign=sign, weight=weight):
                        gap = np.maximum(0, 1 - sign * (xs @ w))
                        return -2 * (xs.T @ (weight * sign * gap)) / len(xs) + 1e-5 * w

                    self.pairs[a, b] = _descend(hinge, np.zeros(x1.shape[1], np.float32), 300, 0.4).astype(np.float32)

    @staticmethod
    def _softmax(z: np.ndarray) -> np.ndarray:
        e = np.exp(z - z.max(axis=1, keepdims=True))
        return e / e.sum(axis=1, keepdims=True)

    def predict(self, x: np.ndarray) -> tuple[list[str], np.ndarray]:
        x1 = np.hstack([x, np.ones((len(x), 1), np.float32)])
        p = self._softmax(x1 @ self.family)
        best = p.argmax(axis=1)
        out, score = [""] * len(x), p.max(axis=1).astype(np.float64)
        for f, name in enumerate(self.families):
            rows = np.flatnonzero(best == f)
            own = [v for v in self.langs if family_of(v) == name]
            votes, worst = np.zeros((len(rows), len(own))), np.ones((len(rows), len(own)))
            for i, a in enumerate(own):
                for j in range(i + 1, len(own)):
                    chance = 1 / (1 + np.exp(-np.clip(4.0 * (x1[rows] @ self.pairs[a, own[j]]), -30, 30)))
                    votes[:, i] += (chance >= 0.5) + chance / 1e3
                    votes[:, j] += (chance < 0.5) + (1 - chance) / 1e3
                    worst[:, i], worst[:, j] = np.minimum(worst[:, i], chance), np.minimum(worst[:, j], 1 - chance)
            won = votes.argmax(axis=1)
            for r, k in zip(rows, won, strict=True):
                out[r] = own[k]
            score[rows] *= worst[np.arange(len(rows)), won]
        return out, np.clip(score, 0.0, 1.0)


def train(docs: DataFrame, per_language: int = PER_LANGUAGE, width: int = WIDTH) -> Model | None:
    """Learn from text and non-null lang of the documents that are not held out; a bounded sample reaches the driver."""
    rows = docs.where(~common.held_out() & F.col("lang").isNotNull() & F.col("text").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))
    counts = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not counts:
        return None
    place = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) / F.lit(float(1 << 30))
    share = F.element_at(F.create_map(*[F.lit(v) for k, n in counts.items() for v in (k, min(1.0, per_language / n))]), F.col("lang"))
    picked = rows.withColumn("place", place).where(F.col("place") < share)

    def vectors(batches):
        for batch in batches:
            for part in common.slices(batch):
                x = [packed(trigrams(t, width)) if has_letter(t) else b"" for t in part.column(1).to_pylist()]
                yield pa.record_batch([part.column(2), part.column(3), part.column(0), pa.array(x, pa.binary())], ["place", "doc_id", "lang", "x"])

    # texts become vectors where they lie; the share is exact only on average, so a limit in hash order bounds what the driver gets
    made = common.arrow_map(picked.select("lang", "text", "place", "doc_id"), vectors, "place double, doc_id long, lang string, x binary")
    # and they come as packed counts, a part of the size of their features
    got = [(r["lang"], bytes(r["x"])) for r in made.orderBy("place", "doc_id", "lang", "x").limit(2 * per_language * len(counts)).collect() if r["x"]]
    if not got:
        return None
    got.sort()
    x1 = np.ones((len(got), width + 1), np.float32)
    for row, (_, x) in zip(x1, got, strict=True):
        row[:width] = shares(unpacked(x, width))
    langs = [lang for lang, _ in got]
    del got, x, row
    model = Model(x1, langs)
    del x1
    common.give_back()
    common.driver_gives_back(docs.sparkSession)
    return model


def identify(docs: DataFrame, model: Model | None, width: int = WIDTH) -> DataFrame:
    """``doc_id, held_out, lang_pred, score`` of every row; one narrow pass."""
    sent = docs.sparkSession.sparkContext.broadcast(model)  # bounded by languages x width

    def predict(batches):
        m = sent.value
        for batch in batches:
            for part in common.slices(batch):
                texts = part.column(2).to_pylist()
                rows = [i for i, t in enumerate(texts) if has_letter(t)] if m else []
                langs, score = [UNKNOWN] * len(texts), np.zeros(len(texts))
                if rows:
                    got, s = m.predict(np.stack([features(texts[i], width) for i in rows]))
                    score[rows] = s
                    for i, lang in zip(rows, got, strict=True):
                        langs[i] = lang
                yield pa.record_batch([part.column(0), part.column(1), pa.array(langs), pa.array(score)], ["doc_id", "held_out", "lang_pred", "score"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), common.held_out().alias("held_out"), F.col("text").cast("string").alias("text"))
    return common.arrow_map(rows, predict, "doc_id long, held_out boolean, lang_pred string, score double")
