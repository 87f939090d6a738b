"""Operator 6, token counts: byte-pair merging with a heap and a linked list, no identifiers.

A text's count is the sum over its pre-tokens of (bytes - merges).  The merges of one
pre-token come from repeatedly popping the lowest-rank adjacent pair from a heap whose
entries point into a doubly linked list of symbols; stale entries are skipped when popped.
Counts are kept per distinct pre-token in a bounded dictionary of each Python worker.

Edge cases: null and empty texts count 0 tokens; the vocabulary's special strings inside a
text are single tokens, as the library's default has it; null ids pass through; repeated
rows are counted each; other columns, whatever their names, are not read.  A vocabulary file
that is not plain byte-level byte-pair encoding is refused, as its steps would give other tokens.
"""

from __future__ import annotations

import heapq
import json

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: Fixed value: the byte-level pre-token pattern of the vocabulary.
PRETOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"

#: Settings of a vocabulary's model that would change which merges are made, or the symbols that they start from.
ALTERING = ("dropout", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback", "ignore_merges")

#: Entries of the per-worker dictionary of counted pre-tokens (about 100 bytes each).
MEMO_ENTRIES = 1_500_000

_loaded: dict[str, PairCounter] = {}


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte: itself if printable, else the next letter from 256 up."""
    shown = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in shown else chr(next(spare)) for b in range(256)]


class PairCounter:
    """Counts the tokens of byte-level byte-pair encoding from a vocabulary file's merge list."""

    def __init__(self, path: str):
        import regex

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, before = spec["model"], spec.get("pre_tokenizer") or {}
        plain = spec.get("normalizer") is None and spec.get("truncation") is None and spec.get("padding") is None
        plain = plain and before.get("type") == "ByteLevel" and before.get("add_prefix_space") is False and before.get("use_regex", True) is True
        if not plain or model.get("type") != "BPE" or any(model.get(k) for k in ALTERING):
            raise ValueError(f"{path} isn't plain byte-level byte-pair encoding, so counting its merges would not give its tokens")
        merges = model["merges"]
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in merges]
        self.rank = {pair: r for r, pair in enumerate(pairs)}
        self.letters = byte_letters()
        self.find = regex.compile(PRETOKEN).findall
        special = sorted((t["content"] for t in spec.get("added_tokens", [])), key=len, reverse=True)
        self.split = regex.compile("|".join(map(regex.escape, special))).split if special else None
        self.special = special
        self.memo: dict[str, int] = {}

    def pretoken(self, word: str) -> int:
        """Symbols left of one pre-token: its bytes less the merges made."""
        raw = word.encode("utf-8", "surrogatepass")
        n = len(raw)
        if n < 2:
            return n
        letters, rank = self.letters, self.rank
        symbol = [letters[b] for b in raw]
        after = list(range(1, n + 1))
        before = list(range(-1, n - 1))
        heap = []
        for at in range(n - 1):
            r = rank.get((symbol[at], symbol[at + 1]))
            if r is not None:
                heap.append((r, at, symbol[at], symbol[at + 1]))
        heapq.heapify(heap)
        merged = 0
        while heap:
            _, at, left, right = heapq.heappop(heap)
            nxt = after[at]
            if symbol[at] != left or nxt >= n or symbol[nxt] != right:
                continue  # one of the two has been merged since
            symbol[at], symbol[nxt] = left + right, ""
            after[at] = far = after[nxt]
            merged += 1
            if far < n:
                before[far] = at
                r = rank.get((symbol[at], symbol[far]))
                if r is not None:
                    heapq.heappush(heap, (r, at, symbol[at], symbol[far]))
            if (near := before[at]) >= 0:
                r = rank.get((symbol[near], symbol[at]))
                if r is not None:
                    heapq.heappush(heap, (r, near, symbol[near], symbol[at]))
        return n - merged

    def _plain(self, text: str) -> int:
        words = self.find(text)
        try:
            return sum(map(self.memo.__getitem__, words))
        except KeyError:
            memo = self.memo
            if len(memo) > MEMO_ENTRIES:
                memo.clear()
            for w in words:
                if w not in memo:
                    memo[w] = self.pretoken(w)
            return sum(map(memo.__getitem__, words))

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if any(s in text for s in self.special):
            parts = self.split(text)
            return len(parts) - 1 + sum(map(self._plain, parts))
        return self._plain(text)


def counter(path: str) -> PairCounter:
    """One counter, and so one dictionary, for each vocabulary and Python worker."""
    if path not in _loaded:
        _loaded[path] = PairCounter(path)
    return _loaded[path]


def count_tokens(docs: DataFrame, vocab: str, limit: int = 512, text: str = "text", key: str = "doc_id") -> DataFrame:
    """``doc_id, n_bytes, n_tokens, over_limit`` of every row; one narrow pass, nothing shuffled."""

    def count(batches):
        made = counter(vocab)
        common.claim("counts", made.memo.clear)
        of = made.count
        for batch in batches:
            for part in common.slices(batch):
                n = [of(t) for t in part.column(1).to_pylist()]
                yield pa.record_batch([part.column(0), part.column(2), pa.array(n, pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    body = F.coalesce(F.col(text), F.lit(""))
    rows = docs.select(F.col(key).cast("long").alias("doc_id"), body.alias("text"), F.octet_length(body).cast("long").alias("n_bytes"))
    out = common.arrow_map(rows, count, "doc_id long, n_bytes long, n_tokens long")
    return out.withColumn("over_limit", F.col("n_tokens") > limit)
