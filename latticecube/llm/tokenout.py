"""Operator 3, token-ID output: binary shards with a minimal perfect hash index.

A shard file holds, in this order, a fixed header, the index and the raw id payload:

* header: magic, version, id width in bytes, number of keys, number of entries, number of ids,
  number of buckets, seed, number of entries without a key;
* index: one 32-bit displacement for each bucket, then for each slot an 8-byte fingerprint and the 32-bit
  number of its first entry, and for each entry its 8-byte key, the 8-byte offset of its first id and its
  32-bit length;
* payload: little-endian unsigned ids, two bytes each where the vocabulary has at most 65,536 ids, else four.

A key's slot is found by hash-and-displace: hash to a bucket, add the bucket's displacement, hash
again to a slot; every key of the shard has a slot of its own and no slot is empty.  The stored
fingerprint tells unknown keys from known ones, so a lookup costs one bucket read, one slot read
and one payload read, whatever the shard's size.

Shards cover ascending, disjoint ranges of document keys.  Each is written under a temporary name
and moved, so a lost executor's task can run again.

Edge cases: null text is the empty text (only the end id is stored); rows with a null key are
stored first, in that order too, and have no index entry; rows that share a key are stored next to each
other in order of a hash of their text, and the index points at the first of them; an empty table writes no shard.
"""

from __future__ import annotations

import json
import re
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .bpecount import byte_letters

MAGIC = b"LCIDSHRD"
HEADER = struct.Struct("<8sIIQQQQQQ")
#: Text bytes a shard should hold at most, about.
SHARD_BYTES = 256 << 20
#: White-space-free chunks, and distinct words, whose ids a worker keeps (about 200 bytes each).
MEMO_CHUNKS, MEMO_WORDS = 250_000, 200_000
#: Mean number of keys in a bucket of the index.
BUCKET_KEYS = 3

_mask = np.uint64(0xFFFFFFFFFFFFFFFF)


def mix(x: np.ndarray, seed: int) -> np.ndarray:
    """A 64-bit finaliser: every output bit depends on every input bit."""
    with np.errstate(over="ignore"):
        x = x.astype(np.uint64) + np.uint64((seed * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & 0xFFFFFFFFFFFFFFFF)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


class PerfectIndex:
    """Minimal perfect hash over distinct 64-bit keys."""

    def __init__(self, displacement: np.ndarray, n: int, seed: int):
        self.displacement, self.n, self.seed = displacement, n, seed

    @classmethod
    def build(cls, keys: np.ndarray) -> PerfectIndex:
        n = len(keys)
        if not n:
            return cls(np.zeros(0, np.uint32), 0, 0)
        for seed in range(1, 64):
            if (made := cls._try(keys, n, seed)) is not None:
                return cls(made, n, seed)
        raise ValueError("no displacement found; are the keys distinct?")

    @staticmethod
    def _try(keys: np.ndarray, n: int, seed: int) -> np.ndarray | None:
        buckets = max(1, n // BUCKET_KEYS)
        of = (mix(keys, seed) % np.uint64(buckets)).astype(np.int64)
        order = np.argsort(of, kind="stable")
        sizes = np.bincount(of, minlength=buckets)
        ends = np.cumsum(sizes)
        taken = np.zeros(n, bool)
        out = np.zeros(buckets, np.uint32)
        # large buckets first, while slots are free; all open buckets of a size try a displacement at once
        for size in range(int(sizes.max()), 1, -1):
            open_ = np.flatnonzero(sizes == size)
            own = keys[order[(ends[open_] - size)[:, None] + np.arange(size)]] if len(open_) else None
            for d in range(1, 1 << 20):
                if not len(open_):
                    break
                slots = (mix(own, seed + 64 * d) % np.uint64(n)).astype(np.int64)
                apart = np.sort(slots, axis=1)
                good = np.flatnonzero(~taken[slots].any(axis=1) & (apart[:, 1:] != apart[:, :-1]).all(axis=1))
                if len(good):
                    # a slot that two buckets want goes to the first; a bucket that gets only some of its slots waits
                    flat = slots[good].ravel()
                    claimed, first = np.unique(flat, return_index=True)
                    owner = first[np.searchsorted(claimed, flat)].reshape(len(good), size) // size
                    done = good[(owner == np.arange(len(good))[:, None]).all(axis=1)]
                    taken[slots[done].ravel()] = True
                    out[open_[done]] = d
                    rest = np.ones(len(open_), bool)
                    rest[done] = False
                    open_, own = open_[rest], own[rest]
            if len(open_):
                return None
        # a bucket of one key names its slot outright: the top bit marks it
        single = np.flatnonzero(sizes == 1)
        out[single] = np.flatnonzero(~taken)[: len(single)].astype(np.uint32) | np.uint32(0x80000000)
        return out

    def slots(self, keys: np.ndarray) -> np.ndarray:
        """The slot of each key; a key that was not built in gets some slot, which its fingerprint refutes."""
        if not self.n:
            return np.zeros(len(keys), np.int64)
        d = self.displacement[(mix(keys, self.seed) % np.uint64(len(self.displacement))).astype(np.int64)]
        named = (d >> np.uint32(31)).astype(bool)
        out = (d & np.uint32(0x7FFFFFFF)).astype(np.int64)
        with np.errstate(over="ignore"):
            x = keys.astype(np.uint64)
            seeds = (np.uint64(self.seed) + np.uint64(64) * d.astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(0x632BE59BD9B4E019)
            x = x + seeds
            x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
            x = x ^ (x >> np.uint64(31))
        return np.where(named, out, (x % np.uint64(self.n)).astype(np.int64))


def fingerprint(keys: np.ndarray) -> np.ndarray:
    return mix(keys, 0x5EED)


#: The normaliser's and the pre-tokeniser's steps for which words can be encoded one by one.
WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
WORD_NORMALIZER = {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]}
WORD_SPLIT = {
    "type": "Sequence",
    "pretokenizers": [
        {"type": "Split", "pattern": {"Regex": WORD_PATTERN}, "behavior": "Removed", "invert": True},
        {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False},
    ],
}


class Encoder:
    """Whole-text ids of a vocabulary file, from the tokenizers library.

    Where the file's steps are exactly the fixed ones above (any other file's texts go to the library whole), a text's ids are those of its
    white-space-free chunks in order, and a chunk's those of its lower-case words: each distinct word goes to the
    library's model once, and words and chunks are remembered.  Texts with letters beyond the extended Latin
    blocks, with odd control characters or with what may be a special string go to the library whole.
    """

    def __init__(self, path: str):
        import regex
        from tokenizers import Tokenizer

        self.of = Tokenizer.from_file(path)
        size = self.of.get_vocab_size()
        self.width = 2 if size <= 1 << 16 else 4
        self.dtype = np.dtype("<u2" if self.width == 2 else "<u4")
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        whole = spec.get("truncation") is None and spec.get("padding") is None and spec["model"].get("type") == "BPE" and not spec["model"].get("dropout")
        self.by_word = whole and spec.get("normalizer") == WORD_NORMALIZER and spec.get("pre_tokenizer") == WORD_SPLIT
        if self.by_word:
            self.find = regex.compile(WORD_PATTERN).findall
            self.model, self.letters = self.of.model, byte_letters()
        self.odd = re.compile(r"[^\t-\r -~\xa1-ɏ‐-‧]|<\|").search
        self.chunks: dict[str, bytes] = {}
        self.words: dict[str, bytes] = {}

    def forget(self) -> None:
        self.chunks.clear()
        self.words.clear()

    def _word(self, word: str) -> bytes:
        shown = word if word.isascii() else "".join(map(self.letters.__getitem__, word.encode()))
        self.words[word] = ids = np.array([t.id for t in self.model.tokenize(shown)], self.dtype).tobytes()
        return ids

    def _chunk(self, chunk: str) -> bytes:
        words = self.words
        low = chunk.lower()
        if low.isalpha():  # one word: the pattern would find just that
            ids = words.get(low) or self._word(low)
        else:
            ids = b"".join([words.get(w) or self._word(w) for w in self.find(low)])
        self.chunks[chunk] = ids
        return ids

    def encode(self, text: str | None) -> bytes:
        if not text:
            return b""
        if not self.by_word or self.odd(text):
            return np.asarray(self.of.encode(text, add_special_tokens=False).ids, self.dtype).tobytes()
        if len(self.chunks) > MEMO_CHUNKS:
            self.chunks.clear()
        if len(self.words) > MEMO_WORDS:
            self.words.clear()
        of, make = self.chunks.get, self._chunk
        return b"".join([of(c) or make(c) for c in text.split()])


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    import os

    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def shard_bytes(keys: list[int | None], lengths: np.ndarray, payload: list[bytes], width: int) -> tuple[bytes, list[bytes]]:
    """Header with index, and payload, of one shard; keys ascend, those that are null come first."""
    nulls = sum(k is None for k in keys)
    plain = np.array([k or 0 for k in keys], np.int64)
    known, first = np.unique(plain[nulls:], return_index=True)
    index = PerfectIndex.build(known.view(np.uint64))
    slot = index.slots(known.view(np.uint64))
    prints, entry = np.zeros(len(known), "<u8"), np.zeros(len(known), "<u4")
    prints[slot], entry[slot] = fingerprint(known.view(np.uint64)), first + nulls
    offsets = np.concatenate([[0], np.cumsum(lengths)[:-1]]).astype("<u8") if len(keys) else np.zeros(0, "<u8")
    head = HEADER.pack(MAGIC, 1, width, len(known), len(keys), int(lengths.sum()), len(index.displacement), index.seed, nulls)
    return b"".join([head, index.displacement.astype("<u4").tobytes(), prints.tobytes(), entry.tobytes(), plain.astype("<i8").tobytes(), offsets.tobytes(), lengths.astype("<u4").tobytes()]), payload


class Shard:
    """Reads a shard: whole, in order, or by key in constant time."""

    def __init__(self, uri: str):
        self.file = common.get_file(uri)
        magic, _, self.width, self.keys_n, self.n, self.ids_n, buckets, seed, self.nulls = HEADER.unpack(self.file.read(HEADER.size))
        if magic != MAGIC:
            raise ValueError(f"{uri} is no id shard")
        self.dtype = np.dtype("<u2" if self.width == 2 else "<u4")
        take = lambda kind, n: np.frombuffer(self.file.read(np.dtype(kind).itemsize * n), kind)
        self.index = PerfectIndex(take("<u4", buckets), self.keys_n, seed)
        self.prints, self.entry = take("<u8", self.keys_n), take("<u4", self.keys_n)
        self.keys, self.offsets, self.lengths = take("<i8", self.n), take("<u8", self.n), take("<u4", self.n)
        self.base = self.file.tell()

    def find(self, keys: np.ndarray) -> np.ndarray:
        """The first entry of each key, -1 where the shard has no such key."""
        keys = np.asarray(keys, np.int64).view(np.uint64)
        if not self.keys_n:
            return np.full(len(keys), -1, np.int64)
        slot = self.index.slots(keys)
        return np.where(self.prints[slot] == fingerprint(keys), self.entry[slot].astype(np.int64), -1)

    def ids(self, entry: int) -> np.ndarray:
        self.file.seek(self.base + int(self.offsets[entry]) * self.width)
        return np.frombuffer(self.file.read(int(self.lengths[entry]) * self.width), self.dtype)

    def get(self, key: int) -> np.ndarray | None:
        entry = int(self.find(np.array([key]))[0])
        return None if entry < 0 else self.ids(entry)

    def close(self) -> None:
        self.file.close()


def write_shards(docs: DataFrame, vocab: str, out: str, end_id: int = 2, shard_bytes_target: int = SHARD_BYTES) -> list[dict]:
    """Encode whole texts and write ascending shards under ``out``; returns the manifest, also stored there.

    The driver holds one small record for each shard, nothing for each document.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    stats = rows.agg(F.count("*").alias("n"), F.sum(F.octet_length("text")).alias("b")).first()
    if not stats["n"]:
        common.put_bytes(f"{out}/manifest.json", b"[]")
        return []
    shards = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-int(stats["b"]) // shard_bytes_target))
    # texts travel, not ids: the exchange samples its input first, and encoding twice costs more than the difference
    order = [F.col("doc_id").asc_nulls_first(), F.col("text_order")]
    dealt = rows.withColumn("text_order", F.xxhash64("text")).repartitionByRange(shards, *order).sortWithinPartitions(*order, "text").select("doc_id", "text")

    def store(batches):
        from pyspark import TaskContext

        enc = encoder(vocab)
        common.claim("ids", enc.forget)
        width, end = enc.width, np.array([end_id], enc.dtype).tobytes()
        keys, lengths, payload = [], [], []
        for batch in batches:
            keys += batch.column(0).to_pylist()
            for part in common.slices(batch):
                ids = [enc.encode(t) + end for t in part.column(1).to_pylist()]
                lengths += [len(x) // width for x in ids]
                payload.append(b"".join(ids))
        if keys:
            pid = TaskContext.get().partitionId()
            uri = f"{out}/shard-{pid:06d}.ids"
            head, body = shard_bytes(keys, np.array(lengths, np.int64), payload, width)
            with common.replaced(uri) as f:
                f.write(head)
                for x in body:
                    f.write(x)
            yield pa.record_batch([pa.array([pid], pa.int32()), pa.array([uri]), pa.array([len(keys)], pa.int64()), pa.array([int(sum(lengths))], pa.int64()), pa.array([keys[-1]], pa.int64())], ["shard", "uri", "n_docs", "n_ids", "last_key"])

    made = common.arrow_map(dealt, store, "shard int, uri string, n_docs long, n_ids long, last_key long").collect()
    manifest, start = [], 0
    for r in sorted(made, key=lambda r: r["shard"]):
        manifest.append(r.asDict() | {"start": start})
        start += r["n_ids"]
    common.put_bytes(f"{out}/manifest.json", json.dumps(manifest).encode())
    return manifest


def read_shards(spark: SparkSession, manifest: list[dict]) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32, in_index`` of every entry, read back from the files.

    ``in_index`` says that the perfect hash leads from the key to the first entry of that key.
    """
    schema = "shard int, uri string, n_docs long, n_ids long, last_key long, start long"
    listed = spark.createDataFrame([tuple(m[c] for c in ("shard", "uri", "n_docs", "n_ids", "last_key", "start")) for m in manifest], schema)

    def read(batches):
        names = ["doc_id", "start", "n_tokens", "ids_crc32", "in_index"]
        for batch in batches:
            for uri, start in zip(batch.column(1).to_pylist(), batch.column(5).to_pylist(), strict=True):
                shard = Shard(uri)
                found = shard.find(shard.keys)
                ok = (found >= 0) & (shard.keys[np.maximum(found, 0)] == shard.keys)
                ok[: shard.nulls] = False
                for at in range(0, shard.n, 4096):
                    to = min(at + 4096, shard.n)
                    crc = [zlib.crc32(shard.ids(e).astype("<u4").tobytes()) for e in range(at, to)]
                    keys = pa.array(shard.keys[at:to], pa.int64(), mask=np.arange(at, to) < shard.nulls)
                    yield pa.record_batch([keys, pa.array(shard.offsets[at:to].astype(np.int64) + start), pa.array(shard.lengths[at:to].astype(np.int64)), pa.array(crc, pa.int64()), pa.array(ok[at:to])], names)
                shard.close()

    # one task for each shard: the list has a row for each of them
    dealt = listed.repartition(max(1, len(manifest)), "shard") if manifest else listed
    return dealt.mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long, in_index boolean")


def lookup(manifest: list[dict], key: int) -> np.ndarray | None:
    """The ids of one document: binary search for its shard, then constant time."""
    import bisect

    at = bisect.bisect_left([m["last_key"] if m["last_key"] is not None else -(1 << 63) for m in manifest], key)
    if at == len(manifest):
        return None
    shard = Shard(manifest[at]["uri"])
    try:
        return shard.get(key)
    finally:
        shard.close()


def token_output(docs: DataFrame, vocab: str, end_id: int = 2, out: str | None = None) -> DataFrame:
    spark = docs.sparkSession
    return read_shards(spark, write_shards(docs, vocab, out or common.scratch(spark, "ids"), end_id))
