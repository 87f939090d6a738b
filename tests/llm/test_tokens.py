import json
import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from latticecube.llm import bpecount, common, tokenout

ODD = [
    "", None, " ", "  a  b\n\n c\t", "I'll don't he's THEY'RE", "café café naïve", "x<|endoftext|>y <|endoftext|>", " a b\x1cc\x85d",
    "日本語 ΑΣ \U0001f600\U0001f600", "a" * 3000, "12345 6²½", "...!!! --- “q”", "İstanbul ẞ ǅ", "word " * 5000, "\r\n\r\n  x", "<|startoftext|> hi",
]


def texts(spark):
    rows = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("text").collect()
    rng = random.Random(5)
    noise = ["".join(rng.choice("ab \n'sTé中1. ") for _ in range(rng.randrange(1, 60))) for _ in range(300)]
    return [r.text for r in rows] + ODD + noise


def test_counts_equal_library(spark):
    path = public_tokenizers.path("byte_bpe_50k.json")
    lib, own = Tokenizer.from_file(path), bpecount.PairCounter(path)
    for t in texts(spark):
        assert own.count(t) == (len(lib.encode(t, add_special_tokens=False).ids) if t else 0), t


def test_counts_query_edges(spark):
    df = spark.createDataFrame([(1, None, 1), (2, "", 2), (None, "hi there", 3), (4, "a " * 2000, 4), (4, "a " * 2000, 4)], "doc_id long, text string, n_tokens int")
    got = sorted(map(tuple, bpecount.count_tokens(df, public_tokenizers.path("byte_bpe_50k.json")).collect()), key=str)
    assert (1, 0, 0, False) in got and (2, 0, 0, False) in got and (None, 8, 2, False) in got
    assert [g for g in got if g[0] == 4] == [(4, 4000, 2001, True)] * 2
    assert bpecount.count_tokens(df.limit(0), public_tokenizers.path("byte_bpe_50k.json")).count() == 0


def test_encoder_equals_library(spark):
    path = public_tokenizers.path("word_bpe_49k.json")
    lib, own = Tokenizer.from_file(path), tokenout.Encoder(path)
    for t in texts(spark):
        want = lib.encode(t, add_special_tokens=False).ids if t else []
        assert np.frombuffer(own.encode(t), own.dtype).tolist() == want, t


def _variant(tmp_path, name, change):
    with open(public_tokenizers.path(name), encoding="utf-8") as f:
        spec = json.load(f)
    change(spec)
    path = tmp_path / f"{change.__name__}.json"
    path.write_text(json.dumps(spec), encoding="utf-8")
    return str(path)


def test_files_with_other_steps_are_not_shortcut(tmp_path):
    """Another Replace, split flag or pattern: ids still equal the library's, as such a file's texts go to it whole."""

    def replaced(spec):
        spec["normalizer"]["normalizers"][1]["content"] = "_"

    def kept(spec):
        spec["pre_tokenizer"]["pretokenizers"][0]["behavior"] = "Isolated"

    def digits(spec):
        spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"] = r"\p{L}+|\p{N}+|[^\s\p{L}\p{N}]+"

    for change in (replaced, kept, digits):
        path = _variant(tmp_path, "word_bpe_49k.json", change)
        lib, own = Tokenizer.from_file(path), tokenout.Encoder(path)
        assert not own.by_word
        for t in ("I'll  don't 123 abc", "two words"):
            assert np.frombuffer(own.encode(t), own.dtype).tolist() == lib.encode(t, add_special_tokens=False).ids
    assert tokenout.Encoder(public_tokenizers.path("word_bpe_49k.json")).by_word


def test_counter_refuses_other_files(tmp_path):
    def prefixed(spec):
        spec["pre_tokenizer"]["add_prefix_space"] = True

    def lowered(spec):
        spec["normalizer"] = {"type": "Lowercase"}

    def ended(spec):
        spec["model"]["end_of_word_suffix"] = "</w>"

    for change in (prefixed, lowered, ended):
        with pytest.raises(ValueError, match="byte-pair"):
            bpecount.PairCounter(_variant(tmp_path, "byte_bpe_50k.json", change))


def test_perfect_index():
    rng = np.random.default_rng(1)
    for n in (0, 1, 2, 7, 1000, 20000):
        keys = np.unique(rng.integers(-(1 << 62), 1 << 62, n)).view(np.uint64)
        index = tokenout.PerfectIndex.build(keys)
        slots = index.slots(keys)
        assert sorted(slots.tolist()) == list(range(len(keys)))


def test_round_trip(spark, tmp_path):
    path = public_tokenizers.path("word_bpe_49k.json")
    lib = Tokenizer.from_file(path)
    rows = [(i * 7 - 30, t) for i, t in enumerate(texts(spark)[:150])] + [(None, "no key"), (5000, "twice"), (5000, "twice again"), (6000, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    manifest = tokenout.write_shards(df, path, f"file://{tmp_path}/ids")
    got = tokenout.read_shards(spark, manifest).orderBy("start").collect()
    assert len(got) == len(rows) and got[0].doc_id is None
    plain = [g.doc_id for g in got[1:]]
    assert plain == sorted(plain)
    start, by = 0, {}
    for i, t in rows:
        by.setdefault(i, []).append(t)
    for g in got:
        assert g.start == start
        start += g.n_tokens
        want = [np.array((lib.encode(t, add_special_tokens=False).ids if t else []) + [2], "<u4") for t in by[g.doc_id]]
        assert (g.n_tokens, g.ids_crc32) in [(len(w), zlib.crc32(w.tobytes())) for w in want]
        assert g.in_index == (g.doc_id is not None)
    assert tokenout.lookup(manifest, 6000).tolist() == [2]
    assert tokenout.lookup(manifest, -31) is None and tokenout.lookup(manifest, 10**9) is None
    # writing again over the same place gives the same files
    assert [m["n_ids"] for m in tokenout.write_shards(df, path, f"file://{tmp_path}/ids")] == [m["n_ids"] for m in manifest]


def test_round_trip_empty(spark):
    df = spark.createDataFrame([], "doc_id long, text string")
    assert tokenout.token_output(df, public_tokenizers.path("word_bpe_49k.json")).count() == 0


def test_held_out(spark):
    df = spark.range(50).withColumnRenamed("id", "doc_id").withColumn("h", common.held_out())
    assert all(r.h == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in df.collect())
