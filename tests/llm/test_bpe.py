"""BPE against the tokenizers library: ids, digests and decoded text of any text."""

import hashlib
import random

import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from serieslake.llm import bpe
from serieslake.llm.queries import QUERIES

ODD = [None, "", " ", "\n\n  x", "I'll we've 'S 'd", "a<|endoftext|>b <|endoftext|><|endoftext|> ", "<|endoftext|>", "x" * 20000, " " * 5000 + "y", "½ ² ① Ⅷ ٣", "日本語 テスト", "é 👩‍👩‍👧 \x1c\x1f\x85 　z ", "\x00\x01", "a\r\nb\tc", "the the the", "the the the"]


def texts():
    rng = random.Random(4)
    ranges = [(32, 127), (32, 127), (0, 0x250), (0x370, 0x600), (0x900, 0xE00), (0x2000, 0x2C00), (0x3000, 0xA000), (0x1F300, 0x1F900)]
    return ODD + ["".join(chr(rng.randrange(*rng.choice(ranges))) for _ in range(rng.randrange(80))) for _ in range(600)]


@pytest.fixture(scope="module")
def tok():
    return Tokenizer.from_file(bpe.default_vocabulary())


@pytest.mark.parametrize("size", [1 << 20, 50])
def test_equals_the_library(spark, sf, tok, monkeypatch, size):
    monkeypatch.setattr(bpe, "UNIT_WORDS", size)
    monkeypatch.setattr(bpe, "BUCKET_BYTES", 1 << 14)
    said = texts() + ([r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()] if size > 50 else [])
    df = spark.createDataFrame([(i, t, 1, "x") for i, t in enumerate(said)], "doc_id bigint, text string, ids int, word string")
    got = bpe.encode_decode(df).collect()
    assert sorted(r.doc_id for r in got) == list(range(len(said)))
    for r in got:
        want = tok.encode(said[r.doc_id] or "", add_special_tokens=False).ids
        shown = tok.decode(want, skip_special_tokens=False)
        assert (r.ids, r.decoded, r.n_tokens) == (want, shown, len(want)), said[r.doc_id]
        assert r.ids_sha256 == hashlib.sha256(",".join(map(str, want)).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(shown.encode()).hexdigest()


def test_each_distinct_word_is_encoded_once(spark):
    df = spark.createDataFrame([(i, "a hot word and another hot word") for i in range(500)], "doc_id bigint, text string").repartition(7)
    asked = bpe.units(df, ["doc_id"], bpe.default_vocabulary(), 3).where("bucket >= 0")
    assert asked.count() <= 7 * 3 and bpe.word_table(asked, bpe.default_vocabulary()).agg(F.sum("n_words")).first()[0] == 5


def test_odd_rows(spark, tmp_path):
    rows = [(None, "a"), (1, None), (2, "b b"), (2, "b b")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    df.write.parquet(f"{tmp_path}/documents.parquet")
    got = QUERIES["op5_bpe_round_trip"](spark, str(tmp_path))
    assert got.columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
    assert sorted((r.doc_id or 0, r.n_tokens) for r in got.collect()) == [(0, 1), (1, 0), (2, 2), (2, 2)]
    assert bpe.encode_decode(df.limit(0)).count() == 0
    assert bpe.encode_decode(df.where("text is null")).first().ids == []
