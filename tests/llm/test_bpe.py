import base64
import hashlib

import public_tokenizers as P
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st

from spark_nlops.llm import bpe


@pytest.fixture(scope="module")
def codec():
    path, pattern = bpe.default_vocabulary()
    return bpe.Codec(bpe.vocabulary_bytes(path), pattern)


@pytest.fixture(scope="module")
def reference():
    with open(P.path("byte_bpe_50k.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


CASES = ["", " ", "a", "aaaaaaa", "  \n\t x", "it's we'll", "x" * 5000, "ab" * 3000 + "!" * 999, "naïve Ciónllci ß 漢字 🎉", "\x00\x1c\x85\u2028 z", "<|endoftext|>"]


@pytest.mark.parametrize("text", CASES)
def test_matches_library(codec, reference, text):
    ids = codec.encode(text)
    assert ids == reference.encode_ordinary(text)
    assert codec.decode(ids) == text.encode()


@settings(max_examples=300, deadline=None)
@given(st.text(max_size=200))
def test_random_texts(codec, reference, text):
    assert codec.encode(text) == reference.encode_ordinary(text)


@settings(max_examples=200, deadline=None)
@given(st.lists(st.binary(max_size=40), max_size=8))
def test_bulk_equals_single(codec, pieces):
    assert codec.encode_many(pieces) == [codec.encode_one(p) for p in pieces]


def test_split_of_every_character(codec, reference):
    for block in range(0, 0x110000, 0x400):
        text = "".join(f"a{chr(c)}b" for c in range(block, block + 0x400) if not 0xD800 <= c < 0xE000)
        assert codec.encode(text) == reference.encode_ordinary(text), hex(block)


def test_whole_tables(spark, sf001, reference):
    got = {r.doc_id: r for r in bpe.op2_byte_bpe(spark, sf001).collect()}
    rows = spark.read.parquet(f"{sf001}/documents.parquet").collect()
    assert len(got) == len(rows)
    for row in rows:
        ids = reference.encode_ordinary(row.text)
        assert got[row.doc_id].n_tokens == len(ids)
        assert got[row.doc_id].ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert got[row.doc_id].decoded_sha256 == hashlib.sha256(row.text.encode()).hexdigest()


def test_edges_and_round_trip(spark):
    rows = [(1, None, 0, "x"), (2, "", 1, "x"), (None, "many words " * 4000, 2, None), (2, "", 1, "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_tokens int, key string")
    out = bpe.encode_documents(df)
    assert sorted(r.n_tokens for r in out.collect())[:3] == [0, 0, 0]
    back = {r.doc_id: bytes(r.decoded) for r in bpe.decode_documents(out).collect()}
    assert back[None] == ("many words " * 4000).encode() and back[1] == b""
    assert bpe.encode_documents(df.limit(0)).count() == 0


def test_rank_queue_order():
    queue = bpe.RankQueue(50_000)
    for r in (49_999, 64, 0, 4_096, 63):
        queue.open_bucket(r).append(r)
    assert [queue.close(queue.first())[0] for _ in range(5)] == [0, 63, 64, 4_096, 49_999]
    assert queue.first() == -1
