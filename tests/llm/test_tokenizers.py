import base64
import hashlib
import random

import public_tokenizers as P
import pytest
import tiktoken
from pyspark.sql import types as T
from tokenizers import Tokenizer

from cdfblend.llm import byte_bpe
from cdfblend.llm.byte_bpe import encode_digests, encode_texts, load
from cdfblend.llm.token_counts import count_tokens

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("key", T.StringType()), T.StructField("n_tokens", T.StringType())])
BYTES = P.path("byte_bpe_50k.tiktoken")
WORDS = P.path("word_bpe_49k.json")


@pytest.fixture(scope="module")
def texts():
    random.seed(4)
    kinds = ["abcdefghij  '", "éñüß漢字🙂ａ́\xa0  \n\r\t", "0123456789 .,!?<|>", "THEthe ΣΟΦΟΣσοφοςİı "]
    made = ["".join(random.choices(random.choice(kinds), k=random.randint(0, 60))) for _ in range(300)]
    return [*made, "", " ", "<|endoftext|>", "a<|startoftext|>B", "<|ENDOFTEXT|> x", "it's we'll  THEY'VE", "x" * 9000, "word " * 6000, "Same  text", "same text", " SAME\ttext\n"]


def frame(spark, texts):
    return spark.createDataFrame([(i, t, "k", "n") for i, t in enumerate(texts)] + [(None, "null id", "", ""), (-1, None, "", ""), (0, texts[0], "", "")], SCHEMA)


def test_replay_matches_library(texts):
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(BYTES, "rb"))}
    ref = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    bpe = load(BYTES, P.PATTERN)
    got = bpe.encode(texts)
    assert [g.tolist() for g in got] == [ref.encode_ordinary(t) for t in texts]
    assert [bpe.decode(g).decode() for g in got] == texts


def test_words_kept_between_blocks(texts, monkeypatch):
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(BYTES, "rb"))}
    ref = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    monkeypatch.setattr(byte_bpe, "KEEP_WORDS", 40)
    monkeypatch.setattr(byte_bpe, "LONG_TEXT", 50)
    bpe = byte_bpe.ByteBpe(ranks, P.PATTERN)
    for k in range(0, len(texts), 25):
        assert [g.tolist() for g in bpe.encode(texts[k : k + 25])] == [ref.encode_ordinary(t) for t in texts[k : k + 25]]
        assert len(bpe.numbers) <= 40 and len(bpe.start) == len(bpe.numbers) + 1
    monkeypatch.setattr(byte_bpe, "KEEP_BYTES", 10)
    bpe.encode(["some words some words"])
    assert bpe.held <= 10


def test_overlapping_pairs_merge_from_the_left():
    ranks = {bytes([b]): b for b in range(256)} | {b"aa": 256, b"aaa": 257, b"aab": 258, b"aaaa": 259}
    bpe = byte_bpe.ByteBpe(ranks, r"\p{L}+|\s+")
    ref = tiktoken.Encoding("own", pat_str=r"\p{L}+|\s+", mergeable_ranks=ranks, special_tokens={})
    for t in ["a" * k + b for k in range(1, 12) for b in ("", "b", "ba", " aa")]:
        assert bpe.encode([t])[0].tolist() == ref.encode_ordinary(t)


def test_byte_digests(spark, texts):
    bpe = load(BYTES, P.PATTERN)
    rows = encode_digests(frame(spark, texts), BYTES, P.PATTERN).collect()
    assert len(rows) == len(texts) + 3
    for r in rows:
        t = {-1: "", None: "null id"}.get(r.doc_id, texts[r.doc_id] if r.doc_id is not None and r.doc_id >= 0 else None)
        ids = bpe.encode([t])[0]
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest(), hashlib.sha256(t.encode()).hexdigest())
    full = encode_texts(frame(spark, texts), BYTES, P.PATTERN)
    assert full.columns == ["doc_id", "text", "key", "n_tokens", "token_ids"] and full.count() == len(texts) + 3


def test_token_counts_and_cache(spark, texts, tmp_path):
    ref = Tokenizer.from_file(WORDS)
    expected = [len(e.ids) for e in ref.encode_batch(texts, add_special_tokens=False)]
    cache = f"file://{tmp_path}/cache"
    for _ in range(2):
        rows = count_tokens(frame(spark, texts), WORDS, cache=cache, limit=100).collect()
        assert len(rows) == len(texts) + 3
        for r in rows:
            if r.doc_id is not None and r.doc_id >= 0:
                assert (r.n_bytes, r.n_tokens, r.over_limit) == (len(texts[r.doc_id].encode()), expected[r.doc_id], expected[r.doc_id] > 100)
        assert {(r.n_bytes, r.n_tokens) for r in rows if r.doc_id == -1} == {(0, 0)}
        stored = spark.read.parquet(cache)
        assert stored.count() == stored.select("key").distinct().count() < len(texts)
    piece = count_tokens(frame(spark, ["some words", "more"]), P.path("piece_bpe_32k.model")).where("doc_id = 0").first()
    assert piece.n_tokens > 0


def test_empty(spark):
    empty = spark.createDataFrame([], SCHEMA)
    assert count_tokens(empty, WORDS).count() == 0
    assert encode_digests(empty, BYTES, P.PATTERN).count() == 0
