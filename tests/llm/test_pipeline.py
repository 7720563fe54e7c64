import base64
import re
from collections import Counter

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from pyspark.sql import functions as F

import corpus_pipeline as C
from cdfblend.llm.byte_bpe import load
from cdfblend.llm.quality import held_out, score, train

from .test_minhash_dedup import brute
from .test_mixing import fill

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def kept(spark, tmp_path_factory):
    """What each stage left, written and read again."""
    out = [spark.read.parquet(f"{SF}/documents.parquet")]
    for name, stage in C.STAGES:
        path = f"file://{tmp_path_factory.mktemp('stage')}/{name}"
        stage(spark, out[-1], SF).write.parquet(path)
        out.append(spark.read.parquet(path))
    return out


def test_quality_stage(spark, kept):
    model = train(kept[0], spark.read.parquet(f"{SF}/labels.parquet"))
    good = {r.doc_id for r in score(kept[0], model).where("score >= 0.7").collect()}
    assert {r.doc_id for r in kept[1].collect()} == good and kept[1].columns == kept[0].columns
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    assert sum(labels[i] == 1 for i in labels if i in good) / sum(q == 1 for q in labels.values()) > 0.97


def test_dedup_stage(kept):
    rows = [(r.doc_id, r.text) for r in kept[1].collect()]
    assert {r.doc_id for r in kept[2].collect()} == {i for i, _, c in brute(rows, 5, 80) if i == c} and kept[2].columns == kept[0].columns


def test_mixing_stage(kept):
    rows = kept[2].collect()
    size = {r.doc_id: len(re.findall(r"[^\x20\x09-\x0D]+", r.text)) for r in rows}
    total, taken = Counter(), Counter()
    for r in rows:
        total[r.source] += size[r.doc_id]
    copies = Counter()
    for r in kept[3].collect():
        taken[r.source] += size[r.doc_id]
        copies[r.doc_id] += 1
    target = fill(total, (5, 2, 1), 3.0)
    for s in total:
        assert abs(taken[s] - target[s]) <= max(size[r.doc_id] for r in rows if r.source == s) / 2 + 1e-6
    assert max(copies.values()) <= 3 and kept[3].columns == kept[0].columns


def test_encoding_stage(kept):
    path = P.path("byte_bpe_50k.tiktoken")
    bpe = load(path, P.PATTERN)
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(path, "rb"))}
    ref = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    texts = {r.doc_id: r.text for r in kept[3].collect()}
    rows = kept[4].collect()
    assert len(rows) == kept[3].count()
    for r in rows:
        ids = np.frombuffer(r.token_ids, "<i4")
        assert ids.tolist() == ref.encode_ordinary(texts[r.doc_id]) and bpe.decode(ids).decode() == texts[r.doc_id] and r.n_tokens == len(ids)


def test_run(spark, kept):
    got = Counter((r.doc_id, bytes(r.token_ids)) for r in C.run(spark, SF).collect())
    assert got == Counter((r.doc_id, bytes(r.token_ids)) for r in kept[4].collect())


@pytest.mark.parametrize("ids", ["held out", "foreign"])
def test_quality_stage_keeps_all_where_no_label_trains(spark, tmp_path, ids):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    some = labels.where(held_out(labels["doc_id"])) if ids == "held out" else labels.withColumn("doc_id", labels["doc_id"] + 10**9)
    assert some.where("quality in (0, 1)").count() > 0
    some.write.parquet(f"{tmp_path}/labels.parquet")
    assert sorted(r.doc_id for r in C.keep_good(spark, docs, str(tmp_path)).collect()) == sorted(r.doc_id for r in docs.collect())


CLASH = ["score", "gone", "size", "target", "taken", "whole", "cut", "key", "nth", "component_id", "id"]


@pytest.fixture(scope="module")
def odd(spark):
    """Documents with nulls in any column, empty, wordless and very long texts, repeated rows and clashing columns."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").where("doc_id < 60")
    schema = docs.schema
    text, long = docs.orderBy("doc_id").first().text, " ".join(f"w{i}" for i in range(60_000))
    more = [(None, text, None, None, None), (9001, None, None, "a", 0), (9002, "", "en", None, 0), (9003, " \n ", "en", "a", 3), (9004, "one", "en", "a", 3), (9005, long, "en", "a", 9), (9005, long, "en", "a", 9), (9006, text, "en", "a", 9), (9007, text, "en", None, 9)]
    out = docs.unionByName(spark.createDataFrame(more, schema))
    return out.select("*", *[F.lit(f"own {c}").alias(c) for c in CLASH])


@pytest.mark.parametrize("name", [n for n, _ in C.STAGES])
def test_stage_on_odd_rows(spark, odd, name):
    stage = dict(C.STAGES)[name]
    rows = stage(spark, odd, SF).collect()
    before = Counter((r.doc_id, r.text) for r in odd.collect())
    if name == "byte_bpe":
        assert len(rows) == sum(before.values()) and {r.n_tokens for r in rows if r.doc_id in (9001, 9002)} == {0}
    else:
        assert all(r[c] == f"own {c}" for r in rows for c in CLASH)
        after = Counter((r.doc_id, r.text) for r in rows)
        assert set(after) <= set(before)
        if name == "near_dedup":
            assert sum(n for (i, _), n in after.items() if i == 9005) == 2 and after[(9001, None)] == after[(9002, "")] == 1
            assert not any(i in (9006, 9007) for i, _ in after) and sum(i is None for i, _ in after) == 1
    empty = stage(spark, odd.limit(0), SF)
    assert empty.count() == 0 and (name == "byte_bpe" or empty.columns == odd.columns)
