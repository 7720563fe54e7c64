import hashlib
import random
import unicodedata

import pytest
from pyspark.sql import types as T

from cdfblend.llm import fingerprints as M

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("id", T.StringType()), T.StructField("hub", T.StringType())])


def canon(t):
    return " ".join(unicodedata.normalize("NFKC", unicodedata.normalize("NFKC", t).casefold()).split())


def test_matches_brute_force(spark):
    random.seed(3)
    rows = [(i * 3, "".join(random.choices("aAbé ﬁß漢🙂\n\t", k=random.choice([0, 1, 3, 4, 50, 900])))) for i in range(150)]
    rows += [(7, None), (8, "Some Text"), (10, "some  text "), (11, "SOME TEXT")]
    random.shuffle(rows)
    got = {r.doc_id: r for r in M.fingerprint(spark.createDataFrame([(*r, "x", "y") for r in rows], SCHEMA)).collect()}
    assert len(got) == len(rows)
    order = sorted((i, t or "") for i, t in rows)
    seen = {}
    for k, (i, t) in enumerate(order):
        nxt = order[(k + 1) % len(order)][1]
        n = len(t) // 4
        e = t[: len(t) - n] + nxt[:n]
        r = got[i]
        assert r.n_chars == len(t) and r.edited_sha256 == hashlib.sha256(e.encode()).hexdigest()
        assert r.near_edited == float(canon(t) == canon(e)) and r.near_next == float(canon(t) == canon(nxt))
        seen.setdefault(canon(t), set()).add(r.fingerprint)
        seen.setdefault(canon(e), set()).add(r.edited_fingerprint)
    assert all(len(v) == 1 for v in seen.values()) and len({next(iter(v)) for v in seen.values()}) == len(seen)


def test_equal_digests_of_different_bytes_are_told_apart(spark, monkeypatch):
    class Weak:
        xxh3_128_digest = staticmethod(lambda b: hashlib.md5(b[:2]).digest())
        xxh3_128_hexdigest = staticmethod(lambda b: hashlib.md5(b[:2]).hexdigest())

    rows = [(1, "aaXX"), (2, "aaYY"), (3, "aaxx"), (4, "bb")]
    df = spark.createDataFrame([(*r, "x", "y") for r in rows], SCHEMA)
    from pyspark import cloudpickle as shipped

    monkeypatch.setattr(M, "xxhash", Weak)
    shipped.register_pickle_by_value(M)
    try:
        got = {r.doc_id: r.fingerprint for r in M.fingerprint(df).collect()}
    finally:
        shipped.unregister_pickle_by_value(M)
    assert got[1] == got[3] != got[2]


@pytest.mark.parametrize("rows", [[], [(1, "only one text")], [(None, "a b c d e"), (1, None), (1, "rep eat"), (1, "rep eat")]])
def test_small_tables(spark, rows):
    out = M.fingerprint(spark.createDataFrame([(*r, "", "") for r in rows], SCHEMA)).collect()
    assert len(out) == len(rows)
