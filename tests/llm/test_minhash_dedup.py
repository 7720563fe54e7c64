import re
from fractions import Fraction

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import types as T

from cdfblend.llm import minhash_dedup as M
from cdfblend.llm import words
from cdfblend.llm.minhash_dedup import near_duplicates, one_permutation

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("hub", T.StringType()), T.StructField("digest", T.StringType())])


def shingle_set(text, width):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(w[i : i + width]) for i in range(len(w) - width + 1)} if len(w) >= width else ({tuple(w)} if w else set())


def brute(rows, width, percent):
    sets = {i: shingle_set(t, width) for i, t in rows if i is not None}
    ids = sorted(sets)
    low = {i: i for i in ids}

    def find(a):
        while low[a] != a:
            a = low[a]
        return a

    for a in range(len(ids)):
        for b in range(a + 1, len(ids)):
            x, y = sets[ids[a]], sets[ids[b]]
            if x and y and 100 * len(x & y) >= percent * len(x | y):
                p, q = find(ids[a]), find(ids[b])
                low[max(p, q)] = min(p, q)
    return {(i, len(sets[i]), find(i)) for i in ids}


def corpus(n=220, seed=1):
    rng = np.random.default_rng(seed)
    vocab = [f"w{k}É" if k % 7 == 0 else f"W{k}" for k in range(400)]
    rows = []
    for i in range(n):
        if i % 11 == 0 or len(rows) < 3:
            w = list(rng.choice(vocab, rng.integers(1, 120)))
        else:  # chains of edits: neighbours link, ends do not
            w = rows[-1][1].split(" ")
            for _ in range(rng.integers(0, 4)):
                w[rng.integers(0, len(w))] = str(rng.choice(vocab))
        rows.append((int(rng.permutation(10**6)[0]) * 1000 + i, " ".join(w)))
    rows += [(5, None), (6, ""), (7, " \t\n"), (8, "one"), (9, "ONE"), (10, "one two"), (11, rows[0][1].upper().replace("É", "É")), (12, " ")]
    return rows


def test_shingle_sets_agree_with_plain_python():
    rows = corpus()
    for width in (1, 4, 5):
        got = [len(s) for s in words.shingle_sets(pa.array([t for _, t in rows]), width)]
        assert got == [len(shingle_set(t, width)) for _, t in rows]


def test_signature_estimates_similarity():
    oph = one_permutation(160)
    base = words.stream(4000, 5)
    a, b = np.sort(base[:3600]), np.sort(base[400:])
    assert abs((oph.of(a) == oph.of(b)).mean() - 0.8) < 0.12
    small = np.sort(base[:3])
    assert set(oph.of(small).tolist()) == set(small.tolist())


@pytest.mark.parametrize("width,block", [(4, 256), (5, 5)])
def test_matches_brute_force(spark, width, block):
    rows = corpus()
    df = spark.createDataFrame([(*r, "a", "b") for r in rows] + [(None, "x y z", "", "")], SCHEMA)
    got = near_duplicates(df, width=width, block=block).collect()
    assert {(r.doc_id, r.n_shingles, r.component_id) for r in got if r.doc_id is not None} == brute(rows, width, 80)
    assert all(r.kept == (r.doc_id == r.component_id) for r in got if r.doc_id is not None) and len(got) == len(rows) + 1


def test_no_pair_at_the_threshold_is_missed():
    # 2,400 pairs at similarity 0.8 exactly: all share a band, and the tile's sketch excludes none
    oph, fine, seed = one_permutation(160), one_permutation(M.TILE_BINS), 0
    for m in (1, 2, 3, 5, 8, 12, 20, 30, 45, 60, 75, 90):
        for _ in range(200):
            seed += 1
            pool = words.stream(5 * m, 1000 + seed)
            cut = 4 * m + m // 2
            a, b = np.sort(pool[:cut]), np.sort(np.concatenate([pool[: 4 * m], pool[cut:]]))
            assert (oph.of(a).reshape(32, 5) == oph.of(b).reshape(32, 5)).all(axis=1).any()
            sketches = np.stack([fine.of(x).astype(np.uint8) for x in (a, b)])
            tile = M.Tile([1, 2], [1, 2], np.array([len(a), len(b)]), sketches, np.zeros((2, 32), np.int64), 0, 0, lambda r: np.triu(np.ones((2, 2), bool), 1)[r], 80)
            assert len(tile.candidates()[0]) == 1 and tile.forest([a, b]) == [(1, 2)]


def test_hot_bucket_of_many_components(spark):
    # one passage shared by all puts many unlike documents into the same buckets; pairs of near copies hide among them
    rng = np.random.default_rng(3)
    shared = [f"s{k}" for k in range(60)]
    rows = []
    for i in range(90):
        own = [f"d{i}x{k}" for k in range(45)]
        rows.append((2 * i, " ".join(shared + own)))
        if i % 3 == 0:
            own[int(rng.integers(0, 45))] = "other"
            rows.append((2 * i + 1, " ".join(shared + own)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for block in (M.BLOCK, 9):
        got = near_duplicates(df, width=4, block=block).collect()
        assert {(r.doc_id, r.n_shingles, r.component_id) for r in got} == brute(rows, 4, 80)


def test_repeated_ids_and_very_long_text(spark):
    long = " ".join(f"w{i}" for i in range(150_000))
    rows = [(1, "a b c d e f"), (1, "a b c d e f"), (1, "p q r s t u"), (2, "p q r s t u"), (3, long), (4, long + " end"), (5, "p q r s t u v w x y")]
    got = sorted((r.doc_id, r.n_shingles, r.component_id) for r in near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), width=4).collect())
    assert got == [(1, 3, 1), (1, 3, 1), (1, 3, 1), (2, 3, 1), (3, 149_997, 3), (4, 149_998, 3), (5, 7, 5)]


def test_sql_agrees(spark, tmp_path):
    import duckdb

    from cdfblend.llm.queries import ORACLES, QUERIES

    rows = corpus(150, 4)
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    got = [tuple(r) for r in QUERIES["op2_minhash_dedup"](spark, str(tmp_path)).select("doc_id", "n_shingles", "component_id", "kept").collect()]
    want = con.execute(f"SELECT doc_id, n_shingles, component_id, kept FROM ({ORACLES['op2_minhash_dedup']}) AS z").fetchall()
    assert sorted(got) == sorted(want) and sum(not r[3] for r in got) > 20


def test_similarity_bound_is_inclusive(spark):
    words_ = [f"t{i}" for i in range(12)]
    rows = [(1, " ".join(words_)), (2, " ".join(words_[:10]))]  # 9 and 7 windows of four
    assert Fraction(7, 9) < Fraction(8, 10)
    got = {r.doc_id: r.component_id for r in near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), width=4, percent=77).collect()}
    assert got == {1: 1, 2: 1}


def test_empty_table(spark):
    assert near_duplicates(spark.createDataFrame([], SCHEMA)).count() == 0
