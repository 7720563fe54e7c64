import math

import numpy as np
from pyspark.sql import types as T

from cdfblend.llm.embedding_dedup import link_vectors

SCHEMA = T.StructType([T.StructField("vec_id", T.LongType()), T.StructField("embedding", T.ArrayType(T.FloatType())), T.StructField("label", T.IntegerType()), T.StructField("rep", T.StringType()), T.StructField("key", T.StringType())])


def brute(rows, t):
    ids = [r[0] for r in rows]
    ok = []
    for _, v, lab in rows:
        ok.append(v is not None and lab is not None and len(v) > 0 and all(x is not None and math.isfinite(x) for x in v) and any(x != 0 for x in v))
    n = len(rows)
    links, low = [0] * n, list(range(n))
    xs = [np.array(np.array(v, np.float32), np.float64) if o else None for (_, v, _), o in zip(rows, ok)]

    def find(a):
        while low[a] != a:
            a = low[a]
        return a

    for i in range(n):
        for j in range(i + 1, n):
            if ok[i] and ok[j] and rows[i][2] == rows[j][2] and len(xs[i]) == len(xs[j]):
                if xs[i] @ xs[j] / (np.linalg.norm(xs[i]) * np.linalg.norm(xs[j])) >= t:
                    links[i] += 1
                    links[j] += 1
                    a, b = find(i), find(j)
                    if a != b:
                        low[b] = a
    comp = {}
    for i in range(n):
        comp[find(i)] = min(comp.get(find(i), ids[i]), ids[i])
    return {(ids[i], links[i], comp[find(i)]) for i in range(n)}


def result(df):
    return {(r.vec_id, r.n_links, r.component_id) for r in df.collect()}


def test_matches_brute_force_with_bad_vectors(spark):
    rng = np.random.default_rng(3)
    rows = []
    for i in range(260):
        base = rng.normal(size=6) if i % 4 == 0 or not rows else np.array(rows[-1][1][:6], float) + rng.normal(size=6) * 0.06
        rows.append((i, [float(np.float32(x)) for x in base], int(rng.integers(0, 2))))
    hot = rows[5][1]
    rows += [(1000 + i, hot, rows[5][2]) for i in range(40)]
    rows += [(2000, None, 1), (2001, [0.0] * 6, 1), (2002, [float("nan")] * 6, 1), (2003, hot, None), (2004, [1.0, None], 1), (2005, [], 1), (2006, [float("inf")] * 6, 0), (2007, [2.0, 1.0], 1), (2008, [4.0, 2.0], 1)]
    df = spark.createDataFrame([(*r, "x", "y") for r in rows], SCHEMA)
    for t, block, axes in ((0.98, 1024, None), (0.9, 16, None), (0.98, 7, None), (0.98, 64, 3)):
        assert result(link_vectors(df, threshold=t, block=block, axes=axes)) == brute(rows, t)


def test_values_of_any_size_null_and_repeated_ids(spark):
    schema = T.StructType([T.StructField("vec_id", T.LongType()), T.StructField("embedding", T.ArrayType(T.DoubleType())), T.StructField("label", T.StringType())])
    far = [(1, [1e200, 2e200, 0.0], "a"), (2, [1.0, 2.0, 0.001], "a"), (3, [1e-200, 2e-200, 0.0], "a"), (4, [-1.0, -2.0, 0.0], "a"), (5, [1e308, 1e308, 1e308], "a"), (6, [5e-324, 5e-324, 5e-324], "a")]
    rows = {(r.vec_id, r.n_links, r.component_id) for r in link_vectors(spark.createDataFrame(far, schema)).collect()}
    assert rows == {(1, 2, 1), (2, 2, 1), (3, 2, 1), (4, 0, 4), (5, 1, 5), (6, 1, 5)}
    same = [(None, [1.0, 2.0], "a"), (7, [1.0, 2.0], "a"), (7, [1.0, 2.0], "a"), (9, [1.0, 2.01], "a")]
    got = sorted((r.vec_id is None, r.vec_id or 0, r.n_links, r.component_id, r.kept) for r in link_vectors(spark.createDataFrame(same, schema)).collect())
    assert got == [(False, 7, 2, 7, True), (False, 7, 2, 7, True), (False, 9, 2, 7, False), (True, 0, 0, None, False)]


def test_hot_cell_is_cut_into_blocks(spark):
    # a third of all rows in one narrow cone, far more than a block: every link is found, and no tile holds the cell
    rng = np.random.default_rng(8)
    cone = rng.normal(size=(120, 8)) * 0.03 + np.eye(8)[0]
    rest = rng.normal(size=(240, 8))
    rows = [(i, [float(np.float32(x)) for x in v], 1) for i, v in enumerate(np.concatenate([cone, rest]))]
    df = spark.createDataFrame([(*r, "x", "y") for r in rows], SCHEMA)
    assert result(link_vectors(df, block=10)) == brute(rows, 0.98)


def test_sql_agrees_on_planted_links(spark, tmp_path):
    import duckdb

    from cdfblend.llm.queries import ORACLES, QUERIES

    rng = np.random.default_rng(5)
    base = rng.normal(size=(30, 16))
    rows = [(k, [float(np.float32(x)) for x in base[k % 30] + 0.04 * rng.normal(size=16)], k % 3) for k in range(120)] + [(500, None, 1), (501, [0.0] * 16, 1), (502, [float("nan")] * 16, 2), (503, [1.0] * 16, None)]
    spark.createDataFrame([(*r, "x", "y") for r in rows], SCHEMA).select("vec_id", "embedding", "label").write.parquet(f"{tmp_path}/embeddings.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet/*.parquet'")
    want = con.execute(f"SELECT vec_id, n_links, component_id, kept FROM ({ORACLES['op1_embedding_dedup']}) AS z").fetchall()
    got = [tuple(r) for r in QUERIES["op1_embedding_dedup"](spark, str(tmp_path)).select("vec_id", "n_links", "component_id", "kept").collect()]
    assert sorted(got) == sorted(want) and sum(r[1] > 0 for r in got) > 40


def test_empty_table(spark):
    assert link_vectors(spark.createDataFrame([], SCHEMA)).count() == 0
