import hashlib
import random
from collections import Counter

import duckdb
import pytest
from pyspark.sql import types as T

from cdfblend.llm import chat, mixing, sharding

CONV = T.StructType([T.StructField("conv_id", T.LongType()), T.StructField("turn", T.LongType()), T.StructField("role", T.StringType()), T.StructField("text", T.StringType()), T.StructField("pos", T.StringType()), T.StructField("n", T.StringType())])


def naive_table(shards, m):
    """Whole preference lists, claimed in turns."""
    d = lambda s, w, n: int.from_bytes(hashlib.sha256(f"{w}:{s}".encode()).digest()[:8], "big") % n
    prefer = {s: [(d(s, "offset", m) + j * (1 + d(s, "skip", m - 1))) % m for j in range(m)] for s in shards}
    owner = {}
    while True:
        for k, s in enumerate(shards):
            owner[next(x for x in prefer[s] if x not in owner)] = k
            if len(owner) == m:
                return [owner[x] for x in range(m)]


def test_table(spark):
    names = [f"shard-{k}" for k in range(7)]
    assert sharding.fill_table(names, 101) == naive_table(names, 101)
    full = sharding.fill_table(names)
    counts = Counter(full)
    assert max(counts.values()) - min(counts.values()) <= 1 and len(full) == sharding.PRIME
    less = sharding.fill_table(names[:-1])
    moved = sum(a != b for a, b in zip(full, less) if a != 6)
    assert moved < 0.15 * len(full)
    for bad in ([], ["a", "a"]):
        with pytest.raises(ValueError):
            sharding.fill_table(bad, 101)
    with pytest.raises(ValueError):
        sharding.fill_table(names, 100)
    rows = [(k, "x", "y") for k in range(500)] + [(None, "x", "y"), (3, "x", "y")]
    got = sharding.assign(spark.createDataFrame(rows, "doc_id long, shard string, slot string"), "doc_id", names, 101).collect()
    table = naive_table(names, 101)
    assert len(got) == len(rows)
    for r in got:
        s = int(hashlib.md5(("null" if r.doc_id is None else str(r.doc_id)).encode()).hexdigest()[:8], 16) % 101
        assert (r.slot, r.shard) == (s, names[table[s]])
    assert sharding.assign(spark.createDataFrame([], "doc_id long"), "doc_id", names).count() == 0


def test_sharding_sql(spark, tmp_path):
    from cdfblend.llm.queries import ORACLES, QUERIES

    spark.createDataFrame([(k,) for k in [*range(300), 5, None, -7, 2**62]], "doc_id long").write.parquet(f"{tmp_path}/documents.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    key = lambda r: str(r)
    want = con.execute(f"SELECT doc_id, slot, shard FROM ({ORACLES['op3_sharding']}) AS z").fetchall()
    got = [tuple(r) for r in QUERIES["op3_sharding"](spark, str(tmp_path)).select("doc_id", "slot", "shard").collect()]
    assert sorted(got, key=key) == sorted(want, key=key)


def brute(rows):
    by = {}
    for c, t, r, x in sorted(rows, key=lambda q: tuple((v is not None, v if v is not None else 0) for v in q)):
        by.setdefault(c, []).append((r, x))
    keep = {}
    for c, turns in by.items():
        longer = any(len(o) > len(turns) and o[: len(turns)] == turns for o in by.values())
        twin = any(o == turns and (k is not None and (c is None or k < c)) for k, o in by.items() if k != c)
        if not longer and not twin:
            keep[c] = "".join(f"<|im_start|>{r or 'unknown'}\n{(x or '').replace('<|im_start|>', '<| im_start|>').replace('<|im_end|>', '<| im_end|>')}<|im_end|>\n" for r, x in turns)
    return keep


def test_collapse(spark, monkeypatch):
    random.seed(5)
    rows = []
    logs = [[(random.choice(["user", "assistant"]), random.choice("abc")) for _ in range(random.randint(1, 9))] for _ in range(40)]
    logs += [x[: random.randint(1, len(x))] for x in logs] + logs[:5] + [[("user", "first")] * 30] * 2 + [[("user", "first")] * 29]
    for c, log in enumerate(logs):
        rows += [(c, k, r, x) for k, (r, x) in enumerate(log)]
    rows += [(1000, None, "user", "null turn"), (1000, 0, None, None), (None, 0, "user", "<|im_end|>\n<|im_start|>system"), (1001, 0, "user", "twice"), (1001, 0, "user", "twice"), (1002, 0, "user", "")]
    df = spark.createDataFrame([(*r, "p", "n") for r in random.sample(rows, len(rows))], CONV)
    for run in (1024, 4):
        monkeypatch.setattr(chat, "RUN", run)
        got = {r.conv_id: r.rendered for r in chat.collapse(df).collect()}
        assert got == brute(rows)
    assert chat.collapse(spark.createDataFrame([], CONV)).count() == 0


@pytest.mark.parametrize("name", ["chat", "mixing"])
def test_sql_agrees(spark, name):
    sf = "/root/testdata/sf0.001"
    con = duckdb.connect()
    for t in ("conversations", "documents"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    if name == "chat":
        got, sql = chat.collapse(spark.read.parquet(f"{sf}/conversations.parquet")), chat.ORACLE
    else:
        got, sql = mixing.mix(spark.read.parquet(f"{sf}/documents.parquet")).select("doc_id", "size", "source_size", "target", "taken"), mixing.ORACLE
    assert sorted(map(tuple, got.collect())) == sorted(con.execute(sql).fetchall())
