import random
import re
from collections import Counter

from pyspark.sql import functions as F
from pyspark.sql import types as T

from cdfblend.llm.mixing import mix, repeat_rows

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("source", T.StringType()), T.StructField("size", T.StringType()), T.StructField("level", T.StringType())])


def fill(sizes, weights, cap):
    """Clamp and reshare until no source is above its cap."""
    names = sorted([s for s in sizes if s is not None]) + ([None] if None in sizes else [])
    w = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    total, clamped = sum(sizes.values()), set()
    while True:
        rest = total - sum(cap * sizes[s] for s in clamped)
        free = sum(w[s] for s in names if s not in clamped)
        target = {s: cap * sizes[s] if s in clamped else rest * w[s] / free for s in names}
        over = {s for s in names if s not in clamped and target[s] > cap * sizes[s] + 1e-9}
        if not over:
            return target
        clamped |= over


def test_targets_and_quotas(spark):
    random.seed(2)
    for n, sources in ((400, ["b", "a", "é", None, "z"]), (60, [None, "x"]), (30, ["only"])):
        odds = [2.0 ** -i for i in range(len(sources))]
        rows = [(i, " ".join(["w"] * random.choice([1, 2, 5, 40])), random.choices(sources, odds)[0], "s", "l") for i in range(n)]
        rows += [(n, None, sources[0], "s", "l"), (n + 1, "", sources[0], "s", "l")]
        df = spark.createDataFrame(rows, SCHEMA)
        got = {r.doc_id: r for r in mix(df, (5, 2, 1), 3.0).collect()}
        assert len(got) == len(rows)
        size = {i: len(re.findall(r"[^\x20\x09-\x0D]+", t or "")) for i, t, *_ in rows}
        total = {}
        for i, _, s, *_ in rows:
            total[s] = total.get(s, 0) + size[i]
        target = fill(total, (5, 2, 1), 3.0)
        taken = dict.fromkeys(total, 0)
        for i, _, s, *_ in rows:
            r = got[i]
            assert (r.size, r.source_size) == (size[i], total[s]) and abs(r.target - target[s]) < 1e-6 * max(1, target[s])
            assert 0 <= r.taken <= 3 * r.size and r.taken == r.size * r.repeats
            taken[s] += r.taken
        for s in total:
            assert abs(taken[s] - target[s]) <= max(size.values()) / 2 + 1e-6
        again = {r.doc_id: r.taken for r in mix(df.repartition(7), (5, 2, 1), 3.0).collect()}
        assert again == {i: r.taken for i, r in got.items()}


def test_own_columns_stay(spark):
    names = ["doc_id", "text", "source", "_whole", "_cut", "_s", "whole", "cut", "key", "size_", "Repeats_"]
    df = spark.createDataFrame([(i, "w " * (i % 7), "ab"[i % 2], *[f"{c}!" for c in names[3:]]) for i in range(50)], names)
    out = mix(df)
    assert out.columns == [*names, "size", "source_size", "target", "repeats", "taken"]
    assert all(r[c] == f"{c}!" for r in out.collect() for c in names[3:])
    rows = repeat_rows(df.withColumn("size", F.lit("own")).withColumn("REPEATS", F.lit("own"))).collect()
    times = {r.doc_id: r.repeats for r in out.collect()}
    assert all(r["size"] == r["REPEATS"] == "own" for r in rows)
    assert Counter(r.doc_id for r in rows) == Counter({i: n for i, n in times.items() if n})


def test_empty_and_wordless(spark):
    assert mix(spark.createDataFrame([], SCHEMA)).count() == 0
    rows = mix(spark.createDataFrame([(1, None, None, "", ""), (1, " ", "a", "", "")], SCHEMA)).collect()
    assert [(r.size, r.taken) for r in rows] == [(0, 0), (0, 0)]
