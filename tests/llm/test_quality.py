import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import types as T

from cdfblend.llm import quality as Q

DOCS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("score", T.StringType()), T.StructField("y", T.StringType())])
LABELS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("quality", T.IntegerType()), T.StructField("text", T.StringType())])


def made(n=400):
    rng = np.random.default_rng(0)
    docs, labels = [], []
    for i in range(n):
        good = i % 3 > 0
        w = ["".join(rng.choice(list("abcdefgh"), rng.integers(2, 9))) for _ in range(int(rng.integers(5, 300)))]
        text = " ".join(w) if good else " ".join(x.upper() + "!!" if i % 2 else x + "%%%" for x in w)
        docs.append((i, text, "s", "y"))
        labels.append((i, int(good), "t"))
    return docs, labels


def test_features_of_whole_texts_against_plain_python():
    texts = ["", None, "a b c", "word " * 200, " lead\n" + "x! " * 70, "é" * 9]
    x, bags = Q.passages(*Q.words.text_column(pa.array(texts, pa.string())))
    assert bags.tolist() == [1, 1, 1, 4, 2, 1] and x.shape == (10, Q.FEATURES)
    assert not x[0].any() and not x[1].any()
    marks = [m.end() - m.start() for m in re.finditer(r"\S+", texts[4])]
    assert np.isclose(x[7][Q.CLASSES] * 10, np.mean(marks[:64])) and np.isclose(x[8][Q.CLASSES] * 10, np.mean(marks[64:]))


def plain_features(text):
    """Feature rows of one text, passage by passage and word by word."""
    raw = (text or "").encode()
    words = [(m.start(), m.end()) for m in re.finditer(rb"[^\x20\x09-\x0D]+", raw)]
    if not words:
        return [[0.0] * Q.FEATURES]
    low = [raw[a:b].lower() for a, b in words]  # bytes.lower folds A-Z alone
    windows = [tuple(low[i : i + 4]) for i in range(len(low) - 3)] or [tuple(low)]
    spread = [len(set(low)) / len(low) ** 0.8, 1 - len(set(windows)) / len(windows)]
    punctuation = set(b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~")
    out = []
    for lo in range(0, len(words), 64):
        part, mine = words[lo : lo + 64], low[lo : lo + 64]
        begin = 0 if lo == 0 else part[0][0]
        end = words[lo + 64][0] if lo + 64 < len(words) else len(raw)
        span = raw[begin:end]
        shares = [0] * Q.CLASSES
        for byte in span:
            c = 0 if 97 <= byte <= 122 else 1 if 65 <= byte <= 90 else 2 if 48 <= byte <= 57 else 3 if byte == 32 else 4 if byte == 10 else 6 if byte >= 128 else 5
            shares[7 + sorted(punctuation).index(byte) if byte in punctuation else c] += 1
        n = len(part)
        size = [b - a for a, b in part]
        cols = [
            sum(size) / n / 10, sum(s > 15 for s in size) / n, sum(s == 1 for s in size) / n,
            sum(raw[b - 1] in punctuation for _, b in part) / n, sum(raw[a] in punctuation for a, _ in part) / n, sum(65 <= raw[a] <= 90 for a, _ in part) / n,
            len(set(mine)) / n, max(mine.count(w) for w in mine) / n, sum(a == b for a, b in zip(mine, mine[1:])) / n, np.log1p(n) / 5, *spread,
        ]
        out.append([(s / len(span)) ** 0.5 for s in shares] + cols)
    return out


def plain_score(model, rows):
    """The forward pass of one bag in loops."""
    w, hidden, energy = model.w, [], []
    for row in rows:
        x = [(v - m) / s for v, m, s in zip(row, model.mean, model.scale)]
        h = [np.tanh(sum(a * b for a, b in zip(x, w["W"][:, k])) + w["b"][k]) for k in range(len(w["b"]))]
        gate = [np.tanh(sum(a * b for a, b in zip(h, w["V"][:, k]))) / (1 + np.exp(-sum(a * b for a, b in zip(h, w["U"][:, k])))) for k in range(len(w["a"]))]
        hidden.append(h)
        energy.append(np.exp(sum(a * b for a, b in zip(gate, w["a"]))))
    z = [sum(e * h[k] for e, h in zip(energy, hidden)) / sum(energy) for k in range(len(w["b"]))]
    return 1 / (1 + np.exp(-(sum(a * b for a, b in zip(z, w["c"])) + w["d"][0])))


def test_scores_equal_a_pass_in_loops(spark):
    docs, labels = made(60)
    long = " ".join(f"Word{i}, and (more) é" for i in range(2_000))  # 8,000 words: many passages in one bag
    rows = [*docs[:12], (900, None, "", ""), (901, "", "", ""), (902, " \n ", "", ""), (903, "one", "", ""), (904, long, "", ""), (905, "a A a A " * 90, "", "")]
    df = spark.createDataFrame(rows, DOCS)
    model = Q.train(spark.createDataFrame(docs, DOCS), spark.createDataFrame(labels, LABELS))
    for r in Q.score(df, model, name="p").collect():
        assert abs(r.p - plain_score(model, plain_features(r.text))) < 1e-4


def test_labels_that_tie_and_bounds_of_training(spark):
    docs, labels = made(80)
    df = spark.createDataFrame(docs, DOCS)
    twice = spark.createDataFrame(labels + [(i, 0, "again") for i, _, _ in labels], LABELS)
    once = spark.createDataFrame(labels, LABELS)
    a, b = Q.train(df, twice), Q.train(df, once)
    assert a.rows == b.rows and all(np.array_equal(a.w[k], b.w[k]) for k in a.w)
    assert Q.train(df, once, train_docs=10).rows == 10
    one = Q.train(df, once, train_passages=1)
    assert one.rows == b.rows and not np.array_equal(one.w["W"], b.w["W"])


def test_gradient_matches_differences():
    rng = np.random.default_rng(1)
    x, bags, y = rng.normal(size=(12, Q.FEATURES)), np.array([3, 1, 5, 3]), np.array([1.0, 0, 1, 0])
    model = Q.fit(x, bags, y, hidden=6, steps=3)
    grad = model.gradient(x, bags, y, 0.0)

    def loss():
        p = model.forward(x, bags)["p"]
        return -(y * np.log(p) + (1 - y) * np.log(1 - p)).mean()

    for k, w in model.w.items():
        at = tuple(rng.integers(0, s) for s in w.shape)
        old, h = w[at], 1e-6
        w[at] = old + h
        up = loss()
        w[at] = old - h
        down = loss()
        w[at] = old
        assert abs((up - down) / (2 * h) - grad[k][at]) < 1e-6


def test_held_out_accuracy(spark):
    docs, labels = made()
    extra = [(-1, None, "", ""), (-2, "", "", ""), (None, "null id", "", ""), (5, docs[5][1], "", "")]
    rows = Q.classify(spark.createDataFrame(docs + extra, DOCS), spark.createDataFrame(labels + [(7, None, ""), (None, 1, "")], LABELS)).collect()
    assert len(rows) == len(docs) + len(extra)
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in rows)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in rows if r.doc_id is not None)
    truth = dict((i, q) for i, q, _ in labels)
    judged = [r.predicted == truth[r.doc_id] for r in rows if r.held_out and r.doc_id in truth]
    assert np.mean(judged) > 0.97


def test_no_labels_and_no_rows(spark):
    docs, labels = made(6)
    none = spark.createDataFrame([], LABELS)
    assert {r.score for r in Q.classify(spark.createDataFrame(docs, DOCS), none).collect()} == {0.5}
    assert Q.classify(spark.createDataFrame([], DOCS), none).count() == 0
