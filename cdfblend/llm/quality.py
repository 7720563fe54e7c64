"""Quality classifier: attention-based multiple-instance learning.

A document is a bag of passages of 64 words.  Every passage of the whole text is encoded (byte-class shares,
word shapes, repetition inside the passage and in its document) and mapped to a hidden vector; gated attention
gives each passage a weight, and the score reads the weighted sum.  Only document labels are used.

Fitting uses at most ``train_docs`` labelled rows, chosen by a digest of the id, and of each at most
``train_passages`` passages at even steps (documented parameters; the passages, at most 100 MB of them, are
collected to the driver; what a passage says of its document is still taken from the whole text).  Scoring is
one pass of Arrow batches without a shuffle, over every passage of whole texts, in pieces of bounded size.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import words
from .memory import row_ranges, tidy

PASSAGE_WORDS = 64
_PUNCT = b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
_CLASS = np.full(256, 5, dtype=np.int64)
_CLASS[97:123], _CLASS[65:91], _CLASS[48:58], _CLASS[32], _CLASS[10], _CLASS[128:] = 0, 1, 2, 3, 4, 6
for _k, _c in enumerate(_PUNCT):
    _CLASS[_c] = 7 + _k
CLASSES = 7 + len(_PUNCT)
FEATURES = CLASSES + 12
_LOW40 = np.uint64((1 << 40) - 1)


def _distinct(group: np.ndarray, value: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Per group the number of distinct values and the count of the most frequent one."""
    if not len(group):
        return np.zeros(n), np.zeros(n)
    key = np.sort((group.astype(np.uint64) << np.uint64(40)) | (value & _LOW40))
    first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    runs = np.diff(np.concatenate([first, [len(key)]]))
    owner = (key[first] >> np.uint64(40)).astype(np.int64)
    most = np.zeros(n)
    np.maximum.at(most, owner, runs)
    return np.bincount(owner, minlength=n).astype(float), most


def passages(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(feature matrix of all passages, passages per row); a row without words has one empty passage."""
    n = len(offsets) - 1
    starts, ends = words.word_spans(raw, offsets)
    hashes = words.word_hashes(raw, starts, ends)
    row = np.searchsorted(offsets, starts, side="right") - 1
    count = np.bincount(row, minlength=n)
    bags = np.maximum(1, -(-count // PASSAGE_WORDS))
    base = np.cumsum(bags) - bags
    total = int(bags.sum())
    nth = np.arange(len(starts)) - (np.cumsum(count) - count)[row]
    owner = base[row] + nth // PASSAGE_WORDS
    size = np.bincount(owner, minlength=total).astype(float)
    begin = np.repeat(offsets[:-1], bags).astype(np.int64)
    opens = np.flatnonzero((nth % PASSAGE_WORDS == 0) & (nth > 0))
    begin[owner[opens]] = starts[opens]
    length = np.diff(np.concatenate([begin, [len(raw)]]))
    of_byte = np.repeat(np.arange(total), length)
    shares = np.bincount(of_byte * CLASSES + _CLASS[raw], minlength=total * CLASSES).reshape(total, CLASSES) / np.maximum(length, 1)[:, None]
    per = np.maximum(size, 1)
    wlen = (ends - starts).astype(float)
    mean = lambda x: np.bincount(owner, x, minlength=total) / per
    again = np.zeros(len(starts))
    again[1:] = (hashes[1:] == hashes[:-1]) & (owner[1:] == owner[:-1])
    kinds = _CLASS[raw[ends - 1]] if len(ends) else np.zeros(0, np.int64)
    heads = _CLASS[raw[starts]] if len(starts) else np.zeros(0, np.int64)
    distinct, most = _distinct(owner, hashes, total)
    doc_distinct, _ = _distinct(row, hashes, n)
    srow, shash = words.shingles(raw, offsets, 4)
    kept, _ = _distinct(srow, shash, n)
    windows = np.bincount(srow, minlength=n) if len(srow) else np.zeros(n)
    spread = lambda x: np.repeat(x, bags)
    cols = [
        mean(wlen) / 10, mean(wlen > 15), mean(wlen == 1), mean(kinds >= 7), mean(heads >= 7), mean(heads == 1),
        distinct / per, most / per, mean(again), np.log1p(size) / 5,
        spread(doc_distinct / np.maximum(count, 1) ** 0.8), spread(1 - kept / np.maximum(windows, 1)),
    ]
    x = np.concatenate([np.sqrt(shares), np.stack(cols, axis=1)], axis=1)
    x[size == 0] = 0
    return x.astype(np.float32), bags


@dataclass
class AttentionModel:
    """Gated attention over passages; ``w`` holds all parameters by name, ``rows`` is the number of texts it was fitted on."""

    mean: np.ndarray
    scale: np.ndarray
    w: dict[str, np.ndarray]
    rows: int = 0

    def forward(self, x: np.ndarray, bags: np.ndarray) -> dict[str, np.ndarray]:
        w, at = self.w, np.cumsum(bags) - bags
        h = np.tanh(x @ w["W"] + w["b"])
        t, g = np.tanh(h @ w["V"]), 1 / (1 + np.exp(-(h @ w["U"])))
        e = (t * g) @ w["a"]
        e = np.exp(e - np.repeat(np.maximum.reduceat(e, at), bags))
        a = e / np.repeat(np.add.reduceat(e, at), bags)
        z = np.add.reduceat(a[:, None] * h, at, axis=0)
        p = 1 / (1 + np.exp(-(z @ w["c"] + w["d"][0])))
        return {"h": h, "t": t, "g": g, "a": a, "z": z, "p": p}

    def score(self, x: np.ndarray, bags: np.ndarray) -> np.ndarray:
        return self.forward((x - self.mean) / self.scale, bags)["p"] if len(bags) else np.zeros(0)

    def gradient(self, x: np.ndarray, bags: np.ndarray, y: np.ndarray, decay: float) -> dict[str, np.ndarray]:
        w, f = self.w, self.forward(x, bags)
        h, t, g, a, z = (f[k] for k in "htgaz")
        dl = (f["p"] - y) / len(y)
        dz = np.repeat(dl[:, None] * w["c"], bags, axis=0)
        da = (dz * h).sum(axis=1)
        mean = np.repeat(np.add.reduceat(a * da, np.cumsum(bags) - bags), bags)
        de = a * (da - mean)
        dtg = de[:, None] * w["a"]
        dt, dg = dtg * g * (1 - t * t), dtg * t * g * (1 - g)
        dh = (a[:, None] * dz + dt @ w["V"].T + dg @ w["U"].T) * (1 - h * h)
        out = {"W": x.T @ dh, "b": dh.sum(axis=0), "V": h.T @ dt, "U": h.T @ dg, "a": (t * g).T @ de, "c": z.T @ dl, "d": np.array([dl.sum()])}
        return {k: v + decay * w[k] if k not in "bd" else v for k, v in out.items()}


def fit(x: np.ndarray, bags: np.ndarray, y: np.ndarray, hidden: int = 16, steps: int = 500, batch: int = 256, rate: float = 0.01, decay: float = 1e-4, seed: int = 5) -> AttentionModel:
    """Adam over batches of bags. Without rows every score is 0.5; with one class it tends to that class."""
    rng = np.random.default_rng(seed)
    mean = x.mean(axis=0) if len(x) else np.zeros(FEATURES)
    scale = np.maximum(x.std(axis=0), 0.02) if len(x) else np.ones(FEATURES)
    shapes = {"W": (x.shape[1], hidden), "V": (hidden, hidden // 2), "U": (hidden, hidden // 2), "a": (hidden // 2,), "c": (hidden,)}
    w = {k: rng.normal(0, 1 / np.sqrt(s[0]), s) for k, s in shapes.items()} | {"b": np.zeros(hidden), "d": np.zeros(1)}
    model = AttentionModel(mean, scale, w, len(bags))
    if not len(bags):
        w["c"] = np.zeros(hidden)
        return model
    xs, at = (x - mean) / scale, np.cumsum(bags) - bags
    m, v = ({k: np.zeros_like(q) for k, q in w.items()} for _ in range(2))
    for step in range(1, steps + 1):
        pick = rng.choice(len(bags), min(batch, len(bags)), replace=False)
        rows = np.concatenate([np.arange(at[i], at[i] + bags[i]) for i in pick])
        grad = model.gradient(xs[rows], bags[pick], y[pick], decay)
        lr = rate * min(1, step / 20) * (1 - step / (steps + 1)) ** 0.5
        for k, q in grad.items():
            m[k] = 0.9 * m[k] + 0.1 * q
            v[k] = 0.99 * v[k] + 0.01 * q * q
            w[k] -= lr * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-8)
    return model


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def _in_pieces(col: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    raw, offsets = words.text_column(col)
    for i, j in words.pieces(offsets):
        yield passages(raw[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])


def train(docs: DataFrame, labels: DataFrame, doc_id: str = "doc_id", text: str = "text", label: str = "quality", train_docs: int = 4000, train_passages: int = 128) -> AttentionModel:
    """Fit on at most ``train_docs`` labelled rows that are not held out; null labels and ids are left out.

    An id with several labels has the greater one; rows that repeat an id all count; without rows the model scores 0.5.
    """
    good = labels.select(F.col(doc_id).cast("long").alias("id"), F.col(label).cast("int").alias("y")).where("id is not null and y in (0, 1)").where(~held_out(F.col("id")))
    chosen = good.groupBy("id").agg(F.max("y").alias("y")).orderBy(F.md5(F.col("id").cast("string")), "id").limit(train_docs)
    rows = docs.select(F.col(doc_id).cast("long").alias("id"), F.col(text).alias("text")).join(F.broadcast(chosen), "id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            xs = [(x, n) for x, n in _in_pieces(b.column("text"))]
            out, k = [], 0
            for x, n in xs:
                for q in np.split(x, np.cumsum(n)[:-1]):
                    some = np.unique(np.linspace(0, len(q) - 1, min(len(q), train_passages)).astype(np.int64))
                    out.append(q[some].tobytes())
                k += len(n)
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("y"), pa.array(out, pa.binary())], ["id", "y", "x"])

    got = sorted(rows.select("id", "y", "text").mapInArrow(tidy(run), "id long, y int, x binary").collect(), key=lambda r: (r.id, r.x))
    xs = [np.frombuffer(bytes(r.x), np.float32).reshape(-1, FEATURES) for r in got]
    x = np.concatenate(xs).astype(np.float64) if xs else np.zeros((0, FEATURES))
    return fit(x, np.array([len(q) for q in xs], np.int64), np.array([r.y for r in got], float))


def score(df: DataFrame, model: AttentionModel, text: str = "text", name: str = "score") -> DataFrame:
    """``df`` with the score of each whole text.

    Null and empty texts count as one empty passage, repeated rows are repeated, an empty table gives an empty table,
    a column named like ``name`` is replaced.
    """
    base = df.drop(name)
    where = base.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, j in row_ranges(b.column(where), words.PIECE_BYTES):
                rows = b.slice(i, j - i)
                s = np.concatenate([model.score(x, n) for x, n in _in_pieces(rows.column(where))])
                yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(s, pa.float64())], [*rows.schema.names, name])

    return base.mapInArrow(tidy(run), base.withColumn(name, F.lit(0.0).cast("double")).schema)


def classify(docs: DataFrame, labels: DataFrame, threshold: float = 0.7, train_docs: int = 4000, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``(doc_id, held_out, score, predicted)`` for every row of ``docs``; labels, language, source and id never enter a score.

    Null texts count as empty, a null id is not held out, repeated rows are repeated, other columns are ignored, an empty
    table gives an empty table; labels that fit no row leave every score at 0.5.
    """
    model = train(docs, labels, doc_id, text, train_docs=train_docs)
    got = score(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")), model)
    return got.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
