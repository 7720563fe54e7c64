"""Byte-level BPE by corpus-level merge replay.

Texts are split by the vocabulary's pattern.  A task takes its partition in blocks of at most
``BLOCK_BYTES`` of text; the distinct words of a block that the worker does not hold yet form one corpus of symbols,
a linked list in arrays.  An inverted index leads from a merge to the positions of its pair.  Merges are
taken in rank order, each applied at all its positions in one array step (overlapping positions from
left to right), and only the touched neighbours are looked up and indexed anew.

Words in use stay with the worker between blocks and tasks, at most ``KEEP_WORDS`` of them and ``KEEP_BYTES`` of
their text, the most used first, so common words are replayed once per worker.  Encoding needs no shuffle
and no state between rows beyond that bounded memory.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import re
import unicodedata
from array import array
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .memory import row_ranges, tidy

BLOCK_BYTES = 8 << 20
KEEP_WORDS = 100_000
KEEP_BYTES = 2 << 20
#: Texts of more characters are split match by match instead of into a list of words.
LONG_TEXT = 4 << 20
#: The pattern's character classes are spelled out for texts below this code point, where the faster ``re`` applies.
LATIN_END = 0x250


class Merges:
    """All pairs of tokens whose bytes joined are a token, with that token's rank, as a sorted table."""

    def __init__(self, ranks: dict[bytes, int]):
        self.size = max(ranks.values()) + 1
        found: dict[int, int] = {}
        for token, rank in ranks.items():
            for cut in range(1, len(token)):
                a, b = ranks.get(token[:cut]), ranks.get(token[cut:])
                if a is not None and b is not None:
                    found[a * self.size + b] = rank
        self.keys = np.array(sorted(found), np.int64)
        self.ranks = np.array([found[k] for k in self.keys.tolist()], np.int32)

    def of(self, keys: np.ndarray) -> np.ndarray:
        """Rank per pair key, -1 where the pair does not merge."""
        if not len(self.keys):
            return np.full(len(keys), -1, np.int32)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return np.where(self.keys[at] == keys, self.ranks[at], -1)


def replay(merges: Merges, single: np.ndarray, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(ids of all words, one after another; number of ids per word), by one replay over all words."""
    lens = np.array([len(w) for w in words], np.int64)
    stop = np.cumsum(lens)
    token = single[np.frombuffer(b"".join(words), np.uint8)]
    n = len(token)
    ahead, behind = np.arange(1, n + 1, dtype=np.int32), np.arange(-1, n - 1, dtype=np.int32)
    full = lens > 0
    ahead[stop[full] - 1], behind[(stop - lens)[full]] = -1, -1
    index: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {}
    queue: list[int] = []

    def enter(at: np.ndarray) -> None:
        """Index the pairs that begin at some positions."""
        key = token[at].astype(np.int64) * merges.size + token[ahead[at]]
        rank = merges.of(key)
        hit = rank >= 0
        at, key, rank = at[hit], key[hit], rank[hit]
        if not len(at):
            return
        if len(at) > 1:
            order = np.lexsort((at, rank))
            order = order[np.diff(at[order], prepend=-1) != 0]
            at, key, rank = at[order], key[order], rank[order]
        cut = np.flatnonzero(np.diff(rank, prepend=-1)).tolist()
        for lo, hi in zip(cut, [*cut[1:], len(rank)], strict=True):
            r = int(rank[lo])
            if r not in index:
                index[r] = []
                heapq.heappush(queue, r)
            index[r].append((at[lo:hi], key[lo:hi]))

    enter(np.flatnonzero(ahead >= 0).astype(np.int32))
    while queue:
        rank = heapq.heappop(queue)
        found = index.pop(rank)
        at, key = found[0] if len(found) == 1 else (np.concatenate(x) for x in zip(*found, strict=True))
        j = ahead[at]
        # A position is stale once either symbol was merged (then its pair is another, or it has no next one).
        fresh = (j >= 0) & (token[at].astype(np.int64) * merges.size + token[j] == key)
        at = np.unique(at[fresh])
        if not len(at):
            continue
        j = ahead[at]
        linked = j[:-1] == at[1:]
        if linked.any():  # in a run of overlapping pairs every second one merges
            nth = np.arange(len(at))
            first = np.maximum.accumulate(np.where(np.concatenate([[True], ~linked]), nth, 0))
            turn = (nth - first) % 2 == 0
            at, j = at[turn], j[turn]
        k = ahead[j]
        token[at], token[j] = rank, -1
        ahead[at] = k
        inner = k >= 0
        behind[k[inner]] = at[inner]
        h = behind[at]
        enter(np.concatenate([at[inner], h[h >= 0]]))
    left = token >= 0
    upto = np.concatenate([[0], np.cumsum(left)])
    return token[left], upto[stop] - upto[stop - lens]


class _Numbers(dict):
    """Word -> its number, in order of first use."""

    def __missing__(self, word: str) -> int:
        self[word] = n = len(self)
        return n


def _latin(pattern: str) -> re.Pattern | None:
    """The pattern for the ``re`` module, equal on texts below ``LATIN_END``; None where it cannot be rewritten."""
    if re.sub(r"\\p\{[LN]\}|\\[sS]", "", pattern).count("\\"):
        return None
    chars = [chr(i) for i in range(LATIN_END)]
    spell = lambda some: "".join(re.escape(c) for c in some)
    letters, numbers = (spell(c for c in chars if unicodedata.category(c)[0] == kind) for kind in "LN")
    white = spell(c for c in chars if regex.match(r"\s", c))
    inside = False
    out = []
    for part in re.findall(r"\\p\{[LN]\}|\\[sS]|.", pattern):
        if part in "[]":
            inside = part == "["
        some = {r"\p{L}": letters, r"\p{N}": numbers, r"\s": white}.get(part)
        if part == r"\S":
            if inside:
                return None
            out.append(f"[^{white}]")
        else:
            out.append(part if some is None else some if inside else f"[{some}]")
    return re.compile("".join(out))


class ByteBpe:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.merges = Merges(ranks)
        self.single = np.array([ranks[bytes([b])] for b in range(256)], np.int32)
        vocab: list[bytes | None] = [None] * self.merges.size
        for token, rank in ranks.items():
            vocab[rank] = token
        self.vocab = pa.array(vocab, pa.binary())
        self.pattern = regex.compile(pattern)
        self.latin = _latin(pattern)
        self.beyond = re.compile(f"[^\x00-{chr(LATIN_END - 1)}]")
        self._forget()

    def _forget(self) -> None:
        self.numbers = _Numbers()
        self.ids = np.zeros(0, np.int32)
        self.start = np.zeros(1, np.int64)
        self.held = 0

    def _split(self, text: str) -> array:
        """The numbers of a text's words."""
        pattern = self.latin if self.latin is not None and not self.beyond.search(text) else self.pattern
        found = pattern.findall(text) if len(text) <= LONG_TEXT else (m[0] for m in pattern.finditer(text))
        return array("I", map(self.numbers.__getitem__, found))

    def _learn(self) -> None:
        """Replay the words that have a number and no ids yet."""
        known = len(self.start) - 1
        new = [w.encode() for w in list(self.numbers)[known:]]
        if new:
            ids, per = replay(self.merges, self.single, new)
            self.held += sum(map(len, new))
            self.start = np.concatenate([self.start, self.start[-1] + np.cumsum(per)])
            self.ids = np.concatenate([self.ids, ids])

    def _retire(self, used: np.ndarray) -> None:
        """Keep the words that the last block used more than once, the most used first, within the bounds."""
        words = list(self.numbers)
        if len(words) <= KEEP_WORDS and self.held <= KEEP_BYTES:
            return
        times = np.bincount(used, minlength=len(words))
        ranked = np.argsort(-times, kind="stable")
        ranked = ranked[times[ranked] > 1][: KEEP_WORDS // 2]
        size = np.cumsum([len(words[i].encode()) for i in ranked.tolist()])
        stay = np.sort(ranked[: int(np.searchsorted(size, KEEP_BYTES // 2, side="right"))])
        ids, per = self._gather(stay)
        self.numbers = _Numbers((words[i], k) for k, i in enumerate(stay.tolist()))
        self.ids, self.start = ids, np.concatenate([[0], np.cumsum(per)])
        self.held = sum(len(words[i].encode()) for i in stay.tolist())

    def _gather(self, numbers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of some words one after another, ids per word)."""
        begin = self.start[numbers]
        per = self.start[numbers + 1] - begin
        shift = np.repeat(begin - (np.cumsum(per) - per), per)
        shift += np.arange(len(shift))
        return self.ids[shift], per

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        """Per text its ids; all texts of the call form one block."""
        split = [np.frombuffer(self._split(t), np.uint32) for t in texts]
        self._learn()
        out = [self._gather(part.astype(np.int64))[0] for part in split]
        self._retire(np.concatenate(split) if split else np.zeros(0, np.uint32))
        return out

    def decode(self, ids: np.ndarray) -> bytes:
        if not len(ids):
            return b""
        _, offsets, data = self.vocab.take(pa.array(ids, pa.int32())).buffers()
        return data[: int(np.frombuffer(offsets, np.int32)[len(ids)])].to_pybytes()


@lru_cache(maxsize=2)
def load(path: str, pattern: str) -> ByteBpe:
    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
    return ByteBpe(ranks, pattern)


def _blocks(bpe: ByteBpe, batch: pa.RecordBatch, where: int) -> Iterator[tuple[pa.RecordBatch, list[np.ndarray]]]:
    """Slices of a batch, each a block, with the ids of their texts."""
    col = batch.column(where)
    for i, j in row_ranges(col, BLOCK_BYTES):
        yield batch.slice(i, j - i), bpe.encode([t or "" for t in col.slice(i, j - i).to_pylist()])


def encode_texts(df: DataFrame, path: str, pattern: str, text: str = "text", ids: str = "token_ids") -> DataFrame:
    """``df`` with ``ids`` (binary, little-endian unsigned 32-bit).

    A null text encodes as empty, repeated rows are repeated, an empty table gives an empty table. A column named like
    ``ids`` is replaced.
    """
    base = df.drop(ids)
    where = base.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path, pattern)
        for b in batches:
            for rows, found in _blocks(bpe, b, where):
                coded = pa.array([x.astype("<u4", copy=False).tobytes() for x in found], pa.binary())
                yield pa.RecordBatch.from_arrays([*rows.columns, coded], [*rows.schema.names, ids])

    return base.mapInArrow(tidy(run), base.withColumn(ids, F.lit(None).cast("binary")).schema)


def encode_digests(df: DataFrame, path: str, pattern: str, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``(doc_id, n_tokens, ids_sha256, decoded_sha256)`` of every row of ``df``.

    A null text counts as empty, a null id keeps its row, repeated rows are repeated, other columns are
    ignored, an empty table gives an empty table.  ``path`` must be readable on every executor.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path, pattern)
        sha = lambda x: hashlib.sha256(x).hexdigest()
        for b in batches:
            for rows, found in _blocks(bpe, b, 1):
                n = pa.array([len(x) for x in found], pa.int64())
                coded = pa.array([sha(x.astype("<u4", copy=False).tobytes()) for x in found], pa.string())
                plain = pa.array([sha(bpe.decode(x)) for x in found], pa.string())
                yield pa.RecordBatch.from_arrays([rows.column(0), n, coded, plain], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    picked = df.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text"))
    kind = picked.schema["doc_id"].dataType.simpleString()
    return picked.mapInArrow(tidy(run), f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
