"""Main-text extraction by a tree-structured graphical model over the blocks of a page.

Every block is a binary variable, content or not.  Unary potentials read the tag, hashed words and word pieces of the
class, id and role names, and statistics of the block's own text, of all text below it and of its place in the page; no
name has a meaning given by hand.  Parent-child potentials depend on the kind of the child.
Sum-product messages go up and down the tree, so marginals are exact; the text of blocks whose
marginal is at least one half is the result.  Weights are fitted by gradient ascent on the conditional
likelihood of labelled pages, whose gradient uses the same messages.  The labelled pages come
from ``html_training`` (seeded, of fixed number), so nothing is learnt from the table itself.

Messages of all pages in a piece of an Arrow batch run together, one numpy step per tree level.
"""

from __future__ import annotations

import html as html_lib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .html_tree import NAME_BUCKETS, TAGS, Kinds, Page, read
from .memory import tidy

PIECE_CHARS = 1 << 20
STATS = 11
#: Coupling type by tag group of the child: landmarks, text blocks, others.
_LANDMARKS = frozenset("article main nav header footer aside form body".split())
_FLOW = frozenset("p heading list item cell quote figure".split())
COUPLING = np.array([0 if t in _LANDMARKS else 1 if t in _FLOW else 2 for t in TAGS])
NAMED = len(TAGS) + NAME_BUCKETS
FEATURES = NAMED + STATS


@dataclass
class Forest:
    """All blocks of some pages: parent (-1 at roots), depth, kind and text statistics."""

    parent: np.ndarray
    depth: np.ndarray
    kind: np.ndarray
    first: np.ndarray
    stats: np.ndarray | None = None

    @classmethod
    def of(cls, pages: list[Page], kinds: Kinds) -> Forest:
        sizes = np.array([len(p.parent) for p in pages], np.int64)
        first = np.cumsum(sizes) - sizes
        flat = lambda name: np.array([x for p in pages for x in getattr(p, name)], np.int64)
        parent = flat("parent")
        parent = np.where(parent >= 0, parent + np.repeat(first, sizes), -1)
        out = cls(parent, flat("depth"), flat("kind"), first)
        chars, linked = flat("chars").astype(float), flat("linked").astype(float)
        tags = np.array([tag for tag, _ in kinds.rows] or [0])[out.kind]
        under = np.stack([chars, linked, (tags == TAGS.index("p")).astype(float)], axis=1)
        for level in reversed(out.levels()[1:]):  # of whole subtrees, leaves to roots
            np.add.at(under, parent[level], under[level])
        page = np.repeat(np.arange(len(pages)), sizes)
        total = np.maximum(under[first, 0], 1)[page] if len(pages) else np.zeros(0)
        upto = np.cumsum(chars) - chars
        before = (upto - upto[first][page]) / total if len(pages) else np.zeros(0)
        has = (chars > 0).astype(float)
        out.stats = np.stack(
            [
                has, np.log1p(chars) / 6, linked / np.maximum(chars, 1), has * (chars < 25), np.ones(len(chars)),
                np.log1p(under[:, 0]) / 8, under[:, 1] / np.maximum(under[:, 0], 1), under[:, 0] / total, before, np.log1p(under[:, 2]) / 3, (under[:, 0] > 0).astype(float),
            ],
            axis=1,
        )
        return out

    def levels(self) -> list[np.ndarray]:
        order = np.argsort(self.depth, kind="stable")
        top = int(self.depth.max()) if len(order) else 0
        cut = np.searchsorted(self.depth[order], np.arange(top + 2))
        return [order[cut[k] : cut[k + 1]] for k in range(top + 1)]


@dataclass
class KindFeatures:
    """Sparse features of interned kinds: a tag, and names whose weights share one unit length."""

    column: np.ndarray
    value: np.ndarray
    size: np.ndarray
    coupling: np.ndarray

    @classmethod
    def of(cls, kinds: Kinds) -> KindFeatures:
        column = [c for tag, names in kinds.rows for c in (tag, *(len(TAGS) + k for k in sorted(names)))]
        value = [v for _, names in kinds.rows for v in (1.0, *[max(len(names), 1) ** -0.5] * len(names))]
        size = np.array([1 + len(names) for _, names in kinds.rows], np.int64)
        return cls(np.array(column, np.int64), np.array(value), size, COUPLING[np.array([tag for tag, _ in kinds.rows], np.int64)])

    def score(self, weights: np.ndarray) -> np.ndarray:
        return np.add.reduceat(weights[self.column] * self.value, np.cumsum(self.size) - self.size)

    def gradient(self, residual: np.ndarray) -> np.ndarray:
        """Sums per feature of what each kind's blocks left over."""
        return np.bincount(self.column, np.repeat(residual, self.size) * self.value, minlength=NAMED)


def _lse(x: np.ndarray) -> np.ndarray:
    m = x.max(axis=-1)
    return m + np.log(np.exp(x - m[..., None]).sum(axis=-1))


@dataclass
class TreeModel:
    unary: np.ndarray  # weight of "content" per feature
    pair: np.ndarray  # [coupling, parent state, child state]

    def beliefs(self, f: Forest, kinds: KindFeatures) -> tuple[np.ndarray, np.ndarray]:
        """(node marginals, pair marginals of non-roots)."""
        n = len(f.parent)
        coupling = self.pair[kinds.coupling[f.kind]]
        own = np.zeros((n, 2))
        own[:, 1] = kinds.score(self.unary[:NAMED])[f.kind] + f.stats @ self.unary[NAMED:]
        up = np.zeros((n, 2))
        levels = f.levels()
        for level in reversed(levels[1:]):  # leaves to roots
            m = _lse(coupling[level] + own[level][:, None, :])
            up[level] = m
            np.add.at(own, f.parent[level], m)
        full = own.copy()  # own evidence, all children, and from here on the parent too
        node = np.zeros((n, 2))
        edge = np.zeros((n, 2, 2))
        if n:
            node[levels[0]] = np.exp(full[levels[0]] - _lse(full[levels[0]])[:, None])
        for level in levels[1:]:  # roots to leaves
            outside = full[f.parent[level]] - up[level]
            joint = outside[:, :, None] + coupling[level] + own[level][:, None, :]
            full[level] = own[level] + _lse(np.swapaxes(outside[:, :, None] + coupling[level], 1, 2))
            node[level] = np.exp(full[level] - _lse(full[level])[:, None])
            edge[level] = np.exp(joint - _lse(joint.reshape(len(level), 4))[:, None, None])
        return node, edge

    def content(self, f: Forest, kinds: KindFeatures) -> np.ndarray:
        return self.beliefs(f, kinds)[0][:, 1]


def fit(pages: list[tuple[str, str]], steps: int = 250, rate: float = 0.1, decay: float = 1e-3) -> TreeModel:
    """Maximum conditional likelihood on labelled pages ``(html, mark attribute)``; mark value "1" is content."""
    interned = Kinds()
    read_ = [read(h, interned, mark) for h, mark in pages]
    f, kinds = Forest.of(read_, interned), KindFeatures.of(interned)
    y = np.array([m == "1" for p in read_ for m in p.marks], int)
    model = TreeModel(np.zeros(FEATURES), np.zeros((3, 2, 2)))
    inner = np.flatnonzero(f.parent >= 0)
    coupling = kinds.coupling[f.kind]
    m = [np.zeros_like(model.unary), np.zeros_like(model.pair)]
    v = [np.zeros_like(model.unary), np.zeros_like(model.pair)]
    for step in range(1, steps + 1):
        node, edge = model.beliefs(f, kinds)
        left = y - node[:, 1]
        gu = np.concatenate([kinds.gradient(np.bincount(f.kind, left, minlength=len(kinds.size))), f.stats.T @ left]) / len(pages) - decay * model.unary
        gp = np.zeros_like(model.pair)
        np.add.at(gp, (coupling[inner], y[f.parent[inner]], y[inner]), 1)
        np.add.at(gp, coupling[inner], -edge[inner])
        gp = gp / len(pages) - decay * model.pair
        for k, (g, w) in enumerate(((gu, model.unary), (gp, model.pair))):
            m[k] = 0.9 * m[k] + 0.1 * g
            v[k] = 0.99 * v[k] + 0.01 * g * g
            w += rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-8)
    return model


@lru_cache(maxsize=2)
def default_model(n_pages: int = 600, seed: int = 17) -> TreeModel:
    from .html_training import MARK, labelled_pages

    return fit([(h, MARK) for h, _ in labelled_pages(n_pages, seed)])


def page_texts(htmls: list[str], model: TreeModel) -> list[str]:
    """The main text of every page: white space in a block is one space, blocks are joined by one."""
    kinds = Kinds()
    pages = [read(h, kinds) for h in htmls]
    f = Forest.of(pages, kinds)
    keep = model.content(f, KindFeatures.of(kinds)) >= 0.5
    out = []
    for p, at in zip(pages, f.first.tolist(), strict=True):
        blocks = (" ".join(html_lib.unescape("".join(run)).split()) for node, run in p.runs if keep[at + node])
        out.append(" ".join(b for b in blocks if b))
    return out


def extract(df: DataFrame, model: TreeModel | None = None, html: str = "html", text: str = "text") -> DataFrame:
    """``df`` without ``html`` and with ``text``: one row per row, "" where a page has no main text.

    Null pages count as empty, repeated rows are repeated, a column named like ``text`` is replaced.
    """
    model = model or default_model()
    rest = [c for c in df.columns if c not in (html, text)]
    picked = df.select(*rest, F.col(html).alias(html))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[str] = []
            held: list[str] = []
            size = 0
            for h in b.column(len(rest)):
                held.append(h.as_py() or "")
                size += len(held[-1])
                if size >= PIECE_CHARS:
                    out += page_texts(held, model)
                    held, size = [], 0
            if held:
                out += page_texts(held, model)
            yield pa.RecordBatch.from_arrays([*b.columns[: len(rest)], pa.array(out, pa.string())], [*rest, text])

    return picked.mapInArrow(tidy(run), picked.drop(html).withColumn(text, F.lit("")).schema)
