"""Embedding near-dedup: all pairs at or above a cosine, by PCA-ordered tiles.

1. Equal vectors of a label collapse to one representative (a hot vector is one row from there on).
2. The second-moment matrix of the unit vectors is summed by a distributed aggregate of dim^2 rows;
   its eigenvectors, a broadcast constant of dim^2 doubles, rotate vectors so that the leading
   coordinates carry most of the product.
3. Vectors whose cosine is >= t differ by at most sqrt(2 - 2t) in every rotated coordinate, so a grid of
   that width over the leading axes confines links to neighbouring cells.  As many axes cut (up to ``MOST_AXES``) as
   bring the largest cell down to ``CELL_BLOCKS`` blocks.  Neighbours are found in the table of cells; only
   then do vectors travel, under numbers of cells and blocks.  A tile is a pair of blocks of bounded size.
4. Inside a tile products accumulate in slices of dimensions; after each slice a pair stays only while
   its partial product plus the product of both suffix norms can still reach t.
5. Survivors are confirmed by the cosine of the original values in double precision.  A tile gives per
   vector its link count and one edge to the smallest vector it reaches inside the tile, so output is
   linear in the rows of a tile however many pairs link.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .memory import tidy
from .workspace import Workspace, parallelism

SLICES = (8, 16, 32)
MOST_AXES = 4
CELL_BLOCKS = 4
#: Distinct vector lengths that one table may hold: each costs the driver and every worker dim^2 doubles.
MOST_LENGTHS = 16
_EPS = 1e-9


def _matrix(col: pa.Array) -> np.ndarray:
    col = col.combine_chunks() if isinstance(col, pa.ChunkedArray) else col
    flat = np.asarray(col.flatten().to_numpy(zero_copy_only=False), dtype=np.float64)
    if not len(col):
        return flat.reshape(0, 0)
    x = flat.reshape(len(col), -1)
    # By a power of two, so that norms neither overflow nor vanish and the cosine keeps every bit.
    return np.ldexp(x, -np.frexp(np.abs(x).max(axis=1, keepdims=True))[1])


def _second_moments(vectors: DataFrame) -> dict[int, np.ndarray]:
    """dim -> eigenvectors by descending eigenvalue.  The driver gets dim^2 sums for each of at most ``MOST_LENGTHS`` lengths."""
    lengths = vectors.select("dim").distinct().limit(MOST_LENGTHS + 1).count()
    if lengths > MOST_LENGTHS:
        raise ValueError(f"more than {MOST_LENGTHS} different vector lengths in one table")

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for b in batches:
            dims = np.asarray(b.column(0))
            for d in np.unique(dims):
                x = _matrix(b.column(1).filter(pa.array(dims == d)))
                x = x / np.linalg.norm(x, axis=1, keepdims=True)
                total[int(d)] = total.get(int(d), 0) + x.T @ x
        for d, m in total.items():
            yield pa.RecordBatch.from_pydict({"dim": pa.array([d] * (d * d), pa.int32()), "at": pa.array(range(d * d), pa.int32()), "v": pa.array(m.ravel())})

    sums = vectors.select("dim", "vec").mapInArrow(tidy(fold), "dim int, at int, v double").groupBy("dim", "at").agg(F.sum("v").alias("v")).collect()
    out: dict[int, np.ndarray] = {}
    for d in {r.dim for r in sums}:
        m = np.zeros(d * d)
        for r in sums:
            if r.dim == d:
                m[r.at] = r.v
        m = m.reshape(d, d)
        _, vecs = np.linalg.eigh((m + m.T) / 2)
        out[d] = np.ascontiguousarray(vecs[:, ::-1])
    return out


def tile_links(x: np.ndarray, left: np.ndarray, right: np.ndarray, turn: np.ndarray, t: float, same: bool) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs (i in left, j in right) with cosine >= t; ``same``: each unordered pair once."""
    norm = np.linalg.norm(x, axis=1)
    y = (x / norm[:, None]) @ turn
    d = y.shape[1]
    rest = np.sqrt(np.maximum(0, np.cumsum((y * y)[:, ::-1], axis=1)[:, ::-1]))
    cuts = [k for k in SLICES if k < d] + [d]
    a, b = y[left], y[right]
    k = cuts[0]
    p = a[:, :k] @ b[:, :k].T
    tail = (rest[left][:, k][:, None] * rest[right][:, k][None, :]) if k < d else 0.0
    keep = p + tail >= t - _EPS
    if same:
        keep &= np.arange(len(left))[:, None] < np.arange(len(right))[None, :]
    i, j = np.nonzero(keep)
    acc = p[i, j]
    for lo, hi in zip(cuts, cuts[1:], strict=False):
        step = max(1, (1 << 21) // (hi - lo))
        for s in range(0, len(i), step):
            q = slice(s, s + step)
            acc[q] += np.einsum("nd,nd->n", a[i[q], lo:hi], b[j[q], lo:hi])
        bound = rest[left][i, hi] * rest[right][j, hi] if hi < d else 0.0
        ok = acc + bound >= t - _EPS
        i, j, acc = i[ok], j[ok], acc[ok]
    gi, gj = left[i], right[j]
    exact = np.empty(len(gi))
    step = max(1, (1 << 21) // max(1, d))
    for s in range(0, len(gi), step):
        q = slice(s, s + step)
        exact[q] = np.einsum("nd,nd->n", x[gi[q]], x[gj[q]]) / (norm[gi[q]] * norm[gj[q]])
    ok = exact >= t
    return gi[ok], gj[ok]


def _smallest_reach(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Per node the smallest node index of its component inside one tile."""
    low = np.arange(n)
    while len(i):
        m = np.minimum(low[i], low[j])
        nxt = low.copy()
        np.minimum.at(nxt, i, m)
        np.minimum.at(nxt, j, m)
        nxt = nxt[nxt]
        if np.array_equal(nxt, low):
            break
        low = nxt
    return low


def _axes_needed(finest: DataFrame, axis: list[str], block: int) -> int:
    """The least number of axes whose largest cell has at most ``CELL_BLOCKS`` blocks; one small row comes to the driver."""
    for k in range(1, len(axis)):
        top = finest.groupBy("label", "dim", *axis[:k]).agg(F.sum("n").alias("n")).agg(F.max("n")).first()[0] or 0
        if top <= CELL_BLOCKS * block:
            return k
    return len(axis)


def link_vectors(df: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding", label: str = "label", threshold: float = 0.98, axes: int | None = None, block: int = 1024) -> DataFrame:
    """``(vec_id, n_links, component_id, kept)`` for every row of ``df``.

    Vectors link when their labels are equal and not null and their cosine is >= ``threshold``.  Null,
    empty, zero or non-finite vectors link with nothing, nor do vectors of different lengths.  A null
    id gives a row of its own with null component.  Repeated ids are repeated rows; each row counts as a
    vector.  Other columns are ignored, so clashing names do no harm.  An empty table gives an empty table.
    ``axes`` fixes the number of axes that cut; by default the data decide.
    """
    if not 0 < threshold <= 1:
        raise ValueError("threshold must be in (0, 1]")
    spark = df.sparkSession
    ws = Workspace(spark, "embedding-dedup")
    e = F.col(embedding)
    good = F.col(label).isNotNull() & e.isNotNull() & F.col(vec_id).isNotNull() & (F.size(e) > 0)
    good = good & F.forall(e, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists(e, lambda x: x != 0)
    rows = df.select(F.col(vec_id).cast("long").alias("id"), F.coalesce(good, F.lit(False)).alias("good"), F.col(label).cast("string").alias("label"), e.cast("array<double>").alias("vec"))
    valid = rows.where("good").select("id", "label", "vec", F.transform("vec", lambda x: x + F.lit(0.0)).alias("key"))
    classes = valid.groupBy("label", "key").agg(F.min("id").alias("rep"), F.count("*").alias("weight"))
    reps = ws.save(classes.select("rep", "weight", "label", F.col("key").alias("vec"), F.size("key").alias("dim")), "reps")
    turns = _second_moments(reps)
    width = float(np.sqrt(2 - 2 * threshold)) * (1 + 1e-9) + 1e-9
    shared = spark.sparkContext.broadcast(turns)

    most = axes or MOST_AXES

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            dims = np.asarray(b.column("dim"))
            cell = np.zeros((b.num_rows, most), dtype=np.int32)
            for d in np.unique(dims):
                at = np.flatnonzero(dims == d)
                x = _matrix(b.column("vec").take(pa.array(at)))
                x = x / np.linalg.norm(x, axis=1, keepdims=True)
                k = min(most, int(d))
                cell[at, :k] = np.floor(x @ shared.value[int(d)][:, :k] / width)
            cols = {c: b.column(c) for c in ("rep", "weight", "label", "vec", "dim")}
            yield pa.RecordBatch.from_pydict(cols | {f"c{k}": pa.array(cell[:, k]) for k in range(most)})

    axis = [f"c{k}" for k in range(most)]
    home = ws.save(reps.mapInArrow(tidy(cells), "rep long, weight long, label string, vec array<double>, dim int, " + ", ".join(f"{c} int" for c in axis)), "cells")
    finest = ws.save(home.groupBy("label", "dim", *axis).agg(F.count("*").alias("n")), "finest")
    axis = axis[: axes or _axes_needed(finest, axis, block)]
    counts = finest.groupBy("label", "dim", *axis).agg(F.sum("n").alias("n"))
    sizes = ws.save(counts.select("*", F.monotonically_increasing_id().alias("cell"), F.ceil(F.col("n") / block).cast("int").alias("blocks")), "sizes")

    # Each unordered pair of neighbouring cells once: the cell itself, or one that lies ahead of it.
    ahead = [s for s in product((-1, 0, 1), repeat=len(axis)) if s >= (0,) * len(axis)]
    moves = F.array(*[F.struct(*[F.lit(k).alias(c) for c, k in zip(axis, s, strict=True)]) for s in ahead])
    near = sizes.withColumn("move", F.explode(moves)).select("label", "dim", *[(F.col(c) + F.col(f"move.{c}")).alias(c) for c in axis], F.col("cell").alias("p"), F.col("blocks").alias("p_blocks"))
    pairs = near.join(sizes.select("label", "dim", *axis, F.col("cell").alias("q"), F.col("blocks").alias("q_blocks")), ["label", "dim", *axis])
    pairs = ws.save(pairs.select("p", "p_blocks", "q", "q_blocks"), "pairs")
    # A block meets every block of the other cell; within a cell the smaller block number stands left.
    sides = pairs.select(F.col("p").alias("cell"), F.lit(True).alias("left"), "p", "q", "p_blocks", "q_blocks").unionAll(
        pairs.where("p <> q").select(F.col("q").alias("cell"), F.lit(False).alias("left"), "p", "q", "p_blocks", "q_blocks")
    )
    placed = home.join(sizes.select("label", "dim", *axis, "cell", "blocks"), ["label", "dim", *axis])
    placed = placed.select("cell", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int").alias("b"), "rep", "weight", "dim", "vec")
    met = placed.join(sides, "cell").withColumn("o", F.explode(F.sequence(F.lit(0), F.when(F.col("left"), F.col("q_blocks")).otherwise(F.col("p_blocks")) - 1)))
    alone = F.col("p") == F.col("q")
    low = F.when(alone, F.least("b", "o")).when(F.col("left"), F.col("b")).otherwise(F.col("o"))
    high = F.when(alone, F.greatest("b", "o")).when(F.col("left"), F.col("o")).otherwise(F.col("b"))
    role = F.when(alone & (F.col("b") == F.col("o")), 0).when(alone, F.when(F.col("b") < F.col("o"), 1).otherwise(2)).otherwise(F.when(F.col("left"), 1).otherwise(2))
    tile = ["p", "q", "bp", "bq"]
    tiles = met.select("p", "q", low.alias("bp"), high.alias("bq"), role.alias("role"), "rep", "weight", "dim", "vec")
    dealt = tiles.repartition(parallelism(spark), *tile).sortWithinPartitions(*tile)

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        key = None

        def flush() -> Iterator[pa.RecordBatch]:
            if held:
                t = pa.Table.from_batches(held)
                roles, rep, weight = (np.asarray(t.column(c)) for c in ("role", "rep", "weight"))
                x = _matrix(t.column("vec"))
                everyone = np.arange(len(rep))
                same = bool((roles == 0).all())
                left, right = (everyone, everyone) if same else (np.flatnonzero(roles == 1), np.flatnonzero(roles == 2))
                if len(left) and len(right):
                    order = np.argsort(rep, kind="stable")
                    rank = np.empty(len(rep), np.int64)
                    rank[order] = everyone
                    i, j = tile_links(x, left, right, shared.value[x.shape[1]], threshold, same)
                    if len(i):
                        links = np.bincount(i, weight[j], len(rep)) + np.bincount(j, weight[i], len(rep))
                        reach = rep[order][_smallest_reach(len(rep), rank[i], rank[j])][rank]
                        at = np.flatnonzero(links > 0)
                        yield pa.RecordBatch.from_pydict({"rep": pa.array(rep[at]), "links": pa.array(links[at].astype(np.int64)), "low": pa.array(reach[at])})
                held.clear()

        for b in batches:
            names = np.stack([np.asarray(b.column(c)) for c in tile], axis=1)
            cuts = [0, *(np.flatnonzero((names[1:] != names[:-1]).any(axis=1)) + 1).tolist(), len(names)]
            for lo, hi in zip(cuts, cuts[1:], strict=False):
                if hi > lo:
                    if tuple(names[lo]) != key:
                        yield from flush()
                        key = tuple(names[lo])
                    held.append(b.slice(lo, hi - lo))
        yield from flush()

    found = ws.save(dealt.mapInArrow(tidy(compare), "rep long, links long, low long"), "links")
    ws.drop(home, sizes, finest, pairs)
    groups = connected_components(ws, found, "rep", "low")
    links = found.groupBy("rep").agg(F.sum("links").alias("links"))
    known = reps.select(F.col("label").alias("k_label"), F.col("vec").alias("k_vec"), F.col("rep"), "weight")
    known = known.join(links, "rep", "left").join(groups.withColumnRenamed("node", "rep"), "rep", "left")
    match = (F.col("label") == F.col("k_label")) & (F.col("key") == F.col("k_vec")) & F.col("good")
    keyed = rows.withColumn("key", F.transform("vec", lambda x: x + F.lit(0.0)))
    out = keyed.join(known, match, "left")
    component = F.coalesce("component", "rep", "id")
    return out.select(
        F.col("id").alias("vec_id"),
        F.when(F.col("rep").isNull(), F.lit(0)).otherwise(F.coalesce("links", F.lit(0)) + F.col("weight") - 1).cast("long").alias("n_links"),
        component.alias("component_id"),
        F.coalesce(F.col("id") == component, F.lit(False)).alias("kept"),
    )


#: All pairs of a label and the closure of their links; quadratic, for small tables.
ORACLE = """
WITH RECURSIVE v AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings WHERE label IS NOT NULL AND vec_id IS NOT NULL AND len(embedding) > 0
  AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v AS a JOIN v AS b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e) WHERE list_cosine_similarity(a.e, b.e) >= 0.98),
r(id, c) AS (SELECT DISTINCT a, a FROM l UNION SELECT r.id, l.b FROM r JOIN l ON l.a = r.c),
s AS (SELECT id, min(c) AS c FROM r GROUP BY id),
n AS (SELECT a AS id, count(*) AS n FROM l GROUP BY a)
SELECT vec_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_links, CAST(coalesce(s.c, vec_id) AS BIGINT) AS component_id, vec_id = coalesce(s.c, vec_id) AS kept
FROM embeddings LEFT JOIN n ON n.id = vec_id LEFT JOIN s ON s.id = vec_id
"""
