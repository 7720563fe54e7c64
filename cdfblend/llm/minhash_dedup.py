"""MinHash near-dedup: one-permutation hashing, optimal densification, banded buckets, star edges.

1. One pass hashes every whole text into its set of word shingles.  The 64-bit space is cut into
   ``bands * rows`` bins; the smallest hash of a bin is read off the sorted set.  An empty bin borrows
   from the first full bin of a fixed random probe sequence (optimal densification).
2. Texts with equal sets form a class (set digest of 128 bits); only its smallest id goes on.
3. Band keys of representatives meet in buckets.  A bucket's smallest id is its hub, and every other
   member gives one star edge, so candidates are linear in the bucket.
4. Star edges are confirmed on full sets, streamed by hub chunks (``hubs``), and contracted.
5. A bucket whose members still lie in several components may hide links between non-hub members.  It is cut
   into blocks of bounded documents and shingles.  A tile (pair of blocks) first gets sketches of half a kilobyte and
   says which members of different components they leave as candidates, each pair in the first band that it shares.
   Only the texts of these follow; the tile confirms on full sets and gives a spanning forest of links, never all pairs.

Two steps are estimates.  With 32 bands of 5 rows a pair at similarity 0.8 shares no band with probability 3e-6 if bins
are independent (tests: no miss in 2,400 pairs of 4 to 450 shingles at 0.8).  The tile's sketch excludes a pair whose
estimate lies ``SLACK`` deviations below the threshold (tests: none of these 2,400 pairs).  Candidate search is otherwise
exact: no cap on buckets, partners or text length.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import words
from .components import connected_components
from .hubs import agreeing_pairs
from .memory import tidy
from .workspace import Workspace, parallelism

_U = np.uint64
PROBES = 4096
#: A block of an open bucket holds at most about so many documents and so many shingles.
BLOCK = 2048
BLOCK_SHINGLES = 300_000
#: Standard deviations by which a tile's similarity estimate may fall short before a pair is excluded.
SLACK = 6.0
TILE_BINS = 512


class OnePermutation:
    """Signature of a sorted set of distinct 64-bit hashes."""

    def __init__(self, bins: int):
        self.bins = bins
        self.edges = np.array([(k << 64) // bins for k in range(1, bins)], dtype=_U)
        self.probes = (words.stream(bins * PROBES, 23) % _U(bins)).astype(np.int16).reshape(bins, PROBES)

    def of(self, s: np.ndarray) -> np.ndarray:
        at = np.empty(self.bins + 1, np.int64)
        at[0], at[-1] = 0, len(s)
        at[1:-1] = np.searchsorted(s, self.edges)
        full = at[1:] > at[:-1]
        sig = s[np.minimum(at[:-1], len(s) - 1)]
        empty = np.flatnonzero(~full)
        lo, step = 0, 32
        while len(empty):
            if lo >= PROBES:  # no probe met a full bin: the next full one
                ring = np.flatnonzero(full)
                sig[empty] = sig[ring[np.searchsorted(ring, empty) % len(ring)]]
                break
            tries = self.probes[empty, lo : lo + step]
            hit = full[tries]
            got = hit.any(axis=1)
            src = tries[got, hit[got].argmax(axis=1)]
            sig[empty[got]] = s[at[:-1][src]]
            empty = empty[~got]
            lo, step = lo + step, 4 * step
        return sig


_made: dict[int, OnePermutation] = {}


def one_permutation(bins: int) -> OnePermutation:
    if bins not in _made:
        _made[bins] = OnePermutation(bins)
    return _made[bins]


def overlap(a: np.ndarray, b: np.ndarray) -> int:
    """Size of the intersection of two sorted sets."""
    if len(a) > len(b):
        a, b = b, a
    if not len(a):
        return 0
    at = np.searchsorted(b, a)
    at[at == len(b)] = 0
    return int(np.count_nonzero(b[at] == a))


def similar(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    both = overlap(a, b)
    return both > 0 and 100 * both >= percent * (len(a) + len(b) - both)


def sketch(df: DataFrame, width: int, bands: int, rows: int) -> DataFrame:
    """``(id, n, digest, bands)`` of ``(id, text)``; a text without words has null digest and no bands."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        oph = one_permutation(bands * rows)
        mult = words.stream(rows, 31) | _U(1)
        salt = words.stream(bands, 37)
        for b in batches:
            n, digest, keys = [], [], []
            for s in words.shingle_sets(b.column(1), width):
                n.append(len(s))
                if len(s):
                    digest.append(xxhash.xxh3_128_digest(s.tobytes()))
                    with np.errstate(over="ignore"):
                        keys.append(words.mix((oph.of(s).reshape(bands, rows) * mult).sum(axis=1) + salt).view(np.int64))
                else:
                    digest.append(None)
                    keys.append(np.zeros(0, np.int64))
            flat = np.concatenate(keys) if keys else np.zeros(0, np.int64)
            off = np.concatenate([[0], np.cumsum([len(k) for k in keys])]).astype(np.int32)
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(n, pa.int64()), pa.array(digest, pa.binary()), pa.ListArray.from_arrays(pa.array(off), pa.array(flat))], ["id", "n", "digest", "bands"]
            )

    return df.mapInArrow(tidy(run), "id long, n long, digest binary, bands array<long>")


def fine_sketches(texts: DataFrame, width: int) -> DataFrame:
    """``(id, n, fine)`` of ``(id, text)``: the low bytes of ``TILE_BINS`` one-permutation minima."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        oph = one_permutation(TILE_BINS)
        for b in batches:
            n, fine = [], []
            for s in words.shingle_sets(b.column(1), width):
                n.append(len(s))
                fine.append(oph.of(s).astype(np.uint8).tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(fine, pa.binary())], ["id", "n", "fine"])

    return texts.select("id", "text").mapInArrow(tidy(run), "id long, n long, fine binary")


class Tile:
    """The members of a pair of blocks, by their sketches.

    ``cross(rows)`` marks the index pairs of some rows that the tile is to test; pairs with the hub were tested before,
    and so were pairs that share a band ahead of this one.
    """

    def __init__(self, ids: list[int], comps: list[int], size: np.ndarray, fine: np.ndarray, bands: np.ndarray, at: int, hub: int, cross: Callable[[slice], np.ndarray], percent: int):
        self.ids, self.comps, self.size, self.fine, self.bands = ids, comps, size, fine, bands
        self.at, self.hub, self.cross, self.percent = at, hub, cross, percent

    def candidates(self) -> tuple[np.ndarray, np.ndarray]:
        """Index pairs of different components whose estimate does not exclude a link, the likeliest first."""
        comp, size, at, bands, percent = np.asarray(self.comps), self.size, self.at, self.bands, self.percent
        free = np.asarray(self.ids) != self.hub
        t = percent / 100
        kept: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        for lo in range(0, len(comp), 128):  # by rows, so that no n x n table of numbers is held
            r = slice(lo, lo + 128)
            todo = self.cross(r) & free[r, None] & free[None, :] & (comp[r, None] != comp[None, :])
            todo &= (100 * size[None, :] >= percent * size[r, None]) & (100 * size[r, None] >= percent * size[None, :])
            rows, cols = np.nonzero(todo)
            rows += lo
            for q in range(0, len(rows), 8192):
                i, j = rows[q : q + 8192], cols[q : q + 8192]
                if at:
                    first = ~(bands[i, :at] == bands[j, :at]).any(axis=1)
                    i, j = i[first], j[first]
                match = (self.fine[i] == self.fine[j]).mean(axis=1)
                # Densified bins of a small set repeat its few full ones, so the deviation follows the set's size.
                trials = np.minimum(TILE_BINS, np.minimum(size[i], size[j])) / 2
                ok = match >= t - SLACK * np.sqrt(t * (1 - t) / np.maximum(trials, 1))
                kept.append((i[ok], j[ok], match[ok]))
        if not kept:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        i, j, match = (np.concatenate(x) for x in zip(*kept, strict=True))
        order = np.argsort(-match, kind="stable")
        return i[order], j[order]

    def forest(self, sets: list[np.ndarray]) -> list[tuple[int, int]]:
        """A spanning forest of links confirmed on full sets between different components, never all pairs."""
        i, j = self.candidates()
        comps = self.comps
        root = {c: c for c in comps}

        def find(c: int) -> int:
            while root[c] != c:
                root[c] = root[root[c]]
                c = root[c]
            return c

        out = []
        for a, b in zip(i.tolist(), j.tolist(), strict=True):
            x, y = find(comps[a]), find(comps[b])
            if x != y and similar(sets[a], sets[b], self.percent):
                root[max(x, y)] = min(x, y)
                out.append((self.ids[a], self.ids[b]))
        return out


_TILE = ["key", "p", "q"]
_MEMBER = [*_TILE, "side", "id", "component", "band", "hub", "n", "bands", "fine"]


def _each_tile(batches: Iterator[pa.RecordBatch], percent: int, more: Callable[[pa.RecordBatch], Iterator]) -> Iterator[tuple[tuple, Tile, list]]:
    """(key, tile, what ``more`` gives per member) of every tile in rows of ``_MEMBER`` sorted by tile."""
    now: tuple | None = None
    held: list[tuple] = []

    def close() -> Iterator[tuple[tuple, Tile, list]]:
        if len(held) > 1:
            side, ids, comps, n, bands, fine, extra = (list(x) for x in zip(*held, strict=True))
            s, nth, alone = np.asarray(side), np.arange(len(side)), now[1] == now[2]
            cross = lambda r: (nth[r, None] < nth[None, :]) & (alone | (s[r, None] != s[None, :]))
            sketches = np.frombuffer(b"".join(fine), np.uint8).reshape(len(ids), TILE_BINS)
            yield now, Tile(ids, comps, np.asarray(n), sketches, np.stack(bands), now[3], now[4], cross, percent), extra
        held.clear()

    for b in batches:
        c = {name: b.column(name).to_pylist() for name in _MEMBER if name != "bands"}
        bands = np.asarray(b.column("bands").flatten()).reshape(b.num_rows, -1)
        for k, extra in enumerate(more(b)):
            tile = (c["key"][k], c["p"][k], c["q"][k], c["band"][k], c["hub"][k])
            if tile != now:
                yield from close()
                now = tile
            held.append((c["side"][k], c["id"][k], c["component"][k], c["n"][k], bands[k], c["fine"][k], extra))
    yield from close()


def _open_buckets(ws: Workspace, members: DataFrame, comps: DataFrame, texts: DataFrame, sk: DataFrame, width: int, percent: int, block: int) -> DataFrame:
    """Links that the stars left open: tiles of buckets whose members lie in several components.

    Sketches travel to all tiles first; a text follows only to the tiles where its sketch leaves it a candidate.
    """
    placed = members.join(comps.select(F.col("node").alias("id"), "component"), "id", "left").withColumn("component", F.coalesce("component", "id"))
    open_ = placed.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.count("*").alias("size"), F.sum("n").alias("mass")).where("lo <> hi and size > 2")
    blocks = F.greatest(F.ceil(F.col("size") / block), F.ceil(F.col("mass") / BLOCK_SHINGLES)).cast("int")
    rows = ws.save(placed.select("id", "component", "key", "band", "hub").join(open_.select("key", "size", "mass"), "key").withColumn("blocks", blocks).drop("size", "mass"), "open-rows")
    wanted = rows.select("id").distinct()
    fine = fine_sketches(texts.join(wanted, "id", "left_semi"), width).join(sk.select("id", "bands"), "id")
    fine = ws.save(fine, "fine")
    rows = rows.withColumn("own", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = rows.select("id", "component", "key", "band", "hub", F.least("own", "other").alias("p"), F.greatest("own", "other").alias("q"), (F.col("own") > F.col("other")).cast("int").alias("side"))
    full = rows.join(fine, "id").select(*_MEMBER)
    dealt = full.repartition(parallelism(ws.spark), *_TILE).sortWithinPartitions(*_TILE, "side")

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (key, p, q, *_), tile, _ in _each_tile(batches, percent, lambda b: [None] * b.num_rows):
            at = np.unique(np.concatenate(tile.candidates())).tolist()
            if at:
                ids = [tile.ids[k] for k in at]
                yield pa.RecordBatch.from_arrays([pa.array([key] * len(ids), pa.int64()), pa.array([p] * len(ids), pa.int32()), pa.array([q] * len(ids), pa.int32()), pa.array(ids, pa.int64())], [*_TILE, "id"])

    def confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, tile, sets in _each_tile(batches, percent, lambda b: words.shingle_sets(b.column("text"), width)):
            links = tile.forest(sets)
            if links:
                yield pa.RecordBatch.from_pydict({"hub": pa.array([x[0] for x in links], pa.int64()), "member": pa.array([x[1] for x in links], pa.int64())})

    active = ws.save(dealt.mapInArrow(tidy(look), "key long, p int, q int, id long"), "active")
    again = rows.join(active, [*_TILE, "id"]).join(fine, "id").join(texts, "id").select(*_MEMBER, "text")
    again = again.repartition(parallelism(ws.spark), *_TILE).sortWithinPartitions(*_TILE, "side")
    return again.mapInArrow(tidy(confirm), "hub long, member long")


def near_duplicates(df: DataFrame, doc_id: str = "doc_id", text: str = "text", width: int = 5, percent: int = 80, bands: int = 32, rows: int = 5, block: int = BLOCK) -> DataFrame:
    """``(doc_id, n_shingles, component_id, kept)`` for every row of ``df``.

    Documents link when 100 * |intersection| >= ``percent`` * |union| of their shingle sets.  Null or
    wordless texts have an empty set and link with nothing; a null id keeps its row, unlinked, with null
    component.  Ids name documents: rows that repeat an id and its text count once.  Other columns are
    ignored.  An empty table gives an empty table.
    """
    ws = Workspace(df.sparkSession, "minhash-dedup")
    docs = df.select(F.col(doc_id).cast("long").alias("id"), F.col(text).alias("text"))
    sk = ws.save(sketch(docs, width, bands, rows), "sketch")
    classes = ws.save(sk.where("digest is not null and id is not null").groupBy("digest").agg(F.min("id").alias("rep")), "classes")
    reps = sk.where("digest is not null").join(classes.select(F.col("rep").alias("id"), "digest"), ["id", "digest"]).dropDuplicates(["id", "digest"])
    reps = ws.save(reps.select("id", "n", "bands"), "reps")
    keyed = reps.select("id", "n", F.posexplode("bands").alias("band", "key"))
    hubs = keyed.groupBy("key").agg(F.min(F.struct("id", "n")).alias("hub"), F.count("*").alias("size")).where("size > 1")
    members = keyed.join(hubs, "key").select("key", "band", "id", "n", F.col("hub.id").alias("hub"), F.col("hub.n").alias("hub_n"))
    members = ws.save(members, "members")
    texts = ws.save(docs.join(members.select("id").distinct(), "id", "left_semi"), "texts")
    near = F.least("n", "hub_n") * 100 >= F.greatest("n", "hub_n") * percent
    stars = members.where((F.col("id") != F.col("hub")) & near).select("hub", F.col("id").alias("member")).distinct()

    def prepare(col: pa.Array) -> Iterator[np.ndarray]:
        return words.shingle_sets(col, width)

    links = ws.save(agreeing_pairs(stars, texts, prepare, lambda a, b: similar(a, b, percent)), "stars")
    first = connected_components(ws, links, "hub", "member")
    more = ws.save(_open_buckets(ws, members.select("key", "band", "id", "n", "hub"), first, texts, reps, width, percent, block), "open")
    ws.drop(texts, members)
    # The contracted stars stand for the links found before.
    joined = first.select(F.col("node").alias("hub"), F.col("component").alias("member")).unionAll(more)
    final = connected_components(ws, joined, "hub", "member")
    known = classes.join(final.select(F.col("node").alias("rep"), "component"), "rep", "left").select("digest", F.coalesce("component", "rep").alias("component"))
    out = sk.select("id", "n", "digest").join(known, "digest", "left")
    component = F.when(F.col("id").isNotNull(), F.coalesce("component", "id"))
    return out.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(F.col("id") == component, F.lit(False)).alias("kept"))


#: All pairs that share a shingle, and the closure of their links; for small tables.
ORACLE = """
WITH RECURSIVE w AS MATERIALIZED (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
s AS MATERIALIZED (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')] ELSE [array_to_string(w[i:i + 3], ' ') FOR i IN range(1, len(w) - 2)] END) AS g FROM w),
n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS MATERIALIZED (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM s AS a JOIN s AS b USING (g) WHERE a.doc_id <> b.doc_id GROUP BY ALL),
l AS MATERIALIZED (SELECT a, b FROM p JOIN n AS x ON x.doc_id = a JOIN n AS y ON y.doc_id = b WHERE 100 * i >= 80 * (x.n + y.n - i)),
r(id, c) AS (SELECT DISTINCT a, a FROM l UNION SELECT r.id, l.b FROM r JOIN l ON l.a = r.c),
c AS (SELECT id, min(c) AS c FROM r GROUP BY id)
SELECT documents.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, CAST(coalesce(c.c, documents.doc_id) AS BIGINT) AS component_id, documents.doc_id = coalesce(c.c, documents.doc_id) AS kept
FROM documents LEFT JOIN n ON n.doc_id = documents.doc_id LEFT JOIN c ON c.id = documents.doc_id
"""
