"""Document fingerprints: canonical exact digest.

The canonical form of a text is NFKC, case folded, white space runs as one space, trimmed; its fingerprint
is the 128-bit xxhash of the canonical UTF-8.  Rows of equal fingerprint form buckets, and inside a
bucket the canonical bytes of every member are compared with the hub's (streamed by chunks, so a bucket
may hold a third of all rows); a member that differs gets a suffix and so a fingerprint of its own.

The edited text of a document borrows from its successor in id order.  Texts travel once, compressed,
range-partitioned by id; a task walks its sorted rows with one row of look-ahead.  The last row of each
task meets the first row of the next non-empty one in a join of one row per task.

Likeness of two exact digests is 1 where the canonical bytes are equal and 0 elsewhere.
"""

from __future__ import annotations

import hashlib
import unicodedata
from collections.abc import Iterator

import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .hubs import CHUNK, compare_dealt
from .memory import tidy
from .workspace import Workspace, parallelism


def canonical(text: str) -> bytes:
    if text.isascii():
        return " ".join(text.lower().split()).encode()
    folded = unicodedata.normalize("NFKC", unicodedata.normalize("NFKC", text).casefold())
    return " ".join(folded.split()).encode()


def digest(canon: bytes) -> str:
    return xxhash.xxh3_128_hexdigest(canon)


def edited(text: str, following: str) -> str:
    k = len(text) // 4
    return text[: len(text) - k] + following[:k] if k else text


def _pack(values: list[bytes]) -> list[bytes]:
    c = zstandard.ZstdCompressor(level=3)
    return [c.compress(v) for v in values]


def _unpack(values: Iterator[bytes]) -> Iterator[bytes]:
    d = zstandard.ZstdDecompressor()
    return (d.decompress(v) for v in values)


def buckets(df: DataFrame, ws: Workspace) -> DataFrame:
    """``(id, hub, size)`` for every id whose fingerprint occurs under more than one id."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([xxhash.xxh3_128_digest(canonical(t.as_py() or "")) for t in b.column(1)], pa.binary())], ["id", "mark"])

    marks = ws.save(df.where("id is not null").mapInArrow(tidy(run), "id long, mark binary"), "marks")
    many = marks.groupBy("mark").agg(F.min("id").alias("hub"), F.max("id").alias("top"), F.count("*").alias("size")).where("hub <> top")
    return marks.join(many, "mark").select("id", "hub", "size").distinct()


_ROW = "kind int, part int, doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, hub long, size long, packed binary"


def _walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (id, packed, hub, size) by id, flags (packed null) before texts.

    Out: kind 0 finished rows; 1 the last text and 2 the first text of the task; 3 canonical bytes of bucket members.
    """
    part = TaskContext.get().partitionId()
    held: tuple | None = None
    flags: dict[int, tuple[int, int]] = {}
    first = True
    for b in batches:
        out: list[tuple] = []
        ids, packed, hubs, sizes = (b.column(i).to_pylist() for i in range(4))
        for i, z, hub, size in zip(ids, packed, hubs, sizes, strict=True):
            if z is None:
                flags = {k: v for k, v in flags.items() if k == i}
                flags[i] = (hub, size)
                continue
            text = next(_unpack(iter([z]))).decode()
            canon = canonical(text)
            if first:
                out.append((2, part, i, None, None, None, None, None, None, None, None, z))
                first = False
            if i in flags:
                out.append((3, part, i, None, None, None, None, None, None, *flags[i], _pack([canon])[0]))
            if held is not None:
                out.append(finish(held[0], held[1], held[2], text, canon, part))
            held = (i, text, canon)
        if out:
            yield _batch(out)
    if held is not None:
        yield _batch([(1, part, held[0], None, None, None, None, None, None, None, None, _pack([held[1].encode()])[0])])


def finish(i: int | None, text: str, canon: bytes, following: str, following_canon: bytes, part: int) -> tuple:
    changed = edited(text, following)
    changed_canon = canonical(changed)
    sha = hashlib.sha256(changed.encode()).hexdigest()
    return (0, part, i, len(text), sha, digest(canon), digest(changed_canon), float(canon == changed_canon), float(canon == following_canon), None, None, None)


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64(), pa.int64(), pa.int64(), pa.binary()]
    names = [c.split(" ")[0] for c in _ROW.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)


def fingerprint(df: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per row of ``df``: ``doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next``.

    Null texts count as empty.  Rows go by ascending id, null ids first; rows that repeat an id follow
    each other in the order of their packed text.  After the last row comes the first.  Other columns are ignored.
    """
    ws = Workspace(df.sparkSession, "fingerprints")
    docs = df.select(F.col(doc_id).cast("long").alias("id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    flags = buckets(docs, ws)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(_pack([t.as_py().encode() for t in b.column(1)]), pa.binary())], ["id", "packed"])

    texts = docs.mapInArrow(tidy(pack), "id long, packed binary").selectExpr("id", "packed", "cast(null as long) as hub", "cast(null as long) as size")
    stream = texts.unionByName(flags.selectExpr("id", "cast(null as binary) as packed", "hub", "size"))
    dealt = stream.repartitionByRange(parallelism(ws.spark), F.col("id").asc_nulls_first()).sortWithinPartitions(F.col("id").asc_nulls_first(), F.col("packed").asc_nulls_first())
    rows = ws.save(dealt.select("id", "packed", "hub", "size").mapInArrow(tidy(_walk), _ROW), "rows")

    # One row a task: its last text and the first text of the task after it, around the end to the start.
    order = Window.orderBy("part")
    heads = rows.where("kind = 2").select("part")
    ring = heads.select("part", F.coalesce(F.lead("part").over(order), F.min("part").over(Window.partitionBy())).alias("after"))
    tails = rows.where("kind = 1").select("part", F.col("doc_id").alias("id"), F.col("packed").alias("mine"))
    firsts = rows.where("kind = 2").select(F.col("part").alias("after"), F.col("packed").alias("theirs"))
    seams = tails.join(ring, "part").join(firsts, "after").select("part", "id", "mine", "theirs")

    def sew(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for part, i, mine, theirs in zip(*(b.column(k).to_pylist() for k in range(4)), strict=True):
                a, c = (x.decode() for x in _unpack(iter([mine, theirs])))
                out.append(finish(i, a, canonical(a), c, canonical(c), part))
            if out:
                yield _batch(out)

    done = rows.where("kind = 0").unionByName(seams.mapInArrow(sew, _ROW))

    members = rows.where("kind = 3").select("hub", F.col("doc_id").alias("id"), "size", "packed")
    chunks = F.ceil(F.col("size") / CHUNK).cast("int")
    as_hub = members.where("id = hub").select("hub", F.explode(F.sequence(F.lit(0), chunks - 1)).alias("chunk"), F.lit(0).alias("role"), "id", "packed")
    as_member = members.where("id <> hub").select("hub", F.pmod(F.xxhash64("id"), chunks).cast("int").alias("chunk"), F.lit(1).alias("role"), "id", "packed")
    differ = compare_dealt(as_hub.unionAll(as_member), lambda c: _unpack(x.as_py() for x in c), lambda a, b: a == b).where("not same")
    differ = ws.save(differ.select(F.col("member").alias("clash")).distinct(), "clashes")
    own = F.col("fingerprint")
    if not differ.isEmpty():
        done = done.join(differ, done.doc_id == differ.clash, "left")
        own = F.when(F.col("clash").isNull(), own).otherwise(F.concat(own, F.lit("-"), F.col("clash").cast("string")))
    return done.select("doc_id", "n_chars", "edited_sha256", own.alias("fingerprint"), "edited_fingerprint", "near_edited", "near_next")
