"""Exact comparison of many members with their hub, streamed.

Pairs ``(hub, member)`` are split into chunks of bounded member count, so a hub with a third of all
rows becomes many tasks; the hub's text travels once per chunk.  Rows are sorted hub first, so a task
holds one prepared hub and one Arrow batch at a time and never a whole group.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .memory import tidy
from .workspace import parallelism

CHUNK = 128


def agreeing_pairs(pairs: DataFrame, texts: DataFrame, prepare: Callable[[pa.Array], Iterator], agree: Callable[[object, object], bool], chunk: int = CHUNK) -> DataFrame:
    """The pairs ``(hub, member)`` (longs) whose prepared texts agree; ``texts`` is ``(id, text)``."""
    size = pairs.groupBy("hub").agg(F.count("*").alias("size"))
    cut = pairs.join(size, "hub").select("hub", F.pmod(F.xxhash64("member"), F.ceil(F.col("size") / chunk)).alias("chunk"), "member")
    rows = cut.select("hub", "chunk", F.lit(1).alias("role"), F.col("member").alias("id")).unionAll(
        cut.select("hub", "chunk").distinct().select("hub", "chunk", F.lit(0).alias("role"), F.col("hub").alias("id"))
    )
    full = rows.join(texts, "id").select("hub", "chunk", "role", "id", "text")
    return compare_dealt(full, prepare, agree).where("same").select("hub", "member")


def compare_dealt(rows: DataFrame, prepare: Callable[[pa.Array], Iterator], agree: Callable[[object, object], bool]) -> DataFrame:
    """``(hub, member, same)`` from rows ``(hub, chunk, role, id, text)``: role 0 is the hub, 1 a member."""
    dealt = rows.repartition(parallelism(rows.sparkSession), "hub", "chunk").sortWithinPartitions("hub", "chunk", "role")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, base = None, None
        for b in batches:
            hubs, chunks, roles, ids = (b.column(i).to_pylist() for i in range(4))
            out: list[tuple[int, int, bool]] = []
            for h, c, role, i, x in zip(hubs, chunks, roles, ids, prepare(b.column(4)), strict=True):
                if role == 0:
                    key, base = (h, c), x
                elif key == (h, c):
                    out.append((h, i, bool(agree(base, x))))
            yield pa.RecordBatch.from_pydict({"hub": pa.array([o[0] for o in out], pa.int64()), "member": pa.array([o[1] for o in out], pa.int64()), "same": pa.array([o[2] for o in out], pa.bool_())})

    return dealt.mapInArrow(tidy(run), "hub long, member long, same boolean")
