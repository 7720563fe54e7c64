"""Sharding by a permutation-filled lookup table (native DataFrame functions).

Every shard has a permutation of the slots of a prime-sized table, given by an offset and a skip drawn from its
name.  Shards take turns claiming their next free slot until the table is full, so slots per
shard differ by at most one, and removing a shard moves few other slots.  A row's slot is its key's
digest modulo the prime; the table (its size is the prime, a checked bound) is broadcast.
"""

from __future__ import annotations

import hashlib
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

PRIME = 65_537
#: Largest table that is broadcast: about 8 MB as rows.
MAX_SLOTS = 1_000_003


def _draw(name: str, what: str, below: int) -> int:
    return int.from_bytes(hashlib.sha256(f"{what}:{name}".encode()).digest()[:8], "big") % below


def is_prime(n: int) -> bool:
    return n > 1 and all(n % k for k in range(2, int(n**0.5) + 1))


def fill_table(shards: Sequence[str], slots: int = PRIME) -> list[int]:
    """For every slot the index of the shard that claimed it; time is proportional to slots times log slots."""
    if not is_prime(slots) or slots > MAX_SLOTS:
        raise ValueError(f"slots must be a prime of at most {MAX_SLOTS}")
    if not 0 < len(set(shards)) == len(shards) <= slots:
        raise ValueError("shards must be distinct, at least one and at most as many as slots")
    at = [_draw(s, "offset", slots) for s in shards]
    skip = [1 + _draw(s, "skip", slots - 1) for s in shards]
    table, left = [-1] * slots, slots
    while left:
        for k in range(len(shards)):
            slot = at[k]
            while table[slot] >= 0:
                slot = (slot + skip[k]) % slots
            table[slot] = k
            at[k] = (slot + skip[k]) % slots
            left -= 1
            if not left:
                break
    return table


def lookup(spark: SparkSession, shards: Sequence[str], slots: int = PRIME) -> DataFrame:
    """``(slot int, shard string)``, one row a slot, as a literal of bounded size."""
    names = F.array(*[F.lit(s) for s in shards])
    text = ",".join(map(str, fill_table(shards, slots)))
    cells = spark.range(1).select(F.posexplode(F.split(F.lit(text), ",")).alias("slot", "k"))
    return cells.select("slot", F.element_at(names, F.col("k").cast("int") + 1).alias("shard"))


def slot_of(key: Column, slots: int = PRIME) -> Column:
    """Slot of a key: the first 32 bits of the MD5 of its text, modulo the table size; null keys go like the text ``null``."""
    head = F.substring(F.md5(F.coalesce(key.cast("string"), F.lit("null")).cast("binary")), 1, 8)
    return F.pmod(F.conv(head, 16, 10).cast("long"), F.lit(slots)).cast("int")


def assign(df: DataFrame, key: str, shards: Sequence[str], slots: int = PRIME, name: str = "shard") -> DataFrame:
    """``df`` with ``slot`` and ``name``; columns of these names are replaced.

    Equal keys share a shard; use a unique key where one key may hold many rows.  An empty table stays empty.
    """
    base = df.drop("slot", name)
    table = lookup(df.sparkSession, shards, slots).select(F.col("slot").alias("_slot"), F.col("shard").alias("_shard"))
    placed = base.withColumn("slot", slot_of(F.col(key), slots))
    return placed.join(F.broadcast(table), placed["slot"] == table["_slot"], "left").select(*[placed[c] for c in placed.columns], F.col("_shard").alias(name))


def oracle(shards: Sequence[str], slots: int = PRIME) -> str:
    """Placement of ``documents`` in SQL; the slot table is listed (tests hold it to whole preference lists)."""
    listed = ",".join(map(str, fill_table(shards, slots)))
    names = ", ".join(f"'{s}'" for s in shards)
    return f"""
WITH cell AS (SELECT unnest(string_split('{listed}', ',')) AS k, generate_subscripts(string_split('{listed}', ','), 1) - 1 AS slot),
d AS (SELECT doc_id, CAST(('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), 'null')), 1, 8))::BIGINT % {slots} AS INTEGER) AS slot FROM documents)
SELECT doc_id, d.slot, [{names}][CAST(k AS INTEGER) + 1] AS shard FROM d JOIN cell ON cell.slot = d.slot
"""
