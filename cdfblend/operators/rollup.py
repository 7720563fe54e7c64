"""Roll-ups: many digests of a key in, one digest out; the output can be rolled up again.

``merge`` streams digests in arrival order and folds batches of them into the knots.  ``merge_levels`` climbs a
hierarchy.  ``fan_in`` pre-merges salted sub-keys, so that a key with very many digests is a tree and not one
task.  The order-free form that blends all digests at once is in ``relational``.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from .digest import DIGEST, DIGEST_ARROW, Scheme, Summary
from .keyjoin import join_on
from .runs import fold_runs


class _Pile:
    """A summary with pending digests."""

    def __init__(self, scheme: Scheme):
        self.scheme, self.summary = scheme, Summary(scheme)
        self.pool: list[np.ndarray] = []
        self.pool_parts = 0
        self.full: list[tuple] = []
        self.held = 0
        self.carried = 0

    def add(self, d: pa.StructArray) -> None:
        """Digests in order; the values of raw ones are pooled without looking at them one by one."""
        d = d.filter(pc.greater(pc.fill_null(pc.struct_field(d, "n"), 0), 0))
        if not len(d):
            return
        n, parts, raw, grids, vals = d.flatten()[:4] + [d.flatten()[5]]
        n, parts, is_raw = np.asarray(n), np.asarray(parts.fill_null(0)), np.asarray(raw.fill_null(False))
        off = np.asarray(vals.offsets)
        flat = np.asarray(vals.values, dtype=float)
        weight = np.diff(off) if self.scheme.batch_unit == "values" else np.ones(len(n), np.int64)
        upto = np.cumsum(weight)
        lo, done = 0, 0
        while lo < len(n):
            hi = len(n)
            if self.scheme.batch is not None:
                hi = min(hi, int(np.searchsorted(upto, done + self.scheme.batch - self.held, side="left")) + 1)
            if is_raw[lo:hi].all():
                self.pool.append(flat[off[lo] : off[hi]])
                self.pool_parts += int(parts[lo:hi].sum())
            else:
                for k in range(lo, hi):
                    x = flat[off[k] : off[k + 1]]
                    if is_raw[k]:
                        self.pool.append(x)
                        self.pool_parts += int(parts[k])
                    else:
                        self.full.append((int(n[k]), int(parts[k]), False, grids[k].as_py(), x))
            self.held += int(upto[hi - 1]) - done
            done, lo = int(upto[hi - 1]), hi
            if self.scheme.batch is not None and self.held >= self.scheme.batch:
                self.flush()

    def flush(self) -> None:
        if self.held:
            self.summary.add_pooled(np.concatenate(self.pool) if self.pool else np.zeros(0), self.pool_parts, self.full)
        self.pool, self.pool_parts, self.full, self.held = [], 0, [], 0


def merge(df: DataFrame, keys: Sequence[str | Column], digest: str = "digest", order: Sequence[str | Column] = (), scheme: Scheme = Scheme(), fan_in: int | None = None, partitions: int | None = None, carry: str | None = None) -> DataFrame:
    """One row per key: key columns and ``digest``; counts and leaf numbers add up, extremes are kept.

    ``order`` is the order of arrival (random and sorted arrival are just other columns).  Null or empty digests
    count nothing; a key with none gives no row.  Null keys form a key of their own.  ``carry`` names a count (also of rows
    without a digest) whose sum per key is one more column.
    """
    as_col = lambda c: F.col(c) if isinstance(c, str) else c
    names = [k if isinstance(k, str) else df.select(k).columns[0] for k in keys]
    ks = [f"_m{i}" for i in range(len(keys))]
    os_ = [f"_r{i}" for i in range(len(order))]
    src = df.select(*[as_col(c).alias(k) for c, k in zip(keys, ks, strict=True)], *[as_col(c).alias(o) for c, o in zip(order, os_, strict=True)], as_col(digest).alias("_d"), (F.col(carry) if carry else F.lit(0)).cast("long").alias("_c")).where("_d is not null or _c > 0")
    if fan_in:
        count = src.groupBy(*ks).agg(F.ceil(F.count("*") / fan_in).alias("_w"))
        salted = join_on(src, count, ks).select(*ks, *os_, "_d", F.pmod(F.xxhash64("_d", *os_), F.col("_w")).alias("_salt"))
        tier = merge(salted, [*ks, "_salt"], "_d", os_, scheme)
        out = merge(tier, ks, "digest", ["_salt"], scheme)
        return out.select(*[F.col(k).alias(n) for k, n in zip(ks, names, strict=True)], "digest")
    schema = T.StructType([*[T.StructField(k, src.schema[k].dataType) for k in ks], T.StructField("digest", DIGEST), T.StructField("carried", T.LongType())])
    arrow = pa.schema([*[(k, to_arrow_type(src.schema[k].dataType, timestamp_utc=True)) for k in ks], ("digest", DIGEST_ARROW), ("carried", pa.int64())])
    nk, at = len(ks), len(ks) + len(os_)

    def add(pile: _Pile, b: pa.RecordBatch) -> None:
        pile.add(b.column(at))
        pile.carried += pc.sum(b.column(at + 1)).as_py() or 0

    def finish(key: tuple, pile: _Pile) -> dict | None:
        pile.flush()
        d = pile.summary.digest()
        return None if d is None else dict(zip(ks, key, strict=True)) | {"digest": d, "carried": pile.carried}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return fold_runs(batches, nk, lambda: _Pile(scheme), add, finish, arrow)

    dealt = (src.repartition(partitions, *ks) if partitions else src.repartition(*ks)) if ks else src.coalesce(1)
    dealt = dealt.sortWithinPartitions(*ks, *os_) if ks or os_ else dealt
    out = dealt.mapInArrow(run, schema)
    return out.select(*[F.col(k).alias(n) for k, n in zip(ks, names, strict=True)], "digest", *([F.col("carried").alias(carry)] if carry else []))


def merge_levels(df: DataFrame, tiers: Sequence[Sequence[str | Column]], digest: str = "digest", order: Sequence[str | Column] | None = None, scheme: Scheme = Scheme()) -> list[DataFrame]:
    """One roll-up per tier, each from the tier before; the first reads ``df``. Order defaults to the finer tier's keys."""
    out: list[DataFrame] = []
    below = df
    for keys in tiers:
        by = order if order is not None and not out else [c for c in below.columns if c != digest]
        below = merge(below, keys, digest, by, scheme)
        out.append(below)
    return out
