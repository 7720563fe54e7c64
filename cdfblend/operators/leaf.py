"""Leaf summaries: raw values of a key in, one digest out.

Engines
    ``sorted``   canonical: shuffle by key, sort by key and arrival, stream over runs.  Memory is one
                 batch and one set of knots, whatever the size of a key.
    ``group``    same result through grouped Arrow batches, for keys that fit in memory.
    ``partial``  a partition is a leaf: states per key are folded where the rows lie and only digests are
                 shuffled, then rolled up.  No raw row moves, and a hot key is spread over all partitions;
                 the result depends on the layout of the input, within the accuracy of a roll-up.

Nulls and NaN are ignored and counted in ``n_skipped``; infinite values fail or are skipped (``on_bad``).
A key without usable values gives no row.  Null keys form a key of their own.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from ..functions.levels import grid
from ..functions.scale import scale
from .digest import DIGEST, DIGEST_ARROW, STATE_ARROW, STATE_DDL, Scheme, Summary
from .keyjoin import join_on
from .rollup import merge
from .runs import fold_runs

#: Rows that a partial task looks at together, so that a key's values come in longer pieces.
GATHER_ROWS = 1 << 17
#: Keys whose states a partial task keeps open before it emits the oldest as digests.
MAX_OPEN_KEYS = 50_000


class _Intake:
    """A summary with its pending batch."""

    def __init__(self, scheme: Scheme, summary: Summary | None = None):
        self.scheme, self._summary = scheme, summary
        self.pending: list[np.ndarray] = []
        self.held = 0
        self.skipped = 0

    @property
    def summary(self) -> Summary:
        if self._summary is None:
            self._summary = Summary(self.scheme)
        return self._summary

    def digest(self) -> dict | None:
        """Close the last batch; a key with fewer values than the record has needs no summary at all."""
        if self._summary is None and self.held < len(grid(self.scheme.report).levels):
            if not self.held:
                return None
            values = np.sort(np.concatenate(self.pending))
            scale(self.scheme.scale).check(values)
            return {"n": self.held, "parts": 1, "raw": True, "grid": None, "scale": self.scheme.scale, "vals": values.tolist()}
        self.flush()
        return self.summary.digest(parts=1)

    def add(self, values: np.ndarray) -> None:
        usable = ~np.isnan(values)
        if np.isinf(values).any():
            if self.scheme.on_bad == "fail":
                raise ValueError("infinite value; use on_bad='skip' to leave such values out")
            usable &= np.isfinite(values)
        self.skipped += int(len(values) - usable.sum())
        values = values[usable]
        cap = self.scheme.batch
        if cap is None:
            self._hold(values)
            return
        while len(values):
            take = min(cap - self.held, len(values))
            self._hold(values[:take])
            values = values[take:]
            if self.held == cap:
                self.flush()

    def _hold(self, values: np.ndarray) -> None:
        if len(values):
            self.pending.append(values)
            self.held += len(values)

    def flush(self) -> None:
        if self.held:
            self.summary.add_raw(np.concatenate(self.pending))
            self.pending, self.held = [], 0


def _doubles(col: pa.Array) -> np.ndarray:
    return np.asarray(col.cast(pa.float64()).fill_null(float("nan")).to_numpy(zero_copy_only=False), dtype=float)


def keyed(df: DataFrame, keys: Sequence[str | Column], value: str | Column, order: Sequence[str | Column]) -> tuple[DataFrame, list[str], list[str]]:
    """``k0.., o0.., value`` with clash-free names, and the names of the key and order columns."""
    as_col = lambda c: F.col(c) if isinstance(c, str) else c
    ks = [as_col(c).alias(f"_k{i}") for i, c in enumerate(keys)]
    os_ = [as_col(c).alias(f"_o{i}") for i, c in enumerate(order)]
    return df.select(*ks, *os_, as_col(value).cast("double").alias("_v")), [f"_k{i}" for i in range(len(ks))], [f"_o{i}" for i in range(len(os_))]


def key_names(df: DataFrame, keys: Sequence[str | Column]) -> list[str]:
    return [k if isinstance(k, str) else df.select(k).columns[0] for k in keys]


def out_schema(src: DataFrame, ks: list[str], *more: T.StructField) -> tuple[T.StructType, pa.Schema]:
    fields = [T.StructField(k, src.schema[k].dataType) for k in ks]
    arrow = [(f.name, to_arrow_type(f.dataType, timestamp_utc=True)) for f in fields]
    extra = {"digest": DIGEST_ARROW, "n_skipped": pa.int64(), "state": STATE_ARROW}
    return T.StructType([*fields, *more]), pa.schema([*arrow, *[(m.name, extra[m.name]) for m in more]])


def summarize(df: DataFrame, keys: Sequence[str | Column], value: str | Column, order: Sequence[str | Column] = (), scheme: Scheme = Scheme(), engine: str = "sorted", initial: DataFrame | None = None, emit_state: bool = False, period: str | None = None, time: str | None = None, metrics: Sequence[str] | None = None, partitions: int | None = None) -> DataFrame:
    """One row per key: the key columns, ``digest`` and ``n_skipped`` (with ``emit_state`` also ``state``).

    ``order`` is the arrival order and should be total; without it order is that of the input.
    ``period`` with ``time`` adds a ``period`` key (``window`` struct).  ``metrics`` unpivots several value
    columns into a ``metric`` key.  ``initial`` holds states of an earlier call (same keys) to go on from.
    """
    if metrics:
        pairs = ", ".join(f"'{m}', cast(`{m}` as double)" for m in metrics)
        rest = [c for c in df.columns if c not in metrics]
        df = df.select(*rest, F.expr(f"stack({len(metrics)}, {pairs}) as (metric, _metric_value)"))
        keys, value = [*keys, "metric"], "_metric_value"
    if period:
        df = df.withColumn("period", F.window(F.col(time), period))
        keys = [*keys, "period"]
    names = key_names(df, keys)
    src, ks, os_ = keyed(df, keys, value, order)
    nk = len(ks)
    if engine == "partial":
        out = _partial(src, ks, os_, scheme)
    elif engine in ("sorted", "group"):
        fields = [T.StructField("digest", DIGEST), T.StructField("n_skipped", T.LongType())]
        if emit_state:
            fields.append(T.StructField("state", T._parse_datatype_string(STATE_DDL)))
        schema, arrow = out_schema(src, ks, *fields)
        resumes = initial is not None
        if resumes:
            start = initial.select(*[F.col(n).alias(k) for n, k in zip(names, ks, strict=True)], F.col("state").alias("_state"))
            src = join_on(src, start, ks, "left")  # a state is small; it rides on the rows of its key and is read once
        vcol = nk + len(os_)

        def start_run() -> list:
            return [None]

        def add(cell: list, b: pa.RecordBatch) -> None:
            if cell[0] is None:
                stored = b.column(vcol + 1)[0].as_py() if resumes else None
                cell[0] = _Intake(scheme, Summary.resume(scheme, stored) if stored else None)
            cell[0].add(_doubles(b.column(vcol)))

        def finish(key: tuple, cell: list) -> dict | None:
            x = cell[0]
            if emit_state:
                x.flush()
            d = x.digest()
            if d is None:
                return None
            row = dict(zip(ks, key, strict=True)) | {"digest": d, "n_skipped": x.skipped}
            return row | {"state": x.summary.store()} if emit_state else row

        if engine == "sorted":

            plain = bool(ks) and not emit_state and not resumes

            def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                bulk = (lambda b, lo, hi: _raw_digests(b, nk, vcol, lo, hi, scheme, arrow)) if plain else None
                return fold_runs(batches, nk, start_run, add, finish, arrow, len(grid(scheme.report).levels), bulk)

            dealt = src if not ks else (src.repartition(partitions, *ks) if partitions else src.repartition(*ks))
            dealt = dealt.coalesce(1) if not ks else dealt
            out = dealt.sortWithinPartitions(*ks, *os_).mapInArrow(run, schema) if ks or os_ else dealt.mapInArrow(run, schema)
        else:

            def group(t: pa.Table) -> pa.Table:
                t = t.sort_by([(o, "ascending") for o in os_]) if os_ else t
                rows = list(fold_runs(iter(t.combine_chunks().to_batches()), nk, start_run, add, finish, arrow))
                return pa.Table.from_batches(rows, schema=arrow)

            out = src.groupBy(*ks).applyInArrow(group, schema)
    else:
        raise ValueError(f"unknown engine {engine!r}")
    return out.select(*[F.col(k).alias(n) for k, n in zip(ks, names, strict=True)], *out.columns[nk:])


def _raw_digests(b: pa.RecordBatch, nk: int, vcol: int, lo: np.ndarray, hi: np.ndarray, scheme: Scheme, schema: pa.Schema) -> pa.RecordBatch:
    """Raw digests of many short runs ``[lo, hi)`` of a batch in array steps: a key of few values is its sorted values."""
    length = hi - lo
    at = np.repeat(lo - (np.cumsum(length) - length), length) + np.arange(int(length.sum()))
    run, values = np.repeat(np.arange(len(lo)), length), _doubles(b.column(vcol))[at]
    if scheme.on_bad == "fail" and np.isinf(values).any():
        raise ValueError("infinite value; use on_bad='skip' to leave such values out")
    usable = np.isfinite(values)
    run, values = run[usable], values[usable]
    order = np.lexsort((values, run))
    values = values[order]
    scale(scheme.scale).check(values)
    n = np.bincount(run, minlength=len(lo))
    kept = np.flatnonzero(n > 0)
    ends = np.concatenate([[0], np.cumsum(n[kept])]).astype(np.int32)
    size = len(kept)
    cols = {
        "n": pa.array(n[kept], pa.int64()), "parts": pa.array(np.ones(size, np.int64)), "raw": pa.array(np.ones(size, bool)), "grid": pa.nulls(size, pa.string()),
        "scale": pa.array([scheme.scale] * size, pa.string()), "vals": pa.ListArray.from_arrays(pa.array(ends), pa.array(values)),
    }
    digest = pa.StructArray.from_arrays([cols[f.name] for f in DIGEST_ARROW], fields=list(DIGEST_ARROW))
    keys = [b.column(k).take(pa.array(lo[kept])).cast(schema.field(k).type) for k in range(nk)]
    return pa.RecordBatch.from_arrays([*keys, digest, pa.array((length - n)[kept], pa.int64())], schema=schema)


def summarize_arms(df: DataFrame, keys: Sequence[str], value: str | Column, order: Sequence[str | Column], arms: dict[str, Scheme]) -> DataFrame:
    """``keys, arm, digest``: the digests of several schemes from one shuffle, one sort and one pass over the rows."""
    src, ks, os_ = keyed(df, keys, value, order)
    schema, arrow = out_schema(src, ks, T.StructField("digest", DIGEST))
    schema, arrow = T.StructType([T.StructField("arm", T.StringType()), *schema.fields]), pa.schema([("arm", pa.string()), *arrow])
    vcol = len(ks) + len(os_)

    def add(cells: dict[str, _Intake], b: pa.RecordBatch) -> None:
        values = _doubles(b.column(vcol))
        for x in cells.values():
            x.add(values)

    def finish(key: tuple, cells: dict[str, _Intake]) -> list[dict]:
        rows = [{"arm": arm, "digest": x.digest()} | dict(zip(ks, key, strict=True)) for arm, x in cells.items()]
        return [r for r in rows if r["digest"] is not None]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return fold_runs(batches, len(ks), lambda: {arm: _Intake(s) for arm, s in arms.items()}, add, finish, arrow)

    out = src.repartition(*ks).sortWithinPartitions(*ks, *os_).mapInArrow(run, schema)
    return out.select(*[F.col(k).alias(n) for k, n in zip(ks, keys, strict=True)], "arm", "digest")


class _Struct:
    """A hashable struct value."""

    def __init__(self, value: dict):
        self.items = tuple(value.items())

    def __hash__(self) -> int:
        return hash(self.items)

    def __eq__(self, other) -> bool:
        return isinstance(other, _Struct) and self.items == other.items


def _hashable(v):
    return _Struct(v) if isinstance(v, dict) else v


def gathered(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about ``rows``."""
    held: list[pa.RecordBatch] = []
    size = 0
    for b in batches:
        held.append(b)
        size += b.num_rows
        if size >= rows:
            yield from pa.Table.from_batches(held).combine_chunks().to_batches()
            held, size = [], 0
    if size:
        yield from pa.Table.from_batches(held).combine_chunks().to_batches()


def partial_digests(src: DataFrame, ks: list[str], os_: list[str], scheme: Scheme, max_open: int = MAX_OPEN_KEYS) -> DataFrame:
    """Digests per (task, key) without moving a row; several per key where a task closes states early."""
    nk, vcol = len(ks), len(ks) + len(os_)
    schema, arrow = out_schema(src, ks, T.StructField("digest", DIGEST), T.StructField("n_skipped", T.LongType()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        open_: dict[tuple, _Intake] = {}

        def close(keys: list[tuple]) -> Iterator[pa.RecordBatch]:
            rows = []
            for key in keys:
                x = open_.pop(key)
                d = x.digest()
                if d is not None or x.skipped:
                    rows.append({k: dict(v.items) if isinstance(v, _Struct) else v for k, v in zip(ks, key, strict=True)} | {"digest": d, "n_skipped": x.skipped})
            if rows:
                yield pa.RecordBatch.from_pylist(rows, schema=arrow)

        for b in gathered(batches, GATHER_ROWS):
            values = _doubles(b.column(vcol))
            if nk:
                table = pa.table({f"{k}": b.column(k) for k in range(nk)})
                code = np.zeros(b.num_rows, np.int64)
                for k in range(nk):
                    c = table.column(k).combine_chunks()
                    if pa.types.is_nested(c.type):
                        seen: dict = {}
                        ids = np.array([seen.setdefault(repr(v), len(seen)) for v in c.to_pylist()])
                        size = len(seen)
                    else:
                        d = c.dictionary_encode(null_encoding="encode")
                        ids, size = np.asarray(d.indices.fill_null(0)), max(1, len(d.dictionary))
                    _, code = np.unique(code * size + ids, return_inverse=True)
                order = np.argsort(code, kind="stable")
                cuts = np.flatnonzero(np.diff(code[order], prepend=-1, append=-2))
            else:
                order, cuts = np.arange(b.num_rows), np.array([0, b.num_rows])
            for lo, hi in zip(cuts, cuts[1:], strict=False):
                rows = order[lo:hi]
                if not len(rows):
                    continue
                key = tuple(_hashable(b.column(k)[int(rows[0])].as_py()) for k in range(nk))
                x = open_.pop(key, None) or _Intake(scheme)
                open_[key] = x  # most recent last
                x.add(values[rows])
            if len(open_) > max_open:
                yield from close(list(open_)[: len(open_) // 2])
        yield from close(list(open_))

    return src.mapInArrow(run, schema)


def _partial(src: DataFrame, ks: list[str], os_: list[str], scheme: Scheme) -> DataFrame:
    pieces = partial_digests(src, ks, os_, scheme)
    whole = merge(pieces, ks, "digest", ["digest.n", "digest.vals"], scheme.but(batch=max(2, (scheme.batch or 100))), carry="n_skipped")
    one = F.struct(F.col("digest.n").alias("n"), F.lit(1).cast("long").alias("parts"), *[F.col(f"digest.{c}").alias(c) for c in ("raw", "grid", "scale", "vals")])
    return whole.select(*ks, one.alias("digest"), "n_skipped")


def most_held(df: DataFrame, value: str | Column, scheme: Scheme = Scheme()) -> DataFrame:
    """``values_held``: the most values that a leaf stores at any time (knots, first values, pending batch); a partition is a leaf."""
    src, _, _ = keyed(df, [], value, [])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x, most = _Intake(scheme), 0
        take_in = x._hold

        def look() -> None:
            nonlocal most
            most = max(most, sum(map(len, x.pending)) + (x._summary.held if x._summary else 0))

        def hold(values: np.ndarray) -> None:
            take_in(values)
            look()

        x._hold = hold
        for b in batches:
            x.add(_doubles(b.column(0)))
        x.digest()
        look()
        yield pa.RecordBatch.from_arrays([pa.array([most], pa.int32())], ["values_held"])

    return src.mapInArrow(run, "values_held int").agg(F.max("values_held").alias("values_held"))


def digest_agg(scheme: Scheme = Scheme()):
    """A grouped aggregate for ``groupBy().agg()`` and SQL: the digest of a column, in input order."""
    from pyspark.sql.functions import ArrowUDFType, arrow_udf

    def run(v: pa.Array) -> dict:
        x = _Intake(scheme)
        x.add(_doubles(v))
        return x.digest()

    return arrow_udf(run, DIGEST, ArrowUDFType.GROUPED_AGG)
