"""Online leaves: one summary per key and period, kept in Spark's state store.

State is the knots, the counts and the pending batch, a few kilobytes whatever the length of the stream.  An
event-time timer at the end of a period emits the digest and clears the state.  Rows of a micro-batch are
sorted by arrival inside a key before they enter.  A period closes when the watermark passes its end, so a row of a
closed period lies behind the watermark: Spark drops it and counts it in the query's progress.  The watermark's delay is
the time that late rows are waited for; what comes later still can be summarised as a batch, and its digests merged.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..operators.digest import DIGEST, STATE_DDL, Scheme, Summary
from ..operators.leaf import _Intake
from ..operators.rollup import merge

ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def with_event_time(df: DataFrame, column: str, delay: str) -> DataFrame:
    """Time-zone-free timestamps cannot carry a watermark; they are read as UTC."""
    return df.withColumn(column, F.col(column).cast("timestamp")).withWatermark(column, delay)


class _Leaf(StatefulProcessor):
    def __init__(self, scheme: Scheme, keys: Sequence[str], value: str, order: Sequence[str]):
        self.scheme, self.keys, self.value, self.order = scheme, list(keys), value, list(order)
        self.summary_type = T._parse_datatype_string(STATE_DDL)  # needs the driver's parser

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        schema = T.StructType([T.StructField("summary", self.summary_type), T.StructField("pending", T.ArrayType(T.DoubleType())), T.StructField("skipped", T.LongType()), T.StructField("closes", T.LongType())])
        self.state = handle.getValueState("leaf", schema)

    def _load(self) -> tuple[_Intake, int]:
        if not self.state.exists():
            return _Intake(self.scheme), 0
        summary, pending, skipped, closes = self.state.get()
        names = self.summary_type.fieldNames()
        stored = summary.asDict() if hasattr(summary, "asDict") else dict(zip(names, summary, strict=True))
        x = _Intake(self.scheme, Summary.resume(self.scheme, stored))
        x.skipped = skipped
        if len(pending):
            x._hold(np.array(pending, dtype=float))
        return x, closes

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        x, closes = self._load()
        pdf = pd.concat(list(rows))
        if self.order:
            pdf = pdf.sort_values(self.order, kind="stable")
        x.add(pdf[self.value].to_numpy(dtype=float, na_value=np.nan))
        if not closes:
            closes = int(pd.Timestamp(pdf["leaf_closes"].iloc[0]).value // 1_000_000)
            self.handle.registerTimer(max(closes, int(timerValues.getCurrentWatermarkInMs()) + 1))
        s = x.summary.store()
        held = np.concatenate(x.pending).tolist() if x.pending else []
        self.state.update((tuple(s[f] for f in self.summary_type.fieldNames()), held, x.skipped, closes))
        return iter(())

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        x, closes = self._load()
        x.flush()
        d = x.summary.digest(parts=1)
        self.state.clear()
        if d is not None:
            row = dict(zip([*self.keys, "period_start"], key, strict=True)) | {"period_end": pd.Timestamp(closes, unit="ms", tz="UTC"), "digest": d, "n_skipped": x.skipped}
            yield pd.DataFrame([row])

    def close(self) -> None:
        pass


def leaf_stream(df: DataFrame, keys: Sequence[str], value: str, time: str, period: str, scheme: Scheme = Scheme(), order: Sequence[str] = ()) -> DataFrame:
    """``keys, period_start, period_end, digest, n_skipped`` from a stream with a watermark on ``time``."""
    w = F.window(time, period)
    plain = lambda o: F.unix_micros(o) if isinstance(df.schema[o].dataType, T.TimestampType) else F.col(o)  # noqa: E731  a stream has one event-time column
    rows = df.select(*keys, F.col(time), *[plain(o).alias(f"leaf_order_{i}") for i, o in enumerate(order)], F.col(value).cast("double").alias("leaf_value"), w["start"].alias("period_start"), w["end"].alias("leaf_closes"))
    out = T.StructType([*[T.StructField(k, df.schema[k].dataType) for k in keys], T.StructField("period_start", T.TimestampType()), T.StructField("period_end", T.TimestampType()), T.StructField("digest", DIGEST), T.StructField("n_skipped", T.LongType())])
    leaf = _Leaf(scheme, keys, "leaf_value", [f"leaf_order_{i}" for i in range(len(order))])
    return rows.groupBy(*keys, "period_start").transformWithStateInPandas(leaf, outputStructType=out, outputMode="Append", timeMode="EventTime")


def event_counts(df: DataFrame, time: str, keys: Sequence[str], period: str, slide: str | None = None) -> DataFrame:
    """Tumbling or sliding counts and totals: ``keys, start, n``."""
    w = F.window(time, period, slide) if slide else F.window(time, period)
    return df.groupBy(w.alias("w"), *keys).agg(F.count("*").alias("n")).select(*keys, F.col("w.start").alias("start"), "n")


def session_counts(df: DataFrame, time: str, keys: Sequence[str], gap: str) -> DataFrame:
    return df.groupBy(F.session_window(time, gap).alias("w"), *keys).agg(F.count("*").alias("n")).select(*keys, F.col("w.start").alias("start"), "n")


def deduplicated(df: DataFrame, ident: Sequence[str]) -> DataFrame:
    """One row per identifier inside the watermark."""
    return df.dropDuplicatesWithinWatermark(list(ident))


def following_errors(events: DataFrame, errors: DataFrame, hours: int = 6) -> DataFrame:
    """Stream-stream interval join: later events of the same user within ``hours`` of an error (both sides have watermarks)."""
    e = errors.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("user_id").alias("error_user"), F.col("ts").alias("error_ts"))
    match = F.expr(f"user_id = error_user and ts > error_ts and ts <= error_ts + interval {hours} hours")
    return events.join(e, match).select("error_id", F.col("event_id").alias("later_id"))


def roll_up_sink(path: str, keys: Sequence[str], scheme: Scheme):
    """A ``foreachBatch`` function: every micro-batch of digests is merged per key and stored under its batch number,
    so a repeated batch replaces what it wrote before."""

    def write(batch: DataFrame, number: int) -> None:
        merged = merge(batch, [*keys, "period_start"], "digest", ["digest.n", "digest.vals"], scheme)
        merged.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{path}/batch={number:012d}")

    return write
