import datetime as dt

import pytest
from pyspark.sql import functions as F

from cdfblend.functions import readout as R
from cdfblend.operators.digest import Scheme
from cdfblend.operators.leaf import summarize
from cdfblend.operators.rollup import merge
from cdfblend.sources.tables import hierarchy, table
from cdfblend.streaming import leaf_stream as S

SF = "/root/testdata/sf0.001"
SCHEME = Scheme(grid="report11", batch=10)


@pytest.fixture(scope="module")
def replay(spark, tmp_path_factory):
    """Events as files in time order, a late row, repeated rows and a sentinel that closes all windows."""
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", S.ROCKSDB)
    path = str(tmp_path_factory.mktemp("replay"))
    e = table(spark, SF, "events").where("event_type in ('error', 'click')")
    rows = sorted(e.collect(), key=lambda r: (r.ts, r.event_id))
    for k in range(3):
        part = rows[k * len(rows) // 3 : (k + 1) * len(rows) // 3]
        spark.createDataFrame(part, e.schema).coalesce(1).write.mode("append").parquet(f"{path}/{k}")
    end = rows[-1].ts + dt.timedelta(days=60)
    late = rows[0].asDict() | {"event_id": -1}
    spark.createDataFrame([tuple(late[c] for c in e.columns), (-2, end, 0, "click", 1.0, "{}")], e.schema).coalesce(1).write.parquet(f"{path}/3")
    spark.createDataFrame([(-3, end + dt.timedelta(days=60), 0, "click", 1.0, "{}")], e.schema).coalesce(1).write.parquet(f"{path}/4")
    return path, e.schema, rows


def stream(spark, replay, delay="1 hour"):
    path, schema, _ = replay
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/*")
    return S.with_event_time(raw, "ts", delay)


def collect(spark, df, name, mode="append"):
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    q.awaitTermination(240)
    assert q.exception() is None
    return spark.table(name), q


def test_windows_equal_their_batch_twins(spark, replay):
    rows = replay[2]
    batch = spark.createDataFrame(rows, replay[1]).withColumn("ts", F.col("ts").cast("timestamp"))
    got, _ = collect(spark, S.event_counts(stream(spark, replay), "ts", ["event_type"], "1 day"), "tumble")
    want = S.event_counts(batch, "ts", ["event_type"], "1 day")
    end = max(r.ts for r in rows) + dt.timedelta(days=2)
    assert {tuple(r) for r in got.where(F.col("start") < F.lit(end)).collect()} == {tuple(r) for r in want.collect()}
    got, _ = collect(spark, S.session_counts(stream(spark, replay), "ts", ["user_id"], "6 hours"), "sessions")
    want = S.session_counts(batch, "ts", ["user_id"], "6 hours")
    assert {tuple(r) for r in want.collect()} <= {tuple(r) for r in got.collect()}


def test_sliding_windows_and_output_modes(spark, replay):
    rows = replay[2]
    batch = spark.createDataFrame(rows, replay[1]).withColumn("ts", F.col("ts").cast("timestamp"))
    want = {tuple(r) for r in S.event_counts(batch, "ts", ["event_type"], "2 days", "1 day").collect()}
    end = F.lit(max(r.ts for r in rows) + dt.timedelta(days=2))
    got, _ = collect(spark, S.event_counts(stream(spark, replay), "ts", ["event_type"], "2 days", "1 day"), "sliding")
    assert {tuple(r) for r in got.where(F.col("start") < end).collect()} == want
    # complete mode keeps every group (and so the late row, which append mode leaves out); update mode repeats a group as it grows
    late = (rows[0].event_type, rows[0].ts)
    full, _ = collect(spark, S.event_counts(stream(spark, replay), "ts", ["event_type"], "2 days", "1 day"), "full", "complete")
    off = {tuple(r) for r in full.where(F.col("start") < end).collect()} ^ want
    assert all(t == late[0] for t, *_ in off)
    grown, _ = collect(spark, S.event_counts(stream(spark, replay), "ts", ["event_type"], "2 days", "1 day"), "grown", "update")
    last = {tuple(r) for r in grown.where(F.col("start") < end).groupBy("event_type", "start").agg(F.max("n")).collect()}
    assert all(t == late[0] for t, *_ in last ^ want) and grown.count() >= len(want)


def test_sink_inside_a_stream(spark, replay, tmp_path):
    leaves = S.leaf_stream(stream(spark, replay), ["event_type"], "value", "ts", "1 day", SCHEME, ["ts", "event_id"])
    sink = S.roll_up_sink(f"file://{tmp_path}/out", ["event_type"], Scheme(batch=10))
    q = leaves.writeStream.foreachBatch(sink).outputMode("append").option("checkpointLocation", f"file://{tmp_path}/cp").trigger(availableNow=True).start()
    q.awaitTermination(240)
    assert q.exception() is None
    got = {r.event_type: r.n for r in spark.read.parquet(f"file://{tmp_path}/out").where("period_start < timestamp'2024-02-15'").groupBy("event_type").agg(F.sum("digest.n").alias("n")).collect()}
    want = {}
    for r in replay[2]:
        want[r.event_type] = want.get(r.event_type, 0) + 1
    assert got == want


def test_leaf_stream_equals_batch_and_late_rows_are_counted(spark, replay):
    rows = replay[2]
    out = S.leaf_stream(stream(spark, replay), ["event_type"], "value", "ts", "1 day", SCHEME, ["ts", "event_id"])
    got, q = collect(spark, out, "leaves")
    batch = spark.createDataFrame(rows, replay[1]).withColumn("ts", F.col("ts").cast("timestamp"))
    want = summarize(batch, ["event_type"], "value", ["ts", "event_id"], SCHEME, period="1 day", time="ts")
    a = {(r.event_type, r.period_start): (r.digest.n, list(r.digest.vals)) for r in got.collect()}
    b = {(r.event_type, r.period.start): (r.digest.n, list(r.digest.vals)) for r in want.collect()}
    assert b.keys() <= a.keys()
    for k, (n, vals) in b.items():
        assert a[k][0] == n and a[k][1] == pytest.approx(vals, rel=1e-12)
    dropped = sum(s.numRowsDroppedByWatermark for p in q.recentProgress for s in p.stateOperators)
    assert dropped >= 1


def test_dedup_static_join_and_interval_join(spark, replay):
    rows = replay[2]
    twice = stream(spark, replay).unionAll(stream(spark, replay))
    got, _ = collect(spark, S.deduplicated(twice, ["event_id"]), "dedup")
    assert got.where("event_id >= 0").count() == len(rows)
    joined, _ = collect(spark, stream(spark, replay).join(hierarchy(spark, SF), "user_id").select("event_id", "nation"), "static")
    assert joined.where("event_id >= 0").count() == len(rows)
    got, _ = collect(spark, S.following_errors(stream(spark, replay, "1 day"), stream(spark, replay, "1 day")), "pairs")
    want = {(a.event_id, b.event_id) for a in rows if a.event_type == "error" for b in rows if b.user_id == a.user_id and a.ts < b.ts <= a.ts + dt.timedelta(hours=6)}
    assert {tuple(r) for r in got.where("error_id >= 0 and later_id >= 0").collect()} == want


def test_roll_up_sink_is_idempotent(spark, replay, tmp_path):
    rows = replay[2]
    batch = spark.createDataFrame(rows, replay[1]).withColumn("period_start", F.date_trunc("day", "ts"))
    d = summarize(batch, ["event_type", "period_start"], "value", ["ts", "event_id"], SCHEME)
    sink = S.roll_up_sink(f"file://{tmp_path}/out", ["event_type"], SCHEME)
    for _ in range(2):
        sink(d, 7)
    stored = spark.read.parquet(f"file://{tmp_path}/out")
    assert stored.agg(F.sum("digest.n")).first()[0] == len(rows)
    assert merge(stored, ["event_type"], "digest", ["period_start"], SCHEME).select(R.quantile_at("digest", 0.5)).count() == 2
