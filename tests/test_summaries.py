import numpy as np
import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from cdfblend.functions import readout as R
from cdfblend.functions.curve import FlushRules
from cdfblend.operators import baselines as B
from cdfblend.operators import measures as A
from cdfblend.operators import relational as rel
from cdfblend.operators.digest import Scheme
from cdfblend.operators.leaf import digest_agg, summarize
from cdfblend.operators.rollup import merge
from cdfblend.sources.tables import ORDER, table

SF = "/root/testdata/sf0.001"
S = Scheme(grid="report11", batch=20)


@pytest.fixture(scope="module")
def ev(spark):
    return table(spark, SF, "events").cache()


def as_dict(df, *keys):
    return {tuple(r[k] for k in keys): (r.digest.n, r.digest.raw, list(r.digest.vals)) for r in df.collect()}


def test_engines_agree(spark, ev):
    a = as_dict(summarize(ev, ["user_id"], "value", ORDER["events"], S), "user_id")
    b = as_dict(summarize(ev, ["user_id"], "value", ORDER["events"], S, engine="group"), "user_id")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    c = as_dict(summarize(ev.repartition(5), ["user_id"], "value", ORDER["events"], S), "user_id")
    spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert a == b == c
    p = as_dict(summarize(ev.repartition(4), ["user_id"], "value", (), S, engine="partial"), "user_id")
    for k, (n, _, vals) in a.items():
        assert p[k][0] == n and (p[k][2][0], p[k][2][-1]) == (vals[0], vals[-1])
        assert abs(p[k][2][4] - vals[4]) < 0.35 * (vals[6] - vals[2])


def test_cut_and_resume(ev):
    whole = as_dict(summarize(ev, ["event_type"], "value", ORDER["events"], S), "event_type")
    n = ev.withColumn("rn", F.expr("row_number() over (partition by event_type order by ts, event_id)"))
    head = summarize(n.where("rn <= 60"), ["event_type"], "value", ["rn"], S, emit_state=True)
    assert as_dict(summarize(n.where("rn > 60"), ["event_type"], "value", ["rn"], S, initial=head), "event_type") == whole


def test_nulls_nan_infinities_empty_and_clashing_names(spark):
    schema = T.StructType([T.StructField("k", T.StringType()), T.StructField("v", T.DoubleType()), T.StructField("digest", T.IntegerType()), T.StructField("n", T.IntegerType())])
    inf, nan = float("inf"), float("nan")
    rows = [("a", 1.0), ("a", None), ("a", nan), (None, 2.0), (None, 3.0), ("b", None), ("c", 5.0), ("c", 5.0)]
    df = spark.createDataFrame([(*r, 1, 2) for r in rows], schema)
    for engine in ("sorted", "group", "partial"):
        got = {r.k: (r.digest.n, list(r.digest.vals), r.digest.raw, r.n_skipped) for r in summarize(df, ["k"], "v", ["v"], S, engine=engine).collect()}
        assert got == {"a": (1, [1.0], True, 2), None: (2, [2.0, 3.0], True, 0), "c": (2, [5.0, 5.0], True, 0)}
        assert summarize(spark.createDataFrame([], schema), ["k"], "v", ["v"], S, engine=engine).count() == 0
    bad = spark.createDataFrame([("a", inf, 1, 2), ("a", 1.0, 1, 2)], schema)
    with pytest.raises(Exception, match="infinite"):
        summarize(bad, ["k"], "v", ["v"], S).collect()
    assert summarize(bad, ["k"], "v", ["v"], S.but(on_bad="skip")).first().n_skipped == 1
    d = summarize(df, ["k"], "v", ["v"], S)
    assert merge(d.where("false"), ["k"]).count() == 0 and merge(d, [], scheme=S).first().digest.n == 5


def test_constant_and_two_atom_data(spark):
    df = spark.range(500).select(F.lit(7.0).alias("v"), (F.col("id") % 5 == 0).cast("double").alias("w"), "id")
    assert set(summarize(df, [], "v", ["id"], S).first().digest.vals) == {7.0}
    s = S.but(rules=FlushRules("mid", "two_sided", "inner"), batch=100)
    assert set(summarize(df, [], "w", ["id"], s).first().digest.vals) == {0.0, 1.0}


def test_roll_up_is_additive_and_order_free_in_one_blend(ev):
    d = summarize(ev, ["user_id", "event_type"], "value", ORDER["events"], S).cache()
    tree = merge(d, ["event_type"], "digest", ["user_id"], S, fan_in=4)
    flat = merge(d, ["event_type"], "digest", ["user_id"], S)
    exact = {r.event_type: r for r in ev.groupBy("event_type").agg(F.count("*").alias("n"), F.min("value").alias("lo"), F.max("value").alias("hi"), F.count_distinct("user_id").alias("u")).collect()}
    for out in (tree, flat):
        for r in out.collect():
            x = exact[r.event_type]
            assert (r.digest.n, r.digest.parts, r.digest.vals[0], r.digest.vals[-1]) == (x.n, x.u, x.lo, x.hi)
    one = {r.event_type: list(r.digest.vals) for r in merge(d, ["event_type"], "digest", ["user_id"], S.but(batch=None)).collect()}
    two = {r.event_type: list(r.digest.vals) for r in merge(d, ["event_type"], "digest", ["digest.n", "user_id"], S.but(batch=None)).collect()}
    native = {}
    for r in rel.merge_one_blend(d, ["event_type"], [0, 0.05, 0.10, 0.25, 0.50, 0.75, 0.90, 0.95, 0.99, 0.999, 1]).orderBy("level").collect():
        native.setdefault(r.event_type, []).append(r.value)
    for k, v in one.items():
        assert v == pytest.approx(two[k], rel=1e-9) and v == pytest.approx(native[k], rel=1e-9)


def test_sweep_equals_direct_evaluation_in_global_form(ev):
    d = summarize(ev, ["user_id"], "value", ORDER["events"], S)
    a = {r.level: r.value for r in rel.merge_one_blend(d.withColumn("k", F.lit(0)), ["k"], [0.0, 0.25, 0.5, 0.9, 1.0]).collect()}
    b = {r.level: r.value for r in rel.global_blend(d, [0.0, 0.25, 0.5, 0.9, 1.0], buckets=7).collect()}
    assert a == pytest.approx(b, rel=1e-9)


def test_readout_and_aggregate_function(spark, ev):
    d = ev.groupBy("user_id").agg(digest_agg(Scheme(grid="report11", batch=None))("value").alias("digest"))
    exact = {(r.user_id, r.level): r.value for r in B.exact_quantiles(ev, ["user_id"], "value", [0.25, 0.5, 0.9], "mid").collect()}
    for r in d.select("user_id", *[R.quantile_at("digest", p).alias(f"p{k}") for k, p in enumerate((0.25, 0.5, 0.9))], R.as_map("digest").alias("m")).collect():
        for k, p in enumerate((0.25, 0.5, 0.9)):
            assert r[f"p{k}"] == pytest.approx(exact[r.user_id, p]) and r.m[p] == pytest.approx(exact[r.user_id, p])


def test_plans(spark, ev):
    raw = table(spark, SF, "events")
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    part = plan(summarize(raw, ["user_id"], "value", (), S, engine="partial"))
    assert part.count("FileScan") == 1 and "MapInArrow" in part
    one = plan(summarize(table(spark, SF, "lineitem"), ["l_suppkey"], "l_extendedprice", ["l_shipdate", "l_orderkey"], S))
    assert one.count("FileScan") == 1 and one.count("Exchange hash") == 1 and "l_returnflag" not in one.split("ReadSchema")[1]
    native = plan(rel.one_flush(raw, ["user_id"], "value", [0.5]))
    assert "Python" not in native and "Arrow" not in native
    push = plan(table(spark, SF, "lineitem").where("l_quantity > 40").select("l_orderkey"))
    assert "GreaterThan(l_quantity,40.0)" in push


def test_baselines_against_exact(ev):
    exact = {(r.event_type, r.level): r.value for r in B.exact_quantiles(ev, ["event_type"], "value", [0.5, 0.9]).collect()}
    spread = {k: v * 0.35 + 5 for k, v in exact.items()}
    for out in (B.rank_sketch(ev, ["event_type"], "value", [0.5, 0.9]), B.kll(ev, ["event_type"], "value", [0.5, 0.9]), B.bracket_buffers(ev, ["event_type"], "value", ORDER["events"], [0.5, 0.9])):
        for r in out.collect():
            assert abs(r.value - exact[r.event_type, r.level]) < spread[r.event_type, r.level]
    for w in (None, 0.02):
        for r in B.stochastic_quantile(ev, ["event_type"], "value", ORDER["events"], 0.5, w).collect():
            assert abs(r.value - exact[r.event_type, 0.5]) < 2 * spread[r.event_type, 0.5]
    assert B.multipass_select(ev, "value", 0.5, memory=50).first().value == B.exact_quantiles(ev, [], "value", [0.5]).first().value


def test_rank_error_bounds_of_the_sketches(ev):
    n = min(r["count"] for r in ev.groupBy("event_type").count().collect())
    p = [0.05, 0.25, 0.5, 0.75, 0.9, 0.99]
    # the deterministic summary promises 1/accuracy; the randomised one about 1.3% at k = 200 (99% of the time)
    for got, bound in ((B.rank_sketch(ev, ["event_type"], "value", p, 100), 0.01), (B.kll(ev, ["event_type"], "value", p), 0.026)):
        errors = A.rank_error(got, ev, ["event_type"], "value").collect()
        assert len(errors) == 5 * len(p) and max(r.rank_error for r in errors) <= bound + 1 / n


def test_trackers_settle_near_the_quantile(spark):
    """Stochastic steps and bracketing buffers on one long random stream.

    With a constant step weight w the tracker's rank swings around p with variance about w p (1 - p) / 2; the band is three deviations.
    """
    rng = np.random.default_rng(6)
    x = np.exp(rng.normal(size=20_000))
    df = spark.createDataFrame([("a", i, float(v)) for i, v in enumerate(x)], "k string, i long, v double")
    rank = lambda q: float((x <= q).mean())
    for p in (0.5, 0.9):
        assert abs(rank(B.stochastic_quantile(df, ["k"], "v", ["i"], p).first().value) - p) < 0.02
        assert abs(rank(B.stochastic_quantile(df, ["k"], "v", ["i"], p, 0.01).first().value) - p) < 3 * np.sqrt(0.01 * p * (1 - p) / 2)
    for r in B.bracket_buffers(df, ["k"], "v", ["i"], [0.1, 0.5, 0.9]).collect():
        assert abs(rank(r.value) - r.level) < 0.03


def test_seeded_periods_equal_the_kernel(spark, ev):
    from cdfblend.operators.digest import Summary
    from cdfblend.operators.extensions import seeded_by
    from cdfblend.operators.leaf import _Intake

    s, since = Scheme(grid="five", report="five", batch=7), "2024-01-20"
    got = {(r.part, str(r.period)): (r.digest.n, r.digest.vals) for r in seeded_by(ev, F.hour("ts"), F.to_date("ts"), "value", ORDER["events"], since, s, 0.25).collect()}
    rows = sorted(((r.ts, r.event_id, r.value) for r in ev.collect()))
    cells: dict = {}
    for ts, _, v in rows:
        cells.setdefault(((ts.hour, "past") if str(ts.date()) < since else (ts.hour, str(ts.date()))), []).append(v)
    assert set(got) == {k for k in cells if k[1] != "past"}
    for (hour, day), values in cells.items():
        if day == "past":
            continue
        start = None
        if (hour, "past") in cells:
            past = _Intake(s)
            past.add(np.array(cells[hour, "past"]))
            past.flush()
            kept = past.summary.store()
            start = Summary.resume(s, kept | {"n": 0, "parts": 0, "low": np.inf, "high": -np.inf, "early": [], "only_raw": False, "weight": kept["weight"] * 0.25})
        now = _Intake(s, start)
        now.add(np.array(values))
        d = now.digest()
        assert got[hour, day][0] == d["n"] == len(values) and np.allclose(got[hour, day][1], d["vals"])


def test_short_runs_in_bulk_equal_single_ones(spark):
    rows = [(k, i, [None, float("nan"), 3.0 * k - i, -1.0][(k + i) % 4]) for k in range(400) for i in range(k % 14)] + [(None, 0, 5.0), (None, 1, 4.0)]
    df = spark.createDataFrame(rows, "k int, i int, v double").repartition(3)
    got = {r.k: (r.digest.raw, r.digest.n, r.digest.vals, r.n_skipped) for r in summarize(df, ["k"], "v", ["i"], S).collect()}
    one = {r.k: (r.digest.raw, r.digest.n, r.digest.vals, r.n_skipped) for r in summarize(df, ["k"], "v", ["i"], S, engine="group").collect()}
    assert got == one and got[None][2] == [4.0, 5.0] and 0 not in got
    with pytest.raises(Exception, match="infinite"):
        summarize(spark.createDataFrame([(k, 0, float("inf")) for k in range(9)], "k int, i int, v double"), ["k"], "v", ["i"], S).collect()


def test_arms_equal_single_schemes(ev):
    from cdfblend.operators.leaf import summarize_arms

    arms = {"a": S, "b": S.but(batch=9, interp="logit", grid="round41")}
    got = {(r.arm, r.event_type): r.digest.vals for r in summarize_arms(ev, ["event_type"], "value", ORDER["events"], arms).collect()}
    for arm, s in arms.items():
        for r in summarize(ev, ["event_type"], "value", ORDER["events"], s).collect():
            assert got[arm, r.event_type] == r.digest.vals


def test_partial_states_are_bounded(ev):
    from cdfblend.operators.leaf import keyed, partial_digests

    src, ks, os_ = keyed(ev.repartition(3), ["user_id", "event_type"], "value", [])
    few, many = (partial_digests(src, ks, os_, S, n) for n in (4, 10_000))
    total = lambda d: {tuple(r) for r in d.groupBy(*ks).agg(F.sum("digest.n"), F.min(F.array_min("digest.vals")), F.max(F.array_max("digest.vals"))).collect()}
    assert total(few) == total(many)


def test_sql_surface(spark):
    from cdfblend.functions.sqlsurface import register

    register(spark)
    got = [r.y for r in spark.sql("SELECT logit(p) AS y FROM VALUES (0.5D), (0.0D), (1.0D), (CAST(NULL AS DOUBLE)), (0.75D) AS t(p)").collect()]
    assert got[0] == 0 and got[1:4] == [None, None, None] and got[4] == pytest.approx(np.log(3))


def test_trained_grid_learns_from_all_values(spark, monkeypatch):
    from cdfblend.functions import levels as L
    from cdfblend.plans import methods as M

    sf, used = "/root/testdata/sf0.01", []
    monkeypatch.setattr(M, "summarize", lambda df, keys, value, order, scheme: used.append(scheme.tracked()))
    monkeypatch.setattr(M, "flat", lambda *a: None)
    M.grid_trained(spark, sf)
    want = L.train_levels(spark.read.parquet(f"{sf}/events.parquet").toPandas()["value"].to_numpy(), 41)
    # even steps on the arc; on the steep tail a step is a tiny step of the level, hence log odds
    odds = lambda p: np.log(p[1:-1] / (1 - p[1:-1]))
    assert odds(used[0]) == pytest.approx(odds(want), abs=0.05)


@pytest.mark.parametrize("farthest", [123_456.7, 1e12])
def test_range_join_keeps_values_outside_the_usual(spark, tmp_path, farthest):
    """Counts of cells, by hand, where values are negative or far out."""
    from cdfblend.plans import load

    e = spark.read.parquet(f"{SF}/events.parquet")
    values = [-30.0, -0.5, 0.0, 24.9, 25.0, 9_999.0, 10_000.0, farthest]
    far = e.limit(1).drop("value").crossJoin(spark.createDataFrame([(v,) for v in values], "value double")).select(*e.columns)
    far.write.parquet(f"{tmp_path}/events.parquet")
    got = {r.lo: r.n for r in load().QUERIES["join_range"](spark, str(tmp_path)).collect()}
    assert got == {-50.0: 1, -25.0: 1, 0.0: 2, 25.0: 1, 9_975.0: 1, 10_000.0: 1, farthest // 25 * 25: 1}


def test_values_held_are_measured(spark, tmp_path):
    from cdfblend.operators.leaf import most_held
    from cdfblend.plans import load

    one = lambda n, s: most_held(spark.range(0, n, 1, 1), "id", s).first().values_held
    s = Scheme(grid="uniform:41", batch=41)
    # a batch alone; knots and a part of a batch; knots and a batch, which is the bound
    assert [one(n, s) for n in (7, 41, 60, 82, 5000)] == [7, 41, 60, 82, 82]
    assert one(5000, s.but(grid="uniform:50", batch=20)) == 70
    query = load().QUERIES["memory_values"]
    spark.read.parquet(f"{SF}/events.parquet").limit(50).coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    assert [query(spark, d).first().values_held for d in (SF, str(tmp_path))] == [82, 50]
