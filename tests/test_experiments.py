"""The behaviour that the experiments are known for, at reduced run counts; bands were fixed before any tuning."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from cdfblend import oracles as O
from cdfblend.functions import levels as L
from cdfblend.operators.measures import flush_counts
from cdfblend.plans import workloads as W
from cdfblend.registry import QUERIES
from cdfblend.sources import simulate as S
from cdfblend.sources.tables import table

SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def small(spark):
    return {(r.arm, r.dist, r.n, r.level): r.ratio for r in W.sim_small(spark, 32, (1000, 4000)).collect()}


def test_uniform_linear_fails_in_long_tails_and_worse_with_size(small):
    for dist, level in (("normal", 0.006), ("lognormal", 0.9875)):
        a, b = small["uniform+linear", dist, 1000, level], small["uniform+linear", dist, 4000, level]
        assert a > 2.5 and b > a


def test_logit_stays_close_to_exact_everywhere(small):
    inner = [v for (arm, _, n, p), v in small.items() if arm == "logit+logit" and 0.004 <= p <= 0.996]
    assert np.quantile(inner, 0.95) < 2 and np.median(inner) < 1.2


def test_flushes_of_the_published_sizes(spark):
    df = spark.range(10_000).select((F.col("id") >= 1000).cast("int").alias("k"), F.col("id").cast("double").alias("v"))
    ten = flush_counts(spark.range(10_000).select(F.col("id").cast("double").alias("v")), [], "v", 41).first()
    one = flush_counts(df.where("k = 0"), ["k"], "v", 41).first()
    assert (one.full_flushes, one.rest, ten.full_flushes, ten.rest) == (24, 16, 243, 37)


def test_large_samples_grow_slowly(spark):
    got = {r.n: r.mean_ratio for r in S.ratio_by_size(W.sim_large(spark, 6, (1000, 20_000))).collect()}
    assert got[1000] == pytest.approx(1.0, abs=0.02) and got[20_000] < 1.2


def test_measures_of_one_study_share_its_runs(spark):
    first = W.sim_large(spark, 3, (1000, 2000))
    again = W.sim_large(spark, 3, (1000, 2000))
    s = W.Scheme(grid="logit:1000:1e-6", report="list:0.0,0.01,0.05,0.1,0.25,0.5,0.75,0.9,0.95,0.99,1.0", batch=1000, interp="logit")
    fresh = S.leaf_ratios(S.leaf_runs(spark, 3, (1000, 2000), {"logit1000": s}, ("lognormal",)))
    rows = lambda df: sorted((r.n, r.level, r.runs, round(r.ratio, 12)) for r in df.collect())
    assert first.inputFiles() == again.inputFiles() and rows(again) == rows(fresh)
    other = W.sim_large(spark, 3, (1000, 2000), grid="logit:1000:0.0025")
    assert other.inputFiles() != first.inputFiles()


def test_pooled_stream_within_two_standard_errors(spark):
    rows = W.pooled(spark, SF, "events", "value").collect()
    assert len(rows) == 6 and sum(r.within for r in rows) >= 5


def test_three_tiers(spark):
    """The published cells hold about 55 values an hour; the largest tables (133 an hour) are the comparable ones."""
    SF = "/root/testdata/sf0.1"
    hour = {r.level: r.fraction for r in W.A.within_fraction(W.series(spark, SF, 1, "hour"), ["level"]).collect()}
    day = {r.level: r.fraction for r in W.A.within_fraction(W.series(spark, SF, 2, "day"), ["level"]).collect()}
    assert day[0.5] >= 0.9 and day[0.9] >= 0.9 and hour[0.5] >= 0.9 and hour[0.9] >= 0.9


def test_inhomogeneous_leaves(spark):
    """The published setting at 40 of its 500 runs, held to the published bands (BASELINE)."""
    rows = S.inhomogeneous_ratios(S.inhomogeneous_runs(spark, 40)).collect()
    by = {(r.arm, r.level): r.ratio for r in rows}
    levels = sorted({p for _, p in by})
    for order in ("random", "sorted"):
        natural = {p: by[f"identity/{order}", p] for p in levels}
        assert max(natural.values()) < 2 and 0.25 <= max(natural, key=natural.get) <= 0.75
        assert max(by[f"log/{order}", p] for p in levels) < 1.2
        assert all(abs(by[f"{scale}/{order}", 0.999] - 1) < 0.1 for scale in ("identity", "log"))
    assert max(abs(by[f"{scale}/random", p] - by[f"{scale}/sorted", p]) for scale in ("identity", "log") for p in levels) < 0.1
    assert S.mixture_quantile(0.999) == pytest.approx(10**2.551, rel=0.01)


def test_longer_records_are_more_accurate(spark):
    err = {r.record: r.error for r in W.record_errors(spark, SF, (5, 20)).collect()}
    assert err[20] < err[5]


def test_leaves_vary_as_much_as_values_within_a_leaf(monkeypatch):
    """Records of one run: variance of leaf medians against the spread of a leaf, on log10 values."""
    kept = []
    monkeypatch.setattr(S, "_rows", lambda spark, runs, work, seed: work)
    monkeypatch.setattr(S.Summary, "add_digests", lambda self, records: kept.extend(records))
    monkeypatch.setattr(S.Summary, "digest", lambda self: {"vals": [1.0] * 13})
    list(S.inhomogeneous_runs(None, 1, leaves=2000, per_leaf=400, record="five", scales=("log",), orders=("random",), outlying=0.0)(0, np.random.default_rng(3)))
    logs = np.log10([r[4] for r in kept])
    within = ((logs[:, 3] - logs[:, 1]) / (2 * 0.67449)).mean() ** 2
    assert within == pytest.approx(0.0924, rel=0.05) and logs[:, 2].var() == pytest.approx(0.0924, rel=0.1)


def test_both_errors_in_one_pass(spark):
    by = ["arm", "dist", "n", "level"]
    runs = S.inhomogeneous_runs(spark, 3, leaves=100, per_leaf=50, scales=("log",)).cache()
    one = {tuple(r[c] for c in by): r for r in W.A.rmse_both(runs, by).collect()}
    two = W.A.rmse_ratio(*[W.A.rmse(runs.withColumnRenamed(c, "value"), by) for c in ("estimate", "exact")], by).collect()
    assert len(one) == len(two) == 22
    for r in two:
        assert one[tuple(r[c] for c in by)].asDict() == pytest.approx(r.asDict())


_SLICE = "SELECT 0 AS k, row_number() OVER (ORDER BY doc_id) AS rn, ln(1 + n_chars) AS x FROM (SELECT * FROM documents ORDER BY doc_id LIMIT 180) AS z"
_ALL = "SELECT 0 AS k, row_number() OVER (ORDER BY doc_id) AS rn, ln(1 + n_chars) AS x FROM documents"


@pytest.mark.parametrize(("rows", "flushes", "source"), [(180, 3, _SLICE), (None, 4, _ALL)])
def test_small_knots_against_unrolled_sql(spark, rows, flushes, source):
    """The first 180 documents by the SQL that stood beside the query, and all 200 of the smallest table by one flush more."""
    sf = "/root/testdata/sf0.001"
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    assert 180 < con.execute("SELECT count(*) FROM documents").fetchone()[0] <= 240
    sql = O.final(O.unrolled([float(p) for p in L.grid("logit:30:0.0025").levels], flushes, 60, source), flushes, "m AS i, round(exp(v) - 1, 6) AS value")
    docs = table(spark, sf, "documents")
    got = W.small_knots(docs.orderBy("doc_id").limit(rows)) if rows else QUERIES["tab1_slice"](spark, sf)
    assert dict(map(tuple, got.collect())) == pytest.approx(dict(con.execute(sql).fetchall()), abs=2e-6)


def test_third_flush_is_a_state_of_the_whole_stream(spark):
    """Folding all events of each user, and looking at the knots when 30 values are in."""
    from cdfblend.operators.digest import Scheme

    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet").toPandas().sort_values(["user_id", "ts", "event_id"])
    got = {}
    for r in QUERIES["fig4_three_flushes"](spark, "/root/testdata/sf0.001").collect():
        got.setdefault(r.user_id, {})[r.level] = r.value
    for user, x in events.groupby("user_id")["value"]:
        state, values = S.Summary(Scheme(grid="five", report="five", batch=10)), x.to_numpy()
        for k in range(0, len(values), 10):
            state.add_raw(values[k : k + 10])
            if state.n == 30:
                third = dict(zip(state.report.tolist(), state.digest(1)["vals"], strict=True))
        assert len(values) > 30 and got.pop(user) == pytest.approx(third, abs=1e-6)
    assert not got
