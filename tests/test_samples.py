"""Studies on samples of given tables, held to loops over the same samples."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from cdfblend.functions.levels import grid
from cdfblend.operators.digest import Scheme, Summary
from cdfblend.plans import workloads as W
from cdfblend.registry import QUERIES
from cdfblend.sources import samples as T
from cdfblend.sources.simulate import exact

SF = "/root/testdata/sf0.001"


def test_large_quantiles(spark):
    rng, levels = np.random.default_rng(5), [0.001, 0.25, 0.5, 0.9, 0.999]
    groups = {"tail": np.exp(3 * rng.standard_normal(3000)), "ties": rng.integers(0, 4, 999).astype(float), "one": np.array([7.0]), "equal": np.full(50, -2.5)}
    rows = [(k, float(v)) for k, x in groups.items() for v in x] + [("tail", None), ("ties", float("nan")), ("none", None)]
    df = spark.createDataFrame(rows, "k string, v double")
    for cells in (7, 4096):
        got = {(r.k, r.level): r.value for r in T.large_quantiles(df, ["k"], "v", levels, cells).collect()}
        assert got == {(k, p): v for k, x in groups.items() for p, v in zip(levels, exact(np.sort(x), np.array(levels)).tolist(), strict=True)}


def test_runs_against_a_loop(spark, monkeypatch):
    """All rows of two columns in samples of four sizes, in three passes; one column is too short for the last size."""
    monkeypatch.setattr(T, "SHARED", 250)
    sizes, s = (100, 250, 1000, 2500), Scheme(grid="uniform:11", report="five", batch=30)
    pops = [T.population(spark, SF, name) for name in ("price", "total")]
    want, whole = {}, {}
    for p in pops:
        rows = sorted((r.key, r.value) for r in p.collect())
        dist = p.first().dist
        whole[dist] = len(rows)
        for some in ((100, 250), (1000,), (2500,)):
            counts = [len(rows) // n for n in some if len(rows) // n >= 2]
            runs = {}
            for key, value in sorted(rows, key=lambda r: (r[0] % counts[0], r)) if counts else []:
                run = key % counts[0]
                for k, n in enumerate(some[: len(counts)]):
                    run = run * counts[k] // counts[k - 1] if k else run
                    runs.setdefault((n, run), []).append(value)
            for (n, run), x in runs.items():
                state = Summary(s)
                for k in range(0, len(x), 30):
                    state.add_raw(np.array(x[k : k + 30]))
                at = grid("five").array()
                for p_, v, e in zip(at.tolist(), state.digest(1)["vals"], exact(np.sort(x), at).tolist(), strict=True):
                    want[dist, n, run, p_] = (pytest.approx(float(v)), e)
    got = [((r.dist, r.n, r.run, r.level), (r.estimate, r.exact)) for r in T.sample_runs(pops, sizes, {"a": s}).collect()]
    assert whole["price"] > 5000 and 1000 < whole["total"] < 2000
    assert len(got) == len(want) and dict(got) == want


@pytest.mark.parametrize(("name", "dists"), [("sim_ratio", 3), ("sim_bias", 3), ("sim_rmse", 3), ("sim_ratio_log", 2), ("sim_ratio_mid", 1), ("sim_growth", 1)])
def test_registered_studies_sample_whole_columns(spark, monkeypatch, name, dists):
    seen = []
    monkeypatch.setattr(W, "once", lambda spark, key, make: make())
    real = T.sample_ratios
    monkeypatch.setattr(T, "sample_ratios", lambda pops, sizes, schemes: (seen.append((pops, sizes)), real(pops, sizes, schemes))[1])
    got = QUERIES[name](spark, SF).collect()
    ((pops, sizes),) = seen
    assert sizes == tuple(10**k for k in (range(3, 8) if name in ("sim_ratio_mid", "sim_growth") else (3, 4)))
    assert len(pops) == dists
    rows = {p.first().dist: p.count() for p in pops}
    for r in got:
        assert rows[r.dist] // r.n >= 2 and (not hasattr(r, "runs") or r.runs == rows[r.dist] // r.n)
    assert {(r.dist, r.n) for r in got} == {(d, n) for d, c in rows.items() for n in sizes if c // n >= 2} != set()


def test_no_column_is_long_enough(spark):
    assert T.sample_ratios([T.population(spark, SF, "total")], (10_000,), {"a": W.UNIFORM}).collect() == []


def test_groups_of_suppliers_against_a_loop(spark):
    """Ten suppliers in two groups: one flush each, so that order does not matter."""
    rows = W.far_prices(spark, SF).select("l_suppkey", "price", F.pmod(F.xxhash64("l_suppkey"), F.lit(2)).alias("run")).toPandas()
    assert rows.l_suppkey.nunique() == 10
    at, levels = grid("report10").array(), np.array(W._TAILS)
    got = {(r.arm, r.run, r.level): r for r in W.inhomog_runs(spark, SF).collect()}
    assert len(got) == 4 * 2 * len(levels)
    truth = exact(np.sort(rows.price.to_numpy()), levels)
    digests = {r.l_suppkey: r.digest for r in W.inhomog_suppliers(spark, SF, Scheme(grid="report10", report="report10", batch=None)).collect()}
    for run, part in rows.groupby("run"):
        pooled = exact(np.sort(part.price.to_numpy()), levels)
        for scale in ("identity", "log"):
            s = Summary(Scheme(grid="logit:1000:1e-6", report="list:0.0," + ",".join(map(repr, W._TAILS)) + ",1.0", batch=100, interp="logit", scale=scale))
            s.add_digests([(len(x), 1, False, "report10", np.array(digests[k].vals)) for k, x in part.groupby("l_suppkey")])
            for order in ("random", "sorted"):
                for p, v, e, t in zip(W._TAILS, s.digest()["vals"][1:-1], pooled, truth, strict=True):
                    r = got[f"{scale}/{order}", run, p]
                    assert (r.estimate, r.exact, r.truth) == (pytest.approx(v), e, t)
    assert {r.runs for r in QUERIES["inhomog_ratio"](spark, SF).collect()} == {2}
