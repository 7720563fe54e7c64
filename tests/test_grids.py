"""Queries of grids: the values of the events at the levels of a grid, held to numpy on a table with gaps."""

import numpy as np
import pytest

import cdfblend.plans
from cdfblend.functions.levels import grid
from cdfblend.sources.tables import SCHEMAS

QUERIES = cdfblend.plans.load().QUERIES
GRIDS = {"grid_focus": "focus:21:0.9:0.5", "grid_logit": "logit:100:0.0025", "grid_round41": "round41", "grid_uniform": "uniform:41"}


@pytest.fixture(scope="module")
def events(spark, tmp_path_factory):
    """Long and short groups, ties, nulls and NaN, and a group without values."""
    rng, sf = np.random.default_rng(8), tmp_path_factory.mktemp("grids")
    groups = {"long": np.exp(2 * rng.standard_normal(4400)), "ties": rng.integers(0, 6, 330).astype(float), "short": np.array([3.0, 1.0, 2.0])}
    rows = [(k, float(v)) for k, x in groups.items() for v in x] + [("long", None), ("ties", float("nan")), ("empty", None)]
    df = spark.createDataFrame([(i, None, i, k, v, None) for i, (k, v) in enumerate(rows)], SCHEMAS["events"])
    df.write.parquet(f"{sf}/events.parquet")
    return str(sf), groups


@pytest.mark.parametrize("name", sorted(GRIDS))
def test_values_at_the_levels(spark, events, name):
    sf, groups = events
    got = {(r.event_type, r.i): (r.p, r.value) for r in QUERIES[name](spark, sf).collect()}
    at, want = grid(GRIDS[name]).levels, {}
    for k, x in groups.items():
        x, n = np.sort(x), len(x)
        for i, p in enumerate(at):
            lo, hi = max(int(np.ceil(p * n - 1e-9)), 1) - 1, min(int(np.floor(p * n + 1e-9)), n - 1)
            want[k, i] = (round(p, 9), pytest.approx(x[0] if p <= 0 else x[-1] if p >= 1 else (x[lo] + x[hi]) / 2, abs=1e-6))
    assert got == want
