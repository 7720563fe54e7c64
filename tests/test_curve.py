from fractions import Fraction

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from cdfblend.functions import levels as L
from cdfblend.functions.curve import CLOGLOG, EXACT_INVERSE, LINEAR, LOGIT, PROBIT, FlushRules, Knots, flush, interleave, knot_limits, read_levels, trim_levels
from cdfblend.functions.scale import scale
from cdfblend.operators.digest import Scheme, Summary, adapt_levels

G5 = np.array(L.FIVE, float)


def run(batches, rules=FlushRules(), levels=G5, interp=LINEAR):
    k = Knots(levels)
    for b in batches:
        k = flush(k, np.sort(np.array(b, float)), (), interp, rules)
    return k


def fractions(v):
    return [Fraction(float(x)).limit_denominator(5000) for x in v]


F = Fraction
GOLDEN = [
    (FlushRules(), [[1, 1, 3, 4, 5], [1, F(17, 13), 3, F(22, 5), 6], [1, F(2765, 1963), F(493, 179), F(21, 5), 6]]),
    (EXACT_INVERSE, [[1, 1, 3, 4, 5], [1, F(9, 5), 3, F(14, 3), 6], [1, F(69, 35), F(93, 35), F(31, 7), 6]]),
]


@pytest.mark.parametrize("rules,steps", GOLDEN)
def test_worked_example(rules, steps):
    batches = [[3, 1, 4, 1, 5], [2, 6], [2]]
    for k, want in enumerate(steps):
        assert fractions(run(batches[: k + 1], rules).values) == want


def test_plateau_and_atoms():
    assert [run([[1, 2, 3, 4]], FlushRules(p)).values[2] for p in ("low", "mid", "high")] == [2, 2.5, 3]
    tens = L.uniform_levels(11)
    atoms = [[0] * 15 + [1] * 5] * 2
    assert fractions(run(atoms, levels=tens).values)[8] == F(9, 13)
    assert fractions(run(atoms, EXACT_INVERSE, tens).values)[8] == 1


def test_trim_and_knot_curve():
    assert trim_levels(np.array([0, 0.5, 1.0]), 10).tolist() == [0.05, 0.5, 0.95]
    k, lv = np.array([1.0, 2.0, 2.0, 4.0]), np.array([0, 0.3, 0.6, 1.0])
    lo, hi = knot_limits(np.array([0.5, 1, 1.5, 2, 3, 4, 9]), k, lv, 100, LINEAR, "two_sided")
    assert np.allclose(hi, [0, 0.005, 0.1525, 0.6, 0.7975, 1, 1]) and np.allclose(lo, [0, 0, 0.1525, 0.3, 0.7975, 0.995, 1])


finite = st.floats(-1e6, 1e6, allow_nan=False, width=32)


@settings(max_examples=120, deadline=None)
@given(st.lists(st.lists(finite, min_size=1, max_size=30), min_size=1, max_size=6), st.sampled_from([LINEAR, LOGIT, PROBIT, CLOGLOG]), st.sampled_from([FlushRules(), EXACT_INVERSE, FlushRules("low"), FlushRules("high", "two_sided")]))
def test_invariants(batches, interp, rules):
    k = run(batches, rules, L.uniform_levels(11), interp)
    every = np.concatenate([np.array(b, float) for b in batches])
    assert k.n == len(every) and k.values[0] == every.min() and k.values[-1] == every.max()
    assert np.isfinite(k.values).all() and (np.diff(k.values) >= 0).all()


@settings(max_examples=60, deadline=None)
@given(st.lists(finite, min_size=1, max_size=40))
def test_first_flush_is_exact(batch):
    x = np.sort(np.array(batch, float))
    for p, v in zip(L.uniform_levels(9), run([batch], FlushRules("low"), L.uniform_levels(9)).values, strict=True):
        assert v == x[max(int(np.ceil(p * len(x) - 1e-12 * len(x))) - 1, 0)]


def test_affine_maps_commute_and_log_is_identity_on_logs():
    rng = np.random.default_rng(0)
    batches = [rng.normal(size=20) for _ in range(5)]
    a = run(batches).values
    assert np.allclose(run([3 * b + 2 for b in batches]).values, 3 * a + 2)
    s = Summary(Scheme(grid="uniform:11", report="five", scale="log", batch=20))
    for b in batches:
        s.add_raw(np.exp(b))
    assert np.allclose(s.digest(1)["vals"], np.exp(run(batches, levels=L.uniform_levels(11)).values[[0, 2, 5, 8, 10]]), rtol=0.6)
    assert s.digest(1)["vals"][0] == np.exp(np.concatenate(batches)).min()


def test_reading_tracked_levels_and_one_digest():
    rng = np.random.default_rng(1)
    k = run([rng.normal(size=200)], levels=L.uniform_levels(21))
    assert np.allclose(read_levels(k, k.levels[1:-1]), k.values[1:-1])
    again = flush(Knots(k.levels), np.zeros(0), [(k.values, k.levels, k.n)])
    assert np.allclose(again.values[1:-1], k.values[1:-1])


def test_grids():
    assert len(L.rounded_logit_levels(41)) == 41 and np.allclose(L.rounded_logit_levels(41) + L.rounded_logit_levels(41)[::-1], 1)
    g = L.logit_levels(100, 0.0025)
    assert len(g) == 100 and g[1] == pytest.approx(0.0025) and np.allclose(np.diff(np.log(g[1:-1] / (1 - g[1:-1])), 2), 0, atol=1e-9)
    assert np.allclose(L.grid("report10").levels[1:5], [0.005, 0.02229, 0.09376, 0.31947], atol=1e-5)
    assert (np.abs(L.focus_levels(41, 0.9, 0.5) - 0.9) <= 0.05).sum() >= 19
    wide = L.extend_tails(L.uniform_levels(21), 10_000)
    assert wide[1] == 0.5 / 10_000 and wide[-2] == 1 - 0.5 / 10_000 and len(wide) == 21
    assert (np.diff(wide) > 0).all() and np.allclose(wide[5:-5], L.uniform_levels(21)[5:-5])
    odds = np.log(wide[1:6] / (1 - wide[1:6]))
    assert np.allclose(np.diff(odds), odds[1] - odds[0]) and np.allclose(wide + wide[::-1], 1)
    assert (L.extend_tails(wide, 100) == wide).all() and L.extend_tails(wide, 10**6)[1] == 0.5e-6
    assert L.grid(L.list_grid([0, 0.1, 1])).levels == (0, 0.1, 1)
    assert len(L.train_levels(np.exp(np.random.default_rng(0).normal(size=500)), 41)) == 41
    for bad in ("uniform:1", "logit:2:0.1", "logit:9:0.7", "list:0.5,0.2", "what"):
        with pytest.raises(ValueError):
            L.grid(bad)
    k = run([np.exp(np.random.default_rng(0).normal(size=300))], levels=L.uniform_levels(11))
    gap = lambda s: np.hypot(np.diff(s.values) / (s.values[-1] - s.values[0]), np.diff(s.levels)).max()
    begin = gap(k)
    for _ in range(30):  # levels wander into the long tail: the longest stretch of (value + level) shrinks
        p = adapt_levels(k)
        assert len(p) == 11 and p[0] == 0 and p[-1] == 1
        k = Knots(p, np.interp(p, k.levels, k.values), k.n)
    assert gap(k) < begin / 2


def test_scales():
    x = np.array([-5.0, 0.0, 7.5])
    assert np.allclose(scale("slog").inverse(scale("slog").forward(x)), x)
    with pytest.raises(ValueError):
        scale("log").check(np.array([0.0]))
    scale("log1p").check(np.array([0.0]))
    with pytest.raises(ValueError):
        Scheme(scale="nope")


def test_interleave_counts_as_searches_do():
    rng = np.random.default_rng(5)
    for draw in (lambda m: rng.standard_normal(m), lambda m: rng.integers(-3, 4, m).astype(float)):
        for _ in range(50):
            a, b = np.sort(draw(int(rng.integers(1, 40)))), np.sort(draw(int(rng.integers(1, 40))))
            points, of_a, of_b = interleave(a, b)
            assert np.array_equal(points, np.unique(np.concatenate([a, b])))
            assert np.array_equal(of_a, np.searchsorted(a, points, side="right")) and np.array_equal(of_b, np.searchsorted(b, points, side="right"))
