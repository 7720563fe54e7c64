"""Numpy kernels: cumulative curves, their weighted mean, and its inversion.

A curve is given at points by its left and right limits.  Raw values make a step curve; knots with levels
make a piecewise curve whose levels are trimmed by half an observation.  Blending is a count-weighted
mean of the limits; inversion finds, per level, the first point that reaches it from the right and the last
that has not passed it from the left, and interpolates between them.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass, field
from statistics import NormalDist

import numpy as np

SLACK = 1e-12


@dataclass(frozen=True)
class Interp:
    """Interpolation is linear in ``g`` of the probability."""

    name: str
    g: Callable[[np.ndarray], np.ndarray] = field(compare=False)
    g_inv: Callable[[np.ndarray], np.ndarray] = field(compare=False)
    bounded: bool = True  # g is finite at 0 and 1


def _probit(p: np.ndarray) -> np.ndarray:
    d = NormalDist()
    return np.array([d.inv_cdf(float(v)) for v in np.ravel(p)]).reshape(np.shape(p))


def _phi(x: np.ndarray) -> np.ndarray:
    d = NormalDist()
    return np.array([d.cdf(float(v)) for v in np.ravel(x)]).reshape(np.shape(x))


LINEAR = Interp("linear", lambda p: p, lambda y: y)
LOGIT = Interp("logit", lambda p: np.log(p / (1 - p)), lambda y: 1 / (1 + np.exp(-y)), False)
PROBIT = Interp("probit", _probit, _phi, False)
CLOGLOG = Interp("cloglog", lambda p: np.log(-np.log1p(-p)), lambda y: -np.expm1(-np.exp(y)), False)
INTERPS = {i.name: i for i in (LINEAR, LOGIT, PROBIT, CLOGLOG)}


def interp_of(x: str | Interp) -> Interp:
    return x if isinstance(x, Interp) else INTERPS[x]


@dataclass(frozen=True)
class FlushRules:
    """Edge rules. plateau: low, mid, high; limits: as_stated, two_sided; bracket: outer, inner."""

    plateau: str = "mid"
    limits: str = "as_stated"
    bracket: str = "outer"

    def __post_init__(self):
        if self.plateau not in ("low", "mid", "high") or self.limits not in ("as_stated", "two_sided") or self.bracket not in ("outer", "inner"):
            raise ValueError(f"unknown rule in {self}")


EXACT_INVERSE = FlushRules("mid", "two_sided", "inner")


def trim_levels(levels: np.ndarray, n: float) -> np.ndarray:
    """Levels clipped by half an observation of n at either end."""
    return np.minimum(np.maximum(levels, 0.5 / n), 1 - 0.5 / n) if n >= 1 else np.full(len(levels), 0.5)


def step_limits(x: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Counts of sorted ``values`` below each x, and up to each x."""
    return np.searchsorted(values, x, side="left").astype(float), np.searchsorted(values, x, side="right").astype(float)


def interleave(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct points of two sorted arrays, and how many of a and of b are at or below each: one linear merge, no searches."""
    both = np.concatenate((a, b))
    order = np.argsort(both, kind="stable")  # finds the two ascending runs
    both = both[order]
    ends = np.append(np.flatnonzero(both[1:] != both[:-1]), len(both) - 1)
    of_b = np.cumsum(order >= len(a))[ends]
    return both[ends], ends + 1 - of_b, of_b


def knot_limits(x: np.ndarray, knots: np.ndarray, levels: np.ndarray, n: float, interp: Interp = LINEAR, limits: str = "as_stated", upto: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Left and right limits, as probabilities, of the curve through trimmed (knot, level) pairs.

    ``upto``, where known, counts the knots at or below each x.
    """
    q = trim_levels(levels, n)
    last = len(knots) - 1
    at = (np.searchsorted(knots, x, side="right") if upto is None else upto) - 1
    lo = np.minimum(np.maximum(at, 0), max(last - 1, 0))
    hi = np.minimum(lo + 1, last)
    start = knots[lo]
    width = knots[hi] - start
    with np.errstate(divide="ignore", invalid="ignore"):
        part = np.where(width > 0, (x - start) / width, 0.0)
    part = np.minimum(np.maximum(part, 0.0), 1.0)
    y = interp.g(q)
    base = y[lo]
    mid = base + (y[hi] - base) * part
    right = np.where(at < 0, 0.0, np.where(at >= last, 1.0, interp.g_inv(mid) if interp is not LINEAR else mid))
    if limits == "as_stated":
        return right, right
    first = np.searchsorted(knots, x, side="left")
    on = (first <= last) & (knots[np.minimum(first, last)] == x)
    left = np.where(on, np.where(first == 0, 0.0, q[np.minimum(first, last)]), right)
    return left, right


def blend(curves: Sequence[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Sum of (weighted) limits."""
    return sum(c[0] for c in curves), sum(c[1] for c in curves)


def invert(points: np.ndarray, lo: np.ndarray, hi: np.ndarray, total: float, levels: np.ndarray, interp: Interp = LINEAR, rules: FlushRules = FlushRules()) -> np.ndarray:
    """Values at ``levels`` of the blend whose weighted limits at ``points`` are lo and hi (they end at total)."""
    target = levels * total
    eps = SLACK * total
    up = np.minimum(np.searchsorted(hi, target - eps, side="left"), len(points) - 1)
    dn = np.searchsorted(lo, target + eps, side="right") - 1
    dn = np.where(dn < 0, up, dn)
    p_dn = (lo if rules.bracket == "outer" else hi)[dn] / total
    p_up = (hi if rules.bracket == "outer" else lo)[up] / total
    p = levels
    if not interp.bounded:
        p_dn, p_up, p = (np.minimum(np.maximum(v, 0.5 / total), 1 - 0.5 / total) for v in (p_dn, p_up, p))
    a, b, c = interp.g(p_dn), interp.g(p_up), interp.g(p)
    with np.errstate(divide="ignore", invalid="ignore"):
        rho = np.where(b != a, (b - c) / (b - a), 0.5)
    rho = np.minimum(np.maximum(rho, 0.0), 1.0)
    between = rho * points[dn] + (1 - rho) * points[up]
    out = np.where(dn == up, points[up], between)
    plateau = dn > up
    if plateau.any():
        a, b = points[up[plateau]], points[dn[plateau]]
        out[plateau] = {"low": a, "high": b, "mid": (a + b) / 2}[rules.plateau]
    out[levels <= 0] = points[0]
    out[levels >= 1] = points[-1]
    return np.maximum.accumulate(out)


@dataclass
class Knots:
    """Tracked quantiles of ``n`` values; empty before the first flush."""

    levels: np.ndarray
    values: np.ndarray | None = None
    n: float = 0.0
    parts: int = 0


def flush(state: Knots, raw: np.ndarray, digests: Sequence[tuple[np.ndarray, np.ndarray, float]] = (), interp: Interp = LINEAR, rules: FlushRules = FlushRules(), keep: float = 1.0, levels: np.ndarray | None = None) -> Knots:
    """Fold sorted raw values and digests ``(values, levels, n)`` into the knots.

    ``keep`` multiplies the weight of what was seen before (1 for plain averaging); ``levels``
    replaces the grid from this flush on.
    """
    out_levels = state.levels if levels is None else levels
    seen = state.n * keep if state.values is not None else 0.0
    parts = [d[0] for d in digests] + ([raw] if len(raw) else []) + ([state.values] if seen > 0 else [])
    if not parts:
        return state
    total = seen + len(raw)
    if len(raw) and seen > 0 and not digests:
        points, below, upto = interleave(raw, state.values)
        lo, hi = knot_limits(points, state.values, state.levels, max(seen, 1.0), interp, rules.limits, upto)
        lo, hi = seen * lo + np.concatenate(([0], below[:-1])), seen * hi + below
        return Knots(out_levels, invert(points, lo, hi, total, out_levels, interp, rules), total, state.parts)
    points = np.unique(np.concatenate(parts))
    curves = []
    if seen > 0:
        lo, hi = knot_limits(points, state.values, state.levels, max(seen, 1.0), interp, rules.limits)
        curves.append((seen * lo, seen * hi))
    if len(raw):
        curves.append(step_limits(points, raw))
    for values, lv, n in digests:
        lo, hi = knot_limits(points, values, lv, n, interp, rules.limits)
        curves.append((n * lo, n * hi))
        total += n
    lo, hi = blend(curves)
    return Knots(out_levels, invert(points, lo, hi, total, out_levels, interp, rules), total, state.parts)


def read_levels(state: Knots, levels: np.ndarray, interp: Interp = LINEAR, rules: FlushRules = FlushRules()) -> np.ndarray:
    """Values at other levels, by inverting the knots' own curve; extremes are the outer knots."""
    lo, hi = knot_limits(state.values, state.values, state.levels, max(state.n, 1.0), interp, rules.limits)
    points, first = np.unique(state.values, return_index=True)
    last = np.concatenate([first[1:] - 1, [len(state.values) - 1]])
    n = max(state.n, 1.0)
    return invert(points, lo[first] * n, hi[last] * n, n, levels, interp, rules)
