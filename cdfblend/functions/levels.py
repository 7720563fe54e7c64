"""Level grids: the probability levels that knots and digests stand for.

A grid is named by a short id, so a digest stores a few bytes instead of its levels, and any executor
can rebuild the levels from the id: ``uniform:m``, ``logit:m:eps``, ``focus:m:target:share``,
``round41``, ``report11``, ``report10``, ``five``, ``table6`` and ``list:p1,p2,...``.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np

# Report levels, rounded logit levels and level lists of the published experiments.
REPORT_11 = (0, 0.05, 0.10, 0.25, 0.50, 0.75, 0.90, 0.95, 0.99, 0.999, 1)
FIVE = (0, 0.25, 0.5, 0.75, 1)
TABLE_6 = (0.5, 0.75, 0.9, 0.95, 0.99, 0.995)
_ROUND_LOW = (0, 0.001, 0.0015, 0.002, 0.003, 0.004, 0.006, 0.009, 0.0125, 0.018, 0.025, 0.035, 0.05, 0.075, 0.1, 0.14, 0.19, 0.25, 0.33, 0.41)

#: Inner levels of either tail that move with the outermost one.
TAIL_LEVELS = 4


def uniform_levels(m: int) -> np.ndarray:
    """m evenly spaced levels with 0 and 1."""
    if m < 2:
        raise ValueError("a grid needs at least the levels 0 and 1")
    return np.linspace(0.0, 1.0, m)


def logit_levels(m: int, eps: float) -> np.ndarray:
    """0, 1 and m - 2 levels from eps to 1 - eps, evenly spaced in log odds."""
    if m < 3 or not 0 < eps < 0.5:
        raise ValueError("need m >= 3 and 0 < eps < 0.5")
    edge = np.log((1 - eps) / eps)
    inner = 1 / (1 + np.exp(-np.linspace(-edge, edge, m - 2)))
    return np.concatenate([[0.0], inner, [1.0]])


def rounded_logit_levels(m: int = 41) -> np.ndarray:
    """The fixed grid ``round41``: short decimals whose density follows p (1 - p), mirrored at one half."""
    if m != 41:
        raise ValueError("the rounded grid has 41 levels")
    low = np.array(_ROUND_LOW)
    return np.concatenate([low, [0.5], np.round(1 - low[::-1], 10)])


def focus_levels(m: int, target: float, share: float) -> np.ndarray:
    """A uniform grid that spends ``share`` of its inner levels within 5% of ``target``."""
    near = max(1, int(round((m - 2) * share)))
    dense = np.linspace(max(0.0, target - 0.05), min(1.0, target + 0.05), near + 2)[1:-1]
    wide = uniform_levels(m - near)
    return np.unique(np.concatenate([wide, dense]))


def extend_tails(levels: np.ndarray, n: int) -> np.ndarray:
    """Push the outermost inner levels out to half an observation of n; the levels next to them follow.

    On either side the first ``TAIL_LEVELS`` inner levels (fewer in a small grid) are spread evenly in log odds between the
    new outermost level and the next one, which stays.  The grid keeps its size.
    """
    out = np.array(levels, dtype=float)
    moved = min(TAIL_LEVELS, (len(out) - 3) // 2)
    if moved < 1 or n <= 1:
        return out
    log_odds = lambda p: np.log(p / (1 - p))
    ends = {False: (out[1], out[moved + 1]), True: (1 - out[-2], 1 - out[-moved - 2])}
    for upper, (first, stays) in ends.items():
        if 0.5 / n < first * (1 - 1e-9):
            tail = 1 / (1 + np.exp(-np.linspace(log_odds(0.5 / n), log_odds(stays), moved + 1)[:-1]))
            tail[0] = 0.5 / n
            if upper:
                out[-moved - 1 : -1] = 1 - tail[::-1]
            else:
                out[1 : moved + 1] = tail
    return out


def train_levels(sample: np.ndarray, m: int) -> np.ndarray:
    """Levels whose quantiles in ``sample`` are evenly spaced in (value + level), which favours curved stretches."""
    x = np.sort(np.asarray(sample, dtype=float))
    return arc_levels(x, (np.arange(len(x)) + 0.5) / max(len(x), 1), m)


def train_levels_counts(low: np.ndarray, high: np.ndarray, counts: np.ndarray, m: int) -> np.ndarray:
    """As ``train_levels``, from the least value, the greatest value and the count of each range, in order."""
    up = np.cumsum(np.asarray(counts, dtype=float))
    n = up[-1] if len(up) else 1.0
    p = np.stack([(up - counts + 0.5) / n, (up - 0.5) / n], axis=1).ravel()
    x = np.stack([np.asarray(low, dtype=float), np.asarray(high, dtype=float)], axis=1).ravel()
    p, first = np.unique(p, return_index=True)
    return arc_levels(x[first], p, m)


def arc_levels(x: np.ndarray, p: np.ndarray, m: int) -> np.ndarray:
    """0, 1 and m - 2 levels at even steps along the curve through increasing points (x, p), x as a share of its range."""
    if not len(x) or x[0] == x[-1]:
        return uniform_levels(m)
    arc = np.cumsum(np.hypot(np.diff(x, prepend=x[0]) / (x[-1] - x[0]), np.diff(p, prepend=0)))
    inner = np.interp(np.linspace(arc[0], arc[-1], m)[1:-1], arc, p)
    return np.concatenate([[0.0], inner, [1.0]])


@dataclass(frozen=True)
class Grid:
    id: str
    levels: tuple[float, ...]

    def array(self) -> np.ndarray:
        return np.array(self.levels)


@lru_cache(maxsize=256)
def grid(name: str) -> Grid:
    kind, *rest = name.split(":")
    made = {
        "uniform": lambda m: uniform_levels(int(m)),
        "logit": lambda m, eps: logit_levels(int(m), float(eps)),
        "focus": lambda m, t, s: focus_levels(int(m), float(t), float(s)),
        "round41": rounded_logit_levels,
        "report11": lambda: REPORT_11,
        "report10": lambda: logit_levels(10, 0.005),
        "five": lambda: FIVE,
        "table6": lambda: TABLE_6,
        "list": lambda text: [float(p) for p in text.split(",")],
    }
    if kind not in made:
        raise ValueError(f"unknown grid {name!r}")
    levels = tuple(float(p) for p in made[kind](*rest))
    if any(not 0 <= p <= 1 for p in levels) or any(a >= b for a, b in zip(levels, levels[1:], strict=False)):
        raise ValueError(f"grid {name!r} must increase within [0, 1]")
    return Grid(name, levels)


def list_grid(levels) -> str:
    """Id of an explicit grid."""
    return "list:" + ",".join(repr(float(p)) for p in levels)
