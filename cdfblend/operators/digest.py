"""The fixed-length record that travels upwards, and the scheme that makes it."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import types as T

from ..functions.curve import FlushRules, Interp, Knots, flush, interp_of, read_levels
from ..functions.levels import extend_tails, grid
from ..functions.scale import scale

DIGEST = T.StructType(
    [
        T.StructField("n", T.LongType()),
        T.StructField("parts", T.LongType()),
        T.StructField("raw", T.BooleanType()),
        T.StructField("grid", T.StringType()),
        T.StructField("scale", T.StringType()),
        T.StructField("vals", T.ArrayType(T.DoubleType())),
    ]
)
DIGEST_DDL = "struct<n:bigint,parts:bigint,raw:boolean,grid:string,scale:string,vals:array<double>>"
DIGEST_ARROW = pa.struct([("n", pa.int64()), ("parts", pa.int64()), ("raw", pa.bool_()), ("grid", pa.string()), ("scale", pa.string()), ("vals", pa.list_(pa.float64()))])


@dataclass(frozen=True)
class Scheme:
    """How a summary tracks its quantiles.

    ``grid`` names the tracked levels, ``report`` those of the digest; ``batch`` is the intake capacity,
    in values for a leaf and in digests for a roll-up (``batch_unit='values'`` counts stored values there).
    ``on_bad`` says what infinite values do: 'fail' or 'skip'.
    """

    grid: str = "uniform:41"
    batch: int | None = 41
    report: str = "report11"
    interp: str | Interp = "linear"
    scale: str = "identity"
    rules: FlushRules = field(default_factory=FlushRules)
    report_mode: str = "interpolate"
    batch_unit: str = "records"
    decay: float = 1.0
    tails: bool = False
    adapt: bool = False
    on_bad: str = "fail"

    def __post_init__(self):
        if self.batch is not None and self.batch < 1 or self.report_mode not in ("interpolate", "subset") or self.batch_unit not in ("records", "values") or not 0 < self.decay <= 1 or self.on_bad not in ("fail", "skip"):
            raise ValueError(f"bad scheme {self}")
        scale(self.scale), grid(self.grid), grid(self.report)

    def but(self, **changes) -> Scheme:
        return replace(self, **changes)

    def tracked(self) -> np.ndarray:
        levels = grid(self.grid).array()
        return np.union1d(levels, grid(self.report).array()) if self.report_mode == "subset" else levels


def adapt_levels(state: Knots) -> np.ndarray:
    """Move one inner level from the shortest stretch (value + level) into the middle of the longest."""
    v, p = state.values, state.levels
    if v is None or len(p) < 5 or v[-1] == v[0]:
        return p
    gap = np.hypot(np.diff(v) / (v[-1] - v[0]), np.diff(p))
    merged = gap[:-1] + gap[1:]
    drop = 1 + int(np.argmin(merged))
    longest = int(np.argmax(gap))
    fresh = (p[longest] + p[longest + 1]) / 2
    return np.unique(np.concatenate([np.delete(p, drop), [fresh]])) if longest not in (drop - 1, drop) else p


class Summary:
    """State of one leaf or roll-up: knots on the working scale, exact extremes, first values."""

    def __init__(self, scheme: Scheme):
        self.scheme = scheme
        self.interp = interp_of(scheme.interp)
        self.scale = scale(scheme.scale)
        self.report = grid(scheme.report).array()
        self.knots = Knots(scheme.tracked())
        self.n = 0
        self.parts = 0
        self.low, self.high = np.inf, -np.inf
        self.early: list[float] = []
        self.only_raw = True

    def _seen(self, natural: np.ndarray) -> None:
        if len(natural):
            self.low, self.high = min(self.low, float(natural.min())), max(self.high, float(natural.max()))

    def _keep_early(self, natural: np.ndarray) -> None:
        """First values, for a record of raw values; let go when there are too many for one."""
        self.early = [*self.early, *natural.tolist()] if self.only_raw and self.n < len(self.report) else []

    @property
    def held(self) -> int:
        """Stored values: knots and first values."""
        return len(self.early) + (0 if self.knots.values is None else len(self.knots.values))

    def _flush(self, raw: np.ndarray, digests: list) -> None:
        s = self.scheme
        levels = None
        if s.tails:
            levels = extend_tails(self.knots.levels, self.n)
        self.knots = flush(self.knots, raw, digests, self.interp, s.rules, s.decay, levels)
        if s.adapt:
            levels = adapt_levels(self.knots)
            if len(levels) != len(self.knots.levels) or (levels != self.knots.levels).any():
                self.knots = Knots(levels, read_levels(self.knots, levels, self.interp, s.rules), self.knots.n)

    def add_raw(self, natural: np.ndarray) -> None:
        """One flush of raw values."""
        if not len(natural):
            return
        self.scale.check(natural)
        self._seen(natural)
        self.n += len(natural)
        self._keep_early(natural)
        self._flush(np.sort(self.scale.forward(natural)), [])

    def add_digests(self, records: list[tuple[int, int, bool, str, np.ndarray]]) -> None:
        """One flush of digests ``(n, parts, raw, grid, values)``; raw ones are pooled."""
        records = [r for r in records if r[0] > 0]
        if not records:
            return
        pool = [r[4] for r in records if r[2]]
        raw = np.concatenate(pool) if pool else np.zeros(0)
        self.add_pooled(raw, sum(r[1] for r in records if r[2]), [r for r in records if not r[2]])

    def add_pooled(self, raw: np.ndarray, parts: int, full: list[tuple[int, int, bool, str, np.ndarray]]) -> None:
        """One flush of the pooled values of raw digests (of ``parts`` leaves) and of full digests."""
        for values in [raw, *[r[4] for r in full]]:
            self.scale.check(values)
            self._seen(values)
        self.n += len(raw) + sum(r[0] for r in full)
        self.parts += parts + sum(r[1] for r in full)
        self.only_raw &= not full
        self._keep_early(raw)
        self._flush(np.sort(self.scale.forward(raw)), [(self.scale.forward(r[4]), grid(r[3]).array(), float(r[0])) for r in full])

    def digest(self, parts: int | None = None) -> dict | None:
        """The record, or None if nothing was seen; fewer values than report levels are stored as they are."""
        if not self.n:
            return None
        parts = self.parts if parts is None else parts
        head = {"n": self.n, "parts": parts, "scale": self.scheme.scale}
        if self.n < len(self.report) and self.only_raw:
            return head | {"raw": True, "grid": None, "vals": sorted(self.early)}
        read = read_levels(self.knots, self.report, self.interp, self.scheme.rules)
        at = np.minimum(np.searchsorted(self.knots.levels, self.report), len(self.knots.levels) - 1)
        tracked = self.knots.levels[at] == self.report
        out = self.scale.inverse(np.where(tracked, self.knots.values[at], read))
        out = np.clip(out, self.low, self.high)
        out[0] = self.low if self.report[0] == 0 else out[0]
        out[-1] = self.high if self.report[-1] == 1 else out[-1]
        return head | {"raw": False, "grid": self.scheme.report, "vals": out.tolist()}

    # A summary can be stored and taken up again at a flush boundary.
    def store(self) -> dict:
        k = self.knots
        return {"n": self.n, "parts": self.parts, "low": self.low, "high": self.high, "early": self.early, "only_raw": self.only_raw, "weight": float(k.n), "levels": k.levels.tolist(), "knots": [] if k.values is None else k.values.tolist()}

    @classmethod
    def resume(cls, scheme: Scheme, s: dict) -> Summary:
        out = cls(scheme)
        out.n, out.parts, out.low, out.high, out.early, out.only_raw = s["n"], s["parts"], s["low"], s["high"], list(s["early"]), s["only_raw"]
        out.knots = Knots(np.array(s["levels"]), np.array(s["knots"]) if len(s["knots"]) else None, s["weight"])
        return out


STATE_DDL = "struct<n:bigint,parts:bigint,low:double,high:double,early:array<double>,only_raw:boolean,weight:double,levels:array<double>,knots:array<double>>"
STATE_ARROW = pa.struct([("n", pa.int64()), ("parts", pa.int64()), ("low", pa.float64()), ("high", pa.float64()), ("early", pa.list_(pa.float64())), ("only_raw", pa.bool_()), ("weight", pa.float64()), ("levels", pa.list_(pa.float64())), ("knots", pa.list_(pa.float64()))])
