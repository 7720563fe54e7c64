"""Value scales: interpolation happens on a transformed value, results come back on the natural one."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Scale:
    name: str
    forward: Callable[[np.ndarray], np.ndarray]
    inverse: Callable[[np.ndarray], np.ndarray]
    column: Callable[[Column], Column]
    back: Callable[[Column], Column]
    lowest: float = -np.inf
    open: bool = False

    def check(self, x: np.ndarray) -> None:
        if len(x) and (x.min() <= self.lowest if self.open else x.min() < self.lowest):
            raise ValueError(f"scale {self.name!r} is not defined for {x.min()!r}")


_SCALES: dict[str, Scale] = {}


def register_scale(scale: Scale) -> Scale:
    _SCALES[scale.name] = scale
    return scale


register_scale(Scale("identity", lambda x: np.asarray(x, float), lambda x: x, lambda c: c.cast("double"), lambda c: c))
register_scale(Scale("log", np.log, np.exp, lambda c: F.log(c.cast("double")), F.exp, 0.0, True))
register_scale(Scale("log1p", np.log1p, np.expm1, lambda c: F.log1p(c.cast("double")), F.expm1, 0.0))
register_scale(
    Scale(
        "slog",
        lambda x: np.sign(x) * np.log1p(np.abs(x)),
        lambda y: np.sign(y) * np.expm1(np.abs(y)),
        lambda c: F.signum(c.cast("double")) * F.log1p(F.abs(c.cast("double"))),
        lambda c: F.signum(c) * F.expm1(F.abs(c)),
    )
)


def scale(name: str) -> Scale:
    if name not in _SCALES:
        raise ValueError(f"unknown scale {name!r}; known: {sorted(_SCALES)}")
    return _SCALES[name]
