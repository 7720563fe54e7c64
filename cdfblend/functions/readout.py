"""Column functions on digests: everything here stays in the JVM.

A digest is read as the linear curve through its values and trimmed levels; a raw digest is read as the step
curve of its values.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .levels import grid as grid_of

KNOWN = ("report11", "report10", "five", "table6")


def _col(c: str | Column) -> Column:
    return F.col(c) if isinstance(c, str) else c


def levels(digest: str | Column, grids: Sequence[str] = KNOWN) -> Column:
    """Levels of the digest's values; null for raw digests and for grids that are not named."""
    d = _col(digest)
    out = F.lit(None).cast("array<double>")
    for g in grids:
        out = F.when(d["grid"] == g, F.array(*[F.lit(float(p)) for p in grid_of(g).levels])).otherwise(out)
    return out


def trimmed(digest: str | Column, grids: Sequence[str] = KNOWN) -> Column:
    d = _col(digest)
    edge = F.lit(0.5) / d["n"]
    return F.transform(levels(d, grids), lambda p: F.greatest(F.least(p, 1 - edge), edge))


def _between(x: Column, x0: Column, x1: Column, y0: Column, y1: Column) -> Column:
    return F.when(x1 > x0, y0 + (y1 - y0) * (x - x0) / (x1 - x0)).otherwise(y0)


def _g(p: Column, interp: str) -> Column:
    return F.log(p / (1 - p)) if interp == "logit" else p


def quantile_at(digest: str | Column, p: float | Column, grids: Sequence[str] = KNOWN, interp: str = "linear") -> Column:
    """Value at level p: interpolated between stored values; of a raw digest the smallest value that reaches p."""
    d, p = _col(digest), p if isinstance(p, Column) else F.lit(float(p))
    v, q = d["vals"], trimmed(d, grids)
    k = F.size(F.filter(q, lambda x: x <= p))
    size = F.size(v)
    inner = _between(_g(p, interp), _g(F.get(q, k - 1), interp), _g(F.get(q, k), interp), F.get(v, k - 1), F.get(v, k))
    smooth = F.when(k < 1, F.get(v, F.lit(0))).when(k >= size, F.get(v, size - 1)).otherwise(inner)
    step = F.get(v, F.greatest(F.ceil(p * d["n"] - F.lit(1e-9)).cast("int"), F.lit(1)) - 1)
    return F.when(d["raw"], step).otherwise(smooth)


def cdf_at(digest: str | Column, x: float | Column, grids: Sequence[str] = KNOWN, interp: str = "linear") -> Column:
    """Share of values up to x."""
    d, x = _col(digest), x if isinstance(x, Column) else F.lit(float(x))
    v, q = d["vals"], trimmed(d, grids)
    k, size = F.size(F.filter(v, lambda y: y <= x)), F.size(v)
    inner = _between(x, F.get(v, k - 1), F.get(v, k), _g(F.get(q, k - 1), interp), _g(F.get(q, k), interp))
    inner = 1 / (1 + F.exp(-inner)) if interp == "logit" else inner
    smooth = F.when(k < 1, F.lit(0.0)).when(k >= size, F.lit(1.0)).otherwise(inner)
    return F.when(d["raw"], k / size).otherwise(smooth)


def share_above(digest: str | Column, x: float | Column, grids: Sequence[str] = KNOWN) -> Column:
    return 1 - cdf_at(digest, x, grids)


def as_map(digest: str | Column, grids: Sequence[str] = KNOWN) -> Column:
    """level -> value; null for raw digests."""
    d = _col(digest)
    return F.when(~d["raw"], F.map_from_arrays(levels(d, grids), d["vals"]))


def long(df: DataFrame, keys: Sequence[str], digest: str = "digest", grids: Sequence[str] = KNOWN, digits: int | None = 6) -> DataFrame:
    """One row per stored value: keys, ``level`` (null if raw), ``value``."""
    d = F.col(digest)
    rows = df.select(*keys, levels(d, grids).alias("_p"), F.posexplode(d["vals"]).alias("_i", "_v"))
    value = F.round("_v", digits) if digits is not None else F.col("_v")
    return rows.select(*keys, F.get("_p", F.col("_i")).alias("level"), value.alias("value"))
