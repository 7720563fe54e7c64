"""Choosing the stored tier that answers a request with the fewest digests.

A catalogue lists tiers of digests with their key columns.  A request names the keys of its result and the
columns that its filter reads; a tier covers it when it has all of them (coarser period columns can be derived
from finer ones).  Of the covering tiers the one with the fewest rows is read, then rolled up once.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.digest import Scheme
from ..operators.relational import merge_one_blend
from ..operators.rollup import merge

#: Period columns from fine to coarse, and how each follows from a finer one.
PERIODS = ("minute", "hour", "day", "month", "year")


@dataclass(frozen=True)
class Tier:
    name: str
    keys: tuple[str, ...]
    rows: int
    load: Callable[[], DataFrame]

    def covers(self, columns: set[str]) -> bool:
        finest = min((PERIODS.index(k) for k in self.keys if k in PERIODS), default=None)
        derived = set(PERIODS[finest:]) if finest is not None else set()
        return columns <= set(self.keys) | derived

    def frame(self, columns: set[str]) -> DataFrame:
        df = self.load()
        have = [k for k in PERIODS if k in self.keys]
        for c in sorted(columns & set(PERIODS) - set(self.keys)):
            df = df.withColumn(c, F.date_trunc(c, have[0]).cast("timestamp_ntz"))
        return df


def choose(tiers: Sequence[Tier], keys: Sequence[str], filters: Sequence[str] = ()) -> Tier:
    """The covering tier with the fewest digests."""
    fit = [t for t in tiers if t.covers({*keys, *filters})]
    if not fit:
        raise ValueError(f"no tier has {sorted({*keys, *filters})}")
    return min(fit, key=lambda t: (t.rows, t.name))


def answer(tiers: Sequence[Tier], keys: Sequence[str], where: str | None = None, filters: Sequence[str] = (), levels: Sequence[float] | None = None, scheme: Scheme = Scheme(), grids: Sequence[str] = ("report11", "five")) -> DataFrame:
    """Digests per ``keys`` (or ``keys, level, value`` where levels are asked for) from the cheapest tier."""
    tier = choose(tiers, keys, filters)
    df = tier.frame({*keys, *filters})
    df = df.where(where) if where else df
    if levels is not None:
        return merge_one_blend(df, list(keys), levels, grids=grids)
    return merge(df, list(keys), "digest", [k for k in tier.keys if k not in keys], scheme)
