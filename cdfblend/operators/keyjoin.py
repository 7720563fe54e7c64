"""Null-safe equi-join on key columns, safe for self-joins."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def join_on(left: DataFrame, right: DataFrame, keys: Sequence[str], how: str = "inner") -> DataFrame:
    """``left`` with the other columns of ``right``; null keys match null keys; no keys: every row with every row (right must be one row)."""
    if not keys:
        return left.crossJoin(right)
    rest = [c for c in right.columns if c not in keys]
    r = right.select(*[F.col(k).alias(f"_rk{i}") for i, k in enumerate(keys)], *rest)
    match = None
    for i, k in enumerate(keys):
        c = F.col(k).eqNullSafe(F.col(f"_rk{i}"))
        match = c if match is None else match & c
    return left.join(r, match, how).select(*left.columns, *rest)
