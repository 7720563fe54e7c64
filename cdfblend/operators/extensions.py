"""Extensions: period-specific starting knots and atoms counted apart (decay, trained, adaptive and
extended grids are options of ``Scheme`` and functions of ``levels``)."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .digest import DIGEST_DDL, Scheme
from .leaf import summarize
from .relational import invert, segments, sweep


def seeded_by(df: DataFrame, part: Column, period: Column, value: str, order: Sequence[str], since: str, scheme: Scheme, weight: float = 0.25) -> DataFrame:
    """Digests per (part, period) from ``since`` on, each starting from the knots that its part (hour of the day, day
    of the week) had before; the start counts as ``weight`` of its values. Keys: ``part, period``."""
    x = df.select("*", part.alias("part"), period.alias("period"))
    past = summarize(x.where(F.col("period") < F.lit(since).cast("date")), ["part"], value, order, scheme, emit_state=True)
    s = F.col("state")
    start = past.select(
        "part",
        F.struct(
            F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("parts"), F.lit(float("inf")).alias("low"), F.lit(float("-inf")).alias("high"),
            F.array().cast("array<double>").alias("early"), F.lit(False).alias("only_raw"), (s["weight"] * weight).alias("weight"), s["levels"].alias("levels"), s["knots"].alias("knots"),
        ).alias("state"),
    )
    now = x.where(F.col("period") >= F.lit(since).cast("date"))
    cells = now.select("part", "period").distinct().join(start, "part")
    return summarize(now, ["part", "period"], value, order, scheme, initial=cells)


def spike_counts(df: DataFrame, keys: Sequence[str], value: str, atoms: Sequence[float]) -> DataFrame:
    """``keys, atom, n``: known atoms counted where they lie."""
    return df.where(F.col(value).isin([float(a) for a in atoms])).groupBy(*keys, F.col(value).cast("double").alias("atom")).agg(F.count("*").alias("n"))


def with_spikes(df: DataFrame, keys: Sequence[str], value: str, order: Sequence[str], atoms: Sequence[float], levels: Sequence[float], scheme: Scheme) -> DataFrame:
    """``keys, level, value``: counters of the atoms and the digest of all other values, recombined at read-out."""
    atoms = [float(a) for a in atoms]
    spikes = spike_counts(df, keys, value, atoms).select(*keys, F.col("atom").alias("x"), F.lit(0.0).alias("jump"), F.col("n").cast("double").alias("raw_jump"), F.lit(0.0).alias("slope"))
    rest = summarize(df.where(~F.col(value).isin(atoms)), keys, value, order, scheme)
    smooth = segments(rest.withColumn("digest", F.col("digest").cast(DIGEST_DDL)), keys)
    both = smooth.unionByName(spikes).groupBy(*keys, "x").agg(*[F.sum(c).alias(c) for c in ("jump", "raw_jump", "slope")])
    return invert(sweep(both, keys), keys, levels)
