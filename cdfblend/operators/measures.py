"""Accuracy and cost measures, as plans over ``(keys, level, value)`` tables."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scale import scale as scale_of
from .baselines import exact_quantiles


def compare(est: DataFrame, exact: DataFrame, keys: Sequence[str]) -> DataFrame:
    """``keys, level, estimate, exact, difference`` (signed)."""
    a = est.select(*keys, "level", F.col("value").alias("estimate"))
    b = exact.select(*keys, "level", F.col("value").alias("exact"))
    return a.join(b, [*keys, "level"]).withColumn("difference", F.col("estimate") - F.col("exact"))


def asymptotic_se(df: DataFrame, value: str, levels: Sequence[float], h: float = 0.01, keys: Sequence[str] = ()) -> DataFrame:
    """Standard error of the exact quantile: sqrt(p (1 - p) / n) times the slope of the quantile curve over p +- h."""
    around = sorted({round(min(max(p + d, 0.0), 1.0), 12) for p in levels for d in (-h, h)})
    q = exact_quantiles(df, keys, value, around, "cont")
    n = df.groupBy(*keys).agg(F.count(value).alias("n"))
    both = q.groupBy(*keys).agg(F.map_from_entries(F.collect_list(F.struct("level", "value"))).alias("m"))
    both = both.join(n, list(keys)) if keys else both.crossJoin(n)
    cells = []
    for p in levels:
        lo, hi = round(max(p - h, 0.0), 12), round(min(p + h, 1.0), 12)
        slope = (F.element_at("m", F.lit(hi)) - F.element_at("m", F.lit(lo))) / (hi - lo)
        cells.append(F.struct(F.lit(float(p)).alias("level"), (F.sqrt(F.lit(p * (1 - p)) / F.col("n")) * slope).alias("se")))
    return both.select(*keys, F.explode(F.array(*cells)).alias("c")).select(*keys, "c.level", "c.se")


def within_two_se(compared: DataFrame, se: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    return compared.join(se, [*keys, "level"]).withColumn("two_se", 2 * F.col("se")).withColumn("within", F.abs("difference") <= F.col("two_se"))


def rmse(runs: DataFrame, by: Sequence[str], estimate: str = "value", truth: str = "truth") -> DataFrame:
    d = F.col(estimate) - F.col(truth)
    return runs.groupBy(*by).agg(F.sqrt(F.avg(d * d)).alias("rmse"), F.avg(d).alias("bias"), F.count("*").alias("runs"))


def rmse_ratio(est: DataFrame, exact: DataFrame, by: Sequence[str]) -> DataFrame:
    a = est.select(*by, F.col("rmse").alias("rmse_est"), F.col("bias").alias("bias_est"), "runs")
    b = exact.select(*by, F.col("rmse").alias("rmse_exact"))
    return a.join(b, list(by)).withColumn("ratio", F.try_divide("rmse_est", "rmse_exact"))


def rmse_both(runs: DataFrame, by: Sequence[str]) -> DataFrame:
    """``rmse_ratio`` of the columns ``estimate`` and ``exact``, in one pass over the runs."""
    d, x = F.col("estimate") - F.col("truth"), F.col("exact") - F.col("truth")
    out = runs.groupBy(*by).agg(F.sqrt(F.avg(d * d)).alias("rmse_est"), F.avg(d).alias("bias_est"), F.count("*").alias("runs"), F.sqrt(F.avg(x * x)).alias("rmse_exact"))
    return out.withColumn("ratio", F.try_divide("rmse_est", "rmse_exact"))


def mean_ratio(ratios: DataFrame, by: Sequence[str], low: float = 0.025, high: float = 0.975) -> DataFrame:
    """Mean of the ratio over the levels inside (low, high)."""
    return ratios.where((F.col("level") > low) & (F.col("level") < high)).groupBy(*by).agg(F.avg("ratio").alias("mean_ratio"), F.count("*").alias("levels"))


def growth(ratios: DataFrame, by: Sequence[str], size: str = "n") -> DataFrame:
    """Relative change of the ratio from one sample size to the next."""
    w = Window.partitionBy(*by).orderBy(size)
    return ratios.withColumn("growth", F.col("ratio") / F.lag("ratio").over(w) - 1)


def within_fraction(compared: DataFrame, by: Sequence[str], share: float = 0.10) -> DataFrame:
    """Fraction of cells whose estimate lies within ``share`` of the exact value."""
    ok = F.abs("difference") <= share * F.abs("exact")
    return compared.groupBy(*by).agg(F.avg(ok.cast("double")).alias("fraction"), F.count("*").alias("cells"))


def rank_error(est: DataFrame, raw: DataFrame, keys: Sequence[str], value: str) -> DataFrame:
    """|F_exact(estimate) - level| per key and level, by one conditional count join on the key."""
    a = est.select(*keys, "level", F.col("value").alias("_q"))
    packed = a.groupBy(*keys).agg(F.collect_list(F.struct("level", "_q")).alias("_cells"))  # bounded by the number of levels
    x = raw.select(*keys, F.col(value).cast("double").alias("_x")).where("_x is not null")
    joined = x.join(packed, list(keys)) if keys else x.crossJoin(F.broadcast(packed))
    rows = joined.select(*keys, "_x", F.explode("_cells").alias("c"))
    got = rows.groupBy(*keys, F.col("c.level").alias("level"), F.col("c._q").alias("value")).agg(F.avg((F.col("_x") <= F.col("c._q") + 1e-9 * F.abs(F.col("c._q"))).cast("double")).alias("share"))
    return got.withColumn("rank_error", F.abs(F.col("share") - F.col("level")))


def order_gap(a: DataFrame, b: DataFrame, keys: Sequence[str], scale: str = "identity") -> DataFrame:
    """Largest absolute and relative gap between two estimates of the same cells."""
    s = scale_of(scale)
    j = a.select(*keys, "level", F.col("value").alias("_a")).join(b.select(*keys, "level", F.col("value").alias("_b")), [*keys, "level"])
    gap = F.abs(s.column(F.col("_a")) - s.column(F.col("_b")))
    return j.agg(F.max(gap).alias("max_gap"), F.max(F.try_divide(F.abs(F.col("_a") - F.col("_b")), F.abs("_a"))).alias("max_relative"), F.count("*").alias("cells"))


def flush_counts(df: DataFrame, keys: Sequence[str], value: str, batch: int) -> DataFrame:
    """Values, full flushes and the length of the last partial one."""
    n = F.count(value)
    return df.groupBy(*keys).agg(n.alias("n"), F.floor(n / batch).cast("long").alias("full_flushes"), (n % batch).alias("rest"))


def bytes_moved(digests: DataFrame, digest: str = "digest") -> DataFrame:
    """Bytes of values that travel as digests (values plus the count) against shipping every value."""
    d = F.col(digest)
    return digests.agg(F.sum(d["n"] * 8).cast("long").alias("raw_bytes"), F.sum((F.size(d["vals"]) + 1) * 8).cast("long").alias("digest_bytes"), F.count("*").alias("digests"))


def spread_ratio(quantiles: DataFrame, keys: Sequence[str], low: float = 0.01, high: float = 0.99) -> DataFrame:
    """Value at ``high`` over value at ``low``."""
    pick = lambda p: F.max(F.when(F.col("level") == p, F.col("value")))
    return quantiles.groupBy(*keys).agg(F.try_divide(pick(high), pick(low)).alias("spread"))
