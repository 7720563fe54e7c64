"""The same curves as relational plans: windows and aggregates, no Python.

``one_flush``   a whole group as one batch.
``blend_sweep`` all digests of a key in one linear blend.  Each interval between two stored values adds a
                slope where it begins and removes it where it ends, jumps add mass; two running sums give
                the curve at every point, so the cost is one sort of all stored values and not points x digests.
``invert``      brackets by conditional minimum and maximum, one aggregate for all levels.
``global_blend`` the keyless case: range buckets of x, prefix sums over the few buckets, then windows inside.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.curve import SLACK, FlushRules
from ..functions.readout import KNOWN, trimmed
from ..scratch import scratch


def step_cdf(df: DataFrame, keys: Sequence[str], value: str) -> DataFrame:
    """Distinct values with weighted limits: ``keys, x, lo, hi, total`` (counts below, up to, of all)."""
    counts = df.where(F.col(value).isNotNull() & ~F.isnan(F.col(value).cast("double"))).groupBy(*keys, F.col(value).cast("double").alias("x")).agg(F.count("*").alias("c"))
    w = Window.partitionBy(*keys)
    hi = F.sum("c").over(w.orderBy("x"))
    return counts.select(*keys, "x", (hi - F.col("c")).cast("double").alias("lo"), hi.cast("double").alias("hi"), F.sum("c").over(w).cast("double").alias("total"))


def _value(p: float, up: Column, dn: Column, total: Column, rules: FlushRules) -> Column:
    dn = F.when(dn.isNull(), up).otherwise(dn)
    p_dn, p_up = (dn["lo"], up["hi"]) if rules.bracket == "outer" else (dn["hi"], up["lo"])
    b, a = p_up / total, p_dn / total
    rho = F.when(b != a, F.least(F.greatest((b - F.lit(p)) / F.nullif(b - a, F.lit(0.0)), F.lit(0.0)), F.lit(1.0))).otherwise(F.lit(0.5))
    flat = {"low": up["x"], "high": dn["x"], "mid": (up["x"] + dn["x"]) / 2}[rules.plateau]
    return F.when(dn["x"] > up["x"], flat).when(dn["x"] == up["x"], up["x"]).otherwise(rho * dn["x"] + (1 - rho) * up["x"])


def invert(limits: DataFrame, keys: Sequence[str], levels: Sequence[float], rules: FlushRules = FlushRules()) -> DataFrame:
    """``keys, level, value`` from ``keys, x, lo, hi, total``."""
    point = F.struct("x", "lo", "hi")
    aggs = [F.max("total").alias("total"), F.min("x").alias("first"), F.max("x").alias("last")]
    eps = F.col("total") * SLACK
    for k, p in enumerate(levels):
        aggs.append(F.min(F.when(F.col("hi") >= F.col("total") * p - eps, point)).alias(f"up{k}"))
        aggs.append(F.max(F.when(F.col("lo") <= F.col("total") * p + eps, point)).alias(f"dn{k}"))
    got = limits.groupBy(*keys).agg(*aggs)
    cells = []
    for k, p in enumerate(levels):
        up = F.coalesce(F.col(f"up{k}"), F.col(f"dn{k}"))
        v = F.col("first") if p <= 0 else F.col("last") if p >= 1 else _value(p, up, F.col(f"dn{k}"), F.col("total"), rules)
        cells.append(F.struct(F.lit(float(p)).alias("level"), v.alias("value")))
    return got.select(*keys, F.explode(F.array(*cells)).alias("c")).select(*keys, "c.level", "c.value")


def one_flush(df: DataFrame, keys: Sequence[str], value: str, levels: Sequence[float], rules: FlushRules = FlushRules()) -> DataFrame:
    """Every group as a single batch: ``keys, level, value``."""
    return invert(step_cdf(df, keys, value), keys, levels, rules)


def segments(df: DataFrame, keys: Sequence[str], digest: str = "digest", grids: Sequence[str] = KNOWN) -> DataFrame:
    """Slope and jump rows of every digest: ``keys, x, jump, raw_jump, slope`` (weights are counts)."""
    d = F.col(digest)
    q, v, n = trimmed(d, grids), d["vals"], d["n"].cast("double")
    last = F.size(v) - 1
    edge = F.array(
        F.struct(F.get(v, F.lit(0)).alias("x"), (n * F.get(q, F.lit(0))).alias("jump"), F.lit(0.0).alias("raw_jump"), F.lit(0.0).alias("slope")),
        F.struct(F.get(v, last).alias("x"), (n * (1 - F.get(q, last))).alias("jump"), F.lit(0.0).alias("raw_jump"), F.lit(0.0).alias("slope")),
    )

    def rise(i: Column) -> Column:
        x0, x1 = F.get(v, i), F.get(v, i + 1)
        mass = n * (F.get(q, i + 1) - F.get(q, i))
        s = F.when(x1 > x0, mass / (x1 - x0)).otherwise(0.0)
        jump = F.when(x1 > x0, F.lit(0.0)).otherwise(mass)
        zero = F.lit(0.0)
        return F.array(F.struct(x0.alias("x"), jump.alias("jump"), zero.alias("raw_jump"), s.alias("slope")), F.struct(x1.alias("x"), zero.alias("jump"), zero.alias("raw_jump"), (-s).alias("slope")))

    smooth = F.concat(edge, F.flatten(F.transform(F.sequence(F.lit(0), last - 1), rise)))
    raw = F.transform(v, lambda x: F.struct(x.alias("x"), F.lit(0.0).alias("jump"), F.lit(1.0).alias("raw_jump"), F.lit(0.0).alias("slope")))
    rows = df.where(d.isNotNull() & (d["n"] > 0)).select(*keys, F.explode(F.when(d["raw"], raw).otherwise(smooth)).alias("s"))
    return rows.groupBy(*keys, F.col("s.x").alias("x")).agg(*[F.sum(f"s.{c}").alias(c) for c in ("jump", "raw_jump", "slope")])


def sweep(seg: DataFrame, keys: Sequence[str], rules: FlushRules = FlushRules()) -> DataFrame:
    """``keys, x, lo, hi, total`` from slope and jump rows, by running sums along x."""
    w = Window.partitionBy(*keys).orderBy("x")
    run = w.rowsBetween(Window.unboundedPreceding, 0)
    stepped = seg.withColumn("rate", F.sum("slope").over(run)).withColumn("gain", F.coalesce(F.lag("rate").over(w) * (F.col("x") - F.lag("x").over(w)), F.lit(0.0)))
    hi = F.sum(F.col("gain") + F.col("jump") + F.col("raw_jump")).over(run)
    drop = F.col("raw_jump") + (F.col("jump") if rules.limits == "two_sided" else F.lit(0.0))
    total = F.max("hi").over(Window.partitionBy(*keys))
    return stepped.withColumn("hi", hi).select(*keys, "x", (F.col("hi") - drop).alias("lo"), "hi").withColumn("total", total)


def merge_one_blend(df: DataFrame, keys: Sequence[str], levels: Sequence[float], digest: str = "digest", rules: FlushRules = FlushRules(), grids: Sequence[str] = KNOWN) -> DataFrame:
    """All digests of a key at once, free of order: ``keys, level, value``."""
    return invert(sweep(segments(df, keys, digest, grids), keys, rules), keys, levels, rules)


def global_blend(df: DataFrame, levels: Sequence[float], digest: str = "digest", rules: FlushRules = FlushRules(), grids: Sequence[str] = KNOWN, buckets: int = 64) -> DataFrame:
    """The blend of all digests, without a one-partition sort: ``level, value``.

    The slope and jump rows are written once to the session's shared folder and read from there by every step.
    Rows go to ``buckets`` ranges of x by approximate quantiles; slope and mass before a bucket come from
    prefix sums over the table of buckets, whose size is fixed.
    """
    path = scratch(df.sparkSession)
    segments(df, [], digest, grids).write.parquet(path)
    seg = df.sparkSession.read.parquet(path)
    cuts = seg.select(F.percentile_approx("x", [k / buckets for k in range(1, buckets)], 10_000).alias("cuts"))
    placed = seg.crossJoin(F.broadcast(cuts)).withColumn("b", F.size(F.filter("cuts", lambda c: c < F.col("x")))).drop("cuts")
    inside = sweep(placed, ["b"], rules)
    facts = placed.groupBy("b").agg(F.sum("slope").alias("slope"), F.min("x").alias("x0"), F.max("x").alias("x1"))
    facts = facts.join(inside.groupBy("b").agg(F.max_by("hi", "x").alias("mass")), "b")
    w = Window.orderBy("b")
    before = w.rowsBetween(Window.unboundedPreceding, -1)
    facts = facts.withColumn("rate", F.coalesce(F.sum("slope").over(before), F.lit(0.0)))
    # What the slopes of earlier buckets add up to the first and the last point of this one.
    facts = facts.withColumn("enter", F.col("rate") * F.coalesce(F.col("x0") - F.lag("x1").over(w), F.lit(0.0))).withColumn("cross", F.col("rate") * (F.col("x1") - F.col("x0")))
    start = F.coalesce(F.sum(F.col("mass") + F.col("enter") + F.col("cross")).over(before), F.lit(0.0)) + F.col("enter")
    facts = facts.select("b", "rate", "x0", start.alias("start"))
    lifted = inside.join(F.broadcast(facts), "b").withColumn("up", F.col("start") + F.col("rate") * (F.col("x") - F.col("x0")))
    limits = lifted.select("x", (F.col("lo") + F.col("up")).alias("lo"), (F.col("hi") + F.col("up")).alias("hi"))
    total = limits.agg(F.max("hi").alias("total"))
    return invert(limits.crossJoin(F.broadcast(total)), [], levels, rules)
