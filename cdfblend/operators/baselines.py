"""Baselines to compare digests with: exact quantiles, moments, sequential trackers, sketches, samples."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from ..functions.curve import FlushRules
from .relational import one_flush
from .runs import fold_runs


def _long(df: DataFrame, keys: Sequence[str], levels: Sequence[float], values: Column) -> DataFrame:
    pairs = F.arrays_zip(F.array(*[F.lit(float(p)) for p in levels]).alias("level"), values.alias("value"))
    return df.select(*keys, F.explode(pairs).alias("c")).select(*keys, F.col("c.level").alias("level"), F.col("c.value").alias("value"))


def exact_quantiles(df: DataFrame, keys: Sequence[str], value: str, levels: Sequence[float], kind: str = "disc", engine: str = "aggregate") -> DataFrame:
    """``keys, level, value``. kind: disc, cont or mid; engine ``windows`` sorts (and spills) instead of holding a group."""
    if kind == "mid":
        return one_flush(df, keys, value, levels)
    if engine == "windows":
        if kind == "disc":
            return one_flush(df, keys, value, levels, FlushRules("low"))
        w = Window.partitionBy(*keys).orderBy("_x")
        ranked = df.select(*keys, F.col(value).cast("double").alias("_x")).where("_x is not null")
        ranked = ranked.select(*keys, "_x", (F.row_number().over(w) - 1).alias("_r"), F.count("*").over(Window.partitionBy(*keys)).alias("_n"))
        weight = lambda p: F.greatest(F.lit(0.0), 1 - F.abs(F.col("_r") - (F.col("_n") - 1) * p))
        return _long(ranked.groupBy(*keys).agg(F.array(*[F.sum(F.col("_x") * weight(p)) for p in levels]).alias("_q")), keys, levels, F.col("_q"))
    if kind == "cont":
        return _long(df.groupBy(*keys).agg(F.percentile(F.col(value).cast("double"), F.array(*[F.lit(float(p)) for p in levels])).alias("_q")), keys, levels, F.col("_q"))
    one = [F.expr(f"percentile_disc({p!r}) within group (order by cast(`{value}` as double))").alias(f"_q{k}") for k, p in enumerate(levels)]
    return _long(df.groupBy(*keys).agg(*one), keys, levels, F.array(*[F.col(f"_q{k}") for k in range(len(levels))]))


def moments(df: DataFrame, keys: Sequence[str], value: str) -> DataFrame:
    return df.groupBy(*keys).agg(F.count(value).alias("n"), F.avg(value).alias("mean"), F.stddev_samp(value).alias("sd"))


def normal_fit_quantiles(df: DataFrame, keys: Sequence[str], value: str, levels: Sequence[float]) -> DataFrame:
    """Quantiles of the normal with the group's mean and deviation: what two moments alone would claim."""
    z = [NormalDist().inv_cdf(p) for p in levels]
    return _long(moments(df, keys, value), keys, levels, F.array(*[F.col("mean") + F.col("sd") * v for v in z]))


def _fold(df: DataFrame, keys: Sequence[str], value: str, order: Sequence[str], start, add, finish, fields: list[T.StructField]) -> DataFrame:
    src = df.select(*[F.col(k) for k in keys], *[F.col(o).alias(f"_o{i}") for i, o in enumerate(order)], F.col(value).cast("double").alias("_v")).where("_v is not null")
    schema = T.StructType([*[T.StructField(k, src.schema[k].dataType) for k in keys], *fields])
    arrow = pa.schema([(f.name, to_arrow_type(f.dataType, timestamp_utc=True)) for f in schema.fields])
    nk, at = len(keys), len(keys) + len(order)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return fold_runs(batches, nk, start, lambda s, b: add(s, np.asarray(b.column(at))), lambda k, s: dict(zip(keys, k, strict=True)) | finish(s), arrow)

    dealt = src.repartition(*keys) if keys else src.coalesce(1)
    return dealt.sortWithinPartitions(*keys, *[f"_o{i}" for i in range(len(order))]).mapInArrow(run, schema)


def stochastic_quantile(df: DataFrame, keys: Sequence[str], value: str, order: Sequence[str], p: float, weight: float | None = None, first: int = 20) -> DataFrame:
    """Stochastic approximation of one quantile: steps of (p - [x <= q]) over (density times count).

    The density near q is tracked from the share of values within a shrinking window.  ``weight`` replaces
    1/count by a constant, which forgets the past exponentially (for drifting streams).
    """

    def start() -> dict:
        return {"early": [], "n": 0}

    def add(s: dict, xs: np.ndarray) -> None:
        for x in xs.tolist():
            s["n"] += 1
            if s["n"] <= first:
                s["early"].append(x)
                if s["n"] == first:
                    e = np.array(s["early"])
                    s["q"] = float(np.quantile(e, p))
                    s["r"] = max(float(np.subtract(*np.quantile(e, [0.75, 0.25]))), 1e-9)
                    s["f"] = max(float((np.abs(e - s["q"]) <= s["r"]).mean()) / (2 * s["r"]), 1e-12)
                continue
            a = weight if weight is not None else 1 / s["n"]
            h = s["r"] / np.sqrt(s["n"] / first) if weight is None else s["r"] / 2
            s["f"] = (1 - a) * s["f"] + a * (abs(x - s["q"]) <= h) / (2 * h)
            s["q"] += a / max(s["f"], 0.1 / s["r"] / np.sqrt(s["n"])) * (p - (x <= s["q"]))

    def finish(s: dict) -> dict:
        return {"n": s["n"], "level": p, "value": s.get("q", float(np.quantile(s["early"], p)) if s["early"] else None)}

    return _fold(df, keys, value, order, start, add, finish, [T.StructField("n", T.LongType()), T.StructField("level", T.DoubleType()), T.StructField("value", T.DoubleType())])


def bracket_buffers(df: DataFrame, keys: Sequence[str], value: str, order: Sequence[str], levels: Sequence[float], size: int = 50) -> DataFrame:
    """One buffer per level that tries to bracket its quantile: inside values are kept, outside ones only counted.

    When a buffer overflows, the end that lies farther from the wanted rank gives up its outermost value.
    """

    def start() -> dict:
        return {"n": 0, "b": [[] for _ in levels], "below": [0] * len(levels)}

    def add(s: dict, xs: np.ndarray) -> None:
        from bisect import insort

        for x in xs.tolist():
            s["n"] += 1
            for k, p in enumerate(levels):
                b = s["b"][k]
                full = s["n"] > size
                if full and b and x < b[0]:
                    s["below"][k] += 1
                elif not (full and b and x > b[-1]):
                    insort(b, x)
                if len(b) > size:
                    want = p * s["n"] - s["below"][k]
                    if want > len(b) / 2:
                        b.pop(0)
                        s["below"][k] += 1
                    else:
                        b.pop()

    def finish(s: dict) -> dict:
        out = []
        for k, p in enumerate(levels):
            at = int(np.clip(np.ceil(p * s["n"]) - s["below"][k] - 1, 0, len(s["b"][k]) - 1))
            out.append(s["b"][k][at])
        return {"vals": out}

    got = _fold(df, keys, value, order, start, add, finish, [T.StructField("vals", T.ArrayType(T.DoubleType()))])
    return _long(got, keys, levels, F.col("vals"))


def multipass_select(df: DataFrame, value: str, p: float, buckets: int = 64, memory: int = 10_000) -> DataFrame:
    """Exact selection by passes that narrow an interval; only ``buckets`` counts reach the driver per pass.

    One row ``level, value, passes``: the smallest value whose rank is at least p * n.
    """
    src = df.select(F.col(value).cast("double").alias("x")).where("x is not null")
    n, lo, hi = src.agg(F.count("*"), F.min("x"), F.max("x")).first()
    spark, schema = df.sparkSession, "level double, value double, passes int"
    if not n:
        return spark.createDataFrame([], schema)
    rank, below, passes = max(1, int(np.ceil(p * n - 1e-9))), 0, 1
    while True:
        inside = src.where((F.col("x") >= lo) & (F.col("x") <= hi))
        count = inside.count()
        passes += 1
        if count <= memory or lo == hi:
            x = inside.orderBy("x").limit(rank - below).agg(F.max("x")).first()[0] if lo != hi else lo
            return spark.createDataFrame([(float(p), float(x), passes)], schema)
        width = (hi - lo) / buckets
        b = F.least(F.floor((F.col("x") - lo) / width), F.lit(buckets - 1)).cast("int")
        rows = sorted(inside.groupBy(b.alias("b")).agg(F.count("*").alias("c"), F.min("x").alias("lo"), F.max("x").alias("hi")).collect(), key=lambda r: r.b)
        passes += 1
        for r in rows:
            if below + r.c >= rank:
                lo, hi = r.lo, r.hi
                break
            below += r.c


def rank_sketch(df: DataFrame, keys: Sequence[str], value: str, levels: Sequence[float], accuracy: int = 1000) -> DataFrame:
    """Rank error of at most 1/accuracy, answers are observed values (Spark's built-in summary of that family)."""
    got = df.groupBy(*keys).agg(F.percentile_approx(F.col(value).cast("double"), [float(p) for p in levels], accuracy).alias("_q"))
    return _long(got, keys, levels, F.col("_q"))


def kll(df: DataFrame, keys: Sequence[str], value: str, levels: Sequence[float], k: int = 200) -> DataFrame:
    """Randomised mergeable rank sketch."""
    got = df.groupBy(*keys).agg(F.expr(f"kll_sketch_agg_double(cast(`{value}` as double), {k})").alias("_s"))
    return _long(got, keys, levels, F.array(*[F.expr(f"kll_sketch_get_quantile_double(_s, {float(p)!r}D)") for p in levels]))


def mean_of_quantiles(df: DataFrame, keys: Sequence[str], levels: Sequence[float], digest: str = "digest", at=None) -> DataFrame:
    """Count-weighted mean of the digests' quantiles: what averaging quantiles instead of curves gives."""
    from ..functions.readout import quantile_at

    n = F.col(f"{digest}.n")
    got = df.groupBy(*keys).agg(F.array(*[F.sum(n * quantile_at(digest, p)) / F.sum(n) for p in levels]).alias("_q"))
    return _long(got, keys, levels, F.col("_q"))


def reservoir(df: DataFrame, keys: Sequence[str], value: str, ident: Sequence[str], size: int = 11, seed: str = "r") -> DataFrame:
    """A uniform sample of ``size`` values per key, by smallest digest of (seed, ident): repeatable, one window."""
    h = F.md5(F.concat_ws("|", F.lit(seed), *[F.col(c).cast("string") for c in ident]))
    w = Window.partitionBy(*keys).orderBy("_h")
    return df.select(*keys, F.col(value).cast("double").alias("value"), h.alias("_h")).withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= size).select(*keys, "value")
