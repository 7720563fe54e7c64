"""Seeded Monte-Carlo experiments: every run is one row of ``spark.range`` and draws its own sample in the worker.

Nothing but ``(run, arm, level, estimate, exact)`` leaves a worker, and a run's draws depend on
(seed, run) only, so results do not depend on the partitioning.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.levels import grid
from ..operators.digest import Scheme, Summary
from ..operators.measures import growth, mean_ratio, rmse_both

_N = NormalDist()
#: Outlying leaves sit two decades above; both groups have a 1%..99% spread of 100 (fixed values of the study).
WITHIN_VAR, BETWEEN_VAR, SHIFT = 0.0924, 0.0924, 2.0


def draw(dist: str, n: int, rng: np.random.Generator) -> np.ndarray:
    if dist == "normal":
        return rng.standard_normal(n)
    if dist == "lognormal":
        return np.exp(rng.standard_normal(n))
    if dist == "beta92":
        return rng.beta(9, 2, n)
    raise ValueError(f"unknown distribution {dist!r}")


def truth(dist: str, p: float) -> float:
    """True quantile; levels 0 and 1 have none (nan)."""
    if not 0 < p < 1:
        return float("nan")
    if dist == "normal":
        return _N.inv_cdf(p)
    if dist == "lognormal":
        return float(np.exp(_N.inv_cdf(p)))
    lo, hi = 0.0, 1.0  # the 9th of 10 order statistics of uniforms
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if 10 * mid**9 - 9 * mid**10 < p else (lo, mid)
    return (lo + hi) / 2


def exact(sorted_x: np.ndarray, levels: np.ndarray) -> np.ndarray:
    """Smallest value whose rank reaches the level."""
    at = np.clip(np.ceil(levels * len(sorted_x) - 1e-9).astype(int) - 1, 0, len(sorted_x) - 1)
    return sorted_x[at]


def _rows(spark: SparkSession, runs: int, work, seed: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = [row for r in b.column(0).to_pylist() for row in work(r, np.random.Generator(np.random.Philox(key=[seed, r])))]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out, strict=True)], ["run", "arm", "dist", "n", "level", "estimate", "exact", "truth"])

    return spark.range(0, runs, 1, min(runs, 4 * spark.sparkContext.defaultParallelism)).mapInArrow(run, "run long, arm string, dist string, n long, level double, estimate double, exact double, truth double")


def leaf_runs(spark: SparkSession, runs: int, sizes: Sequence[int], schemes: dict[str, Scheme], dists: Sequence[str] = ("normal", "lognormal", "beta92"), levels: Sequence[float] | None = None, seed: int = 1) -> DataFrame:
    """Estimates of single leaves after each of ``sizes`` values, for every scheme and distribution."""
    truths = {(d, arm): [truth(d, p) for p in (levels or grid(s.report).levels)] for d in dists for arm, s in schemes.items()}

    def work(r: int, rng: np.random.Generator):
        for d in dists:
            for n in sizes:
                x = draw(d, n, rng)
                ordered = np.sort(x)
                for arm, s in schemes.items():
                    state = Summary(s)
                    for k in range(0, n, s.batch or n):
                        state.add_raw(x[k : k + (s.batch or n)])
                    at = grid(s.report).array()
                    got = state.digest(1)["vals"]
                    for p, v, e, t in zip(at.tolist(), got, exact(ordered, at).tolist(), truths[d, arm], strict=True):
                        yield (r, arm, d, n, p, float(v), float(e), t)

    return _rows(spark, runs, work, seed)


def leaf_ratios(runs: DataFrame) -> DataFrame:
    """``arm, dist, n, level, rmse_est, rmse_exact, ratio, bias_est, runs`` for inner levels."""
    by = ["arm", "dist", "n", "level"]
    return rmse_both(runs.where(~F.isnan("truth")), by)


def ratio_by_size(ratios: DataFrame) -> DataFrame:
    return mean_ratio(ratios, ["arm", "dist", "n"])


def ratio_growth(ratios: DataFrame) -> DataFrame:
    return growth(ratios, ["arm", "dist", "level"])


def mixture_quantile(p: float, outlying: float = 0.01) -> float:
    """Quantile of the inhomogeneous population, on the natural scale."""
    s = float(np.sqrt(WITHIN_VAR + BETWEEN_VAR))
    lo, hi = -6.0, 10.0
    for _ in range(200):
        mid = (lo + hi) / 2
        f = (1 - outlying) * _N.cdf(mid / s) + outlying * _N.cdf((mid - SHIFT) / s)
        lo, hi = (mid, hi) if f < p else (lo, mid)
    return 10 ** ((lo + hi) / 2)


def inhomogeneous_runs(spark: SparkSession, runs: int, leaves: int = 1000, per_leaf: int = 1000, record: str = "report10", scales: Sequence[str] = ("identity", "log"), orders: Sequence[str] = ("random", "sorted"), batch: int = 100, knots: str = "logit:1000:1e-6", levels: Sequence[float] = (0.01, 0.05, 0.1, 0.25, 0.5, 0.75, 0.9, 0.95, 0.99, 0.995, 0.999), outlying: float = 0.01, seed: int = 9, interp: str = "logit") -> DataFrame:
    """Roll-ups of leaf digests of which 1% sit two decades higher; arms are ``scale/order``."""
    report = "list:0.0," + ",".join(repr(float(p)) for p in levels) + ",1.0"
    at = grid(record).array()
    truths = [mixture_quantile(p, outlying) for p in levels]

    def work(r: int, rng: np.random.Generator):
        far = rng.permutation(leaves) < round(leaves * outlying)
        centre = rng.normal(np.where(far, SHIFT, 0.0), np.sqrt(BETWEEN_VAR))
        x = 10 ** rng.normal(centre[:, None], np.sqrt(WITHIN_VAR), (leaves, per_leaf))
        ordered = np.sort(x, axis=1)
        digests = [(per_leaf, 1, False, record, exact(row, at)) for row in ordered]
        pooled = exact(np.sort(x.ravel()), np.array(levels))
        for sc in scales:
            for order in orders:
                seq = range(leaves) if order == "random" else np.argsort(ordered[:, per_leaf // 2]).tolist()
                s = Summary(Scheme(grid=knots, report=report, batch=batch, interp=interp, scale=sc))
                pile = [digests[k] for k in seq]
                for k in range(0, leaves, batch):
                    s.add_digests(pile[k : k + batch])
                got = s.digest()["vals"][1:-1]
                for p, v, e, t in zip(levels, got, pooled.tolist(), truths, strict=True):
                    yield (r, f"{sc}/{order}", "mixture", leaves, float(p), float(v), float(e), t)

    return _rows(spark, runs, work, seed)


def inhomogeneous_ratios(runs: DataFrame) -> DataFrame:
    """As ``leaf_ratios``, with errors of log10 values for the log arms."""
    by = ["arm", "dist", "n", "level"]
    logs = F.col("arm").startswith("log")
    x = runs.select(*by, *[F.when(logs, F.log10(c)).otherwise(F.col(c)).alias(c) for c in ("estimate", "exact", "truth")])
    return rmse_both(x, by)
