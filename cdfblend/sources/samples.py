"""Monte-Carlo experiments on given tables: disjoint random samples of a column are the runs, its exact quantiles the truth.

Every row belongs to one run of each size. A hash of its key deals it to a run of the smallest size and orders it there; a
run of a larger size is made of neighbouring runs of the size before. So one shuffle serves several sizes, and results do not
depend on the partitioning. The number of runs is what the table holds: its rows over the size, two at least; sizes
of which a table does not hold two samples have no runs there.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Iterator, Sequence
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.levels import grid
from ..operators.digest import Scheme
from ..operators.leaf import _doubles, _Intake
from ..operators.measures import rmse_both
from ..operators.runs import boundaries
from .simulate import exact
from .tables import ORDER, table

#: Columns that stand for the distributions of the study: a long right tail with zeros, and two positive ones.
POPULATIONS = {"value": ("events", "value"), "price": ("lineitem", "l_extendedprice"), "total": ("orders", "o_totalprice")}


#: Sizes up to this share one pass over the rows.
SHARED = 100_000
_RUNS = "run long, arm string, dist string, n long, level double, estimate double, exact double"


def large_quantiles(df: DataFrame, keys: Sequence[str], value: str, levels: Sequence[float], cells: int = 4096) -> DataFrame:
    """``keys, level, value``: exact quantiles of groups of any size, by the smallest value whose rank reaches the level.

    Counts of equal ranges of the values name the ranges that hold a level; only their values are sorted, each range by itself.
    """
    keys = list(keys)
    x = df.select(*keys, F.col(value).cast("double").alias("_x")).where("_x is not null and not isnan(_x)")
    ends = x.groupBy(*keys).agg(F.min("_x").alias("_low"), F.max("_x").alias("_high"), F.count("*").alias("_n"))
    cell = F.coalesce(F.least(F.floor(F.try_divide(F.col("_x") - F.col("_low"), F.col("_high") - F.col("_low")) * cells), F.lit(cells - 1)), F.lit(0))
    placed = x.join(ends, keys).select(*keys, "_x", "_n", cell.alias("_cell"))
    upto = F.sum("_c").over(Window.partitionBy(*keys).orderBy("_cell"))
    counts = placed.groupBy(*keys, "_cell").agg(F.count("*").alias("_c"), F.max("_n").alias("_n")).withColumn("_upto", upto)
    rank = F.greatest(F.lit(1), F.ceil(F.col("level") * F.col("_n") - 1e-9))
    want = counts.withColumn("level", F.explode(F.array(*[F.lit(float(p)) for p in levels]))).withColumn("_rank", rank)
    want = want.where("_upto - _c < _rank and _rank <= _upto").select(*keys, "_cell", "level", (F.col("_rank") - F.col("_upto") + F.col("_c")).alias("_rank"))
    inside = placed.join(want.select(*keys, "_cell").distinct(), [*keys, "_cell"]).groupBy(*keys, "_cell", "_x").agg(F.count("*").alias("_c"))
    inside = inside.withColumn("_upto", F.sum("_c").over(Window.partitionBy(*keys, "_cell").orderBy("_x")))
    return inside.join(want, [*keys, "_cell"]).where("_upto - _c < _rank and _rank <= _upto").select(*keys, "level", F.col("_x").alias("value"))


def population(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """``dist, key, value``: the usable values of a column, with a hash of the row's key."""
    source, value = POPULATIONS[name]
    rows = table(spark, sf_dir, source).select(F.lit(name).alias("dist"), F.xxhash64(*ORDER[source]).alias("key"), F.col(value).cast("double").alias("value"))
    return rows.where("value is not null and not isnan(value)")


def run_counts(n: int, sizes: Sequence[int]) -> list[int]:
    """Runs of each size (ascending) in ``n`` rows, as far as there are two."""
    return [n // s for s in sizes if n // s >= 2]


def _ids(first: int, counts: Sequence[int]) -> list[int]:
    """The runs of all sizes that a run of the first size belongs to."""
    out = [first]
    for below, here in zip(counts, counts[1:], strict=False):
        out.append(out[-1] * here // below)
    return out


def sample_runs(populations: Sequence[DataFrame], sizes: Sequence[int], schemes: dict[str, Scheme]) -> DataFrame:
    """``run, arm, dist, n, level, estimate, exact``: leaves of every sample, for every scheme, beside its exact quantiles.

    Sizes up to ``SHARED`` share a pass and every larger one has its own. A task holds the values of one sample of the largest
    size of its pass, for its exact quantiles; the leaves hold one batch and one set of knots, as ever.
    """
    counted = [(p, p.groupBy("dist").agg(F.count("*").alias("n")).first()) for p in populations]
    known = [(p, c.dist, c.n) for p, c in counted if c]
    passes = [[s for s in sizes if s <= SHARED], *[[s] for s in sizes if s > SHARED]]
    out = [_pass([(p, dist, run_counts(n, some)) for p, dist, n in known], some, schemes) for some in passes if any(run_counts(n, some) for _, _, n in known)]
    return reduce(DataFrame.unionAll, out) if out else populations[0].sparkSession.createDataFrame([], _RUNS)


def _pass(parts: Sequence[tuple[DataFrame, str, list[int]]], sizes: Sequence[int], schemes: dict[str, Scheme]) -> DataFrame:
    """One shuffle: a task gets whole samples of the largest size, in order of the samples of the smallest."""
    at = {arm: grid(s.report).array() for arm, s in schemes.items()}
    rows, starts, held, tops = [], [], [], 0
    offset = 0
    for p, dist, counts in parts:
        if not counts:
            continue
        first = F.pmod("key", F.lit(counts[0]))
        top = F.pmod("key", F.lit(counts[0])).alias("top")
        part = p.select("key", "value", (first + offset).alias("first"), top)
        for below, here in zip(counts, counts[1:], strict=False):
            part = part.withColumn("top", F.expr(f"top * {here}L div {below}L"))
        rows.append(part.withColumn("top", F.col("top") + tops))
        starts.append(offset)
        held.append((dist, counts))
        offset, tops = offset + counts[0], tops + counts[-1]

    def close(cell: tuple, size: int) -> Iterator[pa.RecordBatch]:
        (dist, run), values, leaves = cell
        ordered = np.sort(np.concatenate(values))
        for arm, leaf in leaves.items():
            leaf.flush()
            k = len(at[arm])
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(np.full(k, run, np.int64)), pa.array([arm] * k), pa.array([dist] * k), pa.array(np.full(k, size, np.int64)),
                    pa.array(at[arm]), pa.array(np.asarray(leaf.summary.digest(1)["vals"], float)), pa.array(exact(ordered, at[arm])),
                ],
                ["run", "arm", "dist", "n", "level", "estimate", "exact"],
            )

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells: list[tuple | None] = [None] * len(sizes)
        for b in batches:
            if not b.num_rows:
                continue
            out: list[pa.RecordBatch] = []
            every = _doubles(b.column(1))
            cuts = [0, *boundaries(b, 1).tolist(), b.num_rows]
            for i, j in zip(cuts, cuts[1:], strict=False):
                first, values = b.column(0)[i].as_py(), every[i:j]
                which = bisect_right(starts, first) - 1
                dist, counts = held[which]
                ids: list[int | None] = _ids(first - starts[which], counts)
                for k, run in enumerate(ids + [None] * (len(sizes) - len(ids))):
                    if cells[k] is not None and cells[k][0] != (dist, run):
                        out += close(cells[k], sizes[k])
                        cells[k] = None
                    if run is None:
                        continue
                    if cells[k] is None:
                        cells[k] = ((dist, run), [], {arm: _Intake(s) for arm, s in schemes.items()})
                    cells[k][1].append(values)
                    for leaf in cells[k][2].values():
                        leaf.add(values)
            yield from pa.Table.from_batches(out).combine_chunks().to_batches() if out else []
        for k, cell in enumerate(cells):
            if cell is not None:
                yield from close(cell, sizes[k])

    tasks = min(tops, 1000)
    dealt = reduce(DataFrame.unionAll, rows).repartitionById(tasks, F.pmod("top", F.lit(tasks)).cast("int")).sortWithinPartitions("first", "key", "value")
    return dealt.select("first", "value").mapInArrow(fold, _RUNS)


def sample_ratios(populations: Sequence[DataFrame], sizes: Sequence[int], schemes: dict[str, Scheme]) -> DataFrame:
    """``arm, dist, n, level, rmse_est, rmse_exact, ratio, bias_est, runs`` for inner levels, against the quantiles of whole columns."""
    levels = sorted({float(p) for s in schemes.values() for p in grid(s.report).levels if 0 < p < 1})
    truth = large_quantiles(reduce(DataFrame.unionAll, populations), ["dist"], "value", levels).withColumnRenamed("value", "truth")
    return rmse_both(sample_runs(populations, sizes, schemes).join(truth, ["dist", "level"]), ["arm", "dist", "n", "level"])
