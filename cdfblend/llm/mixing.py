"""Mixing sources to target weights by capped water-filling.

Shares of the total are proportional to weights; a source above ``cap`` epochs is clamped there and the
excess goes to the others by weight, until none is above.  Clamping in ascending order of
capacity per weight reaches that fixed point in one pass, which is a running sum over the (small)
table of sources.

A target is taken as whole epochs plus a fractional one.  The fractional epoch takes documents in
the order of a seeded digest until the quota is met.  The cut is found in two steps, by digest buckets and
then inside the one bucket that holds it, so no task ever orders a whole source; the decision per
document is then a comparison with its source's cut, joined from the table of sources.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .workspace import Workspace, unused

WORD = "[^\\x20\\x09-\\x0D]+"
#: Hexadecimal digits of the digest that name a bucket: 4,096 buckets a source.
BUCKET_DIGITS = 3


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def order_key(doc_id: Column, seed: str) -> Column:
    return F.md5(F.concat(F.lit(seed + ":"), F.coalesce(doc_id.cast("string"), F.lit("null"))))


def targets(sizes: DataFrame, weights: Sequence[float], cap: float) -> DataFrame:
    """``(source, source_size, target)`` from ``(source, source_size)``; weights go by code point, null last, repeating."""
    table = F.array(*[F.lit(float(w)) for w in weights])
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last()))
    ranked = sizes.withColumn("w", F.element_at(table, ((place - 1) % len(weights) + 1).cast("int")))
    full = ranked.withColumn("most", F.col("source_size") * F.lit(float(cap)))
    by_ratio = Window.orderBy(F.col("most") / F.col("w"), F.col("source").asc_nulls_last())
    before, after = by_ratio.rowsBetween(Window.unboundedPreceding, -1), by_ratio.rowsBetween(0, Window.unboundedFollowing)
    everything = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing).orderBy(F.lit(1))
    total = F.sum("source_size").over(everything).cast("double")
    level = (total - F.coalesce(F.sum("most").over(before), F.lit(0.0))) / F.sum("w").over(after)
    # The first source that its level does not clamp sets the water level of all that follow.
    rated = full.withColumn("level", level).withColumn("free", F.col("level") * F.col("w") <= F.col("most"))
    water = rated.withColumn("water", F.first(F.when(F.col("free"), F.col("level")), ignorenulls=True).over(by_ratio.rowsBetween(Window.unboundedPreceding, 0)))
    return water.select("source", "source_size", F.when(F.col("water").isNull(), F.col("most")).otherwise(F.least("most", F.col("water") * F.col("w"))).alias("target"))


def plan(ws: Workspace, sized: DataFrame, weights: Sequence[float], cap: float) -> DataFrame:
    """One row a source: ``source, source_size, target, whole, cut``; documents with digest <= cut take one epoch more."""
    sources = targets(sized.groupBy("source").agg(F.sum("size").alias("source_size")), weights, cap)
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    sources = sources.withColumn("whole", whole).withColumn("quota", F.col("target") - F.col("whole") * F.col("source_size"))
    sources = ws.save(sources, "sources")
    bucket = F.substring("digest", 1, BUCKET_DIGITS)
    buckets = sized.groupBy("source", bucket.alias("bucket")).agg(F.sum("size").alias("size"))
    run = F.sum("size").over(Window.partitionBy("source").orderBy("bucket"))
    edges = buckets.select("source", "bucket", (run - F.col("size")).alias("below"), run.alias("upto"))
    same = lambda a, b: F.col(a).eqNullSafe(F.col(b))
    named = sources.select(F.col("source").alias("s"), "quota")
    edge = edges.join(named, same("source", "s")).where("below < quota and upto >= quota").select("s", "bucket", "below", "quota")
    edge = ws.save(edge, "edge")
    inside = sized.withColumn("bucket", bucket).join(edge.withColumnRenamed("bucket", "b"), same("source", "s") & (F.col("bucket") == F.col("b")))
    ties = inside.groupBy("s", "digest", "below", "quota").agg(F.sum("size").alias("size"))
    done = F.col("below") + F.sum("size").over(Window.partitionBy("s").orderBy("digest"))
    taken = ties.withColumn("done", done).where(F.col("done") - F.col("size") / 2 <= F.col("quota"))
    last = taken.groupBy("s").agg(F.max("digest").alias("exact"))
    cuts = edge.select("s", "bucket").join(last.withColumnRenamed("s", "t"), same("s", "t"), "left").select(F.col("s").alias("e"), F.coalesce("exact", "bucket").alias("cut"))
    out = sources.join(cuts, same("source", "e"), "left")
    return ws.save(out.select("source", "source_size", "target", "whole", F.coalesce("cut", F.lit("")).alias("cut")), "plan")


def _with_repeats(df: DataFrame, weights: Sequence[float], cap: float, seed: str, doc_id: str, text: str, source: str) -> tuple[DataFrame, list[str]]:
    """``df`` with ``size, source_size, target, repeats`` under names that no column of ``df`` has, and these names."""
    if min(weights) <= 0 or cap < 1:
        raise ValueError("weights must be positive and cap at least 1")
    ws = Workspace(df.sparkSession, "mixing")
    sized = ws.save(df.select(F.col(source).alias("source"), word_count(F.col(text)).alias("size"), order_key(F.col(doc_id), seed).alias("digest")), "sized")
    size, source_size, target, repeats, whole, cut, key = unused(df.columns, "size", "source_size", "target", "repeats", "whole", "cut", "key")
    p = plan(ws, sized, weights, cap).select(F.col("source").alias(key), F.col("source_size").alias(source_size), F.col("target").alias(target), F.col("whole").alias(whole), F.col("cut").alias(cut))
    ws.drop(sized)
    joined = df.join(p, F.col(source).eqNullSafe(F.col(key)), "left")
    times = (F.col(whole) + (order_key(F.col(doc_id), seed) <= F.col(cut)).cast("long")).alias(repeats)
    return joined.select(*df.columns, word_count(F.col(text)).alias(size), source_size, target, times), [size, source_size, target, repeats]


def repeat_rows(df: DataFrame, weights: Sequence[float] = (5, 2, 1), cap: float = 3.0, seed: str = "mix", doc_id: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """The columns of ``df``, whatever their names; every row as often as the mix takes it. Otherwise as ``mix``."""
    out, (*_, repeats) = _with_repeats(df, weights, cap, seed, doc_id, text, source)
    (nth,) = unused(out.columns, "nth")
    taken = out.where(F.col(repeats) > 0).withColumn(nth, F.explode(F.sequence(F.lit(1), F.col(repeats).cast("int"))))
    return taken.select(*df.columns)


def mix(df: DataFrame, weights: Sequence[float] = (5, 2, 1), cap: float = 3.0, seed: str = "mix", doc_id: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """``df`` with ``size, source_size, target, repeats, taken``: how often the mix takes each row.

    Null texts have size 0; null sources form one source, last in order.  Rows that repeat an id fall on
    the same side of the cut.  An empty table gives an empty table.  Existing columns of these names
    are replaced.  The plan of sources is small; Spark joins it by broadcast while its size allows.
    """
    out, _ = _with_repeats(df.drop("size", "source_size", "target", "repeats", "taken"), weights, cap, seed, doc_id, text, source)
    return out.withColumn("taken", F.col("size") * F.col("repeats"))


ORACLE = """
WITH d AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) AS BIGINT) AS size,
                  md5('mix:' || coalesce(CAST(doc_id AS VARCHAR), 'null')) AS digest FROM documents),
s0 AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
s1 AS (SELECT *, CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN CAST(5 AS DOUBLE) WHEN 1 THEN CAST(2 AS DOUBLE) ELSE CAST(1 AS DOUBLE) END AS w, source_size * CAST(3 AS DOUBLE) AS most FROM s0),
s2 AS (SELECT *, (CAST(sum(source_size) OVER () AS DOUBLE) - coalesce(sum(most) OVER (ORDER BY most / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0))
                 / sum(w) OVER (ORDER BY most / w, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM s1),
s3 AS (SELECT *, (SELECT arg_min(level, most / w) FROM s2 AS z WHERE z.level * z.w <= z.most) AS water FROM s2),
s4 AS (SELECT source, source_size, least(most, water * w) AS target FROM s3),
s5 AS (SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target / source_size) AS BIGINT) ELSE 0 END AS whole FROM s4),
t AS (SELECT d.*, s5.source_size, s5.target, s5.whole, sum(d.size) OVER (PARTITION BY d.source ORDER BY digest) - d.size / 2.0 AS middle
      FROM d JOIN s5 ON d.source IS NOT DISTINCT FROM s5.source)
SELECT doc_id, size, source_size, target, CAST(size * (whole + CASE WHEN middle <= target - whole * source_size THEN 1 ELSE 0 END) AS BIGINT) AS taken FROM t
"""
