"""Chat formatting with cumulative-snapshot collapse (native DataFrame functions).

A logged conversation is redundant if it is a proper prefix of a longer one, or equal to one with a smaller id.
The digest of a prefix is the exclusive-or of its turns' digests, each bound to its position, so
prefix digests are a running aggregate.  Running aggregates go in two steps, over runs of turns and then inside a
run, so a conversation with a third of all turns is no single task.  Distinct prefix digests are
anti-joined with whole-conversation digests; only maximal conversations are rendered.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .workspace import Workspace

#: Turns of a conversation that one task orders at a time.
RUN = 1024
OPEN, CLOSE = "<|im_start|>", "<|im_end|>"


def turn_text(role: Column, text: Column) -> Column:
    """One rendered turn; markers inside a text are broken up so that a text cannot forge a turn."""
    safe = F.replace(F.replace(F.coalesce(text, F.lit("")), F.lit(OPEN), F.lit("<| im_start|>")), F.lit(CLOSE), F.lit("<| im_end|>"))
    return F.concat(F.lit(OPEN), F.coalesce(role, F.lit("unknown")), F.lit("\n"), safe, F.lit(CLOSE + "\n"))


def positions(df: DataFrame) -> DataFrame:
    """``df`` with ``pos`` from 0 by (turn, role, text) inside ``conv``; needs ``bin``, a coarse run of turns.

    Rows of a bin are numbered inside the bin and shifted by the counts of the bins before it.
    """
    counts = df.groupBy("conv", "bin").agg(F.count("*").alias("c"))
    before = F.coalesce(F.sum("c").over(Window.partitionBy("conv").orderBy(F.col("bin").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    shift = counts.select(F.col("conv").alias("s_conv"), F.col("bin").alias("s_bin"), before.alias("shift"))
    inside = F.row_number().over(Window.partitionBy("conv", "bin").orderBy(F.col("turn").asc_nulls_first(), F.col("role").asc_nulls_first(), F.col("text").asc_nulls_first())) - 1
    numbered = df.withColumn("inside", inside)
    joined = numbered.join(shift, F.col("conv").eqNullSafe(F.col("s_conv")) & F.col("bin").eqNullSafe(F.col("s_bin")))
    return joined.select("conv", "turn", "role", "text", (F.col("inside") + F.col("shift")).alias("pos"))


def collapse(df: DataFrame, conv_id: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """``(conv_id, n_turns, rendered)`` of the maximal conversations.

    Turns go by (turn, role, text), nulls first; repeated rows are repeated turns.  A null role renders as
    ``unknown``, a null text as empty; rows of null conversation id form one conversation.  Other columns are
    ignored.  An empty table gives an empty table.
    """
    ws = Workspace(df.sparkSession, "chat")
    turns = df.select(F.col(conv_id).alias("conv"), F.col(turn).cast("long").alias("turn"), F.col(role).alias("role"), F.col(text).alias("text"))
    turns = turns.withColumn("bin", F.floor(F.col("turn") / RUN))
    placed = positions(turns)
    piece = lambda seed: F.xxhash64(F.lit(seed), F.col("pos"), F.col("role").isNull(), F.col("role"), F.col("text").isNull(), F.col("text"))
    marked = placed.withColumn("h1", piece(1)).withColumn("h2", piece(2)).withColumn("run", F.floor(F.col("pos") / RUN))
    marked = ws.save(marked, "turns")
    runs = marked.groupBy("conv", "run").agg(F.bit_xor("h1").alias("r1"), F.bit_xor("h2").alias("r2"), F.count("*").alias("c"))
    earlier = Window.partitionBy("conv").orderBy("run").rowsBetween(Window.unboundedPreceding, -1)
    runs = ws.save(runs.select(F.col("conv").alias("r_conv"), F.col("run").alias("r_run"), *[F.coalesce(F.bit_xor(r).over(earlier), F.lit(0)).alias(f"b{r[1]}") for r in ("r1", "r2")], "r1", "r2", "c"), "runs")
    within = Window.partitionBy("conv", "run").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    inside = marked.select("conv", "run", "pos", F.bit_xor("h1").over(within).alias("p1"), F.bit_xor("h2").over(within).alias("p2"))
    whole = marked.groupBy("conv").agg(F.count("*").alias("n"), F.bit_xor("h1").alias("w1"), F.bit_xor("h2").alias("w2"))
    first = whole.groupBy("n", "w1", "w2").agg(F.min("conv").alias("conv"))
    known = inside.join(runs, F.col("conv").eqNullSafe(F.col("r_conv")) & (F.col("run") == F.col("r_run")))
    sizes = whole.select(F.col("conv").alias("w_conv"), F.col("n").alias("w_n"))
    prefixes = known.join(sizes, F.col("conv").eqNullSafe(F.col("w_conv"))).where(F.col("pos") + 1 < F.col("w_n"))
    prefixes = prefixes.select((F.col("pos") + 1).alias("n"), F.col("p1").bitwiseXOR(F.col("b1")).alias("w1"), F.col("p2").bitwiseXOR(F.col("b2")).alias("w2")).distinct()
    maximal = ws.save(first.join(prefixes, ["n", "w1", "w2"], "left_anti").select(F.col("conv").alias("m_conv"), "n"), "maximal")
    lines = marked.join(maximal, F.col("conv").eqNullSafe(F.col("m_conv"))).select("conv", "n", "pos", turn_text(F.col("role"), F.col("text")).alias("line"))
    parts = lines.groupBy("conv", "n", F.floor(F.col("pos") / RUN).alias("run")).agg(F.array_sort(F.collect_list(F.struct("pos", "line"))).alias("x"))
    parts = parts.select("conv", "n", "run", F.concat_ws("", F.transform("x", lambda s: s["line"])).alias("part"))
    out = parts.groupBy("conv", "n").agg(F.array_sort(F.collect_list(F.struct("run", "part"))).alias("x"))
    return out.select(F.col("conv").alias("conv_id"), F.col("n").cast("long").alias("n_turns"), F.concat_ws("", F.transform("x", lambda s: s["part"])).alias("rendered"))


ORACLE = """
WITH t AS (SELECT conv_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role NULLS FIRST, text NULLS FIRST) AS pos, role, text FROM conversations),
p AS (SELECT conv_id, pos, count(*) OVER (PARTITION BY conv_id) AS n, list(struct_pack(r := role, x := text)) OVER (PARTITION BY conv_id ORDER BY pos) AS prefix FROM t),
w AS (SELECT n, prefix, min(conv_id) AS conv_id FROM p WHERE pos = n GROUP BY n, prefix),
m AS (SELECT conv_id, n FROM w WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.pos = w.n AND p.pos < p.n AND p.prefix = w.prefix))
SELECT m.conv_id, CAST(m.n AS BIGINT) AS n_turns,
       string_agg('<|im_start|>' || coalesce(t.role, 'unknown') || chr(10) || replace(replace(coalesce(t.text, ''), '<|im_start|>', '<| im_start|>'), '<|im_end|>', '<| im_end|>') || '<|im_end|>' || chr(10), '' ORDER BY t.pos) AS rendered
FROM m JOIN t ON t.conv_id IS NOT DISTINCT FROM m.conv_id GROUP BY m.conv_id, m.n
"""
