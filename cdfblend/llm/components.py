"""Connected components over an edge table, by alternating star contractions.

Every round is two minimum aggregates (which combine before they shuffle) and two equi-joins (which
adaptive execution can split when a hub holds many edges).  No neighbour list is ever collected, so a
hub with a third of all edges costs no more memory than any other node.  The number of rounds grows
with the logarithm of the longest path; every round is written to the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .workspace import Workspace


def _state(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("v", "u")).alias("h")).first()
    return row.n, row.h


def connected_components(ws: Workspace, edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """``(node, component)`` for every node that has an edge; component is its smallest reachable node.

    Nulls and self-loops are ignored, repeated edges count once, an empty table gives an empty table.
    """
    e = edges.select(F.col(a).cast("long").alias("x"), F.col(b).cast("long").alias("y")).where("x is not null and y is not null and x <> y")
    e = ws.save(e.select(F.greatest("x", "y").alias("v"), F.least("x", "y").alias("u")).distinct(), "edges")
    before = _state(e)
    for _ in range(max_rounds):
        both = e.select(F.col("v").alias("x"), F.col("u").alias("y")).unionAll(e.select(F.col("u").alias("x"), F.col("v").alias("y")))
        low = both.groupBy("x").agg(F.min("y").alias("m")).select("x", F.least("x", "m").alias("m"))
        large = both.where("y > x").join(low, "x").select(F.col("y").alias("v"), F.col("m").alias("u")).where("v <> u").distinct()
        large = ws.save(large, "large")
        low2 = large.groupBy("v").agg(F.min("u").alias("m"))
        small = large.join(low2, "v").where("u <> m").select(F.col("u").alias("v"), F.col("m").alias("u"))
        nxt = ws.save(small.unionAll(low2.select("v", F.col("m").alias("u"))).distinct(), "small")
        ws.drop(e, large)
        e, after = nxt, _state(nxt)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    centres = e.select(F.col("u").alias("node")).distinct().select("node", F.col("node").alias("component"))
    return e.select(F.col("v").alias("node"), F.col("u").alias("component")).unionAll(centres)
