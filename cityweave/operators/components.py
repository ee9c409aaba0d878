"""Connected components by alternating star contraction, without a driver-side graph.

Every round is two joins over the edge table. Edges only ever get re-pointed
at smaller neighbours, so the table never has more rows than it began with.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cityweave.scratch import Scratch


def _large_star(edges: DataFrame) -> DataFrame:
    """Each vertex hands its larger neighbours to its smallest neighbour."""
    both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("m"))
    return both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Each vertex hands its smaller neighbours, and itself, to the smallest of them."""
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    moved = down.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v")))
    return moved.where("u <> v").distinct()


def components(edges: DataFrame, scratch: Scratch, limit: int = 60) -> DataFrame:
    """(u, v) links of longs to (node, root), root being the smallest node reachable.

    Only nodes with links appear, and no node that is its own root. An empty
    table of links gives an empty result.
    """
    spark = edges.sparkSession
    now = scratch.keep(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    seen = None
    for _ in range(limit):
        state = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if tuple(state) == seen or not state[0]:
            return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
        seen = tuple(state)
        step = _small_star(_large_star(now))
        now = scratch.keep(step, now._scratch_path)
    raise RuntimeError(f"no fixpoint after {limit} rounds")
