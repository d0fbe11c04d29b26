"""Connected components of an edge DataFrame by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from regpath.operators.scratch import Scratch


def _to_least(pairs: DataFrame) -> DataFrame:
    """For each node, its least neighbour or itself; pre-aggregated before the shuffle."""
    return pairs.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("m"))


def connected_components(edges: DataFrame, scratch: Scratch | None = None, max_rounds: int = 100) -> DataFrame:
    """Edges (a, b) of any order and repetition -> (node, component), component the least node id.

    Every round links each node's greater, then its smaller neighbours to its least
    neighbour, until only stars are left; rounds grow with the logarithm of the
    longest shortest path.  State is one row per node or edge, never a list.
    Null ends and loops link nothing; nodes without edges are not returned.
    """
    scratch = scratch or Scratch(edges.sparkSession, "components")
    a, b = F.col(edges.columns[0]), F.col(edges.columns[1])
    now = scratch.table(edges.where(a.isNotNull() & b.isNotNull() & (a != b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct())
    mark = _mark(now)
    for _ in range(max_rounds):
        if not mark[0]:
            break
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = scratch.table(_to_least(both))  # written, so that Spark can split the join at a frequent node
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.where("u != v").distinct()
        small = large.join(_to_least(large), "u")
        small = small.select(F.col("v").alias("u"), F.col("m").alias("v")).union(small.select("u", F.col("m").alias("v")))
        after = scratch.table(small.where("u != v").distinct())
        now_mark = _mark(after)
        scratch.drop(now)
        now = after
        if now_mark == mark:
            break
        mark = now_mark
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def _mark(edges: DataFrame) -> tuple[int, int, int]:
    row = edges.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v")), F.sum(F.xxhash64("u", "v") % 1000003)).first()
    return row[0], row[1] or 0, row[2] or 0
