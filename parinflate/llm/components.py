"""Connected components by alternating large-star and small-star over an edge table; nothing reaches the driver but counts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parinflate.runtime import materialize


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One star step. ``edges`` holds (u, v), u > v. Every node's neighbours (those above it for the large star, those below and itself for the small) link to the least node around it."""
    if large:
        both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    else:
        both = edges.select("u", "v")
    least = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("n"), F.least("n", "m").alias("m"))
    side = both.where("v > u") if large else both
    linked = side.join(least, side.u == least.n).select(F.col("v").alias("a"), F.col("m").alias("b"))
    if not large:
        linked = linked.union(least.select(F.col("n").alias("a"), F.col("m").alias("b")))
    else:
        linked = linked.union(least.where("n > m").select(F.col("n").alias("a"), F.col("m").alias("b")))
    return linked.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()


def components(edges: DataFrame, max_rounds: int = 64) -> DataFrame:
    """(node, component) of every node with an edge; ``edges`` has two columns of ids, in any direction; component is the least id reachable."""
    a, b = edges.columns[:2]
    cur = materialize(edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct(), "cc")
    for _ in range(max_rounds):
        nxt = materialize(_star(_star(cur, True), False), "cc")
        # A forest of stars: every node has one edge and no node is both a leaf and a centre.
        leaves = nxt.groupBy("u").agg(F.count(F.lit(1)).alias("k"))
        settled = not leaves.where("k > 1").take(1) and not nxt.join(leaves.select(F.col("u").alias("l")), nxt.v == F.col("l"), "left_semi").take(1)
        cur = nxt
        if settled:
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return cur.select(F.col("u").alias("node"), F.col("v").alias("component")).union(cur.select("v", "v").distinct())
