"""Connected components by alternating star contraction, in DataFrame functions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import materialise, skew_safe_lookup


def _star(edges: DataFrame, count: int, large: bool) -> DataFrame:
    """One contraction: every node's neighbours (large: the greater ones, small: the lesser) move to its least neighbour."""
    down = edges.select(F.col("u").alias("x"), F.col("v").alias("y"))
    near = down.unionByName(edges.select(F.col("v").alias("x"), F.col("u").alias("y"))) if large else down
    least = materialise(near.groupBy("x").agg(F.min("y").alias("m"), F.count(F.lit(1)).alias("n")), "star")
    least = least.withColumn("m", F.least("m", "x"))
    pairs = skew_safe_lookup(near, least, "x", "n", count * (2 if large else 1), ["m"])
    pairs = pairs.filter((F.col("y") > F.col("x")) & (F.col("y") != F.col("m")) if large else F.col("y") != F.col("m"))
    out = pairs.select(F.col("y").alias("u"), F.col("m").alias("v"))
    if not large:
        out = out.unionByName(least.filter("x != m").select(F.col("x").alias("u"), F.col("m").alias("v")))
    return out.distinct()


def connected_components(edges: DataFrame, a: str, b: str) -> DataFrame:
    """(node, component): the least node reachable, for every node with an edge to a lesser one.

    ``edges``: pairs of longs, in any direction, repeats and loops allowed. Each round is a handful of
    hash aggregates and lookups on the edge list, whose number never grows; hubs
    are looked up by broadcast, so a node with a third of all edges doesn't meet in one task. Rounds
    end when the edges are stars; the count of rounds is logarithmic.
    """
    mark = lambda e: e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    now = materialise(
        edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).filter("u != v").distinct(), "edges"
    )
    seen = mark(now)
    while seen[0]:
        wide = materialise(_star(now, seen[0], True), "edges")
        now = materialise(_star(wide, wide.count(), False), "edges")
        last, seen = seen, mark(now)
        if tuple(last) == tuple(seen):
            break
    return now.select(F.col("u").alias("node"), F.col("v").alias("component"))
