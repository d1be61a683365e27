"""What the methods are compared with: plain, non-hiding forms."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.components import connected_components as _stars
from ..plans.shared import materialise
from .primitives import doubling_aggregate  # noqa: F401  the naive scan
from .sorts import engine_sort  # noqa: F401  the plain sort


def pointer_jump(df: DataFrame, id_col: str, succ_col: str, out: str = "ahead") -> DataFrame:
    """List ranking by doubling on the real ids."""
    n = df.count()
    now = df.select(F.col(id_col).alias("x"), F.when(F.col(succ_col) != 0, F.col(succ_col)).alias("s"))
    now = now.withColumn(out, F.col("s").isNotNull().cast("long"))
    for _ in range(max(1, math.ceil(math.log2(max(n, 2))) + 1)):
        other = now.select(F.col("x").alias("_x"), F.col("s").alias("_s"), F.col(out).alias("_a"))
        now = materialise(now.join(other, F.col("s") == F.col("_x"), "left").select("x", F.col("_s").alias("s"), (F.col(out) + F.coalesce("_a", F.lit(0))).alias(out)), "jump")
    return now.select(F.col("x").alias(id_col), out)


def euler_tour(edges: DataFrame) -> DataFrame:
    """The tour by windows over the real vertices."""
    both = edges.select("a", "b").union(edges.select("b", "a")).toDF("u", "v")
    w = Window.partitionBy("u").orderBy("v")
    circle = both.select("u", "v", F.coalesce(F.lead("v").over(w), F.first("v").over(w)).alias("n"))
    return both.join(circle.toDF("v", "u", "sv"), ["u", "v"]).select("u", "v", F.col("v").alias("su"), "sv")


def components(edges: DataFrame) -> DataFrame:
    """Components by star contraction until nothing moves, on the real ids."""
    return _stars(edges, "u", "v")


def rollup_tree(nodes: DataFrame, value: str, depth: int) -> DataFrame:
    """Sums of a tree of the given depth, level by level: (id, total). ``nodes``: (id, parent, value)."""
    total = nodes.select("id", "parent", F.coalesce(F.col(value), F.lit(0)).alias("total"))
    now = total
    for _ in range(depth):
        up = now.filter("parent is not null").groupBy("parent").agg(F.sum("total").alias("_t")).withColumnRenamed("parent", "_p")
        now = materialise(total.join(up, F.col("id") == F.col("_p"), "left").select("id", "parent", (F.col("total") + F.coalesce("_t", F.lit(0))).alias("total")), "rollup")
    return now.select("id", "total")


def plain_join(facts: DataFrame, dim: DataFrame, key: str, dim_key: str, how: str = "inner") -> DataFrame:
    return facts.join(dim, F.col(key) == F.col(dim_key), how)


def spanning_forest(edges: DataFrame) -> DataFrame:
    """The lightest forest of (u, v, w, e) as a user would write it: the edges in order of weight through union-find, in one task."""

    def kruskal(t):
        parent: dict[int, int] = {}

        def top(x):
            while parent.setdefault(x, x) != x:
                parent[x] = parent[parent[x]]
                x = parent[x]
            return x

        keep = []
        for i, (u, v) in enumerate(zip(t.sort_values(["w", "e"])["u"], t.sort_values(["w", "e"])["v"])):
            a, b = top(u), top(v)
            if a != b:
                parent[a] = b
                keep.append(i)
        return t.sort_values(["w", "e"]).iloc[keep]

    return edges.select("e", "u", "v", "w").groupBy(F.lit(0).alias("all")).applyInPandas(kruskal, edges.select("e", "u", "v", "w").schema)


def plain_group(df: DataFrame, keys: list[str], aggs: dict) -> DataFrame:
    return df.groupBy(*keys).agg(*(c.alias(k) for k, c in aggs.items()))
