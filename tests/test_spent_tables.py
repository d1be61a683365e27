"""Tables and exchanges that no later step reads don't stay on disk."""

from __future__ import annotations

import os

import pytest
from pyspark.sql import functions as F

from oblivspark.operators import graphs
from oblivspark.plans.shared import kept, materialise, scratch


def size(path: str) -> int:
    path = path.removeprefix("file:")
    return sum(os.path.getsize(os.path.join(r, f)) for r, _, files in os.walk(path) for f in files)


@pytest.mark.parametrize("tail", [1 << 21, 500])
def test_a_tree_leaves_few_tables(spark, monkeypatch, tail):
    """what stays of the tour, the ranking and the sorts is less than half of what is written."""
    monkeypatch.setattr(graphs.list_rank, "__defaults__", tuple(tail if x == graphs.TAIL else x for x in graphs.list_rank.__defaults__))
    edges, written = spark.range(1, 6000).select((F.col("id") / 3).cast("long").alias("a"), F.col("id").alias("b")), []
    real = materialise

    def note(df, name="table"):
        out = real(df, name)
        written.append(size(out._written))
        return out

    for module in (graphs, __import__("oblivspark.operators.sorts", fromlist=["x"]), __import__("oblivspark.operators.permute", fromlist=["x"]), __import__("oblivspark.operators.primitives", fromlist=["x"]), __import__("oblivspark.plans.shared", fromlist=["x"])):
        monkeypatch.setattr(module, "materialise", note)
    with scratch(spark) as held:
        got = {r.node: (r.parent, r.depth, r["size"]) for r in graphs.tree_functions(edges, 0, seed=3, level="cluster").collect()}
        left = [size(x) for x in held if os.path.exists(x.removeprefix("file:"))]
        assert 2 * sum(left) < sum(written) and len(left) < len(written) / 2
    depth = {0: 0}
    for i in range(1, 6000):
        depth[i] = depth[i // 3] + 1
    below = [1] * 6000
    for i in range(5999, 0, -1):
        below[i // 3] += below[i]
    assert got == {i: (i // 3 if i else None, depth[i], below[i]) for i in range(6000)}


def test_kept_leaves_its_own_table(spark):
    with scratch(spark) as held:
        out = kept(spark, lambda: materialise(spark.range(9)).select((F.col("id") * 2).alias("x")))
        assert sorted(r.x for r in out.collect()) == list(range(0, 18, 2))
        assert [os.path.exists(x.removeprefix("file:")) for x in held] == [False, True]
