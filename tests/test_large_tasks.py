"""No task holds more than a public number of rows, whatever the length."""

from __future__ import annotations

from pyspark.sql import functions as F

from oblivspark.operators import permute as P
from oblivspark.operators import sorts
from oblivspark.plans import params


def test_tasks_grow_with_the_length(spark):
    df = spark.range(1)
    for n in (3_600_000, 36_000_000):
        p = params.from_length(n)
        assert P.task_digits(df, p, None, 1)[0] * P.TASK_SLOTS >= n
        assert all(d * p.z <= 4 * P.TASK_SLOTS for d in P.task_digits(df, params.from_length(100 * n), None, 1))


def test_rows_are_routed_in_chunks(spark, monkeypatch):
    monkeypatch.setattr(P, "CHUNK", 700)
    monkeypatch.setattr(P, "TASK_SLOTS", 2048)
    monkeypatch.setattr(sorts, "CHUNK", 700)
    df = spark.range(20_000).select("id", F.hash("id").alias("k"))
    want = [r.id for r in df.orderBy("k", "id").collect()]
    for level, phases in (("cluster", 1), ("cluster", 2), ("memory", 1)):
        drawn = P.permute(df, seed=3, level=level, phases=phases)
        got = drawn.df.groupBy("_task").agg(F.count("*").alias("n")).collect()
        assert len(got) >= 16 and max(r.n for r in got) <= 2048 and sum(r.n for r in got) == 20_000
    for second in ("engine", "pivots"):
        got = sorts.oblivious_sort(df, ["k", "id"], second=second, seed=3, level="cluster").orderBy("pos").collect()
        assert [r.id for r in got] == want and [r.pos for r in got] == list(range(20_000))


def test_forests_of_a_task(spark, monkeypatch):
    """150,000 nodes and as many edges are one task's; chains of ten in a scattered order."""
    from oblivspark.operators import graphs

    def refuse(*_, **__):
        raise AssertionError("memory steps")

    monkeypatch.setattr(graphs, "_least_neighbour_steps", refuse)
    nodes = spark.range(150_000).select("id")
    edges = nodes.filter("id % 10 > 0").select(F.col("id").alias("u"), (F.col("id") - 1).alias("v")).repartition(7)
    got = graphs.connected_components(nodes, edges)
    assert got.count() == 150_000 and got.filter("component <> id - id % 10").count() == 0
    heavy = edges.withColumns({"w": F.col("u") % 3, "e": F.col("u")}).unionByName(edges.select("u", F.col("v").alias("v"), F.lit(9).cast("long").alias("w"), (F.col("u") + 1_000_000).alias("e")))
    kept = graphs.min_spanning_forest(nodes, heavy)
    assert kept.count() == 135_000 and kept.filter("w = 9").count() == 0


def test_expanding_join_has_no_more_places_than_matches(spark, sf, monkeypatch):
    from oblivspark import workloads
    from oblivspark.operators import relational

    bounds, real = [], relational.expand_join
    monkeypatch.setattr(relational, "expand_join", lambda a, b, key, bound, **o: bounds.append(bound) or real(a, b, key, bound, **o))
    got = workloads.expand_join_same_nation(spark, sf).count()
    assert bounds[0] < 2 * max(1, got)


def test_tree_memory_in_one_task(spark):
    """All depths in one task: answers as stated, entries on their own paths and in slots of their own, and few jobs a batch."""
    import random

    import numpy as np

    from oblivspark.operators.tree_memory import BUCKET, TreeMemory

    r, n = random.Random(5), 700
    ref = [100 + i for i in range(n)]
    mem = TreeMemory(spark.createDataFrame(list(enumerate(ref)), "addr long, val long"), procs=2, seed=3, level="cluster")
    tracker = spark.sparkContext.statusTracker()
    for batch, size in enumerate((8, 300, 60)):
        req = [(i, r.choice("rw"), r.choice([r.randrange(n), 3, n + 3]), r.randrange(1000)) for i in range(size)]
        spark.sparkContext.setJobGroup(f"tree-{batch}", "tree")
        got = {x["i"]: x["val"] for x in mem.access(spark.createDataFrame(req, "i long, op string, addr long, val long")).collect()}
        assert len(tracker.getJobIdsForGroup(f"tree-{batch}")) < 70
        assert got == {i: ref[a] if a < n else None for i, _, a, _ in req}
        done = set()
        for _, op, a, v in req:
            if op == "w" and a < n and a not in done:
                ref[a] = v
                done.add(a)
        s = mem.state.toPandas()
        s = s[s["at"] >= 0]
        node, depth = (s["at"] // BUCKET).to_numpy(), s["depth"].to_numpy()
        level = np.log2(node).astype(int)
        assert not s.duplicated(["depth", "at"]).any() and (level > mem.top).all()
        assert (((s["leaf"].to_numpy() + (1 << depth)) >> (depth - level)) == node).all()
        assert [x.count() for x in mem.seen[-11:]] == [size] * 11
    assert sorted(map(tuple, mem.dump().collect())) == list(enumerate(ref))


def test_phases_share_rows_alike(spark, monkeypatch):
    """One long input reaches all tasks of the second phase, not those of one turn alone."""
    monkeypatch.setattr(P, "CHUNK", 700)
    df, p = spark.range(0, 20_000, 1, 1).select("id", F.hash("id").alias("k")), params.from_length(20_000)
    spark.sparkContext.setJobGroup("phases", "phases")
    out = P.routed(df, p, P.Codec(df.schema, {}), (4, 4), P.K.coin_key(3), "cluster", "recursive").select("dest")
    assert out.distinct().count() == 16
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(10_000)
    tracker, store = spark.sparkContext.statusTracker(), spark.sparkContext._jsc.sc().statusStore()
    stages = sorted({i for j in tracker.getJobIdsForGroup("phases") for i in tracker.getJobInfo(j).stageIds})
    loads = []
    for i in stages:
        tasks = store.taskList(i, 0, 1000)
        if tasks.size() == 16:
            loads.append([tasks.apply(x).taskMetrics().get().shuffleReadMetrics().recordsRead() for x in range(16)])
    assert len(loads) == 2 and all(min(x) > 0 and max(x) <= 4 * sum(x) / 16 for x in loads)


def test_sliding_counts_group_rows_once(spark, sf, monkeypatch):
    from oblivspark import streaming, workloads

    sizes, real = [], streaming.group_aggregate
    monkeypatch.setattr(streaming, "group_aggregate", lambda rows, *a, **o: sizes.append(rows.count()) or real(rows, *a, **o))
    got = workloads.stream_sliding_counts(spark, sf)
    n = workloads.t(spark, sf, "events").count()
    panes = got.count()
    assert len(sizes) == 6 and max(sizes) <= -(-n // 3) + 4 * panes


def test_tree_memory_of_many_cells_in_one_task(spark):
    """300,000 cells are one task's, which holds a depth at a time."""
    from oblivspark.operators.tree_memory import TreeMemory

    n = 300_000
    mem = TreeMemory(spark.range(n).select(F.col("id").alias("addr"), (F.col("id") * 3).alias("val")), top=7, seed=3, level="cluster")
    assert mem.lean is not None
    req = spark.range(0, 90_000, 1, 3).select(F.col("id").alias("i"), F.lit("w").alias("op"), (F.col("id") * 7 % 310_000).alias("addr"), (F.col("id") + 1).alias("val"))
    old = mem.access(req)
    assert old.count() == 90_000
    assert old.join(req.drop("val"), "i").filter(~F.col("val").eqNullSafe(F.when(F.col("addr") < n, F.col("addr") * 3))).count() == 0
    want = {r.addr: r.v for r in req.filter(F.col("addr") < n).groupBy("addr").agg(F.min_by("val", "i").alias("v")).collect()}
    got = {r.addr: r.val for r in mem.dump().collect()}
    assert got == {a: want.get(a, 3 * a) for a in range(n)}
    assert mem.seen[-1].select("k").distinct().count() == 90_000
