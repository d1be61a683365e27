"""Operators on handmade cases: lengths 0 and 1, groups over block borders, conflicts, trees and lists, refusals."""

import random

import pytest
from pyspark.sql import functions as F

from oblivspark.functions.codec import Key
from oblivspark.operators import graphs, pram, primitives, relational, sorts
from oblivspark.operators.permute import permute
from oblivspark.plans import trace
from oblivspark.plans.components import connected_components as stars
from oblivspark.plans.shared import materialise, skew_safe_lookup

S = {"seed": 3, "level": "cluster"}


@pytest.mark.parametrize("n", [0, 1, 2, 3, 17])
@pytest.mark.parametrize("small", [0, 4096])
def test_short_sorts(spark, n, small):
    vals = [(i, (i * 7) % 5, None if i % 4 == 0 else f"s{i % 3}") for i in range(n)]
    df = spark.createDataFrame(vals, "id long, v long, s string").coalesce(1)
    got = sorts.oblivious_sort(df, [Key("s", False, False), "v", "id"], small=small, **S).orderBy("pos").collect()
    want = sorted(sorted(vals, key=lambda r: (r[1], r[0])), key=lambda r: (r[2] is None, [-ord(c) for c in r[2] or ""]))
    assert [r["id"] for r in got] == [r[0] for r in want] and [r["pos"] for r in got] == list(range(n))


def test_sorts_agree(spark, sf):
    df = spark.read.parquet(f"{sf}/orders.parquet").select("o_orderkey", "o_orderpriority", "o_totalprice")
    keys = [Key("o_orderpriority"), Key("o_totalprice", False), Key("o_orderkey")]
    want = [r[0] for r in df.orderBy("o_orderpriority", F.desc("o_totalprice"), "o_orderkey").select("o_orderkey").collect()]
    ways = [
        sorts.oblivious_sort(df, keys, small=0, **S), sorts.oblivious_sort(df, keys, small=0, seed=3, level="memory"), sorts.oblivious_sort(df, keys, small=0, level="cluster"),
        sorts.oblivious_sort(df, keys, second="pivots", **S), sorts.oblivious_sort(df, keys, second="pivots", relaxed=True, network="search", **S),
        sorts.oblivious_sort(df, keys, small=0, phases=2, form="layered", gamma=2, **S), sorts.network_sort(df, keys), sorts.bitonic_sort(df, keys), sorts.bitonic_sort(df, keys, merge="layered"), sorts.engine_sort(df, keys),
    ]
    for w in ways:
        assert [r[0] for r in w.orderBy("pos").select("o_orderkey").collect()] == want
    with pytest.raises(ValueError):
        sorts.oblivious_sort(df, keys, second="radix", small=0)


def test_a_permutation_serves_once(spark):
    p = permute(spark.range(100), **S)
    order = [r[0] for r in p.df.orderBy("_task", "_at").select("id").collect()]
    assert sorted(order) == list(range(100)) != order
    p.take()
    with pytest.raises(ValueError):
        p.take()


@pytest.mark.parametrize("f", ["sum", "count", "min", "max"])
@pytest.mark.parametrize("direction", ["suffix", "prefix"])
def test_scans_over_block_borders(spark, f, direction):
    groups = ["a"] + ["b"] * 4 + ["c"] * 7 + ["d"] * 30
    data = [(i, g, None if i % 5 == 0 else (i * 11) % 13) for i, g in enumerate(groups)]
    df = spark.createDataFrame(data, "pos long, g string, v long")
    fold = {"sum": lambda x: sum(x), "count": len, "min": lambda x: min(x, default=None), "max": lambda x: max(x, default=None)}[f]
    for blocks in (1, 5, 11, 42):
        for inclusive in (False, True):
            got = primitives.segmented_aggregate(df, ["g"], F.col("v"), f, "r", inclusive, direction, blocks=blocks).collect()
            for r in got:
                mine = [v for p, g, v in data if g == r["g"] and v is not None and (p > r["pos"] if direction == "suffix" else p < r["pos"] or False or (inclusive and p == r["pos"])) or (g == r["g"] and v is not None and inclusive and p == r["pos"])]
                assert r["r"] == fold(mine), (blocks, inclusive, r)


def test_propagate_nulls(spark):
    df = spark.createDataFrame([(0, 1, None), (1, 1, 5), (2, 2, 6), (3, 2, None)], "pos long, g long, v long")
    assert [r["head"] for r in primitives.propagate(df, ["g"], F.col("v"), blocks=3).orderBy("pos").collect()] == [None, None, 6, 6]


def test_send_receive(spark):
    a = spark.createDataFrame([(1, "x"), (2, None), (None, "z")], "k long, v string")
    b = spark.createDataFrame([(1, 10), (1, 11), (2, 12), (3, 13), (None, 14)], "k long, i long")
    got = {r["i"]: (r["v"], r["found"]) for r in primitives.send_receive(a, b, ["k"], ["v"], **S).collect()}
    assert got == {10: ("x", True), 11: ("x", True), 12: (None, True), 13: (None, False), 14: (None, False)}
    with pytest.raises(primitives.DuplicateSender):
        primitives.send_receive(a.union(a), b, ["k"], ["v"], **S)
    with pytest.raises(ValueError):
        primitives.send_receive(a, b.withColumn("v", F.lit(1)), ["k"], ["v"], **S)


def test_write_rules(spark):
    mem = spark.createDataFrame([(i, 100 + i) for i in range(5)], "addr long, val long")
    req = spark.createDataFrame([(3, 1, 7), (1, 1, 5), (2, 1, 9), (4, 1, 9), (5, None, 1), (6, 77, 2)], "proc long, addr long, val long")
    for rule, want in (("priority", 5), ("sum", 30), ("min", 5), ("max", 9)):
        got = {r["addr"]: r["val"] for r in pram.pram_write(mem, req, rule, **S).collect()}
        assert got == {0: 100, 1: want, 2: 102, 3: 103, 4: 104}
    assert {r["val"] for r in pram.pram_write(mem, req, "arbitrary", **S).filter("addr = 1").collect()} <= {5, 7, 9}
    with pytest.raises(pram.WriteConflict):
        pram.pram_write(mem, req, "common", **S)
    assert pram.pram_read(mem, req.select("proc", "addr"), **S).filter("proc = 6").collect()[0]["val"] is None


def test_broadcast_program(spark):
    mem = spark.createDataFrame([(i, 5 if i == 0 else 0) for i in range(5)], "addr long, val long")
    out, _ = pram.run_pram(pram.broadcast_program(5), mem, spark.range(5).select(F.col("id").alias("proc")), **S)
    assert {r["val"] for r in out.collect()} == {5}


@pytest.mark.parametrize("kw", [{}, {"tail": 4}, {"ranker": "jump"}])
def test_lists(spark, kw):
    ids = list(range(1, 31))
    random.Random(1).shuffle(ids)
    lists = [ids[:20], ids[20:21], ids[21:]]
    df = spark.createDataFrame([(x, l[i + 1] if i + 1 < len(l) else 0, x % 7) for l in lists for i, x in enumerate(l)], "id long, succ long, w long")
    got = {r["id"]: r["ahead"] for r in graphs.list_rank(df, "id", "succ", weight="w", **kw, **S).collect()}
    assert got == {x: sum(y % 7 for y in l[i + 1 :]) for l in lists for i, x in enumerate(l)}


@pytest.mark.parametrize("edges,root", [([(0, 1)], 0), ([(0, 1), (1, 2), (2, 3)], 2), ([(0, i) for i in range(1, 6)], 3), ([(0, 1), (0, 2), (1, 3), (1, 4), (2, 5), (2, 6)], 0)])
def test_trees(spark, edges, root):
    near: dict[int, list[int]] = {}
    for a, b in edges:
        near.setdefault(a, []).append(b)
        near.setdefault(b, []).append(a)
    first = min(near[root])  # the tour starts at the least neighbour and goes round each vertex from where it came in
    want, count = {}, [0, 0]

    def walk(x, parent, depth):
        mine = count[0]
        count[0] += 1
        ns = sorted(near[x])
        turn = ns.index(parent) + 1 if parent is not None else ns.index(first)
        size = 1 + sum(walk(y, x, depth + 1) for y in ns[turn:] + ns[:turn] if y != parent)
        want[x] = (parent, depth, mine, count[1], size)
        count[1] += 1
        return size

    walk(root, None, 0)
    got = {r["node"]: tuple(r)[1:] for r in graphs.tree_functions(spark.createDataFrame(edges, "a long, b long"), root, **S).drop("is_leaf").collect()}
    assert got == want


@pytest.mark.parametrize("ring", ["sum_product", "max_plus"])
def test_contraction(spark, ring):
    r, rows, n = random.Random(2), [], [0, 0]

    def build(depth, parent, side):
        n[0] += 1
        me = n[0]
        if not depth or (depth < 3 and r.random() < 0.3):
            n[1] += 1
            v = r.randrange(1, 90)
            rows.append((me, parent, side, None, v, n[1]))
            return v
        op = r.choice("+*")
        rows.append((me, parent, side, op, None, None))
        a, b = build(depth - 1, me, 0), build(depth - 1, me, 1)
        if ring == "sum_product":
            return (a + b if op == "+" else a * b) % graphs.PRIME
        return max(a, b) if op == "+" else a + b

    want = build(3, None, None)
    df = spark.createDataFrame(rows, "id long, parent long, side int, op string, value long, number long")
    assert graphs.contract_tree(df, n[1], ring, seed=1) == want


def test_components_and_forest(spark):
    v = spark.range(9)
    e = spark.createDataFrame([(0, 1, 3), (1, 2, 3), (0, 2, 3), (4, 5, 1), (5, 4, 0), (6, 6, 1), (7, 8, 2)], "u long, v long, w long").coalesce(1).withColumn("e", F.monotonically_increasing_id())
    want = {0: 0, 1: 0, 2: 0, 3: 3, 4: 4, 5: 4, 6: 6, 7: 7, 8: 7}
    assert {r["id"]: r["component"] for r in graphs.connected_components(v, e).collect()} == want
    got = stars(e.select("u", "v"), "u", "v").collect()
    assert {r["node"]: r["component"] for r in got} == {k: c for k, c in want.items() if k != c}
    assert sorted(r["e"] for r in graphs.min_spanning_forest(v, e).collect()) == [0, 1, 4, 6]


def test_components_as_memory_steps(spark):
    v = spark.range(4)
    e = spark.createDataFrame([(0, 1), (3, 1)], "u long, v long")
    got = graphs.connected_components(v, e, tail=0, rounds=2, **S).collect()
    assert {r["id"]: r["component"] for r in got} == {0: 0, 1: 0, 2: 2, 3: 0}


def test_forest_as_memory_steps(spark):
    v = spark.range(5)
    e = spark.createDataFrame([(0, 1, 3, 10), (1, 2, 3, 11), (0, 2, 3, 12), (3, 2, 1, 13), (2, 3, 1, 9)], "u long, v long, w long, e long")
    got = graphs.min_spanning_forest(v, e, tail=0, rounds=2, **S).collect()
    assert sorted(map(tuple, got)) == [(9, 2, 3, 1), (10, 0, 1, 3), (11, 1, 2, 3)]


def test_compaction_and_placement(spark):
    df = spark.createDataFrame([(i, i % 3) for i in range(12)], "pos long, g int")
    done = primitives.compact(df, F.col("g") == 1, bound=4, **S).orderBy("pos").collect()
    assert [r["is_filler"] for r in done] == [False] * 4 and len(done) == 4
    placed = primitives.place_bins(df.withColumn("x", F.col("pos")), "g", 3, 4, **S)
    assert placed.count() == 12 and placed.filter("is_real").count() == 12
    with pytest.raises(Exception, match="overflows"):
        primitives.place_bins(df.withColumn("x", F.col("pos")), "g", 3, 3, **S)


def test_lookup_spreads_hot_keys(spark):
    df = spark.range(5000).select("id", F.when(F.col("id") < 4000, 7).otherwise(F.col("id")).alias("k"))
    table = materialise(df.groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("m")))
    got = skew_safe_lookup(df, table, "k", "n", 5000, ["m"])
    assert got.count() == 5000 and got.filter("m <> CASE WHEN id < 4000 THEN 0 ELSE id END OR m IS NULL").count() == 0


def test_guard(spark):
    df = spark.range(100).withColumn("secret", F.col("id") % 3)
    with trace.oblivious_session(spark):
        with pytest.raises(trace.SecretExchange):
            trace.assert_public_plan(df.groupBy("secret").count())
        trace.assert_public_plan(df.withColumn("_blk", F.col("id") % 5).groupBy("_blk").count())
    assert spark.conf.get("spark.sql.adaptive.enabled") == "true"


def test_blocks_of_one_size(spark):
    """What permuted tables of equal length show between tasks is the same blocks, whatever their rows."""
    from oblivspark.functions.codec import Codec
    from oblivspark.operators.permute import routed, task_digits
    from oblivspark.plans.params import from_length

    views = []
    for value in (F.col("id"), F.lit(0).cast("long")):
        df = spark.range(0, 3000, 1, 3).select(value.alias("v"))
        p = from_length(3000)
        views.append(trace.job_view(routed(df, p, Codec(df.schema), task_digits(df, p, 4, 1), 9, "cluster", "recursive")))
    assert views[0] == views[1] and len({b // n for _, n, b in views[0]}) == 1


def test_relational_fillers(spark):
    df = spark.createDataFrame([(1, 2.0), (1, None), (2, 4.0), (None, 5.0)], "k long, v double")
    hidden = relational.where(df, F.col("v") < 5)
    got = relational.group_aggregate(hidden, ["k"], {"s": ("sum", F.col("v")), "a": ("avg", F.col("v"))}, **S)
    assert got.count() == 4 and {(r["k"], r["s"], r["a"]) for r in relational.release(got).collect()} == {(1, 2.0, 2.0), (2, 4.0, 4.0)}
    assert relational.rollup(["a", "b"]) == [["a", "b"], ["a"], []] and len(relational.cube(["a", "b"])) == 4
    with pytest.raises(ValueError):
        relational.expand_join(df.select("k"), df.select("k", "v"), "k", 1, **S)


def test_coins_survive_recomputation(spark, sf):
    """With secret coins the same blocks leave every task however often it runs; rows that come through an exchange are written down first."""
    from oblivspark.functions import kernels as K
    from oblivspark.functions.codec import Codec
    from oblivspark.operators.permute import routed, task_digits
    from oblivspark.plans.params import from_length
    from oblivspark.plans.shared import fixed_rows

    df = spark.read.parquet(f"{sf}/orders.parquet").select("o_orderkey", "o_totalprice")
    p = from_length(df.count())
    blocks = routed(df, p, Codec(df.schema, {}), task_digits(df, p, 4, 1), K.coin_key(None), "cluster", "recursive")
    told = lambda: sorted((r[0], bytes(r[1])) for r in blocks.collect())
    first = told()
    assert first == told() and len(first) > 4
    moved = df.repartition(3)
    assert fixed_rows(df) is df and "Exchange" not in fixed_rows(moved)._jdf.queryExecution().executedPlan().toString()
    assert sorted(permute(moved, level="cluster").take().select("o_orderkey").collect()) == sorted(df.select("o_orderkey").collect())


def test_positions_of_many_partitions(spark):
    from oblivspark.plans.shared import numbered

    df = spark.range(1000, numPartitions=7)
    got = numbered(df).orderBy("pos").collect()
    assert [r["pos"] for r in got] == list(range(1000)) == [r["id"] for r in got]


@pytest.mark.parametrize("merge", ["recursive", "layered"])
@pytest.mark.parametrize("ascending", [True, False])
def test_merge_of_a_bitonic_sequence(spark, merge, ascending):
    r = random.Random(4)
    for n, length, blocks in ((0, 16, 4), (1, 1, 4), (50, 64, 4), (300, 512, 8), (100, 128, 1)):
        vals = [r.randrange(1000) for _ in range(n)]
        half = n // 2
        if ascending:  # fillers are greater than all: they stand between the rising and the falling run
            at = [*range(half), *range(length - (n - half), length)]
            vals = sorted(vals[:half]) + sorted(vals[half:], reverse=True)
        else:  # less than all: a falling run, fillers, a rising run
            at = [*range(half), *range(length - (n - half), length)]
            vals = sorted(vals[:half], reverse=True) + sorted(vals[half:])
        df = spark.createDataFrame(list(zip(vals, at)), "v long, at long").repartition(3)
        got = sorts.bitonic_merge(df, ["v"], "at", length, merge=merge, ascending=ascending, blocks=blocks).orderBy("pos").collect()
        assert [x["pos"] for x in got] == list(range(n)) and [x["v"] for x in got] == sorted(vals, reverse=not ascending)


@pytest.mark.parametrize("form", ["recursive", "layered"])
@pytest.mark.parametrize("network", ["search", "bitonic"])
def test_pivot_router(spark, sf, form, network):
    df = permute(spark.read.parquet(f"{sf}/lineitem.parquet").select("l_partkey"), **S).take()
    pivots = sorts.choose_pivots(df, sorts.as_keys(["l_partkey"]), 6000, seed=3, sampler="bitonic" if form == "layered" else "engine")
    cuts = [(x["l_partkey"], x["_task"], x["_at"]) for x in pivots.orderBy("_p").collect()]
    assert len(cuts) > 2 and cuts == sorted(cuts)
    got = sorts.route_by_pivots(df, pivots, len(cuts), ["l_partkey"], form, network, tasks=8, gamma=2).collect()
    assert len(got) == 6000
    for x in got:
        assert x["_bin"] == sum(c < (x["l_partkey"], x["_task"], x["_at"]) for c in cuts)


def test_tree_memory_serves_batches(spark):
    """Against an array: reads see the memory before the batch, the least request number wins, foreign addresses read null; paths and evictions are public shapes."""
    from oblivspark.operators.tree_memory import TreeMemory

    r = random.Random(5)
    ref = [100 + i for i in range(37)]
    mem = TreeMemory(spark.createDataFrame(list(enumerate(ref)), "addr long, val long"), procs=2, **S)
    assert mem.height == 6 and mem.top == 1 and sorted(map(tuple, mem.dump().collect())) == list(enumerate(ref))
    for _ in range(2):
        req = [(i, r.choice("rw"), r.choice([r.randrange(37), 3, 40]), r.randrange(1000)) for i in range(8)]
        got = {x["i"]: x["val"] for x in mem.access(spark.createDataFrame(req, "i long, op string, addr long, val long")).collect()}
        assert got == {i: ref[a] if a < 37 else None for i, _, a, _ in req}
        done = set()
        for _, op, a, v in req:
            if op == "w" and a < 37 and a not in done:
                ref[a] = v
                done.add(a)
    assert sorted(map(tuple, mem.dump().collect())) == list(enumerate(ref))
    # as many paths as requests at every depth, and two different paths a subtree and batch, others each time
    shown = [x.groupBy("batch", "depth").count().first() for x in mem.seen]
    assert all(x["count"] == 8 for x in shown) and len(shown) == 2 * 7
    for _, d, ends in mem.evicted:
        assert len(set(ends)) == 2 and all(e < 1 << (d - 1) for e in ends)
    assert {e for b, d, ends in mem.evicted if d == 6 for e in ends} == {8, 24, 4, 20}


def test_guard(spark, sf):
    """Operators move rows by public numbers only; a plain join, or a column of a table named like a public one, doesn't pass."""
    orders, cust = (spark.read.parquet(f"{sf}/{x}.parquet") for x in ("orders", "customer"))
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        with trace.guarded(orders, cust) as g:
            primitives.send_receive(cust.select(F.col("c_custkey").alias("key"), "c_acctbal"), orders.select(F.col("o_custkey").alias("key"), "o_orderkey"), ["key"], ["c_acctbal"], **S)
            relational.group_aggregate(orders, ["o_orderstatus"], {"n": ("count", F.lit(1))}, small=0, **S)
        assert g.seen > 4
        with pytest.raises(trace.SecretExchange), trace.guarded():
            materialise(orders.join(cust, F.col("o_custkey") == F.col("c_custkey")))
        named = orders.select(F.col("o_custkey").alias("x"))
        with pytest.raises(trace.SecretExchange), trace.guarded(named):
            materialise(named.groupBy("x").count())
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_meter(spark):
    with trace.SparkMeter(spark) as m:
        spark.range(1000).repartition(3).count()
    assert m.cost["stages"] >= 2 and m.cost["exchanged_rows"] >= 1000 and m.cost["exchanged_bytes"] > 0 and m.cost["seconds"] > 0


def test_samples_and_shares(spark):
    df = spark.range(4000, numPartitions=3).withColumnRenamed("id", "v")
    a, b = (relational.sample(df, 0.25, seed=s).filter("is_real").count() for s in (1, 2))
    assert 850 < a < 1150 and 850 < b < 1150 and relational.sample(df, 0.25, seed=1).count() == 4000
    assert relational.quantiles(df.filter("1 = 0"), "v", [0.5], **S).count() == 0


def test_catalog_and_functions(spark, sf):
    from oblivspark import sources
    from oblivspark.plans import bounds, params

    sources.catalog(spark, sf, ["orders", "nation"])
    sources.register_functions(spark)
    n, z, b = spark.sql("SELECT count(*), router_slots(count(*)), router_bins(count(*)) FROM orders").first()
    assert (z, b) == (params.from_length(n).z, params.from_length(n).beta)
    with pytest.raises(ValueError):
        bounds.q_sort(1000, 8, 16)


def test_scratch(spark, sf):
    import os

    from oblivspark.plans.shared import scratch

    with scratch(spark) as held:
        n = sorts.oblivious_sort(spark.read.parquet(f"{sf}/orders.parquet").select("o_orderkey"), ["o_orderkey"], small=0, **S).count()
        assert n == 1500 and len(held) >= 2 and all(os.path.exists(p.removeprefix("file:")) for p in held)
    assert not any(os.path.exists(p.removeprefix("file:")) for p in held)
