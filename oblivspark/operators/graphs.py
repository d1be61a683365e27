"""Lists, trees and graphs: ranking, Euler tours, tree functions, contraction, components, lightest forests."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.codec import Key
from ..functions.kernels import coin_key
from ..plans.shared import dense_positions, discard, kept, materialise, ship_package
from .permute import permute
from .pram import pram_read, pram_write
from .primitives import propagate, send_receive
from .sorts import oblivious_sort

#: Up to this (public) number of nodes the rest of a list, and up to this number of nodes and edges a forest, is one task's: some 200 MB each.
TAIL, FOREST = 1 << 21, 1 << 22


# -- lists ------------------------------------------------------------------------------------------------------


def _tail(nodes: DataFrame) -> DataFrame:
    """(x, ahead) of nodes (x, s, w, b): one task. A step from x to s adds ``w``; a node without successor has ``b`` ahead."""

    def kernel(batches):
        parts = list(batches)
        if not sum(p.num_rows for p in parts):
            return
        t = pa.Table.from_batches(parts)
        x, s, w, b = t["x"].to_numpy(), t["s"].fill_null(-1).to_numpy(), t["w"].to_numpy(), t["b"].to_numpy()
        order = np.argsort(x)
        at = np.searchsorted(x[order], s)
        n = len(x)
        last = s < 0
        to = np.where(last, np.arange(n), order[np.minimum(at, n - 1)])
        ahead = np.where(last, 0, w)
        for _ in range(max(1, math.ceil(math.log2(max(n, 2))))):
            ahead = ahead + np.where(to == np.arange(n), 0, ahead[to])
            to = to[to]
        yield pa.record_batch([pa.array(x), pa.array(ahead + b[to])], names=["x", "ahead"])

    ship_package(nodes.sparkSession)
    return nodes.select("x", "s", "w", "b").coalesce(1).mapInArrow(kernel, "x long, ahead long")


def _jump(nodes: DataFrame, n: int) -> DataFrame:
    """Pointer doubling by joins on public ids: log n rounds over all nodes."""
    now = nodes.select("x", "s", F.when(F.col("s").isNull(), F.col("b")).otherwise(F.col("w")).alias("ahead"))
    for _ in range(max(1, math.ceil(math.log2(max(n, 2))) + 1)):
        other = now.select(F.col("x").alias("_x"), F.col("s").alias("_s"), F.col("ahead").alias("_a"))
        now = materialise(
            now.join(other, F.col("s") == F.col("_x"), "left").select("x", F.col("_s").alias("s"), (F.col("ahead") + F.coalesce("_a", F.lit(0))).alias("ahead")), "jump"
        )
    return now.select("x", "ahead")


def _contract(nodes: DataFrame, n: int, tail: int, seed: int) -> DataFrame:
    """Coins splice nodes out until a task can rank the rest; then they come back, latest first. About 4 n nodes are touched in all.

    Rounds are bounded by the length; where so many lists are left that one task can't hold them, doubling ranks the rest.
    """
    total, live, gone = n, nodes.select("x", "s", "w", "b"), []
    most = 0 if n <= tail else math.ceil(2.41 * math.log2(n / max(tail, 1))) + 8
    for step in range(most):
        coin = lambda c, k=step: F.pmod(F.xxhash64(F.lit(seed + k), c), F.lit(2))
        # y goes when its coin is 1 and its predecessor's is 0; what y has ahead goes over to the predecessor
        pred = live.filter((coin("x") == 0) & F.col("s").isNotNull() & (coin("s") == 1)).select(F.col("x").alias("p"), F.col("s").alias("y"), F.col("w").alias("pw"))
        told = materialise(live.join(pred, F.col("x") == F.col("y"), "left").select("x", "s", "w", "b", "p", "pw"), "spliced")
        if step:
            discard(live)
        out, left = materialise(told.filter(F.col("p").isNotNull()), "out"), told.filter(F.col("p").isNull()).select("x", "s", "w", "b")
        gone.append(out)
        mended = out.select(F.col("p").alias("_p"), F.col("s").alias("_s"), (F.col("pw") + F.col("w")).alias("_w"), (F.col("pw") + F.col("b")).alias("_b"), F.lit(True).alias("_m"))
        left = left.join(mended, F.col("x") == F.col("_p"), "left")
        pick = lambda c: F.when(F.col("_m"), F.col(f"_{c}")).otherwise(F.col(c)).alias(c)
        live = materialise(left.select("x", pick("s"), pick("w"), pick("b")), "live")
        discard(told)
        n = live.count()
        if n <= tail:
            break
    rank = kept(nodes.sparkSession, lambda: _tail(live) if n <= tail else _jump(live, total), "ranks")
    if gone:
        discard(live)
    for out in reversed(gone):
        own = out.join(rank.select(F.col("x").alias("_s"), F.col("ahead").alias("_a")), F.col("s") == F.col("_s"), "left")
        own = own.select("x", F.when(F.col("s").isNull(), F.col("b")).otherwise(F.col("w") + F.coalesce("_a", F.lit(0))).alias("ahead"))
        rank = rank.unionByName(materialise(own, "ranks"))
        discard(out)
    return rank


def list_rank(
    df: DataFrame, id_col: str, succ_col: str, weight: str | None = None, out: str = "ahead", ranker: str = "contract", tail: int = TAIL, seed: int | None = None, level: str = "memory", carry: list[str] | None = None, spent: tuple = (), **options
) -> DataFrame:
    """``df`` with the number (or weight) of nodes ahead of each in its list; the last has 0. Several lists may share the table.

    A successor of 0 or null ends a list; ids are from 1. Nodes are secretly permuted and take their new places for ids, each learns its
    successor's new id by send-receive, and a plain ranker runs on the permuted list: what it touches says nothing about the real ids.
    ``carry``: these columns of ``df`` (and no others) go along with the id, and rows come in the secret order, for callers that sort again anyway. ``spent``: written tables that nobody reads once the list is.
    """
    base = df.select(
        F.col(id_col).cast("long").alias("id"), F.when(F.col(succ_col) != 0, F.col(succ_col).cast("long")).alias("succ"), (F.lit(1).cast("long") if weight is None else F.col(weight).cast("long")).alias("wt"),
        *(F.col(c).alias(f"_carry{i}") for i, c in enumerate(carry or [])),
    )
    drawn = permute(base, seed=seed, level=level, **options)
    placed = kept(df.sparkSession, lambda: dense_positions(drawn.take(), [F.col("_task"), F.col("_at")], "x").drop("_task", "_at"), "list")
    n = drawn.n
    discard(drawn.df, *spent)
    senders = placed.select(F.col("id").alias("succ"), F.col("x").alias("s"), F.col("wt").alias("w"))
    linked = kept(df.sparkSession, lambda: send_receive(senders, placed.select("succ", "x"), ["succ"], ["s", "w"], restore=False, on_duplicate="first", seed=seed, level=level, **options), "list")
    nodes = linked.select("x", F.when(F.col("found"), F.col("s")).alias("s"), F.coalesce("w", F.lit(0)).alias("w"), F.lit(0).cast("long").alias("b"))
    if ranker == "jump":
        ranks = _jump(nodes, n)
    else:
        ranks = _contract(nodes, n, tail, int.from_bytes(coin_key(seed)[:7], "little"))
    back = placed.join(ranks, "x").select(F.col("id").alias(id_col), F.col("ahead").alias(out), *(F.col(f"_carry{i}").alias(c) for i, c in enumerate(carry or [])))
    if carry is not None:
        return back
    return send_receive(back, df, [id_col], [out], restore=False, on_duplicate="first", seed=seed, level=level, **options).drop("found")


# -- trees ------------------------------------------------------------------------------------------------------


def _tour(edges: DataFrame, seed: int | None = None, level: str = "memory", **options) -> DataFrame:
    """(id, u, v, su, sv, succ): each directed edge and the one that follows it, both also by id: 2 k + 1 and 2 k + 2 for the directions of row k.

    At u, the edge after (u, v) in the circle follows its twin (v, u); so a row that knows its right neighbour is all there is to tell about the twin.
    """
    k = F.monotonically_increasing_id() * 2
    rows = materialise(edges.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b"), k.alias("k")), "tour")
    there, back = F.struct(F.col("a").alias("u"), F.col("b").alias("v"), (F.col("k") + 1).alias("id")), F.struct(F.col("b").alias("u"), F.col("a").alias("v"), (F.col("k") + 2).alias("id"))
    both = rows.select(F.explode(F.array(there, back)).alias("e")).select("e.*")
    spark = edges.sparkSession
    placed = kept(spark, lambda: oblivious_sort(both, ["u", "v"], pos="p", seed=seed, level=level, **options), "tour")
    discard(rows)
    sorted_, placed = placed, materialise(propagate(placed, ["u"], F.struct("v", "id"), "first", "p"), "tour")
    discard(sorted_)
    right = placed.select((F.col("p") - 1).alias("_p"), F.col("u").alias("_u"), F.struct("v", "id").alias("_next"))
    circle = placed.join(right, F.col("p") == F.col("_p"), "left")
    circle = circle.withColumn("next", F.when(F.col("_u") == F.col("u"), F.col("_next")).otherwise(F.col("first")))
    twin = (F.col("id") - 1).bitwiseXOR(F.lit(1).cast("long")) + 1
    return circle.select(twin.alias("id"), F.col("v").alias("u"), F.col("u").alias("v"), F.col("u").alias("su"), F.col("next.v").alias("sv"), F.col("next.id").alias("succ"))


def euler_tour(edges: DataFrame, seed: int | None = None, level: str = "memory", **options) -> DataFrame:
    """(u, v, su, sv): for each direction of each edge of an unrooted tree (a, b), the directed edge that follows it in the tour.

    After (u, v) comes, at v, the edge after (v, u) in v's circle of neighbours in order.
    """
    return _tour(edges, seed, level, **options).select("u", "v", "su", "sv")


def tree_functions(edges: DataFrame, root: int, seed: int | None = None, level: str = "memory", **options) -> DataFrame:
    """(node, parent, depth, pre, post, size, is_leaf) of every node but an isolated root, the tree hung up at ``root``.

    The tour is cut where it would come back to its first edge; ranks order its edges, an edge goes down if it comes before its twin. Sorted by
    id, twins stand side by side and make one row a node; its place among those by the time of the way down is its preorder number (root 0),
    and both times give the rest: before the time t of the edge to the node with preorder number i, i - 1 edges went down and t - i + 1 up.
    """
    tour = kept(edges.sparkSession, lambda: _tour(edges, seed, level, **options), "tour")
    n = tour.count()
    start = tour.filter(F.col("u") == root).agg(F.min("v")).first()[0]
    if start is None:
        return edges.sparkSession.createDataFrame([(root, None, 0, 0, 0, 1, True)], "node long, parent long, depth long, pre long, post long, size long, is_leaf boolean")
    linked = tour.select("id", F.when((F.col("su") == root) & (F.col("sv") == start), F.lit(0)).otherwise(F.col("succ")).alias("succ"), "u", "v")
    ranks = lambda: list_rank(linked, "id", "succ", seed=seed, level=level, carry=["u", "v"], spent=(tour,), **options).select("id", "u", "v", (F.lit(n - 1) - F.col("ahead")).alias("t"))
    twins = kept(edges.sparkSession, lambda: oblivious_sort(ranks(), ["id"], pos="p", seed=seed, level=level, **options), "twins")
    both = twins.withColumn("k", F.shiftright("p", 1)).groupBy("k").agg(F.min(F.struct("t", "u", "v")).alias("down"), F.max("t").alias("tt"))
    nodes = both.select(F.col("down.v").alias("node"), F.col("down.u").alias("parent"), F.col("down.t").alias("t"), "tt")
    placed = oblivious_sort(nodes, ["t"], pos="p", seed=seed, level=level, **options)
    pre, size = F.col("p") + 1, F.shiftright(F.col("tt") - F.col("t") + 1, 1)
    below = placed.select("node", "parent", (2 * pre - F.col("t") - 1).alias("depth"), pre.alias("pre"), (F.col("t") + size - pre).alias("post"), size.alias("size"))
    top = edges.sparkSession.createDataFrame([(root, None, 0, 0, n // 2, n // 2 + 1)], "node long, parent long, depth long, pre long, post long, size long")
    return below.unionByName(top).withColumn("is_leaf", F.col("size") == 1)


#: The modulus of the sum-product ring, a prime below 2 ** 31, so that products fit in 64 bits. A fixed value.
PRIME = 2147483647


def contract_tree(nodes: DataFrame, leaves: int, ring: str = "sum_product", seed: int | None = None) -> int | None:
    """Value at the root of a full binary expression tree, by raking leaves: ceil(log2 leaves) + 1 phases, each half as long.

    ``nodes``: (id, parent, side, op, value, number): side 0 or 1 (null at the root), op ``+`` or ``*`` inside, value and number (1 ..
    ``leaves`` from left to right) at leaves. Every second leaf goes, first the left children, then the right ones, so that no two share
    a parent; its parent's operation and the pending linear map a x + b of both move into the sibling, which takes the parent's place.
    ``sum_product``: modulo a prime; ``max_plus``: ``+`` is the maximum and ``*`` the sum. Cells are relabelled at random first, then phases are joins on those labels.
    """
    mod = ring == "sum_product"
    wrap = (lambda c: F.pmod(c, F.lit(PRIME))) if mod else (lambda c: c)
    low = F.lit(-(1 << 60)).cast("long")
    one, zero = (F.lit(1).cast("long"), F.lit(0).cast("long")) if mod else (F.lit(0).cast("long"), low)
    times = (lambda x, y: wrap(x * y)) if mod else (lambda x, y: F.greatest(x + y, low))
    plus = (lambda x, y: wrap(x + y)) if mod else F.greatest
    key = coin_key(seed)
    a, b = (F.lit(int.from_bytes(key[i : i + 8], "little", signed=True)) for i in (0, 8))
    secret = lambda c: F.xxhash64(a, F.col(c), b)
    live = materialise(
        nodes.select(secret("id").alias("id"), F.when(F.col("parent").isNotNull(), secret("parent")).alias("parent"), "side", "op", F.col("value").cast("long").alias("value"), F.col("number").cast("long").alias("number"), one.alias("a"), zero.alias("b")),
        "tree",
    )
    for _ in range(max(0, math.ceil(math.log2(max(leaves, 1))) + (leaves > 1))):
        for side in (0, 1):
            raked = live.filter((F.col("number") % 2 == 1) & (F.col("side") == side)).select(
                F.col("id").alias("lid"), F.col("parent").alias("pid"), plus(times(F.col("a"), F.col("value")), F.col("b")).alias("v")
            )
            up = live.select(F.col("id").alias("pid"), F.col("parent").alias("gp"), F.col("side").alias("gside"), F.col("op").alias("pop"), F.col("a").alias("pa"), F.col("b").alias("pb"))
            plan = materialise(raked.join(up, "pid"), "raked")
            move = plan.select(F.col("pid").alias("_p"), "gp", "gside", "pop", "pa", "pb", "v", F.lit(1 - side).alias("_s"))
            rest = live.join(plan.select(F.col("lid").alias("_l")), F.col("id") == F.col("_l"), "left_anti").join(plan.select(F.col("pid").alias("_q")), F.col("id") == F.col("_q"), "left_anti")
            rest = rest.join(move, (F.col("parent") == F.col("_p")) & (F.col("side") == F.col("_s")), "left")
            hit = F.col("_p").isNotNull()
            # the sibling's x becomes pa * (a x + b op v) + pb
            ina = F.when(F.col("pop") == "+", F.col("a")).otherwise(times(F.col("a"), F.col("v")))
            inb = F.when(F.col("pop") == "+", plus(F.col("b"), F.col("v"))).otherwise(times(F.col("b"), F.col("v")))
            live = rest.select(
                "id", F.when(hit, F.col("gp")).otherwise(F.col("parent")).alias("parent"), F.when(hit, F.col("gside")).otherwise(F.col("side")).alias("side"), "op", "value", "number",
                F.when(hit, times(F.col("pa"), ina)).otherwise(F.col("a")).alias("a"), F.when(hit, plus(times(F.col("pa"), inb), F.col("pb"))).otherwise(F.col("b")).alias("b"),
            )
            live = materialise(live, "tree")
        live = live.withColumn("number", F.floor(F.col("number") / 2).cast("long"))
    last = live.filter("value is not null").select(plus(times(F.col("a"), F.col("value")), F.col("b")).alias("v")).collect()
    if len(last) != 1:
        raise ValueError("not a full binary tree with numbered leaves")
    return last[0][0]


# -- graphs -----------------------------------------------------------------------------------------------------


def rounds_for(n: int) -> int:
    """Rounds of star hooking that suffice for n nodes, whatever the graph."""
    return math.ceil(math.log(max(n, 2)) / math.log(1.5)) + 2


def _stars(d: np.ndarray) -> np.ndarray:
    """Whether each node's tree is a star."""
    star = np.ones(len(d), bool)
    deep = d[d] != d
    star[deep] = False
    star[d[d][deep]] = False
    return star & star[d]


def _hook(n: int, u: np.ndarray, v: np.ndarray, w: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
    """Parents, and edges used, after the fixed rounds: every star takes its least edge out (by weight, then number) and hooks along it."""
    small = np.int32 if max(n, len(u)) < 1 << 31 else np.int64
    d, used = np.arange(n, dtype=small), np.zeros(len(u), bool)
    by_key = key = np.arange(len(u), dtype=small)
    if w is not None:
        by_key = np.argsort(w, kind="stable").astype(small)
        key = np.empty_like(by_key)  # rank by weight and number
        key[by_key] = np.arange(len(u), dtype=small)
    for _ in range(rounds_for(n)):
        star = _stars(d)
        best = np.full(n, len(u), small)
        for a, b in ((u, v), (v, u)):
            out = star[a] & (d[a] != d[b])
            np.minimum.at(best, d[a[out]], key[out])
        roots = np.flatnonzero(best < len(u))
        e = by_key[best[roots]]
        other = np.where(d[u[e]] == roots, d[v[e]], d[u[e]])
        # two stars that chose one edge: the lesser stays a root
        mutual = (best[other] == best[roots]) & (roots < other)
        used[e] = True
        new = d.copy()
        new[roots[~mutual]] = other[~mutual]
        d = new[new]
    for _ in range(math.ceil(math.log2(max(n, 2)))):
        d = d[d]
    return d, used


def _forest_in_task(vertices: DataFrame, edges: DataFrame, weighted: bool) -> DataFrame:
    """One task: rows (kind, a, b): kind 0 a node with its component's least node, kind 1 (``weighted``) a forest edge's number."""
    both = vertices.select(F.lit(0).alias("kind"), F.col("id").alias("a"), F.lit(0).cast("long").alias("b"), F.lit(0).cast("long").alias("w"), F.lit(0).cast("long").alias("e"))
    more = edges.select(F.lit(1).alias("kind"), F.col("u").alias("a"), F.col("v").alias("b"), (F.col("w") if weighted else F.lit(0)).cast("long").alias("w"), F.col("e").cast("long").alias("e"))

    def kernel(batches):
        nodes, cols = [np.empty(0, np.int64)], {c: [np.empty(0, np.int64)] for c in ("a", "b", *(("w", "e") if weighted else ()))}
        for batch in batches:
            edge = batch.column(0).to_numpy() == 1
            nodes.append(batch.column(1).to_numpy()[~edge])
            for c in cols:
                cols[c].append(batch.column(batch.schema.get_field_index(c)).to_numpy()[edge])
        ids = np.unique(np.concatenate(nodes))
        if not len(ids):
            return
        nodes.clear()
        if weighted:
            e = np.concatenate(cols.pop("e"))
            order = np.argsort(e, kind="stable")
            e, w = e[order], np.concatenate(cols.pop("w"))[order]
        ends = []
        for c in ("a", "b"):
            at = np.searchsorted(ids, np.concatenate(cols.pop(c))).astype(np.int32 if len(ids) < 1 << 31 else np.int64)
            ends.append(at[order] if weighted else at)
        d, used = _hook(len(ids), *ends, w if weighted else None)
        least = np.full(len(ids), len(ids))
        np.minimum.at(least, d, np.arange(len(ids)))
        out = [(0, ids, ids[least[d]])]
        if weighted:
            out.append((1, e[used], np.zeros(used.sum(), np.int64)))
        for kind, x, y in out:
            for i in range(0, len(x), 1 << 16):
                x_, y_ = x[i : i + (1 << 16)], y[i : i + (1 << 16)]
                yield pa.record_batch([pa.array(np.full(len(x_), kind, np.int32)), pa.array(x_), pa.array(y_)], names=["kind", "a", "b"])

    ship_package(vertices.sparkSession)
    return both.unionByName(more).coalesce(1).mapInArrow(kernel, "kind int, a long, b long")


def _least_neighbour_steps(vertices: DataFrame, edges: DataFrame, rounds: int | str, **options) -> tuple[DataFrame, DataFrame | None]:
    """(addr, val), and the edges e that stars took: the star-hooking rounds as memory steps, every read and write a sort: for inputs beyond one task.

    ``rounds``: a number, or ``until_stable``, which stops when no edge joins two trees and so shows how many rounds the graph took.
    """
    limit = rounds_for(vertices.count()) if rounds == "until_stable" else rounds
    d = materialise(vertices.select(F.col("id").alias("addr"), F.col("id").alias("val")), "parents")
    ask = lambda mem, rows, at, out: pram_read(mem, rows.withColumn("addr", F.col(at)), **options).withColumnRenamed("val", out).drop("found", "addr")
    arcs = edges.select(F.explode(F.array(F.struct("u", "v", "e"), F.struct(F.col("v").alias("u"), F.col("u").alias("v"), "e"))).alias("x")).select("x.*")
    arcs, used = materialise(arcs.withColumn("proc", F.monotonically_increasing_id()), "arcs"), None
    for _ in range(limit):
        own = d.select(F.col("addr").alias("proc"), F.col("addr").alias("n"), F.col("val").alias("p"))
        own = materialise(ask(d, own, "p", "g"), "stars")
        deep = own.select("proc", F.when(F.col("p") != F.col("g"), F.col("n")).alias("addr"), F.lit(0).cast("long").alias("val")).unionByName(
            own.select("proc", F.when(F.col("p") != F.col("g"), F.col("g")).alias("addr"), F.lit(0).cast("long").alias("val"))
        )
        flag = materialise(pram_write(d.select("addr", F.lit(1).cast("long").alias("val")), deep, "min", **options), "flags")
        own = materialise(ask(flag, ask(flag, own, "n", "s1"), "p", "s2"), "stars")
        star = own.select(F.col("n").alias("addr"), F.least("s1", "s2").alias("val"))
        a = materialise(ask(star, ask(d, ask(d, arcs, "u", "du"), "v", "dv"), "u", "st"), "arcs-now")
        if rounds == "until_stable" and a.filter(F.col("du") != F.col("dv")).isEmpty():
            break
        tries = a.select("proc", F.when((F.col("st") == 1) & (F.col("du") != F.col("dv")), F.col("du")).alias("addr"), F.col("e").alias("val"))
        none = d.select("addr", F.lit(None).cast("long").alias("val"))
        best = materialise(pram_write(none, tries, "min", **options), "best")
        taken = best.select(F.col("val").alias("e"))  # one row a vertex, null where it is no star's root or has no edge out
        used = taken if used is None else used.unionByName(taken)
        c = materialise(ask(best, ask(best, a, "du", "mine"), "dv", "theirs"), "choice")
        go = (F.col("mine") == F.col("e")) & ~((F.col("theirs") == F.col("mine")) & (F.col("du") < F.col("dv"))).eqNullSafe(F.lit(True))
        hooks = c.select("proc", F.when(go & (F.col("st") == 1) & (F.col("du") != F.col("dv")), F.col("du")).alias("addr"), F.col("dv").alias("val"))
        d = materialise(pram_write(d, hooks, "priority", **options), "parents")
        d = materialise(ask(d, d.select(F.col("addr").alias("n"), "val", F.col("addr").alias("proc")).withColumnRenamed("val", "p"), "p", "g").select(F.col("n").alias("addr"), F.col("g").alias("val")), "parents")
    return d, used


def connected_components(vertices: DataFrame, edges: DataFrame, tail: int = FOREST, rounds: int | str | None = None, **options) -> DataFrame:
    """(id, component): the least vertex of each vertex's component. ``vertices``: (id), each once; ``edges``: (u, v).

    Star hooking for a number of rounds that only the number of vertices fixes, each read and write of the parent array a sort
    and a scan. Up to ``tail`` rows in all one task holds the array.
    """
    e = edges.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"))
    v = vertices.select(F.col("id").cast("long").alias("id"))
    n, m = v.count(), e.count()
    numbered = e.withColumn("e", F.monotonically_increasing_id())
    if n + m <= tail:
        out = _forest_in_task(v, numbered, False)
        return out.filter("kind = 0").select(F.col("a").alias("id"), F.col("b").alias("component"))
    d, _ = _least_neighbour_steps(v, materialise(numbered, "edges"), rounds or rounds_for(n), **options)
    for _ in range(math.ceil(math.log2(max(n, 2)))):
        got = pram_read(d, d.select(F.col("addr").alias("n"), F.col("val").alias("addr")), **options)
        d = materialise(got.select(F.col("n").alias("addr"), "val"), "parents")
    least = pram_write(d.select("addr", F.col("addr").alias("val")), d.select(F.col("addr").alias("proc"), F.col("val").alias("addr"), F.col("addr").alias("val")), "min", **options)
    got = pram_read(least, d.select(F.col("addr").alias("n"), F.col("val").alias("addr")), **options)
    return got.select(F.col("n").alias("id"), F.col("val").alias("component"))


def min_spanning_forest(vertices: DataFrame, edges: DataFrame, tail: int = FOREST, rounds: int | str | None = None, **options) -> DataFrame:
    """The rows of ``edges`` (u, v, w, e) in the lightest spanning forest, ties by the edge number e.

    Each star takes its lightest edge out by a min-combining write. Up to ``tail`` rows in all one task holds the parent array.
    Beyond that edges are sorted obliviously, so that the place is one key for weight and number, the rounds of
    ``connected_components`` run as memory steps, and the edges that stars took are marked by send-receive.
    """
    v = vertices.select(F.col("id").cast("long").alias("id"))
    e = edges.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"), F.col("w").cast("long").alias("w"), F.col("e").cast("long").alias("e"))
    n = v.count()
    if n + e.count() <= tail:
        used = _forest_in_task(v, e, True).filter("kind = 1").select(F.col("a").alias("e"))
        return e.join(F.broadcast(used), "e", "left_semi")
    placed = materialise(oblivious_sort(e, ["w", "e"], pos="_place", **options), "edges")
    numbered = placed.select("u", "v", F.col("_place").alias("e"))
    _, used = _least_neighbour_steps(v, numbered, rounds or rounds_for(n), **options)
    if used is None:
        return e.filter("1 = 0")
    marks = used.select(F.coalesce("e", F.lit(-1)).alias("_place"), F.lit(True).alias("_used"))  # as many rows as vertices times rounds, whatever the graph
    got = send_receive(marks, placed, ["_place"], ["_used"], restore=False, on_duplicate="first", **options)
    return got.filter(F.col("found")).select("e", "u", "v", "w")
