"""A large memory for few processors: trees of position labels as tables, pools, one path a request, two evictions a subtree.

Depth i of log2(cells) keeps, for each address prefix of i bits, the current leaves of its two children one depth on; the last depth
keeps the data. Every depth has a tree with 2^i leaves, whose first ``top`` levels are one pool. All tables go by public numbers: of nodes, slots and rows.
"""

from __future__ import annotations

import itertools
import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from ..functions.codec import Key
from ..functions.kernels import coin_key, coins
from ..plans.shared import materialise, ship_package
from .pram import RULES, Step, run_pram, winners
from .primitives import propagate, segmented_aggregates, send_receive, transpose
from .sorts import oblivious_sort

#: Slots of a node; rows that a pool has room for, as a multiple of the asked cells of a batch.
BUCKET, POOL = 4, 4
#: Up to so many cells (a public number) all depths are one task's at the cluster level, which hides only what leaves a task.
LEAN = 1 << 21
#: Rows of a memory that a task hands on at a time.
PIECE = 1 << 16


class PoolOverflow(RuntimeError):
    """A pool outgrew its bound; an event of small probability."""


def veb_place(node: np.ndarray, height: int) -> np.ndarray:
    """Place of nodes (breadth-first numbers from 1) of a full tree of ``height`` levels in the recursive layout: top half first, then each bottom tree."""
    node = np.asarray(node, np.int64)
    if height <= 1 or not len(node):
        return np.zeros(len(node), np.int64)
    top = height // 2
    bottom = height - top
    level = np.frexp(node.astype(np.float64))[1] - 1
    out = np.empty(len(node), np.int64)
    above = level < top
    out[above] = veb_place(node[above], top)
    low, at = node[~above], level[~above] - top
    root = low >> at
    own = low - (root << at) + (1 << at)  # its number in the bottom tree
    out[~above] = (1 << top) - 1 + (root - (1 << top)) * ((1 << bottom) - 1) + veb_place(own, bottom)
    return out


def veb_index(height: int) -> np.ndarray:
    """The places of all nodes, by breadth-first number."""
    return np.concatenate((np.zeros(1, np.int64), veb_place(np.arange(1, 1 << height), height)))


def path_blocks(height: int, block: int, layout: str = "veb") -> float:
    """Blocks of ``block`` nodes that a path from the root to a leaf touches, on average over all leaves."""
    leaves = np.arange(1 << (height - 1), 1 << height)
    nodes = np.stack([leaves >> i for i in range(height)])
    place = veb_index(height)[nodes] if layout == "veb" else nodes - 1
    return float(np.mean([len(np.unique(c)) for c in (place // block).T]))


def reversed_bits(x: int, bits: int) -> int:
    return int(format(x % (1 << bits), f"0{bits}b")[::-1], 2) if bits else 0


def _ranks(group: np.ndarray) -> np.ndarray:
    """The place of each among its equals, in the order given."""
    by = np.argsort(group, kind="stable")
    i = np.arange(len(group))
    new = np.concatenate(([True], np.diff(group[by]) != 0))[: len(group)]
    out = np.empty(len(group), np.int64)
    out[by] = i - np.maximum.accumulate(np.where(new, i, 0))
    return out


@dataclass(frozen=True)
class _OneTask:
    """All depths of a memory within a task: what ``_build``, ``_step`` and ``_evict`` do with tables, on arrays of the entries alone.

    An entry is (at, prefix, leaf, c0, c1, val): its slot (node times ``bucket`` and place) or -1 for the pool, labels, and where its value stands.
    """

    height: int
    top: int
    bucket: int
    room: int
    key: bytes

    def coin(self, depth: int, prefix: np.ndarray, batch: int, dummy: bool = False) -> np.ndarray:
        drawn = coins(prefix.astype(np.uint64), 1, self.key, (batch << 8) + (depth << 1) + dummy)[:, 0]
        return (drawn & np.uint64((1 << depth) - 1)).astype(np.int64)

    def build(self, depth: int) -> dict[str, np.ndarray]:
        """Entries sink to any node of their path that has room, the others go to the pool; values stand at their addresses."""
        prefix = np.arange(1 << depth)
        last, none = depth == self.height, np.full(1 << depth, -1)
        e = {"at": none.copy(), "prefix": prefix, "leaf": self.coin(depth, prefix, 0), "val": prefix if last else none}
        e |= {f"c{side}": none if last else self.coin(depth + 1, 2 * prefix + side, 0) for side in (0, 1)}
        left = prefix
        for up in range(max(0, depth - self.top)):
            node = (e["leaf"][left] + (1 << depth)) >> up
            slot = _ranks(node)
            fits = slot < self.bucket
            e["at"][left[fits]] = node[fits] * self.bucket + slot[fits]
            left = left[~fits]
        return e

    def fetch(self, depth: int, e: dict[str, np.ndarray], want: np.ndarray, leaf: np.ndarray) -> np.ndarray:
        """Where the entries of the asked prefixes are, in the pool or on the path to a leaf; -1 where they are in neither."""
        pool = np.flatnonzero(e["at"] < 0)
        pool = pool[np.argsort(e["prefix"][pool])]
        i = np.minimum(np.searchsorted(e["prefix"][pool], want), max(len(pool) - 1, 0))
        found = np.where(e["prefix"][pool][i] == want, pool[i], -1) if len(pool) else np.full(len(want), -1)
        if depth > self.top:
            slots = np.full((2 << depth, self.bucket), -1, np.int32)
            held = np.flatnonzero(e["at"] >= 0)
            slots.ravel()[e["at"][held]] = held
            for up in range(depth - self.top):
                for there in slots[(leaf + (1 << depth)) >> up].T:
                    found = np.where((there >= 0) & (e["prefix"][there] == want), there, found)
        return found

    def evict(self, depth: int, e: dict[str, np.ndarray], moving: np.ndarray, ends: list[int], bound: int) -> np.ndarray:
        """New slots: what is in the pool, was asked for (``moving``) or lies on two paths a subtree sinks to the deepest node that its own path shares with one of them, while there is room.

        Of the pool only ``bound`` entries are kept; -2 marks the others.
        """
        bits, at = depth - self.top, e["at"].copy()
        node = at // self.bucket
        level = np.frexp(np.maximum(node, 1).astype(np.float64))[1] - 1
        inside = node & ((1 << np.maximum(level - self.top, 0)) - 1)
        out = moving | (at < 0)
        for end in ends:
            out |= (at >= 0) & (inside == end >> (depth - level))
        own, deep = e["leaf"] & ((1 << bits) - 1), np.zeros(len(at), np.int64)
        for end in ends:
            deep = np.maximum(deep, bits - np.frexp((own ^ end).astype(np.float64))[1])
        at[out] = -1
        go = np.flatnonzero(out & (deep > 0))
        go = go[np.argsort(e["prefix"][go])]
        to = (e["leaf"][go] + (1 << depth)) >> (bits - deep[go])
        slot = _ranks(to)
        fits = slot < self.bucket
        at[go[fits]] = to[fits] * self.bucket + slot[fits]
        pool = np.flatnonzero(at == -1)
        at[pool[np.argsort(e["prefix"][pool])[bound:]]] = -2
        return at

    def serve(self, batches, batch: int, ends: dict[int, list[int]], empty: pa.Schema):
        """A batch's requests (k, addr, new, written), in order, one an address and fillers behind them, then the entries depth by depth: yields the new entries, what is served, the leaves shown.

        One depth is held at a time.
        """
        depths = _by_depth(batches)
        d, asks = next(depths, (0, None))
        if d >= 0:  # no requests
            depths, asks = ([] if asks is None else itertools.chain([(d, asks)], depths)), pa.Table.from_batches([], empty)
        k, p, new = asks["k"].to_numpy(), len(asks), asks["new"]
        column = asks["addr"].combine_chunks()
        addr = column.drop_null().to_numpy()
        written = asks["written"].fill_null(False).to_numpy()[: len(addr)]
        del asks
        leaf, there, values = np.zeros(len(addr), np.int64), np.ones(len(addr), bool), pa.nulls(p, new.type)
        for d, t in depths:
            e = {c: t[c].fill_null(-1).to_numpy() for c in ENTRY}
            e = {c: x if x.flags.writeable else x.copy() for c, x in e.items()}
            held, n = t["val"], len(t)
            del t
            prefix = addr >> (self.height - d)
            first = np.concatenate(([True], np.diff(prefix) != 0))[: len(addr)]
            group = np.cumsum(first) - 1
            want, path = prefix[first], leaf[first]
            look = self.coin(d, k, batch, True)
            look[: len(addr)][first] = path
            for i in range(0, p, PIECE):
                yield self.rows(2, pa.nulls(1, new.type), depth=[d], prefix=[i], shown=pa.array([look[i : i + PIECE]], pa.list_(pa.int64())))
            got = self.fetch(d, e, want, path)
            there &= (got >= 0)[group]
            old = {c: e[c][got][group] for c in ("c0", "c1")}
            moving = np.zeros(n, bool)
            moving[got] = True
            e["leaf"][got] = self.coin(d, want, batch)
            if d < self.height:
                bit = addr >> (self.height - d - 1) & 1
                last = np.concatenate((first[1:], [True]))[: len(addr)]
                for side, end in ((0, first), (1, last)):  # the least address of a prefix is below its left child if any is, the greatest below its right one
                    at = bit[end] == side
                    e[f"c{side}"][got[at]] = self.coin(d + 1, 2 * want[at] + side, batch)
                leaf = np.where(bit == 0, old["c0"], old["c1"])
            else:
                vals = pa.chunked_array([*held.chunks, *new.chunks], new.type)
                source = np.full(p, -1)
                source[: len(addr)] = np.where(there, got[group], -1)
                values = vals.take(pa.array(source, pa.int64(), mask=source < 0)).combine_chunks()
                val = np.arange(n)
                val[got] = np.where(written, n + np.arange(len(addr)), got)
                held = vals.take(pa.array(val, pa.int64()))
            if d > self.top:
                e["at"] = self.evict(d, e, moving, ends[d], min(1 << d, max(self.room, POOL * p)))
            kept = np.flatnonzero(e["at"] > -2)
            for i in range(0, len(kept), PIECE):
                now = kept[i : i + PIECE]
                yield self.rows(0, held.take(pa.array(now)), depth=np.full(len(now), d), **{c: x[now] for c, x in e.items()})
        flags = np.concatenate((there, np.ones(p - len(addr), bool)))
        for i in range(0, p, PIECE):
            here = slice(i, min(i + PIECE, p))
            yield self.rows(1, values[here], depth=np.full(here.stop - i, -1), addr=column[here], there=flags[here])

    @staticmethod
    def rows(kind: int, val: pa.Array, **given) -> pa.RecordBatch:
        """Rows of one kind: entries (0), what is served (1), leaves shown from the place ``prefix`` on (2)."""
        val = val.combine_chunks() if isinstance(val, pa.ChunkedArray) else val
        kinds = {"depth": pa.int64(), **dict.fromkeys(ENTRY, pa.int64()), "val": val.type, "addr": pa.int64(), "there": pa.bool_(), "shown": pa.list_(pa.int64())}
        cols = {c: val if c == "val" else pa.array(given[c], x) if c in given else pa.nulls(len(val), x) for c, x in kinds.items()}
        return pa.record_batch({"kind": pa.array(np.full(len(val), kind)), **cols})


def _by_depth(batches):
    """(depth, table) of batches in the order of their first column."""
    now, held = None, []
    for b in batches:
        depth = b.column(0).to_numpy()
        cuts = [0, *(np.flatnonzero(np.diff(depth)) + 1), len(depth)]
        for i, j in zip(cuts, cuts[1:]):
            if i == j:
                continue
            if held and depth[i] != now:
                yield now, pa.Table.from_batches(held)
                held = []
            now = int(depth[i])
            held.append(b.slice(i, j - i))
    if held:
        yield now, pa.Table.from_batches(held)


#: Columns of an entry but its depth and value.
ENTRY = ("at", "prefix", "leaf", "c0", "c1")


class TreeMemory:
    """``cells`` (addr 0 .. n - 1, val) served in batches of requests; reads see the memory before the batch's writes.

    Of several writes to a cell a batch's rule picks one or combines them; what it gives replaces the value. ``top``: levels of each tree that its pool stands for, log2 of the processors where they are few. ``seen`` has, for each batch and depth, the leaves that
    were shown to whoever watches, as (batch, depth, k, leaf), and ``evicted`` the leaves of the evicted paths. Node numbers in ``layout`` order cluster the files.
    """

    def __init__(self, mem: DataFrame, procs: int = 64, top: int | None = None, bucket: int = BUCKET, layout: str = "veb", seed: int | None = None, level: str = "memory", lean: int = LEAN, **options):
        self.spark, self.bucket, self.layout = mem.sparkSession, bucket, layout
        self.cells = mem.count()
        self.height = max(1, math.ceil(math.log2(max(self.cells, 2))))
        self.top = min(self.height - 1, max(0, math.ceil(math.log2(max(procs, 1))) if top is None else top))
        self.options = {"seed": seed, "level": level, **options}
        key = coin_key(seed)
        self.key = [int.from_bytes(key[i : i + 8], "little", signed=True) for i in (0, 8)]
        self.batch, self.seen, self.evicted = 0, [], []
        self.room = POOL * max(procs, 16)
        self.pools: list[DataFrame] = []
        self.sizes: list[int] = []
        self.trees: list[DataFrame | None] = []
        self.lean = _OneTask(self.height, self.top, bucket, self.room, key) if level == "cluster" and self.cells <= lean else None
        if self.lean:
            self.state = self._built(mem)
            return
        for d in range(self.height + 1):
            prefix = F.col("id")
            child = lambda side, d=d: self._coin(d + 1, F.col("id") * 2 + side, 0) if d < self.height else F.lit(None).cast("long")
            rows = self.spark.range(1 << d).select(prefix.alias("prefix"), self._coin(d, prefix, 0).alias("leaf"), child(0).alias("c0"), child(1).alias("c1"))
            if d == self.height:
                rows = rows.join(mem.select(F.col("addr").alias("prefix"), F.col("val")), "prefix", "left")
            else:
                rows = rows.withColumn("val", F.lit(None).cast(mem.schema["val"].dataType))
            self._build(d, rows)

    # -- labels and paths -------------------------------------------------------------------------------------------

    def _coin(self, depth: int, prefix: Column, batch: int) -> Column:
        """The leaf that a prefix gets in a batch: a keyed hash, drawn once for each of them."""
        return F.pmod(F.xxhash64(F.lit(self.key[0]), F.lit(batch), F.lit(depth), prefix, F.lit(self.key[1])), F.lit(1 << depth))

    def _dummy(self, depth: int) -> Column:
        return F.pmod(F.xxhash64(F.lit(self.key[1]), F.lit(self.batch), F.lit(depth), F.lit("path"), F.col("k"), F.lit(self.key[0])), F.lit(1 << depth))

    def _eviction_leaves(self, depth: int) -> list[int]:
        """The two leaves within each subtree, in the order of bit-reversed numbers; no two neighbours of that order are equal."""
        bits = depth - self.top
        return [reversed_bits(2 * self.batch + j, bits) for j in (0, 1)]

    def _clustered(self, rows: DataFrame, depth: int) -> DataFrame:
        """Rows of a tree with ``at``, their node's place in the layout, in files by range of it."""
        height, layout = depth + 1, self.layout
        fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema.fields)

        def kernel(batches):
            for b in batches:
                node = b.column(b.schema.get_field_index("node")).to_numpy()
                at = veb_place(node, height) if layout == "veb" else node - 1
                yield pa.record_batch([*b.columns, pa.array(at, pa.int64())], names=[*b.schema.names, "at"])

        ship_package(self.spark)
        parts = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        size = -(-(1 << height) // parts)  # public: a file holds the nodes of a stretch of the layout
        placed = rows.mapInArrow(kernel, f"{fields}, at long")
        return placed.repartitionById(parts, F.floor(F.col("at") / size).cast("int")).sortWithinPartitions("at", "slot").drop("at")

    # -- all depths in one task -----------------------------------------------------------------------------------------

    def _entries(self, val: str) -> str:
        return f"depth long, {', '.join(f'{c} long' for c in ENTRY)}, val {val}"

    def _built(self, mem: DataFrame) -> DataFrame:
        lean, kind = self.lean, mem.schema["val"].dataType.simpleString()

        def kernel(batches):
            t = pa.Table.from_batches(list(batches), empty)
            addr = t["addr"].to_numpy()
            place = np.full(1 << lean.height, -1)
            place[addr] = np.arange(len(addr))
            for d in range(lean.height + 1):
                e = lean.build(d)
                at = place[e["val"]] if d == lean.height else e["val"]
                yield from pa.table({"depth": np.full(1 << d, d), **{c: e[c] for c in ENTRY}, "val": t["val"].take(pa.array(at, pa.int64(), mask=at < 0))}).to_batches(1 << 16)

        cells = mem.select(F.col("addr").cast("long").alias("addr"), "val")
        empty = to_arrow_schema(cells.schema)
        ship_package(self.spark)
        return materialise(cells.coalesce(1).mapInArrow(kernel, self._entries(kind)), "memory")

    def _served(self, asks: DataFrame) -> DataFrame:
        """(addr, val): a batch's requests, one an address, in one task."""
        lean, batch, kind = self.lean, self.batch, self.state.schema["val"].dataType.simpleString()
        ends = {d: self._eviction_leaves(d) for d in range(self.top + 1, self.height + 1)}
        asked = materialise(asks.select(F.lit(-1).cast("long").alias("depth"), "k", "addr", "new", "written"), "asks")
        both = asked.unionByName(self.state, allowMissingColumns=True)
        empty = to_arrow_schema(both.schema)
        out = both.coalesce(1).sortWithinPartitions("depth", "k").mapInArrow(lambda batches: lean.serve(batches, batch, ends, empty), f"kind long, {self._entries(kind)}, addr long, there boolean, shown array<long>")
        out = materialise(out, "memory")
        self.state = out.filter("kind = 0").select("depth", *ENTRY, "val")
        for r in self.state.groupBy("depth").count().collect():
            if r["count"] != 1 << r["depth"]:
                raise PoolOverflow(f"{(1 << r['depth']) - r['count']} entries had no room in the pool of depth {r['depth']}")
        served = out.filter("kind = 1")
        if served.filter(~F.col("there")).limit(1).count():
            raise KeyError("a cell is lost")
        for d in range(self.height + 1):
            leaves = out.filter((F.col("kind") == 2) & (F.col("depth") == d)).select("prefix", F.posexplode("shown").alias("k", "leaf"))
            self.seen.append(leaves.select(F.lit(batch).alias("batch"), F.lit(d).alias("depth"), (F.col("prefix") + F.col("k")).alias("k"), "leaf"))
        self.evicted += [(batch, d, tuple(x)) for d, x in ends.items()]
        return served.select("addr", "val")

    # -- eviction -----------------------------------------------------------------------------------------------------

    def _build(self, depth: int, entries: DataFrame) -> None:
        """In the open, for labels are fresh and nothing has been asked: entries sink to any node of their path that has room, the others go to the pool."""
        if depth <= self.top:
            self.trees.append(None)
            self.pools.append(materialise(entries, "pool"))
            self.sizes.append(1 << depth)
            return
        low, left, kept = 1 << depth, materialise(entries.withColumn("node", F.col("leaf") + (1 << depth)), "building"), None
        for up in range(depth - self.top):
            rank = F.row_number().over(Window.partitionBy("_n").orderBy("prefix")) - 1
            ranked = materialise(left.withColumn("_n", F.shiftright("node", up)).withColumn("slot", rank), "building")
            mine = ranked.filter(F.col("slot") < self.bucket).select(F.col("_n").alias("node"), "slot", "prefix", "leaf", "c0", "c1", "val")
            kept = mine if kept is None else kept.unionByName(mine)
            left = ranked.filter(F.col("slot") >= self.bucket).drop("_n", "slot")
            if left.isEmpty():
                break
        first = 1 << (self.top + 1)
        slots = self.spark.range(first * self.bucket, 2 * low * self.bucket).select(F.floor(F.col("id") / self.bucket).alias("node"), (F.col("id") % self.bucket).cast("int").alias("slot"))
        full = slots.join(kept, ["node", "slot"], "left").select("node", "slot", "prefix", "leaf", "c0", "c1", "val")
        self.trees.append(materialise(self._clustered(full, depth), "tree"))
        self.pools.append(None)
        self.sizes.append(left.count())
        self._pool(depth, left.drop("node"), self.sizes[depth], 0)

    def _evict(self, depth: int, entries: DataFrame, tree: DataFrame, p: int) -> None:
        """Entries (fillers have no prefix) and what two paths a subtree hold go as deep into those paths as they may, the others into the pool.

        One oblivious sort brings entries to the deepest node that their own path shares with an evicted one, followed by that node's own fillers, and a scan ranks them: each
        node of the paths gets exactly as many rows as it has slots.
        """
        low, bits = 1 << depth, depth - self.top
        ends = self._eviction_leaves(depth)
        node_level = F.floor(F.log2(F.col("node").cast("double")) + 1e-9).cast("int")
        inside = lambda level: F.col("node") - F.shiftleft(F.shiftright(F.col("node"), level - self.top), level - self.top)
        on = F.lit(False)
        for e in ends:
            for level in range(self.top + 1, depth + 1):
                on = on | ((node_level == level) & (inside(level) == (e >> (depth - level))))
        touched = (1 << self.top) * sum(len({e >> (depth - level) for e in ends}) for level in range(self.top + 1, depth + 1)) * self.bucket
        # an entry sinks to the deepest node that one of its subtree's two paths shares with its own
        own = F.col("leaf") - F.shiftleft(F.shiftright("leaf", bits), bits)
        deep = F.lit(0)
        for e in ends:
            apart = own.bitwiseXOR(F.lit(e))
            deep = F.greatest(deep, F.lit(bits) - F.when(apart == 0, 0).otherwise(F.floor(F.log2(apart.cast("double")) + 1e-9).cast("int") + 1))
        moving = entries.unionByName(tree.filter(on).drop("node", "slot")).withColumn("_leafnode", F.col("leaf") + low).withColumn("_up", (F.lit(bits) - deep).cast("int"))
        moving = moving.withColumn("node", F.when(F.col("prefix").isNotNull() & (F.col("_up") < bits), F.expr("shiftright(_leafnode, _up)"))).drop("_leafnode", "_up").withColumn("kind", F.lit(0))
        rows = moving.unionByName(tree.filter(on).select("node", F.lit(1).alias("kind")), allowMissingColumns=True)
        n = self.sizes[depth] + p + 2 * touched
        rows = materialise(oblivious_sort(rows, [Key("node", True, False), Key("kind"), Key("prefix", True, False)], pos="_p", n=n, **self.options), "evicting")
        rows = materialise(segmented_aggregates(rows, ["node"], {"slot": ("count", F.lit(1))}, False, "prefix", "_p", n=n), "evicting")
        here = F.col("node").isNotNull() & (F.col("slot") < self.bucket)
        placed = rows.filter(here).select("node", F.col("slot").cast("int").alias("slot"), "prefix", "leaf", "c0", "c1", "val")
        self.trees[depth] = materialise(self._clustered(tree.filter(~on).unionByName(placed), depth), "tree")
        self._pool(depth, rows.filter(~here).select("prefix", "leaf", "c0", "c1", "val"), n - touched, p)
        self.evicted.append((self.batch, depth, tuple(ends)))

    def _pool(self, depth: int, rows: DataFrame, n: int, p: int) -> None:
        """Clean-up: fillers go to the end and are cut off at the pool's public bound."""
        bound = min(1 << depth, max(self.room, POOL * p))
        if n > bound:
            rows = oblivious_sort(rows, [Key("prefix", True, False)], pos="_p", n=n, **self.options).filter(F.col("_p") < bound).drop("_p")
        self.pools[depth], self.sizes[depth] = materialise(rows, "pool"), min(n, bound)

    def _check(self) -> None:
        """Every depth still has all its entries: one count a batch."""
        held = None
        for d in range(self.top + 1, self.height + 1):
            for part in (self.pools[d], self.trees[d]):
                one = part.select(F.lit(d).alias("d"), F.col("prefix").isNotNull().cast("long").alias("n"))
                held = one if held is None else held.unionByName(one)
        if held is None:
            return
        for r in held.groupBy("d").agg(F.sum("n").alias("n")).collect():
            if r["n"] != 1 << r["d"]:
                raise PoolOverflow(f"{(1 << r['d']) - r['n']} entries had no room in the pool of depth {r['d']}")

    # -- a batch ------------------------------------------------------------------------------------------------------

    def access(self, requests: DataFrame, rule: str = "priority") -> DataFrame:
        """(i, val) for ``requests`` (i, op, addr, val), op ``r`` or ``w``: the value before the batch's writes, null outside the memory. Of several writes to a cell ``rule`` picks or combines, by i.

        Repeated addresses are fetched once: a sort and a scan mark the first of each, the others leave their places as fillers, whose paths
        are random; there are at most as many different cells as the memory has, a public number.
        """
        if rule not in RULES:
            raise ValueError(f"a rule is one of {RULES}")
        self.batch += 1
        bad = ~F.col("addr").between(0, self.cells - 1)
        req = materialise(requests.select("i", "op", F.when(~F.coalesce(bad, F.lit(True)), F.col("addr").cast("long")).alias("addr"), "val"), "requests")
        n = req.count()
        p = min(n, self.cells)
        rows = req.select("i", "addr")
        if "w" in [r[0] for r in req.select("op").distinct().collect()]:  # whether a step writes is part of the program, not of the data
            won = winners(req.select(F.when(F.col("op") == "w", F.col("addr")).alias("addr"), "val", F.col("i").alias("proc")), rule, **self.options)
            won = materialise(won, "writes")
        else:
            won = None
        rows = materialise(oblivious_sort(rows, [Key("addr", True, False), Key("i")], pos="_p", n=n, **self.options), "asked")
        rows = propagate(rows, ["addr"], F.col("_p"), "_first", "_p", n=n)
        rows = rows.select(F.when(F.col("_p") == F.col("_first"), F.col("addr")).alias("addr"))
        asks = materialise(oblivious_sort(rows, [Key("addr", True, False)], pos="k", n=n, **self.options).filter(F.col("k") < p), "asks")
        asks = segmented_aggregates(asks, [], {"prev": ("max", F.col("addr"))}, False, "prefix", "k", n=p)
        if won is not None:
            asks = send_receive(won.select("addr", F.col("val").alias("new")), asks, ["addr"], ["new"], found="written", on_duplicate="first", restore=False, **self.options)
        else:
            asks = asks.withColumn("new", F.lit(None).cast(requests.schema["val"].dataType)).withColumn("written", F.lit(False))
        if self.lean:
            found = self._served(asks)
        else:
            asks = materialise(asks.withColumn("leaf", F.lit(0).cast("long")), "asks")
            for d in range(self.height + 1):
                asks = self._step(d, asks, p)
            self._check()
            if asks.filter(F.col("addr").isNotNull() & ~F.col("there")).limit(1).count():
                raise KeyError("a cell is lost")
            found = asks.select("addr", F.col("value").alias("val"))
        got = send_receive(found, req.select("i", "addr"), ["addr"], ["val"], on_duplicate="first", restore=False, **self.options)
        return materialise(got.select("i", "val"), "served")

    def _step(self, d: int, asks: DataFrame, p: int) -> DataFrame:
        """One depth: fetch from pool and tree, remove what was visited, write it back under a fresh leaf, evict."""
        s = self.height - d
        prefix = F.shiftright("addr", s)
        first = F.col("addr").isNotNull() & (F.col("prev").isNull() | (F.shiftright("prev", s) != prefix))
        rows = segmented_aggregates(asks.withColumn("_x", prefix), ["_x"], {"most": ("max", F.col("addr"))}, True, "suffix", "k", n=p)
        rows = rows.withColumn("prefix", F.when(first, F.col("_x"))).withColumn("shown", F.when(first, F.col("leaf")).otherwise(self._dummy(d)))
        rows = rows.withColumn("change", F.struct("addr", "most", "new", "written"))
        self.seen.append(rows.select(F.lit(self.batch).alias("batch"), F.lit(d).alias("depth"), "k", F.col("shown").alias("leaf")))
        # pool: entries and asked prefixes side by side; what is asked leaves, whoever asks learns
        tree, n = self.trees[d], self.sizes[d] + p
        pool = self.pools[d].withColumn("role", F.lit(0))
        both = pool.unionByName(rows.select("prefix", "k", F.lit(1).alias("role"), "change.*"), allowMissingColumns=True)
        both = materialise(oblivious_sort(both, [Key("prefix", True, False), Key("role")], pos="_p", n=n, **self.options), "fetch")
        both = segmented_aggregates(both, ["prefix"], {"held": ("first", F.struct("role", "c0", "c1", "val"))}, True, "prefix", "_p", n=n)
        asked = F.when((F.col("role") == 1) & F.col("prefix").isNotNull(), F.struct("addr", "most", "new", "written"))
        both = materialise(segmented_aggregates(both, ["prefix"], {"asked": ("max", asked)}, True, "suffix", "_p", n=n), "fetch")
        got = both.filter("role = 1").select(F.col("k").alias("_k"), F.when(F.col("prefix").isNotNull() & (F.col("held.role") == 0), F.struct("held.c0", "held.c1", "held.val")).alias("content"))
        rows = rows.join(got, F.col("k") == F.col("_k")).drop("_k")
        if tree is not None:
            levels = d - self.top
            # each request fills a row with the nodes of its path, the matrix is turned, and nodes meet their slots by public number
            cells = rows.select("k", "prefix", "shown", F.explode(F.sequence(F.lit(0), F.lit(levels - 1))).alias("up")).withColumn("pos", F.col("k") * levels + F.col("up"))
            cells = transpose(cells, p, levels).select("k", F.col("prefix").alias("want"), F.expr(f"shiftright(shown + {1 << d}L, up)").alias("node"))
            visits = materialise(cells.join(tree, "node").withColumn("hit", F.coalesce(F.col("want") == F.col("prefix"), F.lit(False))), "visits")
            taken = visits.groupBy(F.col("k").alias("_k")).agg(F.max(F.when(F.col("hit"), F.struct("c0", "c1", "val"))).alias("from_tree"))
            gone = visits.groupBy(F.col("node").alias("_n"), F.col("slot").alias("_s")).agg(F.bool_or("hit").alias("gone"))
            rows = rows.join(taken, F.col("k") == F.col("_k"), "left").withColumn("content", F.coalesce("content", "from_tree")).drop("_k", "from_tree")
            tree = tree.join(gone, (F.col("node") == F.col("_n")) & (F.col("slot") == F.col("_s")), "left").withColumn("prefix", F.when(~F.coalesce("gone", F.lit(False)), F.col("prefix"))).drop("_n", "_s", "gone")
        rows = materialise(rows, "fetched")
        after = propagate(rows, ["_x"], F.col("content"), "seen", "k", n=p)
        bit = lambda a: F.shiftright(a, s - 1).bitwiseAND(F.lit(1))

        def renewed(change, content) -> list[Column]:
            """What an asked entry becomes: a fresh leaf, and fresh labels for those of its children that are asked too."""
            leaf = self._coin(d, F.col("prefix"), self.batch).alias("leaf")
            if d == self.height:
                none = F.lit(None).cast("long")
                return [leaf, none.alias("c0"), none.alias("c1"), F.when(change("written"), change("new")).otherwise(content("val")).alias("val")]
            fresh = lambda side: self._coin(d + 1, F.col("prefix") * 2 + side, self.batch)
            c0 = F.when(bit(change("addr")) == 0, fresh(0)).otherwise(content("c0"))
            return [leaf, c0.alias("c0"), F.when(bit(change("most")) == 1, fresh(1)).otherwise(content("c1")).alias("c1"), content("val").alias("val")]

        if d < self.height:
            after = after.withColumn("leaf", F.when(bit(F.col("addr")) == 0, F.col("seen.c0")).otherwise(F.col("seen.c1")))
        else:
            after = after.withColumn("value", F.col("seen.val")).withColumn("there", F.col("seen").isNotNull())
        after = materialise(after.drop("_x", "most", "prefix", "shown", "content", "seen", "change"), "asks")
        if tree is None:  # the whole depth is its pool: entries change where they are
            now = both.filter("role = 0").select("prefix", *(F.when(F.col("asked").isNotNull(), x).otherwise(F.col(c)).alias(c) for c, x in zip(("leaf", "c0", "c1", "val"), renewed(lambda c: F.col("asked")[c], F.col))))
            self.pools[d] = materialise(now, "pool")
        else:
            left = both.filter("role = 0").select(F.when(F.col("asked").isNull(), F.col("prefix")).alias("prefix"), "leaf", "c0", "c1", "val")
            back = rows.select("prefix", *renewed(lambda c: F.col("change")[c], lambda c: F.col("content")[c]))
            self._evict(d, left.unionByName(back), tree, p)
        return after

    def dump(self) -> DataFrame:
        """(addr, val) of all cells, in the open."""
        if self.lean:
            return self.state.filter((F.col("depth") == self.height) & (F.col("prefix") < self.cells)).select(F.col("prefix").alias("addr"), "val")
        last = self.pools[-1].select("prefix", "val")
        if self.trees[-1] is not None:
            last = last.unionByName(self.trees[-1].select("prefix", "val"))
        return last.filter(F.col("prefix") < self.cells).select(F.col("prefix").alias("addr"), "val")


def better_memory(cells: int, procs: int) -> str:
    """``space`` (sort all cells each step) or ``tree``, by their work: (p + s) log (p + s) against p log^2 s."""
    lg = lambda x: math.log2(max(x, 2))
    return "space" if (procs + cells) * lg(procs + cells) <= procs * lg(cells) ** 2 else "tree"


def simulate(program: list[Step], mem: DataFrame, procs: DataFrame, mode: str = "auto", **options) -> tuple[DataFrame, DataFrame]:
    """(memory, processors) after a program, in the memory that the numbers of cells and processors favour, or the one named: ``space`` or ``tree``."""
    n = procs.count()
    if mode == "auto":
        mode = better_memory(mem.count(), n)
    if mode == "space":
        return run_pram(program, mem, procs, **options)
    if mode != "tree":
        raise ValueError("a memory is 'space', 'tree' or 'auto'")
    tree = TreeMemory(mem, n, **options)
    kind = mem.schema["val"].dataType
    none = F.lit(None).cast(kind)
    for t, step in enumerate(program):
        if step.read is not None:
            asked = materialise(procs.select(F.col("proc").alias("i"), F.lit("r").alias("op"), step.read(t).alias("addr"), none.alias("val")), "reads")
            got = tree.access(asked).select(F.col("i").alias("_i"), "val")
            procs = procs.join(got, F.col("proc") == F.col("_i")).drop("_i").withColumn("addr", step.read(t))
        else:
            procs = procs.withColumn("val", none).withColumn("addr", F.lit(None).cast("long"))
        procs = materialise(procs.withColumns({c: f(t) for c, f in step.keep.items()}), "processors")
        if step.write is not None:
            asked = procs.select(F.col("proc").alias("i"), F.lit("w").alias("op"), step.write(t).alias("addr"), step.value(t).alias("val"))
            tree.access(materialise(asked, "writes"), step.rule)
        procs = procs.drop("val", "addr")
    return tree.dump(), procs
