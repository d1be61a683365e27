"""Oblivious sorts: permute and sort, permute and route by pivots, and block-wise bitonic networks."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..functions.codec import Codec, Key, as_keys, encode_keys, key_words
from ..plans.params import power_of_two
from ..plans.shared import dense_positions, discard, materialise, numbered, ship_package
from .permute import CHUNK, Permuted, _pack, _unpack, permute


def order_by(keys) -> list[Column]:
    out = []
    for k in as_keys(keys):
        c = F.col(f"`{k.name}`")
        out.append(getattr(c, f"{'asc' if k.ascending else 'desc'}_nulls_{'first' if k.nulls_first else 'last'}")())
    return out


#: Tables of at most so many rows (a public number) are sorted by one network in one task.
SMALL = 4096


def network_sort(df: DataFrame, keys, pos: str = "pos", widths: dict | None = None) -> DataFrame:
    """One task, one bitonic network over the rows and fillers up to a power of two; ties in order of the whole record.

    For small tables: lazy, without coins.
    """
    keys, widths = as_keys(keys), widths or {}
    codec, names = Codec(df.schema, widths), df.columns
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)

    def kernel(batches):
        parts = [b for b in batches if b.num_rows]
        if not parts:
            return
        rec = np.concatenate([codec.encode(b) for b in parts])
        w = np.concatenate([key_words(encode_keys(b, keys, widths)) for b in parts])
        w = np.concatenate((w, key_words(rec)), axis=1)
        size = power_of_two(len(rec))
        s = K.Slab(np.full((size, w.shape[1]), np.iinfo(np.uint64).max), np.arange(size) < len(rec), np.zeros((size, codec.width), np.uint8))
        s.words[: len(w)], s.rec[: len(rec)] = w, rec
        K.bitonic_sort_block(s, size)
        at = np.flatnonzero(s.real)
        yield pa.record_batch([*codec.decode(s.rec[at]), pa.array(np.arange(len(at)), pa.int64())], names=[*names, pos])

    ship_package(df.sparkSession)
    return df.coalesce(1).mapInArrow(kernel, f"{fields}, `{pos}` long")


def oblivious_sort(df: DataFrame, keys, second: str = "engine", pos: str = "pos", seed: int | None = None, level: str = "memory", widths: dict | None = None, small: int = SMALL, n: int | None = None, **options) -> DataFrame:
    """The rows with ``pos``, their dense place in the order of ``keys`` (ties in the order of the permutation).

    A secret permutation, then a comparison sort: ``engine`` range-partitions and sorts, ``pivots`` sorts a sample and routes by its
    quantiles in the shape of the first pass. Whatever the second pass shows depends on ranks in a secret random order.
    ``n``: the number of rows where it is known. ``options``: those of ``permute`` and, for ``pivots``, of ``sort_permuted``.
    """
    own = {k: options.pop(k) for k in ("relaxed", "network") if k in options}
    if small and second == "engine" and (df.count() if n is None else n) <= small:
        return network_sort(df, keys, pos, widths)
    drawn = permute(df, seed=seed, level=level, widths=widths, **options)
    if second == "pivots":
        return sort_permuted(drawn, keys, pos=pos, seed=seed, widths=widths, **own)
    if second != "engine":
        raise ValueError("the second pass must be a comparison sort: 'engine' or 'pivots'")
    out = dense_positions(drawn.take(), [*order_by(keys), F.col("_task"), F.col("_at")], pos)
    discard(drawn.df)
    return out.drop("_task", "_at")


def choose_pivots(df: DataFrame, keys, n: int, relaxed: bool = False, seed: int | None = None, eps: float = 0.5, sampler: str = "engine") -> DataFrame:
    """Pivot rows in order, with their number ``_p``: of a sample with probability 1 / log n, every log(n)^2-th (``relaxed``: every log(n)^(1 + eps)-th).

    ``df`` is a permuted table with ``_task`` and ``_at``. ``sampler``: how the sample is sorted, ``engine`` (its order is a secret random one) or ``bitonic``.
    """
    log = math.log2(max(n, 4))
    step = max(1, round(log ** (1 + eps if relaxed else 2)))
    key = K.coin_key(seed)
    draw = F.xxhash64(F.lit(int.from_bytes(key[:8], "little", signed=True)), "_task", "_at", F.lit(int.from_bytes(key[8:], "little", signed=True)))
    sample = df.filter(F.pmod(draw, F.lit(1 << 30)) < int((1 << 30) / log))
    if sampler == "bitonic":
        placed = bitonic_sort(materialise(sample, "sample"), [*as_keys(keys), Key("_task"), Key("_at")], pos="_s")
    else:
        placed = dense_positions(sample, [*order_by(keys), F.col("_task"), F.col("_at")], "_s")
    return placed.filter(F.pmod(F.col("_s") + 1, F.lit(step)) == 0).withColumn("_p", F.floor((F.col("_s") + 1) / step) - 1).drop("_s")


def _row_keys(batch: pa.RecordBatch, keys, widths) -> np.ndarray:
    """Key words made distinct by the place in the permutation."""
    full = encode_keys(batch, [*keys, Key("_task"), Key("_at")], widths)
    return key_words(full)


#: Rows that one network sorts together with the pivots that they are routed by.
ROUTED = 2048


def _bins_of(words: np.ndarray, pivots: np.ndarray, network: str = "search") -> np.ndarray:
    """Number of pivots below each row: region i holds what is above pivot i - 1 and not above pivot i.

    Rows and pivots are sorted together (``bitonic``: by the network, block for block), then pivots are counted from the left.
    """
    if not len(pivots):
        return np.zeros(len(words), np.int64)
    if network == "bitonic" and len(words) > ROUTED:
        return np.concatenate([_bins_of(words[i : i + ROUTED], pivots, network) for i in range(0, len(words), ROUTED)])
    both = np.concatenate((pivots, words))
    kind = np.concatenate((np.ones(len(pivots), np.int64), np.zeros(len(words), np.int64)))  # a row equal to a pivot comes before it
    if network == "bitonic":
        order = _network_order(np.concatenate((both, kind.astype(np.uint64)[:, None]), axis=1))
    else:
        order = np.lexsort((kind, *both.T[::-1]))
    below = np.cumsum(kind[order]) * (1 - kind[order])
    out = np.empty(len(both), np.int64)
    out[order] = below
    return out[len(pivots) :]


def _network_order(w: np.ndarray) -> np.ndarray:
    """The order of rows of words by the bitonic network, fillers up to a power of two."""
    size = power_of_two(len(w))
    up = np.full((size, w.shape[1]), np.iinfo(np.uint64).max)
    up[: len(w)] = w
    tag = np.concatenate((np.arange(len(w)), np.full(size - len(w), -1))).astype(np.int64)
    s = K.bitonic_sort_block(K.Slab(up, tag >= 0, tag.view(np.uint8).reshape(size, 8).copy()), size)
    got = s.rec.view(np.int64).ravel()
    return got[got >= 0]


def route_by_pivots(df: DataFrame, pivots: DataFrame, r: int, keys, form: str = "recursive", network: str = "search", widths: dict | None = None, tasks: int | None = None, gamma: int = 8, n: int | None = None) -> DataFrame:
    """Rows of a permuted table with ``_bin``, the number of pivots below them, and ``_pid``, their task; bins of a task are neighbours.

    ``recursive``: by every q-th pivot to a task, in one exchange, then by the task's own slice of the pivots. ``layered``: by ``gamma`` ways a
    layer, one exchange each, every layer by the pivots at its own steps within what the layer before left together. The driver and every task see as many
    pivots as there are tasks; a task's own slice comes to it through the exchange. ``network``: ``bitonic`` sorts rows together with pivots by the network,
    ``search`` by a local comparison sort. There are no fillers: loads show, which are ranks in a secret random order. Unless ``tasks`` says how many
    there are, each gets about ``CHUNK`` of the ``n`` rows at most.
    """
    return materialise(_routed_by_pivots(df, pivots, r, keys, form, network, widths, tasks, gamma, n), "regions")


def _routed_by_pivots(df: DataFrame, pivots: DataFrame, r: int, keys, form: str, network: str, widths: dict | None, tasks: int | None, gamma: int = 8, n: int | None = None) -> DataFrame:
    keys, widths = as_keys(keys), widths or {}
    spark, names = df.sparkSession, df.columns
    ship_package(spark)
    want = tasks or max(int(spark.conf.get("spark.sql.shuffle.partitions")), (df.count() if n is None else n) // CHUNK)
    ways = min(power_of_two(want), power_of_two(r + 1))
    per = -(-(r + 1) // ways)  # regions of a task
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)
    # the pivots that end a task's regions: fewer than there are tasks
    ends = pivots.filter(F.pmod(F.col("_p") + 1, F.lit(per)) == 0).orderBy("_p").select(names).toArrow()
    coarse = np.concatenate([_row_keys(b, keys, widths) for b in ends.to_batches() if b.num_rows] or [np.zeros((0, 1), np.uint64)])[: ways - 1]
    shared = spark.sparkContext.broadcast(coarse)

    def dealer(before: int, step: int, first: bool):
        """From groups of ``before`` tasks to groups of ``step``, each by the pivots inside its own group."""

        def deal(batches):
            me = 0 if first else TaskContext.get().partitionId()
            cuts = shared.value[me : me + before - 1][step - 1 :: step]
            for b in batches:
                if b.num_rows:
                    dest = me + _bins_of(_row_keys(b, keys, widths), cuts, network) * step
                    yield pa.record_batch([*(b.column(b.schema.get_field_index(c)) for c in (*names, "_pivot")), pa.array(dest, pa.int32())], names=[*names, "_pivot", "_dest"])

        return deal

    rows = df.withColumn("_pivot", F.lit(-1).cast("long")).unionByName(pivots.select(*names, F.col("_p").cast("long").alias("_pivot")))
    if form not in ("recursive", "layered"):
        raise ValueError("form is 'recursive' or 'layered'")
    before, out = ways, rows
    while True:
        step = max(1, before // gamma) if form == "layered" else 1
        out = out.mapInArrow(dealer(before, step, before == ways), f"{fields}, _pivot long, _dest int").repartitionById(ways, F.col("_dest"))
        before = step
        if step == 1:
            break

    def settle(batches):
        me, parts = TaskContext.get().partitionId(), [b for b in batches if b.num_rows]
        if not parts:
            return
        batch = pa.Table.from_batches(parts).combine_chunks().to_batches()[0]
        number = batch.column(batch.schema.get_field_index("_pivot")).to_numpy()
        w = _row_keys(batch, keys, widths)
        own = number >= 0
        slice_ = w[own][np.argsort(number[own])]
        at = np.flatnonzero(~own)
        fine = _bins_of(w[at], slice_, network) + me * per
        done = batch.take(pa.array(at))
        yield pa.record_batch([*(done.column(done.schema.get_field_index(c)) for c in names), pa.array(np.full(len(at), me), pa.int32()), pa.array(fine, pa.int64())], names=[*names, "_pid", "_bin"])

    return out.mapInArrow(settle, f"{fields}, _pid int, _bin long")


def sort_permuted(
    drawn: Permuted, keys, pos: str = "pos", relaxed: bool = False, network: str = "bitonic", seed: int | None = None, widths: dict | None = None, tasks: int | None = None,
    form: str = "recursive", router: str = "search", sampler: str = "engine",
) -> DataFrame:
    """Sort a permuted table by pivots: rows are routed to the regions between pivots, then each region is sorted.

    ``network``: ``bitonic`` sorts regions by the network, ``search`` by a local comparison sort; ``form``, ``router``: those of ``route_by_pivots``; ``sampler``: that of ``choose_pivots``.
    """
    keys, widths = as_keys(keys), widths or {}
    df, n = drawn.take(), drawn.n
    names = df.columns
    pivots = materialise(choose_pivots(df, keys, n, relaxed, seed, sampler=sampler), "pivots")
    routed = _routed_by_pivots(df, pivots, pivots.count(), keys, form, router, widths, tasks, n=n)
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)

    def settle(batches):
        parts = list(batches)
        if not parts:
            return
        batch = pa.Table.from_batches(parts).combine_chunks().to_batches()[0]
        w = _row_keys(batch, keys, widths)
        bins = batch.column(batch.schema.get_field_index("_bin")).to_numpy()
        by = np.argsort(bins, kind="stable")
        cut = np.flatnonzero(np.diff(bins[by], prepend=-1))
        order = []
        for at in np.split(by, cut[1:]):
            order.append(at[_network_order(w[at]) if network == "bitonic" else np.lexsort(w[at].T[::-1])])
        order = np.concatenate(order)
        out = batch.take(pa.array(order))
        keep = [out.column(out.schema.get_field_index(c)) for c in (*names, "_pid")]
        yield pa.record_batch([*keep, pa.array(np.arange(len(order)), pa.int64())], names=[*names, "_pid", "_rn"])

    done = materialise(routed.mapInArrow(settle, f"{fields}, _pid int, _rn long"), "sorted")
    from pyspark.sql import Window

    off = done.groupBy("_pid").agg(F.count(F.lit(1)).alias("_n")).withColumn("_off", F.sum("_n").over(Window.orderBy("_pid")) - F.col("_n")).select("_pid", "_off")
    return done.join(F.broadcast(off), "_pid").withColumn(pos, F.col("_off") + F.col("_rn")).drop("_pid", "_rn", "_off", "_task", "_at")


def bitonic_sort(df: DataFrame, keys, pos: str = "pos", merge: str = "recursive", widths: dict | None = None, blocks: int | None = None) -> DataFrame:
    """Deterministic: padded to a power of two, blocks of it sorted in tasks, then merged across tasks.

    ``recursive``: each merge is two exchanges, one that gathers the columns of a matrix and one back to its rows. ``layered``: one
    exchange for every layer whose partners lie in different blocks. Blocks travel whole and all of one size, by public number.
    """
    n = df.count()
    return _Network(df, keys, widths, blocks, n).run(numbered(df, "_pos"), pos, merge)


def bitonic_merge(df: DataFrame, keys, at: str = "at", length: int | None = None, pos: str = "pos", merge: str = "recursive", ascending: bool = True, widths: dict | None = None, blocks: int | None = None) -> DataFrame:
    """A bitonic sequence of ``length`` places (a power of two) in order: the last merge of the network alone, across tasks.

    ``at`` is each row's public place; places that no row has hold fillers, which come after all rows, rising or falling. The rows and fillers must first
    rise and then fall, or the reverse.
    """
    n = df.count()
    length = power_of_two(n) if length is None else length
    if length != power_of_two(length) or length < n:
        raise ValueError("the length is a power of two and has room for all rows")
    return _Network(df.drop(at), keys, widths, blocks, length).run(df.withColumnRenamed(at, "_pos"), pos, merge, False, ascending)


class _Network:
    """The block-wise network: ``count`` blocks of ``size`` records, each a task's."""

    def __init__(self, df: DataFrame, keys, widths: dict | None, blocks: int | None, n: int):
        self.keys, self.widths, self.names = as_keys(keys), widths or {}, df.columns
        self.codec = Codec(df.schema, self.widths)
        want = blocks or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        self.count = min(power_of_two(want), power_of_two(max(1, n // 16)))
        while self.count > 1 and self.count**2 > max(power_of_two(n), 1):  # a block holds a record for every block of a merge
            self.count //= 2
        self.size = max(power_of_two(n), self.count) // self.count
        self.fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)
        key_bytes = len(encode_keys(pa.RecordBatch.from_pylist([], schema=_arrow_schema(self.codec)), self.keys, self.widths).T)
        self.words = -(-key_bytes // 8) + 1
        ship_package(df.sparkSession)

    def run(self, placed: DataFrame, pos: str, merge: str, sort: bool = True, ascending: bool = True) -> DataFrame:
        """Rows with ``_pos``, a public place, to rows in order; without ``sort`` the places are a bitonic sequence's."""
        keys, widths, names, codec, words = self.keys, self.widths, self.names, self.codec, self.words
        count, size, fields = self.count, self.size, self.fields

        def enter(batches):
            me = TaskContext.get().partitionId()
            w, rec = [np.zeros((0, words), np.uint64)], [np.zeros((0, codec.width), np.uint8)]
            for b in batches:
                k = key_words(encode_keys(b, keys, widths))
                p = b.column(b.schema.get_field_index("_pos")).to_numpy(zero_copy_only=False).astype(np.uint64)
                w.append(np.concatenate((k, p[:, None]), axis=1))
                rec.append(codec.encode(b.select(names)))
            w, rec = np.concatenate(w), np.concatenate(rec)
            s = K.filler(size, K.Slab(w, np.zeros(len(w), bool), rec))
            s.words[:] = np.iinfo(np.uint64).max
            at = np.arange(len(w)) if sort else (w[:, -1] % np.uint64(size)).astype(np.int64)
            s.words[at], s.real[at], s.rec[at] = w, True, rec
            if sort:
                K.bitonic_sort_block(s, size, ascending=me % 2 == 0)
            elif not ascending:
                s.words[~s.real] = 0
            yield from put(s, [(me, 0)], size)

        def put(s: K.Slab, cells: list[tuple[int, int]], each: int):
            """(dest, place, block): pieces of ``each`` records and where they go."""
            packed = _pack(s, each)
            yield pa.record_batch([pa.array([d for d, _ in cells], pa.int32()), pa.array([i for _, i in cells], pa.int64()), pa.array(packed, pa.binary())], names=["dest", "place", "block"])

        def gather(batches) -> tuple[K.Slab, np.ndarray]:
            rows = sorted((i, x) for b in batches for i, x in zip(b.column(1).to_pylist(), b.column(2).to_pylist()))
            return _unpack([x for _, x in rows], words, codec.width), np.array([i for i, _ in rows], np.int64)

        schema = "dest int, place long, block binary"
        # a sort deals rows evenly, a merge leaves each at its place
        dest = F.col("_pos") % count if sort else F.floor(F.col("_pos") / size)
        state = placed.withColumn("_dest", dest.cast("int")).repartitionById(count, F.col("_dest")).mapInArrow(enter, schema)
        group = 2 if sort else max(count, 2)  # blocks of a merge
        if not sort and count == 1:

            def alone(batches):
                s, _ = gather(batches)
                K.bitonic_merge_block(s, size, K.Meter(), ascending, recursive=True)
                yield from put(s, [(0, 0)], size)

            state = state.mapInArrow(alone, schema)
        while group <= count:
            up = lambda block, g=group: ascending and ((block // g) % 2 == 0 or g == count)
            if merge == "layered":
                gap = group // 2
                while gap:

                    def pair(batches, gap=gap):
                        """A block goes to the lower of the two partners' tasks."""
                        me = TaskContext.get().partitionId()
                        for b in batches:
                            yield pa.record_batch([pa.array([me & ~gap] * b.num_rows, pa.int32()), pa.array([me] * b.num_rows, pa.int64()), b.column(2)], names=["dest", "place", "block"])

                    def compare(batches, gap=gap, up=up):
                        s, owner = gather(batches)
                        if not len(s):
                            return
                        K.exchange(s, 2 * size, 2 * size, size, K.Meter(), up(int(owner[0])))
                        yield from put(s, [(int(o), 0) for o in owner], size)

                    state = state.mapInArrow(pair, schema).repartitionById(count, F.col("dest")).mapInArrow(compare, schema).repartitionById(count, F.col("dest"))
                    gap //= 2

                def inner(batches, up=up):
                    s, _ = gather(batches)
                    me = TaskContext.get().partitionId()
                    K.bitonic_merge_block(s, size, K.Meter(), up(me))
                    yield from put(s, [(me, 0)], size)

                state = state.mapInArrow(inner, schema)
            else:
                piece = size // group  # a block's share of a column task

                def to_columns(batches, group=group, piece=piece):
                    s, _ = gather(batches)
                    me = TaskContext.get().partitionId()
                    base = me // group * group
                    yield from put(s, [(base + c, me) for c in range(group)], piece)

                def columns(batches, group=group, up=up, piece=piece):
                    s, owner = gather(batches)
                    me = TaskContext.get().partitionId()
                    # rows: blocks of the merge; columns: this task's share of places
                    t = lambda x: np.ascontiguousarray(x.reshape(group, piece, *x.shape[1:]).swapaxes(0, 1)).reshape(x.shape)
                    turned = K.Slab(t(s.words), t(s.real), t(s.rec))
                    K.bitonic_merge_block(turned, group, K.Meter(), up(me))
                    b = lambda x: np.ascontiguousarray(x.reshape(piece, group, *x.shape[1:]).swapaxes(0, 1)).reshape(x.shape)
                    yield from put(K.Slab(b(turned.words), b(turned.real), b(turned.rec)), [(int(o), me) for o in owner], piece)

                def rows(batches, up=up):
                    s, _ = gather(batches)
                    me = TaskContext.get().partitionId()
                    K.bitonic_merge_block(s, size, K.Meter(), up(me), recursive=True)
                    yield from put(s, [(me, 0)], size)

                if piece < 1:
                    raise ValueError("a block must hold a record for every block of a merge")
                state = state.mapInArrow(to_columns, schema).repartitionById(count, F.col("dest")).mapInArrow(columns, schema)
                state = state.repartitionById(count, F.col("dest")).mapInArrow(rows, schema)
            group *= 2

        def leave(batches):
            s, _ = gather(batches)
            me = TaskContext.get().partitionId()
            at = np.flatnonzero(s.real)
            yield pa.record_batch([*codec.decode(s.rec[at]), pa.array(at + me * size, pa.int64())], names=[*names, pos])

        # written down: in a union's stage the numbers of tasks, which kernels go by, would be others
        return materialise(state.mapInArrow(leave, f"{fields}, `{pos}` long"), "bitonic")


def _arrow_schema(codec: Codec) -> pa.Schema:
    return pa.schema([(n, t) for n, t in codec.arrow.items()])


def sort_by_text(df: DataFrame, text: str, tie: str, pos: str = "pos", piece: int = 64, **options) -> DataFrame:
    """(tie, pos): the rows in order of their whole texts, whatever their lengths, equal texts by ``tie``.

    A sort by the first ``piece`` characters, then, of the rows whose piece others with different texts share, a sort by the
    next characters, up to ``8 * piece`` a round, until none is left. The numbers of such rows and of rounds become public.
    """
    from .primitives import segmented_aggregates

    def grouped(rows: DataFrame, width: int, at: int) -> DataFrame:
        """Rows (tie, text, h, start) with the first place of their group by the next piece, and whether its texts differ."""
        cut = rows.select(tie, "h", "start", F.substring(text, at + 1, width).alias("part"))
        done = materialise(oblivious_sort(cut, ["start", "part", tie], pos="_p", widths={"part": 4 * width}, **options), "text-piece")
        group, ends = ["start", "part"], {"lo": ("min", F.col("h")), "hi": ("max", F.col("h"))}
        done = segmented_aggregates(done, ["start"], {"_first": ("first", F.col("_p"))}, True, "prefix", "_p")
        done = segmented_aggregates(done, group, {"_own": ("first", F.col("_p"))} | {f"_{k}0": v for k, v in ends.items()}, True, "prefix", "_p")
        done = segmented_aggregates(done, group, {f"_{k}1": v for k, v in ends.items()}, True, "suffix", "_p")
        differ = F.least("_lo0", "_lo1") != F.greatest("_hi0", "_hi1")
        return materialise(done.select(tie, "h", (F.col("start") + F.col("_own") - F.col("_first")).alias("start"), differ.alias("open")), "text-groups")

    base = materialise(df.select(tie, F.coalesce(F.col(text), F.lit("")).alias(text), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("h"), F.lit(0).cast("long").alias("start")), "texts")
    now, settled, at, width = base, None, 0, piece
    while True:
        done = grouped(now, width, at)
        shut = done.filter("NOT open").select(tie, "start")
        settled = shut if settled is None else settled.unionByName(shut)
        left = done.filter("open").select(F.col(tie).alias("_t"), F.col("start").alias("_s"))
        if left.isEmpty():
            break
        now = materialise(base.drop("start").join(left.withColumnRenamed("_s", "start"), F.col(tie) == F.col("_t")).drop("_t"), "texts")
        at, width = at + width, min(width * 2, 8 * piece)
    return oblivious_sort(settled, ["start", tie], pos=pos, **options).select(tie, pos)


def engine_sort(df: DataFrame, keys, pos: str = "pos") -> DataFrame:
    """The baseline that hides nothing: sample, range-partition, sort."""
    return dense_positions(df, order_by(keys), pos)
