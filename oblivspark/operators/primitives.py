"""What sorting and scanning make: aggregation and propagation over groups, send-receive, placement, compaction."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.codec import Key, as_keys
from ..plans.shared import discard, kept, materialise
from .sorts import SMALL, oblivious_sort

#: f: (aggregate over a window, combination of an earlier and a later part, value over nothing).
FUNCTIONS = {
    "sum": (F.sum, lambda a, b: F.coalesce(a, F.lit(0)) + F.coalesce(b, F.lit(0)), 0),
    "count": (F.count, lambda a, b: F.coalesce(a, F.lit(0)) + F.coalesce(b, F.lit(0)), 0),
    "min": (F.min, F.least, None),
    "max": (F.max, F.greatest, None),
    "any": (F.bool_or, lambda a, b: F.coalesce(a | b, a, b), None),
    "all": (F.bool_and, lambda a, b: F.coalesce(a & b, a, b), None),
    "first": (F.first, F.coalesce, None),
    "last": (F.last, lambda a, b: F.coalesce(b, a), None),
}


class DuplicateSender(ValueError):
    """Two senders have one key."""


def blocked(df: DataFrame, pos: str, blocks: int | None = None, n: int | None = None) -> DataFrame:
    """``df`` with ``_blk``: the number of its block of public size."""
    count = blocks or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    n = n if n is not None else 1 if count == 1 else df.count()
    if count == 1:
        return df.withColumn("_blk", F.lit(0))
    size = max(1, -(-n // count))
    return df.withColumn("_blk", F.floor(F.col(pos) / size).cast("int"))


def segmented_aggregate(
    df: DataFrame, group: list[str], value: Column, f: str = "sum", out: str = "agg", inclusive: bool = False, direction: str = "suffix", pos: str = "pos", blocks: int | None = None, n: int | None = None,
) -> DataFrame:
    """For each row f over the rows of its group to its right (``suffix``) or left (``prefix``); groups lie together in the order of ``pos``.

    Two local scans with one small table between them: rows meet by the number of a block of public
    size, never by group; each block hands on what it has of its first and last group, at most two rows, whose running
    combination comes back by broadcast to the rows of each block's first group. Over no rows the result is f's identity, or null.
    """
    return segmented_aggregates(df, group, {out: (f, value)}, inclusive, direction, pos, blocks, n)


def segmented_aggregates(
    df: DataFrame, group: list[str], aggs: dict[str, tuple[str, Column]], inclusive: bool = False, direction: str = "suffix", pos: str = "pos", blocks: int | None = None, n: int | None = None,
) -> DataFrame:
    """Several functions in the same two scans: ``aggs`` is name -> (f, column). Up to ``SMALL`` rows (``n``, a public number) are one block, and one scan is all."""
    if blocks is None:
        n = df.count() if n is None else n
        blocks = 1 if n <= SMALL else None
    order = F.col(pos).asc() if direction == "prefix" else F.col(pos).desc()
    block_order = F.col("_blk") if direction == "prefix" else -F.col("_blk")
    specs = list(enumerate(aggs.items()))
    rows = blocked(df, pos, blocks, n)
    g = F.struct(*[F.col(f"`{c}`") for c in group]) if group else F.struct(F.lit(0))
    local = Window.partitionBy("_blk").orderBy(order)
    rows = rows.withColumns({"_g": g} | {f"_v{i}": value for i, (_, (_, value)) in specs})
    new = F.when(F.lag("_g").over(local).eqNullSafe(F.col("_g")), 0).otherwise(1)
    rows = rows.withColumn("_new", new).withColumn("_seg", F.sum("_new").over(local))
    run = Window.partitionBy("_blk", "_seg").orderBy(order).rowsBetween(Window.unboundedPreceding, 0 if inclusive else -1)
    rows = rows.withColumns({f"_local{i}": FUNCTIONS[f][0](f"_v{i}").over(run) for i, (_, (f, _)) in specs})

    if blocks == 1:
        results = {out: F.col(f"_local{i}") if FUNCTIONS[f][2] is None else F.coalesce(f"_local{i}", F.lit(FUNCTIONS[f][2])) for i, (out, (f, _)) in specs}
        return rows.withColumns(results).drop("_blk", "_seg", "_g", "_new", *(f"{c}{i}" for i, _ in specs for c in ("_v", "_local")))

    def whole(i: int, f: str) -> Column:
        """f over a block's part of a group; first and last by position."""
        if f in ("first", "last"):
            return (F.min_by if (f == "first") == (direction == "prefix") else F.max_by)(f"_v{i}", pos)
        return FUNCTIONS[f][0](f"_v{i}")

    parts = rows.groupBy("_blk", "_seg").agg(F.first("_g").alias("_g"), *(whole(i, f).alias(f"_part{i}") for i, (_, (f, _)) in specs))
    ends = Window.partitionBy("_blk")
    parts = parts.withColumn("_most", F.max("_seg").over(ends)).filter((F.col("_seg") == 1) | (F.col("_seg") == F.col("_most")))
    line = Window.orderBy(block_order, "_seg")
    linked = (F.col("_seg") == 1) & (F.lag("_seg").over(line) == F.lag("_most").over(line)) & F.lag("_g").over(line).eqNullSafe(F.col("_g"))
    parts = parts.withColumn("_run", F.sum(F.when(linked, 0).otherwise(1)).over(line))
    before = Window.partitionBy("_run").orderBy(block_order, "_seg").rowsBetween(Window.unboundedPreceding, -1)
    over = {"sum": F.sum, "count": F.sum}
    carries = {f"_carry{i}": over.get(f, FUNCTIONS[f][0])(f"_part{i}").over(before) for i, (_, (f, _)) in specs}
    carry = parts.withColumns(carries).filter("_seg = 1").select("_blk", F.lit(1).cast("long").alias("_seg"), *carries)
    rows = rows.join(F.broadcast(carry), ["_blk", "_seg"], "left")
    results = {}
    for i, (out, (f, _)) in specs:
        _, combine, nothing = FUNCTIONS[f]
        result = combine(F.col(f"_carry{i}"), F.col(f"_local{i}"))
        results[out] = result if nothing is None else F.coalesce(result, F.lit(nothing))
    rows = rows.withColumns(results)
    return rows.drop("_blk", "_seg", "_g", "_new", *(f"{c}{i}" for i, _ in specs for c in ("_v", "_local", "_carry")))


def propagate(df: DataFrame, group: list[str], value: Column, out: str = "head", pos: str = "pos", blocks: int | None = None, n: int | None = None) -> DataFrame:
    """Every row gets ``value`` of the leftmost row of its group, null or not."""
    wide = segmented_aggregate(df, group, F.struct(value.alias("x")), "first", "_wrapped", True, "prefix", pos, blocks, n)
    return wide.withColumn(out, F.col("_wrapped.x")).drop("_wrapped")


def doubling_aggregate(df: DataFrame, group: list[str], value: Column, out: str = "agg", pos: str = "pos", n: int | None = None) -> DataFrame:
    """The naive baseline: inclusive prefix sums by log n rounds of adding what stands 1, 2, 4 ... places before in the same group."""
    n = df.count() if n is None else n
    g = F.struct(*[F.col(f"`{c}`") for c in group])
    now = materialise(df.withColumn("_g", g).withColumn(out, F.coalesce(value, F.lit(0))), "doubling")
    gap = 1
    while gap < n:
        back = now.select((F.col(pos) + gap).alias("_at"), F.col("_g").alias("_og"), F.col(out).alias("_ov"))
        now = now.join(back, (F.col(pos) == F.col("_at")) & F.col("_g").eqNullSafe(F.col("_og")), "left")
        now = materialise(now.withColumn(out, F.col(out) + F.coalesce("_ov", F.lit(0))).drop("_at", "_og", "_ov"), "doubling")
        gap *= 2
    return now.drop("_g")


def prefix_sum(df: DataFrame, value: Column, out: str = "sum", inclusive: bool = True, pos: str = "pos") -> DataFrame:
    """Running sum over all rows in the order of ``pos``."""
    return segmented_aggregate(df, [], value, "sum", out, inclusive, "prefix", pos)


def renumber(df: DataFrame, keep: Column, out: str = "index", pos: str = "pos") -> DataFrame:
    """``out``: 0, 1, 2 ... on the rows to keep, in order; null on the others."""
    wide = prefix_sum(df.withColumn("_keep", F.coalesce(keep, F.lit(False))), F.col("_keep").cast("long"), "_k", False, pos)
    return wide.withColumn(out, F.when(F.col("_keep"), F.col("_k"))).drop("_keep", "_k")


def send_receive(
    senders: DataFrame, receivers: DataFrame, key: list[str], values: list[str], found: str = "found", on_duplicate: str = "error", restore: bool = True, sorter=None,
    seed: int | None = None, level: str = "memory", widths: dict | None = None, **options,
) -> DataFrame:
    """Receivers with the values of the sender of their key; nulls and ``found`` = false where there is none.

    Both sides in one array, sorted obliviously by key with senders first, values propagated over each key, and sorted back
    to receivers first, of which there is a public number. A null key matches nothing. ``restore=False`` leaves out the way back,
    for callers that sort again anyway. ``sorter``: another sort than the default, called with the rows, keys and ``pos``; the earlier methods' are networks. Receivers carry all their columns; values named like one of them aren't allowed.
    """
    clash = set(values) & set(receivers.columns)
    if clash:
        raise ValueError(f"both sides have {sorted(clash)}")
    extra = [c for c in receivers.columns if c not in key]
    kinds = {f.name: f.dataType for f in [*senders.schema.fields, *receivers.schema.fields]}
    none = lambda c: F.lit(None).cast(kinds[c]).alias(c)
    a = senders.select(*key, *values, *(none(c) for c in extra), F.lit(0).alias("_role"))
    b = receivers.select(*key, *(none(c) for c in values), *extra, F.lit(1).alias("_role"))
    if sorter is None:
        sorter = lambda df, keys, pos: oblivious_sort(df, keys, pos=pos, seed=seed, level=level, widths=widths, **options)
    both = kept(receivers.sparkSession, lambda: sorter(a.unionByName(b), [*as_keys(key), Key("_role")], pos="_pos"), "send-receive")
    head = propagate(both, key, F.struct("_role", "_pos", *values), "_head", "_pos")
    if on_duplicate == "error":
        head = materialise(head, "send-receive")
        discard(both)
        twice = head.filter((F.col("_role") == 0) & (F.col("_head._pos") != F.col("_pos")) & F.col(key[0]).isNotNull()).limit(1).count()
        if twice:
            raise DuplicateSender(f"several senders for one key ({', '.join(key)})")
    known = F.lit(True)
    for k in key:
        known = known & F.col(k).isNotNull()
    hit = (F.col("_head._role") == 0) & known
    out = head.select("_role", *key, *extra, *(F.when(hit, F.col("_head")[c]).alias(c) for c in values), hit.alias(found))
    if restore:
        marked = out.withColumn("_order", F.xxhash64(*key, *extra))
        out = sorter(marked, [Key("_role", False)], pos="_pos").drop("_order")
        return out.filter(F.col("_pos") < receivers.count()).drop("_role", "_pos")
    return out.filter("_role = 1").drop("_role")


def compact(df: DataFrame, keep: Column, pos: str = "pos", bound: int | None = None, **options) -> DataFrame:
    """Rows to keep first, in their order, then the others (null but for ``pos``); cut to ``bound`` rows, a public number, if given."""
    marked = df.withColumn("_out", ~F.coalesce(keep, F.lit(False)))
    done = oblivious_sort(marked, [Key("_out"), Key(pos)], pos="_pos", **options)
    return (done if bound is None else done.filter(F.col("_pos") < bound)).drop(pos).withColumnRenamed("_pos", pos).withColumnRenamed("_out", "is_filler")


def place_bins(df: DataFrame, group: str, bins: int, capacity: int, pos: str = "pos", **options) -> DataFrame:
    """Exactly ``capacity`` slots for each of ``bins`` bins: the rows whose ``group`` names the bin, then fillers (``is_real`` false, null payload)."""
    spark = df.sparkSession
    real = df.withColumn("is_real", F.lit(True))
    slots = spark.range(bins * capacity).select((F.col("id") % bins).cast(df.schema[group].dataType).alias(group), F.lit(False).alias("is_real"))
    both = real.unionByName(slots, allowMissingColumns=True)
    order = [Key(group), Key("is_real", False), *([Key(pos)] if pos in df.columns else [])]
    done = materialise(oblivious_sort(both, order, pos="_pos", **options), "placed")
    ranked = segmented_aggregate(done, [group], F.lit(1), "count", "slot", False, "prefix", "_pos")
    ranked = materialise(ranked, "placed")
    if ranked.filter(F.col("is_real") & (F.col("slot") >= capacity)).limit(1).count():
        from ..functions.kernels import BinOverflow

        raise BinOverflow(f"a bin of {capacity} overflows")
    return ranked.filter(F.col("slot") < capacity).drop("_pos")


def transpose(df: DataFrame, rows: int, cols: int, pos: str = "pos") -> DataFrame:
    """``pos`` of a rows x cols matrix becomes the place in its transpose; rows move by public column number."""
    r, c = F.floor(F.col(pos) / cols), F.col(pos) % cols
    moved = df.withColumn("_c", c.cast("int")).repartitionById(max(1, min(cols, 1024)), (F.col("_c") % max(1, min(cols, 1024))).cast("int"))
    return moved.withColumn("row", c).withColumn("col", r).withColumn(pos, (c * rows + r).cast("long")).drop("_c")
