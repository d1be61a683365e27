"""Mixing sources to target weights along a curriculum, DataFrame functions only."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import word_count
from ..plans.shared import dense_positions, materialise

#: Weights dealt to the sources in order of name, again and again.
WEIGHTS = (5, 2, 1)
#: Rates over training time (time, rate), one per place in ``WEIGHTS``: early, steady, late.
SCHEDULES = (((0.0, 1.5), (1.0, 0.5)), ((0.0, 1.0), (1.0, 1.0)), ((0.0, 0.5), (1.0, 1.5)))
#: A source's rows are cut into this many slices by hash, so that no window holds a hot source.
SLICE_HEX = 3


def integrate(schedule) -> list[tuple[float, float, float, float, float]]:
    """Segments (t0, t1, rate0, rate1, demand before t0) of a piecewise linear rate, of area 1 in all."""
    if len(schedule) < 2 or any(b[0] <= a[0] for a, b in zip(schedule, schedule[1:])) or any(r < 0 for _, r in schedule):
        raise ValueError("a schedule has rising times and rates of 0 or more")
    area = sum((b[0] - a[0]) * (a[1] + b[1]) / 2 for a, b in zip(schedule, schedule[1:]))
    if area <= 0:
        raise ValueError("a schedule needs a rate above 0")
    out, before = [], 0.0
    for (t0, r0), (t1, r1) in zip(schedule, schedule[1:]):
        out.append((t0, t1, r0 / area, r1 / area, before))
        before += (t1 - t0) * (r0 + r1) / 2 / area
    return out


def position_of(share: Column, schedule) -> Column:
    """The time by which ``share`` (0 to 1) of a source's demand has been served: the inverse of the integral."""
    out = F.lit(float(schedule[-1][0]))
    for t0, t1, r0, r1, before in reversed(integrate(schedule)):
        bend = (r1 - r0) / (2 * (t1 - t0))
        rest = share - F.lit(before)
        if bend == 0:
            at = F.lit(t0) + rest / F.lit(r0) if r0 else F.lit(t1)
        else:
            at = F.lit(t0) + (F.sqrt(F.lit(r0 * r0) + F.lit(4 * bend) * rest) - F.lit(r0)) / F.lit(2 * bend)
        out = F.when(share < F.lit(before + (t1 - t0) * (r0 + r1) / 2), at).otherwise(out)
    return out


def source_targets(sizes: DataFrame, weights=WEIGHTS, limit: int = 3) -> DataFrame:
    """``sizes`` (source, source_size) with weight, place and target.

    Targets share the total by weight; one above ``limit`` times its source's size stops there,
    and what it leaves is shared by weight again until none is above. Each round is one aggregate of which
    the driver sees four numbers; capped sources stay capped, so the rounds end.
    """
    order = [F.col("source").asc_nulls_last()]
    ranked = materialise(dense_positions(sizes, order, "_rank"), "sources")
    place = F.pmod(F.col("_rank"), F.lit(len(weights))).cast("int")
    ranked = ranked.withColumn("place", place).withColumn(
        "weight", F.element_at(F.array(*map(F.lit, weights)), F.col("place") + 1).cast("long")
    )
    total, all_weight = ranked.agg(F.coalesce(F.sum("source_size"), F.lit(0)), F.coalesce(F.sum("weight"), F.lit(0))).first()
    left, weight, n = total, all_weight, -1
    over = lambda: F.lit(left).cast("double") * F.col("weight") > F.lit(limit) * F.col("source_size") * F.lit(float(weight))
    while total and weight:
        found = ranked.filter(over()).agg(
            F.count(F.lit(1)), F.coalesce(F.sum("source_size"), F.lit(0)), F.coalesce(F.sum("weight"), F.lit(0))
        ).first()
        if found[0] == n:
            break
        n, left, weight = found[0], total - limit * found[1], all_weight - found[2]
    share = F.lit(left).cast("double") * F.col("weight") / F.lit(float(weight or 1))
    return ranked.withColumn(
        "target", F.when(over(), (F.lit(limit) * F.col("source_size")).cast("double")).otherwise(share)
    ).drop("_rank")


def mix(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source",
    weights=WEIGHTS, schedules=SCHEDULES, limit: int = 3, columns: list[str] | None = None,
) -> DataFrame:
    """One row per document: the input's columns (or those named in ``columns``), size, source_size, target, taken, first_position; in order of position.

    A source's stream is its documents in order of the MD5 of their id, started over when it ends.
    The mix takes the first ``floor(target)`` words of the stream: whole rounds, then documents from the start, of
    which the last may be cut. ``taken`` counts a document's words, repeats included, and never exceeds
    ``limit`` times its size. ``first_position`` is the training time (0 to 1) at which its first word comes: the share of
    its source's demand that lies before it, put through the inverse of the source's integrated rate; null
    when nothing is taken.

    Null text: size 0 and taken 0. Null source: a source of its own, last in order. Null ids sort
    as the empty string; rows that repeat an id are mixed each. Empty table: no rows. A column of ``docs`` named like a
    result column is replaced by it. Where the text isn't among the columns asked for, it is read once and not exchanged.
    """
    made = ["size", "source_size", "target", "taken", "first_position"]
    kept = [c for c in (docs.columns if columns is None else columns) if c.lower() not in made]
    base = docs.select(
        F.struct(*[F.col(f"`{c}`") for c in kept]).alias("_row"),
        F.col(f"`{source_col}`").cast("string").alias("source"),
        F.md5(F.coalesce(F.col(f"`{id_col}`").cast("string"), F.lit("")).cast("binary")).alias("_order"),
        word_count(F.col(f"`{text_col}`").cast("string")).alias("size"),
    )
    # a source as a key that is never null
    key = F.concat(F.when(F.col("source").isNull(), F.lit("n")).otherwise(F.lit("s")), F.coalesce("source", F.lit("")))
    base = base.withColumn("_key", key).withColumn("_slice", F.substring("_order", 1, SLICE_HEX))
    if text_col not in kept:
        base = materialise(base, "document-sizes")
    slices = materialise(
        base.groupBy("_key", "_slice").agg(F.first("source").alias("source"), F.sum("size").alias("_words")), "slices"
    )
    sizes = slices.groupBy("_key").agg(F.first("source").alias("source"), F.sum("_words").alias("source_size"))
    targets = materialise(source_targets(sizes, weights, limit), "targets")
    before = F.sum("_words").over(Window.partitionBy("_key").orderBy("_slice")) - F.col("_words")
    offsets = slices.select("_key", "_slice", before.alias("_before")).join(
        targets.select("_key", "source_size", "target", "place"), "_key"
    )
    rows = base.drop("source").join(offsets, ["_key", "_slice"])
    within = Window.partitionBy("_key", "_slice").orderBy("_order", "size")
    start = F.col("_before") + F.sum("size").over(within.rowsBetween(Window.unboundedPreceding, 0)) - F.col("size")
    rows = rows.withColumn("_start", start)
    words = F.floor("target").cast("long")
    rounds = F.when(F.col("source_size") > 0, F.floor(F.try_divide(words, F.col("source_size")))).otherwise(F.lit(0)).cast("long")
    rows = rows.withColumn("_rounds", rounds)
    rest = words - F.col("_rounds") * F.col("source_size") - F.col("_start")
    taken = F.col("_rounds") * F.col("size") + F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), rest))
    rows = rows.withColumn("taken", taken)
    share = F.try_divide(F.col("_start"), F.col("target"))
    at = F.lit(None).cast("double")
    for i in range(len(weights)):
        at = F.when(F.col("place") == i, position_of(share, schedules[i % len(schedules)])).otherwise(at)
    rows = rows.withColumn("first_position", F.when(F.col("taken") > 0, F.round(at, 9) + F.lit(0.0)))
    # what isn't taken has no position: the hash of the id spreads it over the last partitions
    rows = rows.orderBy(F.col("first_position").asc_nulls_last(), "_order")
    return rows.select(*[F.col("_row")[c].alias(c) for c in kept], *made)
