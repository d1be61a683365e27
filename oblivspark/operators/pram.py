"""Step-by-step simulation of shared-memory programs: reads and writes are sorts and scans, so no address shows."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.codec import Key
from ..functions.kernels import coin_key
from ..plans.shared import materialise
from .primitives import FUNCTIONS, propagate, segmented_aggregate, send_receive
from .sorts import oblivious_sort

#: What becomes of several writes to one cell.
RULES = ("priority", "arbitrary", "common", "sum", "min", "max")


class WriteConflict(ValueError):
    """Under the common rule two processors wrote different values."""


def pram_read(mem: DataFrame, req: DataFrame, restore: bool = False, **options) -> DataFrame:
    """``req`` (proc, addr, ...) with ``val``, null where there is no such cell. ``mem``: (addr, val)."""
    return send_receive(mem.select("addr", "val"), req, ["addr"], ["val"], on_duplicate="first", restore=restore, **options)


def winners(req: DataFrame, rule: str = "priority", seed: int | None = None, **options) -> DataFrame:
    """(addr, val) for each written cell, after the conflict rule; losing rows stay as fillers (null addr), so the length is that of ``req``.

    ``priority``: the lowest proc; ``arbitrary``: the lowest hash of proc under secret coins; ``common``: all must agree;
    ``sum``, ``min``, ``max``: all values combined.
    """
    if rule not in RULES:
        raise ValueError(f"a rule is one of {RULES}")
    rank = F.xxhash64(F.lit(int.from_bytes(coin_key(seed)[:8], "little", signed=True)), "proc") if rule == "arbitrary" else F.col("proc")
    rows = req.select("addr", "val", "proc", rank.alias("_rank"))
    rows = materialise(oblivious_sort(rows, [Key("addr", True, False), Key("_rank"), Key("val")], pos="_p", seed=seed, **options), "writes")
    head = propagate(rows, ["addr"], F.col("_p"), "_first", "_p")
    if rule == "common":
        head = segmented_aggregate(head, ["addr"], F.col("val"), "min", "_least", True, "suffix", "_p")
        head = materialise(segmented_aggregate(head, ["addr"], F.col("val"), "max", "_most", True, "suffix", "_p"), "writes")
        if head.filter(F.col("addr").isNotNull() & (F.col("_least") != F.col("_most"))).limit(1).count():
            raise WriteConflict("processors disagree on a cell")
    elif rule in FUNCTIONS:
        head = segmented_aggregate(head, ["addr"], F.col("val"), rule, "val", True, "suffix", "_p")
    first = F.col("_p") == F.col("_first")
    return head.select(F.when(first, F.col("addr")).alias("addr"), F.when(first, F.col("val")).alias("val"))


def pram_write(mem: DataFrame, req: DataFrame, rule: str = "priority", seed: int | None = None, **options) -> DataFrame:
    """``mem`` after the writes ``req`` (proc, addr, val); a null addr writes nothing."""
    won = winners(req, rule, seed, **options).withColumnRenamed("val", "_new")
    cells = send_receive(won, mem.select("addr", F.col("val").alias("_old")), ["addr"], ["_new"], found="_written", on_duplicate="first", restore=False, seed=seed, **options)
    return cells.select("addr", F.when(F.col("_written"), F.col("_new")).otherwise(F.col("_old")).alias("val"))


@dataclass
class Step:
    """Each processor reads ``read`` (an address), then writes ``value`` to ``write``; columns over the processor's own and ``val``, ``step``."""

    read: Callable[[int], Column] | None = None
    write: Callable[[int], Column] | None = None
    value: Callable[[int], Column] | None = None
    keep: dict[str, Callable[[int], Column]] = field(default_factory=dict)
    rule: str = "priority"
    #: Processors and cells, from 0 on, that are left from this step on: public numbers that fall from phase to phase.
    procs: int | None = None
    cells: int | None = None


def run_pram(steps: list[Step], mem: DataFrame, procs: DataFrame, **options) -> tuple[DataFrame, DataFrame]:
    """(memory, processors) after a fixed list of steps; each step's plan depends on the numbers of cells and processors alone, which steps may let shrink."""
    for t, step in enumerate(steps):
        if step.procs is not None:
            procs = procs.filter(F.col("proc") < step.procs)
        if step.cells is not None:
            mem = mem.filter(F.col("addr") < step.cells)
        if step.read is not None:
            asked = procs.withColumn("addr", step.read(t))
            procs = pram_read(mem, asked, **options).drop("found")
        else:
            procs = procs.withColumn("val", F.lit(None).cast("long")).withColumn("addr", F.lit(None).cast("long"))
        kept = {c: f(t) for c, f in step.keep.items()}
        procs = materialise(procs.withColumns(kept), "processors")
        if step.write is not None:
            req = procs.select("proc", step.write(t).alias("addr"), step.value(t).alias("val"))
            mem = materialise(pram_write(mem, req, step.rule, **options), "memory")
        procs = procs.drop("val", "addr")
    return mem, procs


def prefix_sum_program(cells: int) -> list[Step]:
    """Doubling: cell i becomes the sum of cells 0 to i."""
    steps, gap = [], 1
    load = Step(read=lambda t: F.col("proc"), keep={"own": lambda t: F.col("val")})
    steps.append(load)
    while gap < cells:
        g = gap
        steps.append(
            Step(
                read=lambda t, g=g: F.when(F.col("proc") >= g, F.col("proc") - g), keep={"own": lambda t: F.col("own") + F.coalesce("val", F.lit(0))},
                write=lambda t: F.col("proc"), value=lambda t: F.col("own"),
            )
        )
        gap *= 2
    return steps


def max_program(cells: int) -> list[Step]:
    """A tournament: cell 0 becomes the largest; each step folds the upper half of the cells onto the lower, and only that many processors and cells go on."""
    steps = [Step(read=lambda t: F.col("proc"), keep={"own": lambda t: F.col("val")})]
    left = cells
    while left > 1:
        half = -(-left // 2)
        steps.append(
            Step(
                read=lambda t, h=half, m=left: F.when(F.col("proc") + h < m, F.col("proc") + h), keep={"own": lambda t: F.greatest("own", "val")},
                write=lambda t: F.col("proc"), value=lambda t: F.col("own"), procs=half, cells=left,
            )
        )
        left = half
    return steps


def pointer_jump_program(cells: int) -> list[Step]:
    """Cell i holds a pointer, an end points to itself: after log2 of the number of cells rounds every cell points to its end."""
    steps = [Step(read=lambda t: F.col("proc"), keep={"own": lambda t: F.col("val")})]
    reach = 1
    while reach < cells:
        steps.append(Step(read=lambda t: F.col("own"), keep={"own": lambda t: F.coalesce("val", "own")}, write=lambda t: F.col("proc"), value=lambda t: F.col("own")))
        reach *= 2
    return steps


def histogram_program() -> list[Step]:
    """One combining write: every processor adds 1 to the cell of its own ``key``."""
    return [Step(write=lambda t: F.col("key"), value=lambda t: F.lit(1).cast("long"), rule="sum")]


def broadcast_program(cells: int) -> list[Step]:
    """Cell 0 spreads to all cells, twice as many each step."""
    steps, reach = [], 1
    while reach < cells:
        r = reach
        steps.append(Step(read=lambda t, r=r: F.when(F.col("proc") < 2 * r, F.col("proc") % r), write=lambda t, r=r: F.when(F.col("proc") < 2 * r, F.col("proc")), value=lambda t: F.col("val")))
        reach *= 2
    return steps
