"""Micro-batches of one padded size, and state that is read and written obliviously."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.pram import pram_write
from ..operators.relational import group_aggregate, release
from ..plans.shared import materialise


class BatchTooLarge(ValueError):
    """A micro-batch has more rows than the public batch size."""


def padded(batch: DataFrame, rows: int) -> DataFrame:
    """``batch`` with ``is_real`` and null fillers up to exactly ``rows`` rows."""
    n = batch.count()
    if n > rows:
        raise BatchTooLarge(f"{n} rows, batches have {rows}")
    real = batch.withColumn("is_real", F.lit(True))
    more = batch.sparkSession.range(rows - n).select(F.lit(False).alias("is_real"))
    return real.unionByName(more, allowMissingColumns=True)


def oblivious_foreach(stream: DataFrame, rows: int, fn: Callable[[DataFrame, int], None]):
    """A writer that calls ``fn(padded batch, id)`` for every micro-batch; start it as any other."""
    return stream.writeStream.foreachBatch(lambda batch, i: fn(padded(batch, rows), i))


class TumblingCounts:
    """Counts per window and key over padded batches; rows later than the watermark become fillers and are counted in ``late``."""

    def __init__(self, at: str, key: str, width: str, delay_seconds: int | None = None, **options):
        self.at, self.key, self.width, self.delay, self.options = at, key, width, delay_seconds, options
        self.table: DataFrame | None = None
        self.latest, self.late = None, 0

    def __call__(self, batch: DataFrame, i: int) -> None:
        rows = batch
        if self.delay is not None and self.latest is not None:
            old = F.col(self.at) < F.lit(self.latest) - F.expr(f"INTERVAL {self.delay} SECONDS")
            self.late += rows.filter(F.col("is_real") & old).count()
            rows = rows.withColumn("is_real", F.col("is_real") & ~F.coalesce(old, F.lit(False)))
        newest = batch.agg(F.max(self.at)).first()[0]
        if newest is not None:
            self.latest = newest if self.latest is None else max(self.latest, newest)
        rows = self._windows(rows)
        rows = rows.withColumn("n", F.lit(1).cast("long"))
        if self.table is not None:
            rows = rows.unionByName(self.table.withColumn("is_real", F.lit(True)))
        self.table = self._merged(rows)

    def _merged(self, rows: DataFrame) -> DataFrame:
        return materialise(release(group_aggregate(rows, ["window_start", self.key], {"n": ("sum", F.col("n"))}, **self.options)), "windows")

    def _windows(self, rows: DataFrame) -> DataFrame:
        """(window_start, key, is_real): a row for each window that a row counts in."""
        return rows.select(F.date_trunc(self.width, F.col(self.at)).cast("timestamp_ntz").alias("window_start"), self.key, "is_real")


class SlidingCounts(TumblingCounts):
    """Counts per overlapping window and key: windows of ``width`` seconds begin every ``slide`` seconds, so every row counts in the same public number of them.

    Rows are counted once, in panes of ``slide`` seconds (``panes``: their number becomes public, as that of the windows does); then each pane counts in its windows.
    """

    def __init__(self, at: str, key: str, width: int, slide: int, delay_seconds: int | None = None, **options):
        if width % slide:
            raise ValueError("a window is a whole number of slides long")
        super().__init__(at, key, "", delay_seconds, **options)
        self.seconds, self.slide = width, slide
        self.panes: DataFrame | None = None

    def __call__(self, batch: DataFrame, i: int) -> None:
        self.table = self.panes
        super().__call__(batch, i)
        self.panes = self.table
        starts = F.array(*[F.col("window_start") - F.expr(f"make_dt_interval(0, 0, 0, {k * self.slide})") for k in range(self.seconds // self.slide)])
        self.table = self._merged(self.panes.select(F.explode(starts).alias("window_start"), self.key, "n"))

    def _windows(self, rows: DataFrame) -> DataFrame:
        epoch = "TIMESTAMP_NTZ'1970-01-01 00:00:00'"  # by the wall clock, whatever the session's zone
        second = F.expr(f"timestampdiff(SECOND, {epoch}, `{self.at}`)")
        rows = rows.withColumn("_start", F.floor(second / self.slide) * self.slide)
        return rows.select(F.expr(f"{epoch} + make_dt_interval(0, 0, 0, _start)").alias("window_start"), self.key, "is_real")


class BalanceState:
    """A table (addr, val) of fixed size; each batch adds its values by combining writes."""

    def __init__(self, cells: DataFrame, addr: str, value: str, **options):
        self.cells, self.addr, self.value, self.options = cells, addr, value, options

    def __call__(self, batch: DataFrame, i: int) -> None:
        req = batch.select(F.monotonically_increasing_id().alias("proc"), F.when(F.col("is_real"), F.col(self.addr)).alias("addr"), F.col(self.value).alias("val"))
        zero = self.cells.select("addr", F.lit(0).cast("long").alias("val"))
        added = pram_write(zero, req, "sum", **self.options).withColumnRenamed("val", "_add")
        self.cells = materialise(self.cells.join(added, "addr").select("addr", (F.col("val") + F.col("_add")).alias("val")), "balances")
