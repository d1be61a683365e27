"""Written tables in the shared folder, skew-safe lookups and dense positions.

Everything here survives the loss of executors: intermediate results are
Parquet tables in the folder that the cluster names in ``spark.checkpoint.dir``.
"""

from __future__ import annotations

import re
import tempfile
import uuid
import zipfile
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: A key counts as hot when it holds at least this share of the rows, so there are at most as many hot keys.
HOT_KEYS = 1024


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a local one only where that is unset and the master is local too (tests)."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = tempfile.mkdtemp(prefix="oblivspark-")
        spark.sparkContext.setCheckpointDir(found)
    return found


def ship_package(spark: SparkSession) -> None:
    """Send this package to the Python workers, once a Spark context: executors need no copy of their own."""
    context = spark.sparkContext
    if getattr(context, "_oblivspark_shipped", False):
        return
    package = Path(__file__).resolve().parent.parent
    to = Path(tempfile.mkdtemp(prefix="oblivspark-")) / f"oblivspark-{uuid.uuid4().hex[:8]}.zip"
    with zipfile.ZipFile(to, "w") as z:
        for f in sorted(package.rglob("*.py")):
            z.write(f, f.relative_to(package.parent))
    context.addPyFile(str(to))
    context._oblivspark_shipped = True


#: Paths of the tables written within each open ``scratch``.
_scratch: list[list[str]] = []


@contextmanager
def scratch(spark: SparkSession):
    """Delete, at the end, the tables that steps wrote meanwhile; results must have been read or written elsewhere by then."""
    held: list[str] = []
    _scratch.append(held)
    try:
        yield held
    finally:
        _scratch.remove(held)
        conf = spark.sparkContext._jsc.hadoopConfiguration()
        for path in held:
            at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(conf).delete(at, True)


def discard(*tables: DataFrame) -> None:
    """Delete the files of tables that ``materialise`` wrote and that no later step reads; others stay as they are."""
    for df in tables:
        path = df.__dict__.get("_written")
        if path:
            context = df.sparkSession.sparkContext
            at = context._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(context._jsc.hadoopConfiguration()).delete(at, True)


def kept(spark: SparkSession, make, name: str = "table") -> DataFrame:
    """What ``make()`` gives, written down; the tables that were written on the way there go."""
    with scratch(spark) as held:
        out = materialise(make(), name)
        held.pop()
    return out


#: Spark's setting by which the files of a query's exchanges go as soon as the query has ended, not when the driver next collects garbage.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


#: Called with every table before it is written, while a guard is on.
_watchers: list = []


def materialise(df: DataFrame, name: str = "table") -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it again: cuts the lineage and fixes the rows."""
    for look in _watchers:
        look(df)
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    for held in _scratch:
        held.append(path)
    conf = df.sparkSession.conf
    before = conf.get(_CLEANUP, None)
    conf.set(_CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        conf.unset(_CLEANUP) if before is None else conf.set(_CLEANUP, before)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._written = path
    return out


def fixed_rows(df: DataFrame) -> DataFrame:
    """``df`` if its partitions are read from files, whose rows keep their places; else written down, for a task that runs again may get what an exchange brings in another order."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return materialise(df, "rows") if any(x in plan for x in ("Exchange", "Generate", "InArrow", "InPandas", "Python")) else df


def numbered(df: DataFrame, name: str = "pos") -> DataFrame:
    """Append ``name``: 0, 1, 2 ... in the order in which rows stand, partition after partition; only counts move."""
    place = F.monotonically_increasing_id()
    at = materialise(df.withColumn("_pid", F.shiftright(place, 33)).withColumn("_place", place.bitwiseAND(F.lit((1 << 33) - 1))), "numbered")
    counts = at.groupBy("_pid").agg(F.count(F.lit(1)).alias("_n"))
    offsets = counts.withColumn("_off", F.sum("_n").over(Window.orderBy("_pid")) - F.col("_n")).select("_pid", "_off")
    return at.join(F.broadcast(offsets), "_pid").select(*df.columns, (F.col("_off") + F.col("_place")).alias(name))


def skew_safe_lookup(
    df: DataFrame, table: DataFrame, key: str, rows: str, total: int, payload: list[str]
) -> DataFrame:
    """Left join of ``df`` with ``table`` (unique on ``key``, which is not null on either side).

    ``table[rows]`` says how many rows of ``df`` have the key, ``total`` how many rows ``df`` has.
    Keys with over 1/1024 of the rows, so at most 1,024 of them, are broadcast; their rows
    take part in the shuffled join under a spread-out second key that matches nothing.
    """
    hot = table.filter(F.col(rows) * HOT_KEYS > F.lit(total)).select(
        F.col(key).alias("_hk"), F.struct(*payload).alias("_hot")
    )
    cold = table.select(F.col(key).alias("_ck"), F.lit(0).cast("long").alias("_cs"), F.struct(*payload).alias("_cold"))
    out = df.join(F.broadcast(hot), F.col(key) == F.col("_hk"), "left")
    out = out.withColumn(
        "_s",
        F.when(F.col("_hk").isNull(), F.lit(0).cast("long")).otherwise(
            F.lit(1).cast("long") + F.pmod(F.xxhash64(*df.columns), F.lit(1 << 40))
        ),
    )
    out = out.join(cold, (F.col(key) == F.col("_ck")) & (F.col("_s") == F.col("_cs")), "left")
    got = F.coalesce("_hot", "_cold")
    return out.select(*df.columns, *(got[c].alias(c) for c in payload))


def dense_positions(df: DataFrame, order: list[Column], name: str = "pos", partitions: int | None = None) -> DataFrame:
    """Append ``name``: 0, 1, 2 ... in the given order, without moving all rows to one task.

    One range exchange, written down so that counts and rows agree; the offsets are one
    row per partition. Rows that tie in ``order`` get positions in no fixed order.
    """
    spark = df.sparkSession
    n = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    place = F.monotonically_increasing_id()  # the partition, then the place in its order
    sorted_ = df.repartitionByRange(n, *order).sortWithinPartitions(*order)
    dealt = materialise(sorted_.withColumns({"_pid": F.shiftright(place, 33), "_rn": place.bitwiseAND(F.lit((1 << 33) - 1))}), "ranged")
    counts = dealt.groupBy("_pid").agg(F.count(F.lit(1)).alias("_n"))
    offsets = counts.withColumn("_off", F.sum("_n").over(Window.orderBy("_pid")) - F.col("_n")).select("_pid", "_off")
    return dealt.join(F.broadcast(offsets), "_pid").withColumn(name, F.col("_off") + F.col("_rn")).drop("_pid", "_off", "_rn")
