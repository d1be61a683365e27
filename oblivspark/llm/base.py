"""What the text kernels share: Arrow batches of documents in, Arrow batches of results out."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..plans.shared import ship_package


def read(spark, sf_dir: str, table: str) -> DataFrame:
    """A table of ``sf_dir``, by Spark's reader alone."""
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def id_and_text(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", *more) -> DataFrame:
    """Only the columns that a kernel needs, under fixed names; a null text is the empty text."""
    return docs.select(
        F.col(f"`{id_col}`").alias("doc_id"), F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit("")).alias("text"), *more
    )


def unused(docs: DataFrame, name: str) -> str:
    """``name``, with as many underscores before it as make it no column of ``docs``."""
    taken = {c.lower() for c in docs.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def map_batches(df: DataFrame, kernel: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: StructType | str) -> DataFrame:
    """``mapInArrow``; batches are bounded by ``spark.sql.execution.arrow.maxBytesPerBatch``."""
    ship_package(df.sparkSession)
    return df.mapInArrow(kernel, schema)


def texts_of(batch: pa.RecordBatch, column: str = "text") -> list[bytes]:
    """The UTF-8 bytes of each text, without a detour over Python strings."""
    at = batch.schema.get_field_index(column)
    col = batch.column(at)
    return col.cast(pa.large_binary() if pa.types.is_large_string(col.type) else pa.binary()).to_pylist()


def column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))
