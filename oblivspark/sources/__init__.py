"""Readers and writers that neither skip by secret values nor let compression tell about them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

FORMATS = ("parquet", "csv", "json", "orc", "text", "binaryFile", "jdbc", "avro")


def read(spark: SparkSession, path: str, format: str = "parquet", schema: StructType | str | None = None, **options) -> DataFrame:  # noqa: A002
    """A table by Spark's reader; columns are pruned, which is public, while filters stay above (``plans.trace.OBLIVIOUS_CONF`` turns push-down off)."""
    if format not in FORMATS:
        raise ValueError(f"a format is one of {FORMATS}")
    reader = spark.read.format(format).options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    return reader.load(path)


def rows(spark: SparkSession, data: list, schema: StructType | str) -> DataFrame:
    return spark.createDataFrame(data, schema)


def write(df: DataFrame, path: str, mode: str = "error") -> None:
    """All rows, fillers too, uncompressed and without dictionaries, so that bytes follow from length and widths."""
    df.write.mode(mode).option("parquet.enable.dictionary", "false").option("compression", "none").parquet(path)


def public_widths(df: DataFrame, slack: int = 0) -> dict[str, int]:
    """The largest byte length of each string or binary column: to be called once, when those lengths are declared public."""
    cols = [f.name for f in df.schema if f.dataType.simpleString() in ("string", "binary")]
    if not cols:
        return {}
    r = df.agg(*[F.coalesce(F.max(F.octet_length(c)), F.lit(1)).alias(c) for c in cols]).first()
    return {c: max(1, r[c]) + slack for c in cols}


def chunks(df: DataFrame, text: str, width: int, most: int) -> DataFrame:
    """A wide string as ``most`` rows of one fixed width each: (other columns, chunk_no, chunk); longer texts are refused."""
    over = df.filter(F.length(text) > width * most).limit(1).count()
    if over:
        raise ValueError(f"a text is longer than {most} chunks of {width}")
    rest = [c for c in df.columns if c != text]
    return df.select(*rest, F.explode(F.sequence(F.lit(0), F.lit(most - 1))).alias("chunk_no"), F.col(text).alias("_t")).select(
        *rest, "chunk_no", F.rpad(F.substring(F.col("_t"), F.col("chunk_no") * width + 1, F.lit(width)), width, " ").alias("chunk")
    )


def catalog(spark, folder: str, names: list[str]) -> None:
    """The tables of a folder as temporary views, for SQL."""
    for name in names:
        read(spark, f"{folder}/{name}.parquet").createOrReplaceTempView(name)


def register_functions(spark) -> None:
    """The routers' public numbers as SQL functions of a length: slots of a bin, and bins."""
    from ..plans.params import from_length

    spark.udf.register("router_slots", lambda n: None if n is None else from_length(n).z, "long")
    spark.udf.register("router_bins", lambda n: None if n is None else from_length(n).beta, "long")
