"""A training corpus in five stages, each on all that the one before kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from oblivspark.llm.base import read, unused
from oblivspark.llm.decontaminate import decontaminate
from oblivspark.llm.line_dedup import line_dedup
from oblivspark.llm.mixing import mix
from oblivspark.llm.near_copies import near_copies
from oblivspark.llm.quality import quality
from oblivspark.plans.shared import materialise


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the discriminant rejects go; a document without an id stays or goes by its own score."""
    at = unused(docs, "_at")
    docs = materialise(docs.withColumn(at, F.monotonically_increasing_id()), "stage")
    scored = quality(docs, read(spark, sf_dir, "labels"), row_col=at)
    good = scored.filter("predicted = 1").select(F.col("row").alias(at))
    return docs.join(good, at, "left_semi").drop(at)


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines found in ten documents or more leave the texts; the count of characters follows."""
    out = line_dedup(docs, carry=True)
    dropped = F.col(out.columns[-1]) > 0
    return out.withColumn("n_chars", F.when(dropped, F.length("text")).otherwise(F.col("n_chars"))).select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies, found by SimHash and beyond its reach by bands and compared exactly, the document of the least id stays."""
    return near_copies(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go."""
    out = decontaminate(docs, read(spark, sf_dir, "benchmark"), carry=True)
    return out.filter(~F.col(out.columns[-1])).select(*docs.columns)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that the mix takes, with how many words of each, in order of training position."""
    return mix(docs).filter(F.col("taken") > 0)


STAGES = [
    ("quality classifier", keep_quality),
    ("line dedup", drop_lines),
    ("SimHash near copies, exactly compared", drop_near_copies),
    ("benchmark decontamination", drop_contaminated),
    ("mixing sources to target weights", mix_sources),
]

#: SQL can't express the classifier, so the pipeline is tested against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each stage's result is written and read again."""
    docs = read(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = materialise(docs, "stage")
    return docs
