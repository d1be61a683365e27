"""The registered queries of this subpackage: each operator over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import oracles
from .base import read
from .decontaminate import decontaminate
from .exact_dedup import exact_dedup
from .licenses import license_scan
from .line_dedup import line_dedup
from .mixing import mix
from .ppm import lm_scores
from .quality import quality
from .simhash import near_dedup
from .suffix_dedup import suffix_dedup
from .token_counts import token_counts


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup(read(spark, sf_dir, "documents"))


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scores(read(spark, sf_dir, "documents"))


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark")).drop("spans")


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup(read(spark, sf_dir, "documents"))


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan(read(spark, sf_dir, "documents"))


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup(read(spark, sf_dir, "documents")).drop("spans")


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return token_counts(read(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(read(spark, sf_dir, "documents"), keep="max")


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mix(read(spark, sf_dir, "documents"), columns=["doc_id"])
    return mixed.select("doc_id", "size", "source_size", "target", "taken", "first_position")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    return {
        "op1_line_dedup": op1,
        "op2_lm_scoring": op2,
        "op3_decontamination": op3,
        "op4_simhash_dedup": op4,
        "op5_license_scan": op5,
        "op6_quality": op6,
        "op7_suffix_dedup": op7,
        "op8_token_counts": op8,
        "op9_exact_dedup": op9,
        "op10_mixing": op10,
        "pipeline": pipeline,
    }


oracle_sql = oracles.oracle_sql
