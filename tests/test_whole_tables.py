"""Queries cover all that a table holds, not the ids of one size."""

from collections import Counter

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry


@pytest.fixture(scope="module")
def more_users(spark, sf, tmp_path_factory):
    """The events with user ids moved up beyond 150."""
    d = str(tmp_path_factory.mktemp("users"))
    events = spark.read.parquet(f"{sf}/events.parquet")
    events.withColumn("user_id", (F.col("user_id") * 13 + 7).cast(events.schema["user_id"].dataType)).coalesce(1).write.parquet(f"{d}/events.parquet")
    return d


def test_histogram_has_all_users(spark, more_users):
    want = Counter(r[0] for r in spark.read.parquet(f"{more_users}/events.parquet").select("user_id").collect())
    assert max(want) > 150
    got = {r["cell"]: r["value"] for r in entry.queries()["pram_program_histogram"](spark, more_users).collect()}
    assert got == {i: want[i] for i in range(max(want) + 1)}


def test_balances_have_all_users(spark, more_users):
    rows = spark.read.parquet(f"{more_users}/events.parquet").select("user_id", F.round(F.col("value") * 100).cast("long").alias("c")).collect()
    want = Counter()
    for r in rows:
        want[r["user_id"]] += r["c"] or 0
    got = {r["user_id"]: r["val"] for r in entry.queries()["stream_state_balances"](spark, more_users).collect()}
    assert got == {i: want[i] for i in range(max(want) + 1)}
