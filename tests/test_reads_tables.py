"""Queries on costs and views: Spark's tasks read a given table, and their figures follow from it."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from oblivspark.plans import params, trace

NAMES = [*(f"bounds_T{i}" for i in (1, 2, 3)), "cost_bitonic_counts", "cost_cache_replay", "cost_practical_constants", "cost_router_layers", "permute_uniformity", "view_equal_inputs"]


@pytest.mark.parametrize("name", NAMES)
def test_tasks_read_a_table(spark, sf, name):
    tracker, group = spark.sparkContext.statusTracker(), f"reads-{name}"
    store = spark.sparkContext._jsc.sc().statusStore()
    spark.sparkContext.setJobGroup(group, name)
    entry.queries()[name](spark, sf).collect()
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(10_000)
    stages = {i for j in tracker.getJobIdsForGroup(group) for i in tracker.getJobInfo(j).stageIds}
    rows = sum(store.lastStageAttempt(i).inputRecords() for i in stages)
    assert rows >= 100  # customer, the least of the tables read, has 150 rows


def test_few_rows_are_permuted_often_enough(spark):
    got = trace.table_uniformity(spark.range(70).select(F.col("id") * 7), 32, 400, params.from_length(32))
    assert abs(got["fixed_points"] - 1) < 0.2 and np.isfinite(list(got.values())).all()
