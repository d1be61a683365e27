"""Queries run all steps of the method that they name."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

import __spark_entry__ as entry
from oblivspark import workloads
from oblivspark.functions import kernels as K
from oblivspark.plans import params, trace
from tests.compare import same, views


def test_router_costs_have_layers(spark, sf):
    """ways, layers, tags, slots and the overflow bound, the layers as many as the router itself passes."""
    rows = entry.queries()["cost_router_layers"](spark, sf).collect()
    assert len(rows) == 6
    for r in rows:
        p = params.from_length(r.n)
        assert (r.z, r.beta, r.gamma, r.layers, r.tag_words, r.slots) == (p.z, p.beta, p.gamma, p.layers, p.tag_words, p.z * p.beta)
        assert r.log10_overflow < 0
        meter, s = K.Meter(trace=[]), K.Slab(np.arange(r.n, dtype=np.uint64)[:, None].copy(), np.ones(r.n, bool), np.zeros((r.n, 1), np.uint8))
        full = K.join([s, K.filler(r.slots - r.n, s)])
        K.route_layered(full, np.arange(r.slots) % r.beta, p.bits, p.radix_bits, p.z, "cluster", meter)
        assert sum(e[0] == "place" for e in meter.trace) == r.layers
    same(entry.queries()["cost_router_layers"](spark, sf), entry.oracle_sql()["cost_router_layers"], views(sf))


def test_router_costs_at_other_lengths(spark, tmp_path):
    """from no rows to some thousands, beside the SQL."""
    for i, (table, c) in enumerate(workloads._COUNTED):
        spark.range((0, 5, 40, 300, 2500, 16384)[i]).select(F.col("id").cast("double").alias(c)).coalesce(1).write.parquet(f"{tmp_path}/{table}.parquet")
    same(entry.queries()["cost_router_layers"](spark, str(tmp_path)), entry.oracle_sql()["cost_router_layers"], views(str(tmp_path)))


def test_components_find_what_groups_have_in_common(spark, sf, tmp_path):
    """edges link neighbours of a host, so that the least page is the graph's to find; pages without a url are one group, as in SQL."""
    pages = [(i * 7919 % 1009 + 1, None if i % 11 == 0 else "no host" if i % 13 == 0 else f"http://h{i % 5}.org/{i}", "<p>") for i in range(300)]
    df = spark.createDataFrame(pages, "page_id long, url string, html string")
    df.coalesce(1).write.parquet(f"{tmp_path}/pages.parquet")
    edges = workloads._groups_as_edges(df.select("page_id", F.regexp_extract("url", "://([^/]+)", 1).alias("h")), "page_id", "h").collect()
    assert len(edges) == 300 - 7 and len({e.v for e in edges}) == len({e.u for e in edges}) == len(edges)
    assert all(e.u != e.v for e in edges)
    same(entry.queries()["cc_page_hosts"](spark, str(tmp_path)), entry.oracle_sql()["cc_page_hosts"], views(str(tmp_path)))
