"""The pipeline's stages beside plain Python, each on what the one before kept."""

import corpus_pipeline
from oblivspark.llm.decontaminate import normal_words, windows
from oblivspark.llm.quality import quality
from oblivspark.plans.shared import materialise
from tests.llm.test_llm import BLANK, texts
from tests.llm.test_near_copies import brute_stay


def test_stages(spark, sf):
    from collections import Counter

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    before, kept = {r["doc_id"]: r for r in docs.collect()}, []
    for name, stage in corpus_pipeline.STAGES:
        after = materialise(stage(spark, docs, sf), "test")
        kept.append((name, docs, after))
        docs = after
    (_, d0, d1), (_, _, d2), (_, _, d3), (_, _, d4), (_, _, d5) = kept
    for d in (d1, d2, d3, d4):
        assert d.columns == columns
    good = {r["doc_id"] for r in quality(d0, spark.read.parquet(f"{sf}/labels.parquet")).filter("predicted = 1").collect()}
    assert {r["doc_id"] for r in d1.collect()} == good and len(good) < len(before)
    key = lambda line: line.strip(BLANK).lower()
    seen = Counter(k for _, t in texts(d1) for k in {key(x) for x in t.split(b"\n")} if k)
    want = sorted((i, b"\n".join(x for x in t.split(b"\n") if not key(x) or seen[key(x)] < 10)) for i, t in texts(d1))
    assert sorted(texts(d2)) == want
    assert {r["doc_id"] for r in d3.collect()} == brute_stay(texts(d2))
    held = {w for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect() for w in windows(normal_words(r["text"].encode()), 10)}
    lengths = {w.count(b" ") + 1 for w in held}

    def clean(t):
        ws = normal_words(t)
        return not any(b" ".join(ws[a : a + n]) in held for n in lengths for a in range(len(ws) - n + 1))

    assert {r["doc_id"] for r in d4.collect()} == {i for i, t in texts(d3) if clean(t)}
    final = d5.collect()
    assert {r["doc_id"] for r in final} <= {r["doc_id"] for r in d4.collect()} and all(r["taken"] > 0 for r in final)
    positions = [r["first_position"] for r in corpus_pipeline.STAGES[-1][1](spark, d4, sf).collect()]
    assert positions == sorted(positions)


def test_stages_on_edges(spark, sf, edge, empty):
    """Nulls, ties, repeated rows and columns named as the stages name their own: every stage runs, keeps the columns, and gives what it says."""
    from pyspark.sql import functions as F

    odd = edge
    for name in ("_at", "_row", "_text", "_n_dropped", "_contaminated", "_stay"):
        odd = odd.withColumn(name, F.lit(7))
    for name, stage in corpus_pipeline.STAGES:
        last = stage is corpus_pipeline.mix_sources
        for docs in (odd.limit(0), odd):
            got = stage(spark, materialise(docs, "test"), sf)
            assert last or got.columns == odd.columns, name
            rows = got.collect()
            assert len(rows) <= docs.count() and (docs is odd or not rows)
            ids = [r["doc_id"] for r in docs.collect()]
            assert all(r["doc_id"] in ids for r in rows)
            assert last or all(r["_at"] == r["_stay"] == 7 for r in rows), name
