"""Tree functions by few sorts: twins and nodes are found by their places, not by sending."""

from oblivspark.operators import graphs


def test_one_send_for_a_tree(spark, monkeypatch):
    sent = []
    plain = graphs.send_receive
    monkeypatch.setattr(graphs, "send_receive", lambda *a, **k: sent.append(1) or plain(*a, **k))
    edges = spark.createDataFrame([(0, 1), (0, 2), (2, 3)], "a long, b long")
    got = sorted(tuple(r) for r in graphs.tree_functions(edges, 0, seed=7, level="cluster").collect())
    assert got == [(0, None, 0, 0, 3, 4, False), (1, 0, 1, 1, 0, 1, True), (2, 0, 1, 2, 2, 2, False), (3, 2, 2, 3, 1, 1, True)]
    assert len(sent) == 1  # the list ranker's; six before


def test_carried_columns(spark):
    df = spark.createDataFrame([(1, 2, "a"), (2, 0, "b"), (3, None, None)], "id long, succ long, name string").select("id", "succ", "id", "name").toDF("id", "succ", "same", "name")
    got = graphs.list_rank(df, "id", "succ", seed=7, level="cluster", carry=["same"])
    assert got.columns == ["id", "ahead", "same"] and sorted(map(tuple, got.collect())) == [(1, 1, 1), (2, 0, 2), (3, 0, 3)]
