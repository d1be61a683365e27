"""The near-copy stage beside all pairs in plain Python."""

import random

import corpus_pipeline
from oblivspark.llm.near_copies import near_copies, roots_of, shingles
from oblivspark.llm.simhash import fingerprint
from oblivspark.plans.shared import materialise
from tests.llm.test_llm import texts


def brute_stay(rows):
    """The ids that stay: the least of each group that pairs of 0.8 and more join."""

    def cut(t):
        w = t.lower().split()
        return {b" ".join(w)} if len(w) <= 5 else {b" ".join(w[i : i + 5]) for i in range(len(w) - 4)}

    sets = [cut(t) for _, t in rows]
    group = list(range(len(rows)))
    for a in range(len(rows)):
        for b in range(a):
            common = len(sets[a] & sets[b])
            if common * 5 >= 4 * (len(sets[a]) + len(sets[b]) - common) and group[a] != group[b]:
                old, new = group[a], group[b]
                group = [new if g == old else g for g in group]
    least = {}
    for (i, _), g in zip(rows, group):
        if i is not None:
            least[g] = min(i, least.get(g, i))
    return {i for (i, _), g in zip(rows, group) if i == least.get(g)}


def test_pairs_beyond_two_bits(spark, sf):
    r = random.Random(5)
    rows = []
    for k in range(40):
        words = [f"w{r.randrange(5000)}" for _ in range(120)]
        rows.append((3 * k, " ".join(words)))
        for extra in (1, 2):  # a chain: each is like the one before
            words[r.randrange(120)] = f"x{k}_{extra}"
            words[r.randrange(120)] = f"y{k}_{extra}"
            rows.append((3 * k + extra, " ".join(words)))
    rows = [(i, t.encode()) for i, t in rows]
    far = [(fingerprint(rows[k][1]) ^ fingerprint(rows[k + 1][1])).bit_count() for k in range(0, 120, 3)]
    assert max(far) > 2  # what the stage missed
    want = brute_stay(rows)
    assert len(want) < 80
    docs = spark.createDataFrame([(i, t.decode()) for i, t in rows], "doc_id long, text string").repartition(7)
    got = [x["doc_id"] for x in corpus_pipeline.drop_near_copies(spark, docs, sf).collect()]
    assert len(got) == len(set(got)) and set(got) == want


def test_given_table(spark, sf):
    docs = materialise(corpus_pipeline.drop_lines(spark, spark.read.parquet(f"{sf}/documents.parquet"), sf), "test")
    assert {x["doc_id"] for x in near_copies(docs).collect()} == brute_stay(texts(docs))


def test_edges(edge, empty):
    assert near_copies(empty).count() == 0
    got = near_copies(edge)
    assert got.columns == edge.columns
    assert {x["doc_id"] for x in got.collect()} == brute_stay(texts(edge))


def test_roots():
    sets = [shingles(" ".join(map(str, range(a, a + 60))).encode()) for a in (0, 500, 3, 6, 9, 503, 900)]
    assert roots_of(sets).tolist() == [0, 1, 0, 0, 0, 1, 6]
