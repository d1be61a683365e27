"""The near-copy stage goes through SimHash and its vantage-point tree."""

import random

import corpus_pipeline
from oblivspark.llm import near_copies as N
from oblivspark.llm import simhash


def copies():
    r = random.Random(11)
    rows = []
    for k in range(30):
        words = [f"w{r.randrange(9000)}" for _ in range(400)]
        rows.append((2 * k, " ".join(words)))
        rows.append((2 * k + 1, " ".join(words[1:])))
    return rows


def test_majority_is_the_fingerprint():
    for _, t in [*copies(), (0, "a b c d e"), (0, "x " * 70_000)]:
        assert simhash.majority(N.sequence(t.encode())) == simhash.fingerprint(t.encode(), N.WIDTH)


def test_groups_of_fingerprints(spark):
    """Nodes within two bits, and chains of them, share the band of their group; others don't."""
    fp = {}
    for i, t in copies():
        fp[i] = simhash.fingerprint(t.encode(), N.WIDTH)
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    got = N._by_fingerprint(spark.createDataFrame([(i, signed(x)) for i, x in fp.items()], "node long, fp long")).collect()
    band = {r["node"]: r["band"] for r in got}
    assert len(got) == len(fp)
    links = [(a, b) for a in fp for b in fp if a < b and (fp[a] ^ fp[b]).bit_count() <= 2]
    assert links and {(a, b) for a in fp for b in fp if a < b and band[a] == band[b]} == set(links)


def test_stage_uses_the_tree(spark, sf, monkeypatch):
    seen = []
    plain = simhash.linked
    monkeypatch.setattr(simhash, "linked", lambda *a: seen.append(a[-1]) or plain(*a))
    docs = spark.createDataFrame(copies(), "doc_id long, text string")
    got = {r["doc_id"] for r in corpus_pipeline.drop_near_copies(spark, docs, sf).collect()}
    assert got == set(range(0, 60, 2)) and seen == [N.REACH]
