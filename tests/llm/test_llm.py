"""Every operator on a table of edge cases and on the smallest given tables, beside brute force, SQL or the library it stands in for."""

import hashlib
import math
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from oblivspark.llm import licenses, phash, ppm, queries, simhash, suffix_dedup
from oblivspark.llm.decontaminate import decontaminate, normal_words, windows, word_offsets
from oblivspark.llm.exact_dedup import exact_dedup
from oblivspark.llm.line_dedup import line_dedup
from oblivspark.llm.mixing import integrate, mix, position_of
from oblivspark.llm.quality import quality
from oblivspark.llm.token_counts import token_counts
from tests.compare import same, views

BLANK = b" \t\n\x0b\x0c\r"


def rows(df, *cols):
    return [tuple(r) for r in df.select(*cols).collect()]


def texts(df):
    return [(r[0], (r[1] or "").encode()) for r in df.select("doc_id", "text").collect()]


def sha(b):
    return hashlib.sha256(b).hexdigest()


def documents(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.mark.parametrize("name", ["op1_line_dedup", "op3_decontamination", "op7_suffix_dedup", "op9_exact_dedup", "op10_mixing"])
def test_sql(spark, sf, name):
    same(queries.queries()[name](spark, sf), queries.oracle_sql()[name], views(sf))


# -- lines


def brute_lines(docs, least):
    key = lambda line: line.strip(BLANK).lower()
    seen = Counter(k for _, t in docs for k in {key(x) for x in t.split(b"\n")} if k)
    out = []
    for i, t in docs:
        own = t.split(b"\n")
        left = [x for x in own if not key(x) or seen[key(x)] < least]
        out.append((i, len(own), len(own) - len(left), sha(b"\n".join(left))))
    return out


@pytest.mark.parametrize("shards", [{}, {"shard_keys": 1, "round_shards": 1}])
def test_lines(edge, empty, shards):
    got = rows(line_dedup(edge, 2, **shards), "doc_id", "n_lines", "n_dropped", "kept_sha256")
    assert sorted(map(str, got)) == sorted(map(str, brute_lines(texts(edge), 2)))
    assert rows(line_dedup(empty), "doc_id") == []


def test_perfect_hash():
    keys = np.unique(np.random.default_rng(1).integers(0, 1 << 63, 20_000).astype(np.uint64))
    assert sorted(phash.PerfectHash(keys).index(keys).tolist()) == list(range(len(keys)))
    shard = phash.CountShard(np.array([5, 5, 9], np.uint64), np.array([1, 2, 3], np.uint64), np.array([10, 20, 30]))
    assert shard.counts(np.array([5, 5, 9, 9, 7], np.uint64), np.array([1, 2, 3, 4, 0], np.uint64)).tolist() == [10, 20, 30, 0, 0]


# -- language model


def brute_ppm(train, text, order):
    seen = {}
    for t in train:
        h = (ppm.EDGE,) * order
        for s in [*t, ppm.EDGE]:
            for k in range(order + 1):
                own = seen.setdefault(h[order - k :], {})
                own[s] = own.get(s, 0) + 1
            h = (*h[1:], s) if order else ()
    h, total = (ppm.EDGE,) * order, 0.0
    for s in [*text, ppm.EDGE]:
        out = set()
        for k in range(order, -1, -1):
            own = seen.get(h[order - k :], {})
            left = {c: n for c, n in own.items() if c not in out}
            whole = 2 * sum(left.values())
            if s in left:
                total += math.log10((2 * left[s] - 1) / whole)
                break
            if left:
                total += math.log10(len(left) / whole)
            out |= own.keys()
        else:
            total -= math.log10(max(257 - len(out), 1))
        h = (*h[1:], s) if order else ()
    return total


@pytest.mark.parametrize("order,shard,block", [(5, 1 << 18, 1 << 24), (5, 60, 300), (3, 40, 1), (0, 20, 100)])
def test_language_model(edge, empty, monkeypatch, order, shard, block):
    """The same scores however many shards, blocks and pieces there are."""
    monkeypatch.setattr(ppm, "WORD_BYTES", 100)
    docs = texts(edge.filter("doc_id IS NULL OR doc_id NOT IN (5, 6)"))
    got = ppm.lm_scores(edge.filter("doc_id IS NULL OR doc_id NOT IN (5, 6)"), order=order, shard_grams=shard, block_bytes=block).collect()
    held = lambda i: zlib.crc32(b"" if i is None else str(i).encode()) % 7 == 2
    train = [t for i, t in docs if not held(i)]
    c = Counter(w for t in train for w in [*t.lower().split(), 0])
    n, v = sum(c.values()), len(c)
    want = []
    for i, t in docs:
        ws = [*t.lower().split(), 0]
        want.append((i, held(i), len(ws), sum(c[w] > 0 for w in ws), n, sum(math.log10((c[w] + 1) / (n + v + 1)) for w in ws), brute_ppm(train, t, order)))
    order_by = lambda r: (str(r[0]), r[2], round(r[6], 6))
    for a, b in zip(sorted(map(tuple, got), key=order_by), sorted(want, key=order_by), strict=True):
        assert a[:5] == b[:5] and a[5:] == pytest.approx(b[5:], abs=1e-6)
    assert ppm.lm_scores(empty).collect() == []


def test_dealt_trie_is_the_whole_one():
    """Shards whose ends cut contexts of every length give the probabilities that one trie gives, in pieces too."""
    texts = [bytes(t) for t in np.random.default_rng(1).integers(97, 101, (40, 60)).astype(np.uint8)]
    flat = np.concatenate([ppm.grams_of(t) for t in texts])
    assert all((np.concatenate([ppm.grams_of(t, 5, a, min(a + 7, 61)) for a in range(0, 61, 7)]) == ppm.grams_of(t)).all() for t in texts)
    k, n = np.unique(flat, return_counts=True)
    n[::5] = 0
    whole = ppm.Trie(k, n).log10(k)
    cuts = np.unique(k[17::97] >> np.uint64(9))
    across = ppm.spanning(cuts, 5)
    assert all(len(a) for a in across)
    told = []
    for level in range(5):
        context = ppm.context_at(k, level, 5)
        on = (ppm.find(across[level], context) >= 0) & (n > 0)
        told.append((across[level], *ppm._merge([context[on] << np.uint64(9) | k[on] & np.uint64(511)], [n[on]])))
    at = np.searchsorted(cuts, k >> np.uint64(9), "right")
    for shard in range(len(cuts) + 1):
        mine = at == shard
        assert ppm.Trie(k[mine], n[mine], 5, told).log10(k[mine]) == pytest.approx(whole[mine], abs=1e-12)


def test_probabilities_add_up():
    train = [b"the cat sat", b"the mat", b""]
    k, n = np.unique(np.concatenate([ppm.grams_of(t) for t in train]), return_counts=True)
    model = ppm.Trie(k, n)
    for context in (b"the c", b"zzzzz", b""):
        base = ppm.grams_of(context)[-1] >> np.uint64(9) << np.uint64(9)
        assert sum(10 ** model.log10(np.array([base | np.uint64(s) for s in range(257)]))) == pytest.approx(1, abs=1e-9)
    assert ppm.adaptive_log10(b"abababababab") > ppm.adaptive_log10(b"axbyczdwevfu")


def test_model_beats_words_where_it_has_data(spark, sf):
    r = queries.queries()["op2_lm_scoring"](spark, sf).toPandas()
    seen = r[~r.held_out]
    assert seen.score.sum() > seen.base_score.sum()
    short = ppm.lm_scores(documents(spark, sf), order=1).toPandas()
    assert r[r.held_out].score.sum() > short[short.held_out].score.sum()  # longer contexts foretell texts that training hasn't seen


# -- benchmark


def brute_hits(docs, items, width):
    of = defaultdict(set)
    for i, t in items:
        for w in windows(normal_words(t), width):
            of[w].add(i)
    lengths = {w.count(b" ") + 1 for w in of}
    out = []
    for i, t in docs:
        ws, hit, found = normal_words(t), set(), set()
        for n in lengths:
            for a in range(len(ws) - n + 1):
                got = of.get(b" ".join(ws[a : a + n]))
                if got:
                    hit.update(range(a, a + n))
                    found |= got
        names = sorted(str(x) for x in found if x is not None)
        out.append((i, len(ws), len(hit), len(found), sha(",".join(names).encode()), bool(hit)))
    return out


COLS = ("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def test_benchmark(spark, sf, edge, empty):
    docs, bench = documents(spark, sf), spark.read.parquet(f"{sf}/benchmark.parquet")
    items = [(r[0], r[1].encode()) for r in bench.select("item_id", "text").collect()]
    got = rows(decontaminate(docs, bench), *COLS)
    assert sorted(got) == sorted(brute_hits(texts(docs), items, 10))
    own = spark.createDataFrame([(7, "Cat, SAT on"), (8, "short"), (None, "one line"), (3, None), (4, "!!!"), (70, "cat sat on")], "item_id long, text string")
    items = [(r[0], (r[1] or "").encode()) for r in own.collect()]
    assert sorted(map(str, rows(decontaminate(edge, own, width=3), *COLS))) == sorted(map(str, brute_hits(texts(edge), items, 3)))
    assert not any(r[-1] for r in rows(decontaminate(edge, own.filter("1 = 0")), *COLS)) and rows(decontaminate(empty, own), "doc_id") == []
    # a benchmark of many rounds gives what one automaton gives
    assert sorted(map(str, rows(decontaminate(edge, own, width=3, round_windows=1), *COLS))) == sorted(map(str, brute_hits(texts(edge), items, 3)))
    assert sorted(map(str, decontaminate(docs, bench, round_windows=200).collect())) == sorted(map(str, decontaminate(docs, bench).collect()))
    hit = decontaminate(edge.filter("doc_id = 4"), own, width=3).collect()[0]
    assert [tuple(x) for x in hit["spans"]] == [(0, 8), (18, 26)]
    assert word_offsets("Ä, b".encode()).tolist() == [[0, 2], [4, 5]]


# -- near copies


def brute_components(docs, width=3, reach=2):
    fp = [simhash.fingerprint(t, width) for _, t in docs]
    parent = list(range(len(fp)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(fp)):
        for b in range(a):
            if (fp[a] ^ fp[b]).bit_count() <= reach:
                parent[find(a)] = find(b)
    least = {}
    for a, (i, _) in enumerate(docs):
        if i is not None:
            least[find(a)] = min(i, least.get(find(a), i))
    return [(i, f"{fp[a]:016x}", least.get(find(a))) for a, (i, _) in enumerate(docs)]


def test_near_copies(spark, sf, edge, empty):
    for df in (documents(spark, sf), edge):
        got = rows(simhash.near_dedup(df), "doc_id", "fingerprint", "component_id")
        assert sorted(map(str, got)) == sorted(map(str, brute_components(texts(df))))
    assert simhash.near_dedup(empty).collect() == []
    stay = {r[0] for r in brute_components(texts(edge)) if r[0] == r[2]}
    assert {r[0] for r in rows(simhash.near_dedup(edge, carry=True), "doc_id")} == stay


def test_fingerprint_by_definition():
    import xxhash

    text = "One two\tTHREE four five".encode()
    words = [b"one", b"two", b"three", b"four", b"five"]
    hs = [xxhash.xxh64_intdigest(b" ".join(words[i : i + 3]), 42) for i in range(3)]
    assert simhash.fingerprint(text) == sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hs) * 2 > 3)
    assert simhash.fingerprint(b" \n") == 0 and simhash.fingerprint(b"A b") == xxhash.xxh64_intdigest(b"a b", 42)


@pytest.mark.parametrize("spread", [0, 6])
def test_tree_loses_no_link(spread):
    rng = np.random.default_rng(spread)
    base = rng.integers(0, 1 << 63, 40 if spread else 1500).astype(np.uint64)
    points = np.unique(np.concatenate([base ^ np.bitwise_or.reduce(np.uint64(1) << rng.integers(0, 64, (k, len(base))).astype(np.uint64), axis=0) for k in range(1, 4) for _ in range(1 + spread)]))
    tree, pairs = simhash.grow(points[:200], 16), set()
    for _, home, guests in simhash.route(tree, points, 2):
        every = np.concatenate((home, guests))
        a, b = np.nonzero(np.bitwise_count(points[home][:, None] ^ points[every][None, :]) <= 2)
        pairs |= {(min(x, y), max(x, y)) for x, y in zip(home[a].tolist(), every[b].tolist())}
    a, b = np.nonzero(np.bitwise_count(points[:, None] ^ points[None, :]) <= 2)
    assert pairs == {(min(x, y), max(x, y)) for x, y in zip(a.tolist(), b.tolist())}


# -- licences


def test_licenses(spark, sf, edge, empty):
    docs = documents(spark, sf)
    import re

    cut = lambda t: re.findall(rb"[0-9a-z\x80-\xff]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), t))
    runs = lambda ws: [tuple(ws[i : i + 5]) for i in range(max(1, len(ws) - 4))] if ws else []

    def brute(t):
        """Every stretch of every text against every template, on whole words."""
        own, found = runs(cut(t)), {}
        for name, notices in licenses.TEMPLATES.items():
            for notice in notices:
                ws = cut(notice.encode())
                asked = set(runs(ws))
                stretch = len(runs(ws)) + max(3, len(ws) // 2) - 1
                at = [i for i, x in enumerate(own) if x in asked]
                best = max((len({own[i] for i in at if a <= i < a + stretch}) for a in at), default=0) / len(asked)
                if best >= 0.8:
                    found[name] = max(best, found.get(name, 0))
        return found

    want = []
    for i, t in texts(docs):
        found = brute(t)
        want.append((i, len(found), ",".join(sorted(found)), max(found.values(), default=0.0)))
    assert sorted(rows(licenses.license_scan(docs), "doc_id", "n_licenses", "licenses", "containment")) == sorted(want)
    assert sum(r[1] for r in want) > 0
    assert all(r[1] == 0 for r in rows(licenses.license_scan(edge), "doc_id", "n_licenses")) and licenses.license_scan(empty).collect() == []
    # notices spread by foreign words, at the ends of texts and beside others: the same whatever stands beside a text
    words = cut(licenses.TEMPLATES["MIT"][1].encode())
    spread = [b" ".join(words[: 2 + k % 3] + [b"x"] * k + words[2 + k % 3 :]) for k in range(14)]
    alone = [licenses.Scanner(licenses.TEMPLATES).scan([t])[0] for t in spread]
    assert alone == licenses.Scanner(licenses.TEMPLATES).scan(spread) == [brute(t) for t in spread] and alone[0] and alone[3] and not all(alone)
    most = licenses.most_contained(np.array([1, 2, 9, 3, 1, 2, 3], np.uint64), np.array([1, 2, 3], np.uint64), 3)
    assert most == 1.0


# -- quality


def test_quality(spark, edge, empty):
    sf = "/root/testdata/sf0.01"
    got = queries.queries()["op6_quality"](spark, sf).toPandas()
    labels = spark.read.parquet(f"{sf}/labels.parquet").toPandas().merge(got, on="doc_id")
    held = labels[labels.held_out]
    assert (held.quality == held.predicted).mean() > 0.97
    assert (got.held_out == [zlib.crc32(str(i).encode()) % 3 == 1 for i in got.doc_id]).all() and got.score.between(0, 1).all()
    odd = spark.createDataFrame([(4, 1), (4, 0), (5, None), (None, 1), (7, 1), (8, 0), (12, 1), (10, 0), (11, 0)], "doc_id long, quality int")
    for labels in (odd, odd.filter("1 = 0"), odd.filter("quality = 1")):
        r = quality(edge, labels).collect()
        assert len(r) == edge.count() and all(0 <= x["score"] <= 1 for x in r)
    assert quality(empty, odd).collect() == []


def test_quality_by_definition(spark, sf):
    """Moments, covariances, densities and scores once more, from the statistics of single texts, with no Cholesky factor."""
    from oblivspark.llm import quality as Q

    docs, labels = documents(spark, sf), spark.read.parquet(f"{sf}/labels.parquet")
    got = {r["doc_id"]: r for r in quality(docs, labels).collect()}
    x = {i: np.array(Q.statistics(t)) for i, t in texts(docs)}
    y = {r["doc_id"]: r["quality"] for r in labels.collect()}
    held = lambda i: zlib.crc32(str(i).encode()) % 3 == 1
    train = [i for i in x if i in y and not held(i)]
    own = np.array([x[i] for i in train])
    centre, scale = own.mean(0), own.std(0)
    scale = np.where(scale > 1e-9, scale, 1)
    z = {i: (v - centre) / scale for i, v in x.items()}
    parts = {c: np.array([z[i] for i in train if y[i] == c]) for c in (0, 1)}
    cov = {c: np.cov(p.T, bias=True) for c, p in parts.items()}
    both = sum(len(parts[c]) * cov[c] for c in (0, 1)) / len(train)
    for i, v in z.items():
        v, log = np.clip(v, -Q.CLIP, Q.CLIP), {}
        for c in (0, 1):
            m = (1 - Q.SHRINK_POOLED) * cov[c] + Q.SHRINK_POOLED * both
            m = (1 - Q.SHRINK_DIAGONAL) * m + Q.SHRINK_DIAGONAL * np.diag(np.diag(m)) + 1e-3 * np.eye(len(m))
            d = v - parts[c].mean(0)
            log[c] = np.log(len(parts[c]) / len(train)) - 0.5 * np.linalg.slogdet(m)[1] - 0.5 * d @ np.linalg.solve(m, d)
        want = 1 / (1 + np.exp(-(log[1] - log[0]) / Q.TEMPER))
        assert got[i]["score"] == pytest.approx(want, abs=1e-6) and got[i]["held_out"] == held(i)


# -- passages


def brute_passages(docs, length):
    docs = sorted(docs, key=lambda r: (-(1 << 63) if r[0] is None else r[0], suffix_dedup._key(r[1])))
    seen, out = {}, []
    for i, t in docs:
        gone = bytearray(len(t))
        me = (i, t)
        for p in range(len(t) - length + 1):
            first = seen.setdefault(t[p : p + length], (me, p))
            if first != (me, p):
                gone[p : p + length] = b"\1" * length
        kept = bytes(x for x, g in zip(t, gone) if not g)
        spans = sum(1 for k in range(len(t)) if gone[k] and (k == 0 or not gone[k - 1]))
        out.append((i, len(t), sum(gone), spans, sha(kept)))
    return out


@pytest.mark.parametrize("rounds", [{}, {"round_hashes": 1}])
def test_passages(spark, sf, edge, empty, rounds):
    cols = ("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
    for df in (edge,) if rounds else (edge, documents(spark, sf)):
        got = rows(suffix_dedup.suffix_dedup(df, **rounds), *cols)
        assert sorted(map(str, got)) == sorted(map(str, brute_passages(texts(df), 100)))
    if not rounds:
        assert suffix_dedup.suffix_dedup(empty).collect() == []


def test_slices_grow_with_the_volume(edge, monkeypatch):
    """As many slices as keep each within one task, with the same results."""
    assert suffix_dedup.slice_bits(0, 100) == 6
    for volume in (10**9, 10**12, 10**14):
        bits = suffix_dedup.slice_bits(volume, 100)
        assert 2 * volume / 68 / 2**bits <= suffix_dedup.SLICE_HASHES
    few = suffix_dedup.suffix_dedup(edge).collect()
    grams = ppm.lm_scores(edge).collect()
    monkeypatch.setattr(suffix_dedup, "SLICE_HASHES", 2)
    monkeypatch.setattr(ppm, "SLICE_BYTES", 100)
    assert suffix_dedup.slice_bits(60_000, 100) > 6
    assert sorted(map(str, suffix_dedup.suffix_dedup(edge).collect())) == sorted(map(str, few))
    told = lambda found: sorted((str(r["doc_id"]), r["n_tokens"], round(r["score"], 6)) for r in found)
    assert told(ppm.lm_scores(edge).collect()) == told(grams)


def test_multikey_order():
    w = np.random.default_rng(3).integers(0, 3, (20_000, 4)).astype(np.uint64)
    o = suffix_dedup.multikey_order(w)
    assert (w[o] == w[np.lexsort(w.T[::-1])]).all()
    x = suffix_dedup.as_tokens([b"abcdefghij", b"abcdefghiz", b"b"], 10)
    assert suffix_dedup.shared_bytes(x, np.arange(3)).tolist() == [0, 9, 0]


# -- tokens


def test_tokens(spark, sf, edge, empty):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    tok = Tokenizer.from_file(path)
    for df in (edge, documents(spark, sf)):
        want = [(i, len(t), n := len(tok.encode(t.decode(), add_special_tokens=False).ids), n > 1024) for i, t in texts(df)]
        assert sorted(map(str, rows(token_counts(df, path), "doc_id", "n_bytes", "n_tokens", "over_limit"))) == sorted(map(str, want))
    assert token_counts(empty, path).collect() == []


def test_splits_like_the_library():
    """Every character of Unicode beside letters, digits, blanks, signs, apostrophe suffixes and itself."""
    import public_tokenizers
    from tokenizers import Tokenizer

    from oblivspark.llm.token_counts import Tokens

    path = public_tokenizers.path("byte_bpe_50k.json")
    tok, own = Tokenizer.from_file(path), Tokens(path, {})
    chars = [chr(c) for c in range(0x110000) if not 0xD800 <= c < 0xE000]
    # characters whose class the splitter takes from its own table: each must be split as the library does
    fast = [c for c in chars if not own.odd.search(c)]
    assert len(fast) > 50_000 and {"a", "7", " ", "é", "中", "\u00a0", "😀"} <= set(fast)
    for at in range(0, len(fast), 128):
        text = "".join(f"a{c}b {c} 1{c}. {c}{c}x{c}'s '{c} {c}'ll1{c}1  {c}\n" for c in fast[at : at + 128])
        assert own.count(text) == len(tok.encode(text, add_special_tokens=False).ids)
    for at in range(0, len(chars), 4096):
        text = "".join(f"{c}1{c} {c}'s" for c in chars[at : at + 4096])
        assert own.count(text) == len(tok.encode(text, add_special_tokens=False).ids)
    for text in ("1\u0558 \u0558's", "x\u088f's", "\u10940'll", "<|endoftext|>a <|endoftext|>"):
        assert own.count(text) == len(tok.encode(text, add_special_tokens=False).ids)


def test_other_tokenizer(edge):
    """A file whose way of splitting isn't the known one goes to the library, whole texts at a time."""
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    tok = Tokenizer.from_file(path)
    want = [(i, len(t), n := len(tok.encode(t.decode(), add_special_tokens=False).ids), n > 3) for i, t in texts(edge)]
    assert sorted(map(str, rows(token_counts(edge, path, 3), "doc_id", "n_bytes", "n_tokens", "over_limit"))) == sorted(map(str, want))


# -- exact copies


@pytest.mark.parametrize("bits", [128, 8])
@pytest.mark.parametrize("keep", ["min", "max"])
def test_exact(spark, sf, edge, empty, bits, keep):
    """With 8 bits nearly all groups collide and are told apart by their bytes."""
    for df in (edge, documents(spark, sf)) if bits == 8 else (edge,):
        groups = defaultdict(list)
        for i, t in texts(df):
            groups[t.lower()].append(i)
        pick = {t: (min if keep == "min" else max)([i for i in ids if i is not None], default=None) for t, ids in groups.items()}
        want = [(i, pick[t], len(groups[t]), i == pick[t], sha(t)) for t, ids in groups.items() for i in ids]
        got = rows(exact_dedup(df, keep=keep, hash_bits=bits), "doc_id", "keep_id", "group_size", "kept", "text_sha256")
        assert sorted(map(str, got)) == sorted(map(str, want))
    assert exact_dedup(empty).collect() == []


# -- mixing


def test_mix(spark, sf, edge, empty):
    r = mix(edge).toPandas()
    assert len(r) == edge.count() and (r.taken <= 3 * r["size"]).all()
    by = r.groupby(r.source.fillna("￿"))
    for _, g in by:
        assert g["size"].sum() == g.source_size.iloc[0] and abs(g.taken.sum() - g.target.iloc[0]) < 1
    assert abs(r.drop_duplicates("source").target.sum() - r["size"].sum()) < 1e-6
    assert mix(empty).collect() == []
    again = mix(edge.repartition(3)).toPandas()
    key = ["doc_id", "size", "taken", "first_position"]
    assert sorted(map(str, r[key].fillna(-1).values.tolist())) == sorted(map(str, again[key].fillna(-1).values.tolist()))


def test_schedule(spark):
    from pyspark.sql import functions as F

    knots = ((0.0, 0.0), (0.4, 2.0), (0.5, 2.0), (1.0, 0.5))
    grid = spark.range(101).select((F.col("id") / 100).alias("u")).withColumn("t", position_of(F.col("u"), knots)).toPandas()
    for u, t in zip(grid.u, grid.t):
        area = sum((min(t, t1) - t0) * (2 * r0 + (r1 - r0) * (min(t, t1) - t0) / (t1 - t0)) / 2 for t0, t1, r0, r1, _ in integrate(knots) if t > t0)
        assert area == pytest.approx(u, abs=1e-6)
    with pytest.raises(ValueError):
        integrate(((0.0, 1.0), (0.0, 1.0)))
