"""SimHash near-duplicates: fingerprints, sharded by a vantage-point tree, and components of exact links."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.components import connected_components
from ..plans.shared import materialise, skew_safe_lookup
from .base import column, id_and_text, map_batches, texts_of, unused

#: Fixed value: the seed of the shingles' XXH64.
SEED = 42
#: Shingles whose bits are counted at a time.
BLOCK = 1 << 16
#: Least number of fingerprints that the top of the tree is fitted on, and the number for each shard; fingerprints aimed at per shard, least number of shards.
SAMPLE, PER_SHARD, SHARD, LEAST_SHARDS = 8192, 8, 1 << 18, 32
#: Pairs that are compared in one go at the bottom of a tree.
LEAF_PAIRS = 1 << 20


def fingerprint(text: bytes, width: int = 3) -> int:
    """64 bits, each set if over half of the text's shingle hashes have it; 0 for a text without words."""
    words = text.lower().split()  # bytes: A to Z and the six ASCII blanks only
    if not words:
        return 0
    h = xxhash.xxh64_intdigest
    if len(words) <= width:
        return h(b" ".join(words), SEED)  # a single hash is its own majority
    total, n = np.zeros(64, np.int64), len(words) - width + 1
    for at in range(0, n, BLOCK):
        part = words[at : at + BLOCK + width - 1]
        hashes = np.array([h(b" ".join(s), SEED) for s in zip(*(part[i:] for i in range(width)))], "<u8")
        total += np.unpackbits(hashes.view(np.uint8), bitorder="little").reshape(-1, 64).sum(0, dtype=np.int64)
    return int(np.packbits(total * 2 > n, bitorder="little").view("<u8")[0])


def majority(hashes: np.ndarray) -> int:
    """The fingerprint of shingle hashes, repeats included."""
    total = np.zeros(64, np.int64)
    for at in range(0, len(hashes), BLOCK):
        total += np.unpackbits(hashes[at : at + BLOCK].astype("<u8").view(np.uint8), bitorder="little").reshape(-1, 64).sum(0, dtype=np.int64)
    return int(np.packbits(total * 2 > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(base: DataFrame, width: int) -> DataFrame:
    """(doc_id, fp): the fingerprint as a signed long."""

    def kernel(batches):
        for batch in batches:
            fps = np.array([fingerprint(t, width) for t in texts_of(batch)], np.uint64).view(np.int64)
            yield pa.record_batch([column(batch, "doc_id"), pa.array(fps)], names=["doc_id", "fp"])

    return map_batches(base.select("doc_id", "text"), kernel, f"doc_id {base.schema['doc_id'].dataType.simpleString()}, fp long")


def distance(points: np.ndarray, v) -> np.ndarray:
    return np.bitwise_count(points ^ v)


def grow(sample: np.ndarray, leaves: int) -> list:
    """The top of a vantage-point tree as nested (vantage, radius, inner, outer); a leaf is its shard's number."""
    count = iter(range(1 << 30))

    def node(points: np.ndarray, budget: int):
        if budget <= 1 or len(points) < 4:
            return next(count)
        best = None
        for v in points[:: max(1, len(points) // 8)][:8]:
            d = distance(points, v)
            radius = int(np.median(d))
            inner = d <= radius
            if inner.all():
                radius -= 1
                inner = d <= radius
            near = int(((d > radius) & (d <= radius + 2)).sum())  # what a cut here would copy
            if 0 < inner.sum() < len(points) and (best is None or near < best[0]):
                best = (near, v, radius, inner)
        if best is None:
            return next(count)
        _, v, radius, inner = best
        return (np.uint64(v), radius, node(points[inner], budget // 2), node(points[~inner], budget - budget // 2))

    return node(sample, leaves)


def route(tree, points: np.ndarray, reach: int):
    """(shard, indexes of its own points, indexes of guests): each pair within ``reach`` meets in the shard of one of them.

    A point is at home on its own side of every cut. By the triangle inequality only points within ``reach``
    of the boundary can have partners beyond it: those of the outer side visit the inner side, and guests go wherever they may have partners.
    """

    def walk(node, home, guests):
        if not len(home) and not len(guests):
            return
        if not isinstance(node, tuple):
            yield node, home, guests
            return
        v, radius, inner, outer = node
        dh, dg = distance(points[home], v), distance(points[guests], v)
        inside = dh <= radius
        visit = home[~inside & (dh <= radius + reach)]
        yield from walk(inner, home[inside], np.concatenate((guests[dg <= radius + reach], visit)))
        yield from walk(outer, home[~inside], guests[dg + reach > radius])

    every = np.arange(len(points))
    yield from walk(tree, every, every[:0])


class Links:
    """Union-find over 0 .. n-1, in whole arrays."""

    def __init__(self, n: int):
        self.parent = np.arange(n)

    def add(self, a: np.ndarray, b: np.ndarray) -> None:
        p = self.parent
        while True:
            ra, rb = p[a], p[b]
            open_ = ra != rb
            if not open_.any():
                return
            a, b, ra, rb = a[open_], b[open_], ra[open_], rb[open_]
            np.minimum.at(p, np.maximum(ra, rb), np.minimum(ra, rb))
            while True:
                q = p[p]
                if (q == p).all():
                    break
                p[:] = q


def link(points: np.ndarray, home: np.ndarray, guests: np.ndarray, reach: int, links: Links, rng) -> None:
    """Add all pairs within ``reach`` of which one is at home: a vantage-point tree, cut where the cuts pay."""
    every = np.concatenate((home, guests))
    if len(home) * len(every) > LEAF_PAIRS and len(home) > 64:
        v = points[home[rng.integers(len(home))]]
        dh, dg = distance(points[home], v), distance(points[guests], v)
        radius = int(np.median(dh))
        if not (dh > radius).any():
            radius -= 1
        inside = dh <= radius
        near = np.concatenate((guests[dg <= radius + reach], home[~inside & (dh <= radius + reach)]))
        far = guests[dg + reach > radius]
        work = inside.sum() * (inside.sum() + len(near)) + (~inside).sum() * ((~inside).sum() + len(far))
        if inside.any() and work < 0.9 * len(home) * len(every):
            link(points, home[inside], near, reach, links, rng)
            link(points, home[~inside], far, reach, links, rng)
            return
    step = max(1, LEAF_PAIRS // max(1, len(every)))
    for at in range(0, len(home), step):
        a, b = np.nonzero(np.bitwise_count(points[home[at : at + step], None] ^ points[every][None, :]) <= reach)
        links.add(home[at + a], every[b])


def linked(distinct: DataFrame, tree, shards: int, reach: int) -> DataFrame:
    """(u, v): in each shard a star over every group of fingerprints that its links join."""

    def deal(batches):
        for batch in batches:
            fps = column(batch, "fp").to_numpy(zero_copy_only=False).view(np.uint64)
            for shard, home, guests in route(tree, fps, reach):
                at = np.concatenate((home, guests))
                yield pa.record_batch(
                    [pa.array(np.full(len(at), shard, np.int32)), pa.array(fps[at].view(np.int64)), pa.array(np.arange(len(at)) < len(home))],
                    names=["shard", "fp", "home"],
                )

    def search(table: pa.Table) -> pa.Table:
        points = table["fp"].to_numpy().view(np.uint64)
        home = table["home"].to_numpy()
        links = Links(len(points))
        link(points, np.flatnonzero(home), np.flatnonzero(~home), reach, links, np.random.default_rng(len(points)))
        moved = np.flatnonzero(links.parent != np.arange(len(points)))
        return pa.table({"u": points[moved].view(np.int64), "v": points[links.parent[moved]].view(np.int64)})

    dealt = map_batches(distinct.select("fp"), deal, "shard int, fp long, home boolean").repartition(shards, "shard")
    return dealt.groupBy("shard").applyInArrow(search, "u long, v long")


def groups(distinct: DataFrame, count: int, reach: int) -> DataFrame:
    """(node, component): fingerprints that links of at most ``reach`` bits join to others. ``distinct``: (fp), ``count`` of them, each once.

    A vantage-point tree, fitted on ``SAMPLE`` of them or ``PER_SHARD`` for each shard, deals all of them to shards.
    """
    shards = max(LEAST_SHARDS, -(-count // SHARD))
    picked = [r[0] for r in distinct.select("fp").orderBy(F.xxhash64("fp"), "fp").limit(max(SAMPLE, PER_SHARD * shards)).collect()]
    tree = grow(np.array(picked, np.int64).view(np.uint64), shards)
    return connected_components(linked(distinct, tree, shards, reach), "u", "v")


def near_dedup(docs: DataFrame, width: int = 3, reach: int = 2, id_col: str = "doc_id", text_col: str = "text", carry: bool = False) -> DataFrame:
    """One row per document: doc_id, fingerprint (16 hex digits), component_id (``carry``: all input columns, of the documents that stay).

    Shingles are ``width`` blank-parted words (A to Z lower-cased), repeats included; a text of fewer is one
    shingle, one without words has the fingerprint 0 and is linked like any other. Two fingerprints link at
    ``reach`` or fewer differing bits; component_id is the least doc_id that links reach. Equal fingerprints are
    one node. A vantage-point tree, fitted on 8,192 of the distinct fingerprints or 8 for each shard (8 in 2^18 of them), deals all of them to
    shards, with copies near the boundaries so that every pair meets; each shard finds its pairs exactly and
    hands on a star per group, never the pairs. With ``carry``, the document that stays is the one with component_id for its id.

    Null text: the empty text. Null ids never name a component unless it has no other; with ``carry`` its rows then
    stay. Repeated ids and rows: one row each. Empty table: no rows. Other columns are ignored or carried.
    """
    base = id_and_text(docs, id_col, text_col)
    each = materialise(fingerprints(base, width), "fingerprints")
    distinct = materialise(each.groupBy("fp").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("n")), "distinct")
    facts = distinct.agg(F.count(F.lit(1)), F.coalesce(F.sum("n"), F.lit(0))).first()
    pieces = groups(distinct, facts[0], reach)
    nodes = distinct.join(pieces, F.col("fp") == F.col("node"), "left").withColumn("root", F.coalesce("component", "fp"))
    nodes = materialise(nodes.select("fp", "rep", "n", "root"), "nodes")
    roots = materialise(nodes.groupBy("root").agg(F.min("rep").alias("component_id"), F.count(F.lit(1)).alias("size")), "roots")
    named = skew_safe_lookup(nodes, roots, "root", "size", facts[0], ["component_id"])
    named = materialise(named.select("fp", "n", "component_id"), "named")
    if not carry:
        out = skew_safe_lookup(each, named, "fp", "n", facts[1], ["component_id"])
        return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
    out = skew_safe_lookup(each, named, "fp", "n", facts[1], ["component_id"])
    stay = out.filter(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias(name := unused(docs, "_stay"))).distinct()
    return docs.join(stay, F.col(f"`{id_col}`").eqNullSafe(F.col(name)), "left_semi")
