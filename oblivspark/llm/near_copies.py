"""Near copies by similarity of five-word shingles: candidates by SimHash and, for what lies beyond its reach, by MinHash bands; links by exact comparison."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.components import connected_components
from ..plans.shared import materialise, skew_safe_lookup
from .base import column, id_and_text, map_batches, texts_of, unused
from .simhash import groups, majority

#: Words of a shingle, and the least share of common shingles of two linked texts, in hundredths.
WIDTH, LEAST = 5, 80
#: Bits in which the SimHash fingerprints of candidates differ at most.
REACH = 2
#: Least hashes that a band joins, and bands: a pair at 0.8 has none in common with a chance of (1 - 0.8^6)^40, under 6 in a million.
ROWS, BANDS = 6, 40
#: Fixed value: the seed of all hashes.
SEED = 42
#: Products held at a time, and bits of the map of candidates that is broadcast (8 MB).
BLOCK, MAP_BITS = 1 << 18, 26

_rng = np.random.default_rng(SEED)
_TIMES, _PLUS = _rng.integers(0, 1 << 64, (2, ROWS * BANDS, 1), dtype=np.uint64)
_TIMES |= np.uint64(1)


def sequence(text: bytes, width: int = WIDTH) -> np.ndarray:
    """The shingles' XXH64 as they come; a text of fewer words is one shingle, one without words the empty one."""
    words = text.lower().split()  # bytes: A to Z and the six ASCII blanks only
    h = xxhash.xxh64_intdigest
    if len(words) <= width:
        return np.array([h(b" ".join(words), SEED)], np.uint64)
    return np.array([h(b" ".join(s), SEED) for s in zip(*(words[i:] for i in range(width)))], np.uint64)


def shingles(text: bytes, width: int = WIDTH) -> np.ndarray:
    """The distinct shingles' XXH64, in order."""
    return np.unique(sequence(text, width))


def node_of(found: np.ndarray) -> int:
    return xxhash.xxh64_intdigest(found.tobytes(), SEED)


def mark_of(text: bytes) -> int:
    return xxhash.xxh64_intdigest(text, SEED)


def bands_of(found: np.ndarray) -> np.ndarray:
    """One hash a band, each of the band's number and its least hashes."""
    least = np.empty(ROWS * BANDS, np.uint64)
    step = max(1, BLOCK // len(found))
    for at in range(0, len(least), step):
        part = slice(at, at + step)
        least[part] = (found[None, :] * _TIMES[part] + _PLUS[part]).min(1)
    rows = np.concatenate((np.arange(BANDS, dtype=np.uint64)[:, None], least.reshape(BANDS, ROWS)), 1)
    return np.array([xxhash.xxh64_intdigest(r.tobytes(), SEED) for r in rows], np.uint64)


def roots_of(sets: list[np.ndarray]) -> np.ndarray:
    """For each set the first of those that links of similar pairs reach, all pairs considered.

    A set that was reached is compared with all that weren't yet; near copies are reached by the first, and so seldom compared again.
    """
    sizes = np.array([len(s) for s in sets])
    root = np.arange(len(sets))
    words, flat = np.unique(np.concatenate(sets), return_inverse=True)
    starts = np.cumsum(sizes) - sizes
    owner = np.repeat(np.arange(len(sets)), sizes)
    ids, mark, left = flat, np.zeros(len(words), bool), np.ones(len(sets), bool)
    for first in range(len(sets)):
        if not left[first]:
            continue
        left[first], queue = False, [first]
        while queue and left.any():
            at = queue.pop()
            mine = flat[starts[at] : starts[at] + sizes[at]]
            mark[mine] = True
            common = np.bincount(owner[mark[ids]], minlength=len(sets))
            mark[mine] = False
            near = np.flatnonzero(left & (common * 100 >= LEAST * (sizes + sizes[at] - common)))
            if len(near):
                root[near], left[near] = first, False
                queue.extend(near.tolist())
                still = left[owner]
                ids, owner = ids[still], owner[still]
    return root


def _by_fingerprint(each: DataFrame, reach: int = REACH) -> DataFrame:
    """(node, band): one band for each group that links of SimHash fingerprints, found in the shards of a vantage-point tree, reach. ``each``: (node, fp)."""
    pairs = materialise(each.select("node", "fp").distinct(), "fingerprints")
    distinct = materialise(pairs.groupBy("fp").agg(F.count(F.lit(1)).alias("n")), "fingerprints")
    pieces = groups(distinct, distinct.count(), reach).select(F.col("node").alias("_fp"), "component")
    roots = distinct.join(pieces, F.col("fp") == F.col("_fp"), "left").select("fp", "n", F.coalesce("component", "fp").alias("root"))
    named = skew_safe_lookup(pairs, materialise(roots, "roots"), "fp", "n", pairs.count(), ["root"])
    return named.select("node", F.xxhash64(F.lit("fingerprints"), "root").alias("band")).distinct()


def _candidates(each: DataFrame, distinct: DataFrame) -> DataFrame:
    """(node, component): nodes that groups of fingerprints and bands join, directly or over others."""
    rows = distinct.select("node", F.explode("bands").alias("band")).unionByName(materialise(_by_fingerprint(each), "bands"))
    buckets = rows.groupBy("band").agg(F.min("node").alias("least"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    buckets = materialise(buckets, "bands")
    met = buckets.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    edges = skew_safe_lookup(rows, buckets, "band", "n", met, ["least"]).filter("node != least")
    return connected_components(edges.select(F.col("node").alias("u"), F.col("least").alias("v")), "u", "v")


def _map_of(marks: DataFrame) -> np.ndarray:
    """One bit for each value of the marks' last bits: keeps most other texts from being cut and dealt again, and has no say in the result."""
    place = F.col("mark").bitwiseAND(F.lit((1 << MAP_BITS) - 1))
    words = marks.select(F.shiftright(place, 6).alias("w"), F.expr("shiftleft(1L, int(mark & 63))").alias("b")).groupBy("w").agg(F.bit_or("b").alias("b"))
    got = words.toArrow()
    out = np.zeros(1 << (MAP_BITS - 6), np.uint64)
    out[got["w"].to_numpy()] = got["b"].to_numpy().view(np.uint64)
    return out


def near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents that stay, with all columns: of each group of near copies the one of the least id.

    Two texts link if at least 0.8 of their distinct five-word shingles (A to Z lower-cased) are common; a group is what links
    reach. Texts of one set of shingles are one node. Nodes whose SimHash fingerprints over the five-word shingles link at ``REACH`` or fewer
    bits, by the vantage-point tree of ``simhash``, are candidates; those that are similar but further apart, as most pairs at 0.8 are, meet by a MinHash band in common. So
    are all that chains of either join; each such set is dealt to one task once, which compares its shingles' 64-bit hashes exactly.
    A pair that no chain joins is missed: under 6 in a million at a similarity of 0.8, fewer above.

    Null text: the empty text; texts without words are copies of each other. Rows of null ids stay if their group has no
    other id. Repeated ids: all rows of an id stay if one does. Empty table: no rows.
    """
    spark = docs.sparkSession
    base = id_and_text(docs, id_col, text_col)

    def sign(batches):
        for batch in batches:
            texts = texts_of(batch)
            whole = [sequence(t) for t in texts]
            fps = np.array([majority(h) for h in whole], np.uint64).view(np.int64)
            found = [np.unique(h) for h in whole]
            nodes = np.array([node_of(s) for s in found], np.uint64).view(np.int64)
            marks = np.array([mark_of(t) for t in texts], np.uint64).view(np.int64)
            bands = np.concatenate([bands_of(s) for s in found]).view(np.int64) if found else np.empty(0, np.int64)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, len(bands) + 1, BANDS, dtype=np.int32)), pa.array(bands))
            yield pa.record_batch([column(batch, "doc_id"), pa.array(nodes), pa.array(fps), pa.array(marks), lists], names=["doc_id", "node", "fp", "mark", "bands"])

    kind = base.schema["doc_id"].dataType.simpleString()
    each = materialise(map_batches(base, sign, f"doc_id {kind}, node long, fp long, mark long, bands array<long>"), "signed")
    distinct = each.groupBy("node").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("n"), F.min("mark").alias("mark"), F.first("bands").alias("bands"))
    distinct = materialise(distinct, "distinct")
    total = distinct.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    candidates = materialise(_candidates(each, distinct), "candidates")
    candidates = materialise(candidates.unionByName(candidates.select(F.col("component").alias("node"), "component")).distinct(), "candidates")
    shared = spark.sparkContext.broadcast(_map_of(distinct.join(candidates, "node").select("mark")))

    def take(batches):
        held = shared.value
        for batch in batches:
            texts = texts_of(batch)
            place = np.array([mark_of(t) for t in texts], np.uint64) & np.uint64((1 << MAP_BITS) - 1)
            on = np.flatnonzero(held[place >> np.uint64(6)] >> (place & np.uint64(63)) & np.uint64(1))
            found = [shingles(texts[i]) for i in on]
            nodes = np.array([node_of(s) for s in found], np.uint64).view(np.int64)
            yield pa.record_batch([pa.array(nodes), pa.array([s.tobytes() for s in found], pa.binary())], names=["node", "found"])

    def search(table: pa.Table) -> pa.Table:
        # equal nodes are equal sets: the first of each will do
        nodes, first = np.unique(table["node"].to_numpy(), return_index=True)
        root = roots_of([np.frombuffer(b, np.uint64) for b in table["found"].take(pa.array(first)).to_pylist()])
        moved = np.flatnonzero(root != np.arange(len(root)))
        return pa.table({"node": nodes[moved], "root": nodes[root[moved]]})

    taken = map_batches(base.select("text"), take, "node long, found binary").dropDuplicates(["node"])
    joined = taken.join(candidates, "node")
    pieces = joined.select("component", "node", "found").groupBy("component").applyInArrow(search, "node long, root long")
    nodes = distinct.select("node", "rep", "n").join(materialise(pieces, "pieces"), "node", "left").withColumn("root", F.coalesce("root", "node"))
    nodes = materialise(nodes, "nodes")
    roots = nodes.groupBy("root").agg(F.min("rep").alias("component_id"), F.count(F.lit(1)).alias("size"))
    facts = nodes.count()
    named = skew_safe_lookup(nodes, materialise(roots, "roots"), "root", "size", facts, ["component_id"])
    named = materialise(named.select("node", "n", "component_id"), "named")
    out = skew_safe_lookup(each.select("doc_id", "node"), named, "node", "n", total, ["component_id"])
    stay = out.filter(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias(name := unused(docs, "_stay"))).distinct()
    return docs.join(stay, F.col(f"`{id_col}`").eqNullSafe(F.col(name)), "left_semi")
