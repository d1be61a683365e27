"""Line de-duplication: documents probe a sharded minimal perfect hash of the frequent lines."""

from __future__ import annotations

import hashlib
import pickle
import uuid

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.shared import materialise
from .base import column, id_and_text, map_batches, texts_of, unused

#: Fixed value: the bytes that are stripped at both ends of a line.
BLANK = b" \t\n\x0b\x0c\r"
#: Frequent lines per shard, about 20 bytes each, and shards that are broadcast together.
SHARD_KEYS, ROUND_SHARDS = 1 << 18, 16
#: Line hashes that a counting task holds before it hands them on.
HELD = 1 << 20


def line_keys(text: bytes) -> list[bytes]:
    """The 128-bit hash of each line's key; the empty bytes for a key without any code point."""
    digest = xxhash.xxh3_128_digest
    return [digest(k.lower()) if (k := line.strip(BLANK)) else b"" for line in text.split(b"\n")]


def halves(digests: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    both = np.frombuffer(b"".join(digests), ">u8").reshape(-1, 2).astype(np.uint64)
    return both[:, 0], both[:, 1]


def _count_lines(batches):
    """Distinct line hashes of each document, counted within the task before the exchange."""

    def flush(held):
        if held:
            yield pa.record_batch(
                [pa.array(list(held), pa.binary(16)).cast(pa.binary()), pa.array(list(held.values()), pa.int64())], names=["line", "docs"]
            )

    held: dict[bytes, int] = {}
    for batch in batches:
        for text in texts_of(batch):
            for k in set(line_keys(text)):
                if k:
                    held[k] = held.get(k, 0) + 1
            if len(held) >= HELD:
                yield from flush(held)
                held = {}
    yield from flush(held)


def frequent_lines(base: DataFrame, least: int) -> DataFrame:
    """(line, docs): the hashes of lines found in at least ``least`` documents."""
    counted = map_batches(base.select("text"), _count_lines, "line binary, docs long")
    return counted.groupBy("line").agg(F.sum("docs").alias("docs")).filter(F.col("docs") >= least)


def build_shards(lines: DataFrame, shards: int) -> DataFrame:
    """(shard, blob): a pickled ``CountShard`` for each shard, built where its lines are.

    Shards are cut by hash, so each gets about the same number of lines.
    """

    def build(key, pdf):
        import pandas as pd

        a, b = halves(list(pdf["line"]))
        blob = pickle.dumps(CountShard(a, b, pdf["docs"].to_numpy()), protocol=5)
        return pd.DataFrame({"shard": [key[0]], "blob": [blob]})

    from .phash import CountShard

    dealt = lines.withColumn("shard", F.pmod(F.conv(F.hex(F.substring("line", 9, 4)), 16, 10).cast("long"), F.lit(shards)).cast("int"))
    return dealt.groupBy("shard").applyInPandas(build, "shard int, blob binary")


_loaded: dict[str, dict[int, object]] = {}


def _prober(shared, name: str, shards: int, first: int):
    """A function from line hashes to whether each is frequent, by the shards of one round."""

    def probe(digests: list[bytes]) -> np.ndarray:
        if name not in _loaded:
            _loaded.clear()
            _loaded[name] = {s: pickle.loads(blob) for s, blob in shared.value}
        a, b = halves(digests)
        shard = ((b >> np.uint64(32)) % np.uint64(shards)).astype(np.int64)
        out = np.zeros(len(a), bool)
        for s, table in _loaded[name].items():
            mine = shard == s
            if mine.any():
                out[mine] = table.counts(a[mine], b[mine]) > 0
        return out

    return probe


def _probe_batch(texts: list[bytes], probe) -> list[tuple[list[bytes], np.ndarray]]:
    """Each text's lines and which of them are frequent, with one look-up for the whole batch."""
    keys = [line_keys(t) for t in texts]
    flat = [k for ks in keys for k in ks]
    full = np.fromiter((bool(k) for k in flat), bool, len(flat))
    hit = np.zeros(len(flat), bool)
    if full.any():
        hit[full] = probe([k for k in flat if k])
    out, at = [], 0
    for text, ks in zip(texts, keys):
        out.append((text.split(b"\n"), hit[at : at + len(ks)]))
        at += len(ks)
    return out


def line_dedup(
    docs: DataFrame, least: int = 10, id_col: str = "doc_id", text_col: str = "text", carry: bool = False,
    shard_keys: int = SHARD_KEYS, round_shards: int = ROUND_SHARDS,
) -> DataFrame:
    """One row per document: doc_id, n_lines, n_dropped, kept_sha256 (with ``carry``: all input columns instead of doc_id, the kept text among them, and last the number of dropped lines under a name that is free).

    A line's key is the line without blanks at its ends, A to Z lower-cased. A key of one code point or
    more found in ``least`` or more documents loses all its lines everywhere; the other lines stay
    as they are, joined by newlines. Lines travel as 128-bit hashes, counted in each task
    before the exchange. The frequent ones go into shards of a minimal perfect hash, which documents
    probe; a match is a match of all 128 bits. At most ``round_shards`` shards are broadcast at a
    time: where there are more, each round adds its hits by document and line number, and the documents drop the sum of them.

    Null or empty text: one empty line, never dropped. A document that loses every line keeps the
    empty text. Null or repeated ids: a document for each row (with more rounds than one, rows of one id and text share hits, which are
    the same for each). Empty table: no rows. Other columns are ignored, or carried under their own names.
    """
    base = id_and_text(docs, id_col, text_col, *([F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row")] if carry else []))
    lines = materialise(frequent_lines(base, least), "frequent-lines")
    n = lines.count()
    shards = max(1, -(-n // shard_keys))
    built = materialise(build_shards(lines, shards), "line-shards")
    spark = docs.sparkSession
    rounds = []
    for first in range(0, shards, round_shards):
        part = built.filter(F.col("shard").between(first, first + round_shards - 1)).collect()
        blobs = [(r["shard"], bytes(r["blob"])) for r in part]
        rounds.append(_prober(spark.sparkContext.broadcast(blobs), uuid.uuid4().hex, shards, first))
    if len(rounds) > 1:
        base = _with_earlier_hits(base, rounds[:-1])
    probe, several = rounds[-1], len(rounds) > 1

    def kernel(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                earlier = column(part, "_hits").to_pylist() if several else [None] * part.num_rows
                n_lines, dropped, sha, texts = [], [], [], []
                for (own, hit), more in zip(_probe_batch(texts_of(part), probe), earlier):
                    hit = hit.copy()
                    if more:
                        hit[more] = True
                    left = b"\n".join(x for x, h in zip(own, hit.tolist()) if not h) if hit.any() else b"\n".join(own)
                    n_lines.append(len(own))
                    dropped.append(int(hit.sum()))
                    sha.append(hashlib.sha256(left).hexdigest())
                    texts.append(left)
                got = [column(part, "_row" if carry else "doc_id")]
                got += [pa.array(texts, pa.binary()).cast(pa.string())] if carry else []
                yield pa.record_batch(
                    [*got, pa.array(n_lines, pa.int64()), pa.array(dropped, pa.int64()), pa.array(sha)],
                    names=[*(["_row", "_text"] if carry else ["doc_id"]), "n_lines", "n_dropped", "kept_sha256"],
                )

    facts = "n_lines long, n_dropped long, kept_sha256 string"
    if not carry:
        return map_batches(base, kernel, f"doc_id {base.schema['doc_id'].dataType.simpleString()}, {facts}")
    out = map_batches(base, kernel, f"_row {base.schema['_row'].dataType.simpleString()}, _text string, {facts}")
    return out.select(*[(F.col("_text") if c == text_col else F.col("_row")[c]).alias(c) for c in docs.columns], F.col("n_dropped").alias(unused(docs, "_n_dropped")))


def _with_earlier_hits(base: DataFrame, probes: list) -> DataFrame:
    """``base`` with ``_hits``: the line numbers that the given rounds found, by the text's own hash."""
    keyed = base.withColumn("_key", F.sha2("text", 256))
    found = None
    for probe in probes:

        def hits(batches, probe=probe):
            for batch in batches:
                got = [np.flatnonzero(h).tolist() for _, h in _probe_batch(texts_of(batch), probe)]
                out = pa.record_batch([column(batch, "_key"), pa.array(got, pa.list_(pa.int32()))], names=["_key", "_at"])
                yield out.filter(pa.array([bool(g) for g in got], pa.bool_()))

        one = map_batches(keyed.select("_key", "text"), hits, "_key string, _at array<int>")
        found = one if found is None else found.unionByName(one)
    found = found.groupBy("_key").agg(F.array_distinct(F.flatten(F.collect_set("_at"))).alias("_hits"), F.count(F.lit(1)).alias("_n"))
    from ..plans.shared import skew_safe_lookup

    found = materialise(found, "line-hits")
    return skew_safe_lookup(keyed, found, "_key", "_n", keyed.count() * len(probes), ["_hits"]).drop("_key")
